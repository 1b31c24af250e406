from __future__ import annotations

import pytest

#: nulls, empty and white texts, ties, repeats, odd characters, special strings, a long text
TEXTS = [
    None, "", " ", "\n\t", "a", "The quick brown fox jumps over the lazy dog.", "The quick brown fox jumps over the lazy dog.",
    "a  b", " lead and trail ", "it's I'll 'twas''s", "<s> </s> <|endoftext|> <|startoftext|>x", "aaaa aaaaaaaaaaaaa", "éÉ ǅ İstanbul ΣΑΣ ªº²",
    "日本語 テスト\u3000全角", "😀😀 ok", "x\u00a0y\u2028z", "a\x1cb\x00c", "▁ under ▁▁ bar", "e\u0301 combining \u0307", "word " * 3000, "x" * 5000,
]


@pytest.fixture(scope="session")
def odd_docs(spark):
    """documents with extra columns whose names clash with those the operators use inside."""
    rows = [(i if i % 7 else None if i == 7 else i, t, "en", f"s{i % 2}", None if t is None else len(t), i, "k") for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, id long, found string").repartition(3)


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.filter("1 = 0")
