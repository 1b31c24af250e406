"""Counting subword tokens of a piece vocabulary by heap-driven merging, without building identifiers.

The text's symbols stand in a doubly linked list. A heap yields the adjacent pair of the lowest rank, leftmost first;
the pair is merged and the pairs it now forms are pushed. The count is the initial symbols less the merges. Symbols
that end unmerged and unknown count as their UTF-8 bytes. Null and empty texts have no tokens. Texts of any length are
read whole; repeated texts and ties give equal counts.

A text is cut where no merge can ever reach across: between two characters that no vocabulary entry holds side by
side. Counts of the pieces so found are kept in a bounded table, since words repeat.
"""

from __future__ import annotations

import heapq
import re

from pyspark.sql import DataFrame, SparkSession

from .common import map_columns, table, tokenizer_path

SPACE = "▁"
RUN = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")


class _Memo(dict):
    """Remembers answers of ``fn`` for keys of up to ``room`` characters together (each counted with 64 more, its overhead);
    beyond that it computes them anew."""

    def __init__(self, fn, room: int):
        super().__init__()
        self.fn, self.room = fn, room

    def __missing__(self, key):
        value = self.fn(key)
        if self.room >= len(key) + 64:
            self.room -= len(key) + 64
            self[key] = value
        return value


class PieceCounter:
    """Token counts as a piece model with byte fallback gives them, without begin and end tokens."""

    def __init__(self, model_file: str, room: int = 32_000_000):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_file)
        ids = [i for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
        self.rank = {model.id_to_piece(i): -model.get_score(i) for i in ids}
        self.beside = {p[i : i + 2] for p in self.rank for i in range(len(p) - 1)}
        if any(SPACE in p.strip(SPACE) or p.endswith(SPACE) and p.strip(SPACE) for p in self.rank):
            raise ValueError("a piece holds a space after another character; words can't be counted one by one")
        self.words, self.stems = _Memo(self._word, room), _Memo(self.merge, room)

    def merge(self, text: str) -> int:
        n = len(text)
        if n == 1:
            return 1 if text in self.rank else len(text.encode())
        rank, left, right, symbol = self.rank, [*range(-1, n - 1)], [*range(1, n), -1], [*text]
        heap = [(r, i, p) for i in range(n - 1) if (r := rank.get(p := text[i : i + 2])) is not None]
        heapq.heapify(heap)
        merges = 0
        while heap:
            _, i, pair = heapq.heappop(heap)
            a, j = symbol[i], right[i]
            if a is None or j < 0 or len(a) + len(symbol[j]) != len(pair) or a + symbol[j] != pair:
                continue
            merges += 1
            symbol[i], symbol[j] = pair, None
            right[i] = k = right[j]
            if k >= 0:
                left[k] = i
                if (r := rank.get(p := pair + symbol[k])) is not None:
                    heapq.heappush(heap, (r, i, p))
            if (k := left[i]) >= 0 and (r := rank.get(p := symbol[k] + pair)) is not None:
                heapq.heappush(heap, (r, k, p))
        unknown = sum(len(s.encode()) - 1 for s in symbol if s is not None and len(s) == 1 and s not in rank)
        return n - merges + unknown

    def _word(self, word: str) -> int:
        text, beside, stems = word if SPACE in word else SPACE + word, self.beside, self.stems
        start = total = 0
        for i in range(1, len(text)):
            if text[i - 1 : i + 1] not in beside:
                total += stems[text[start:i]]
                start = i
        return total + stems[text[start:]]

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if SPACE in text or "  " in text or text[0] == " " or text[-1] == " ":
            runs = RUN.findall(SPACE + text.replace(" ", SPACE))
            return sum(self.words[r[1:] if r[0] == SPACE and r[1:2] not in ("", SPACE) else r] for r in runs)
        return sum(map(self.words.__getitem__, text.split(" ")))


_COUNTERS: dict[str, PieceCounter] = {}


def count_tokens(docs: DataFrame, model: str = "piece_bpe_32k.model", limit: int = 4096, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_bytes, n_tokens, over_limit for each row; one map over whole texts, no shuffle."""

    def count(ids, texts):
        path = tokenizer_path(model)
        if path not in _COUNTERS:
            _COUNTERS[path] = PieceCounter(path)
        counter = _COUNTERS[path]
        values = texts.to_pylist()
        n = [counter.count(t) for t in values]
        return [ids, [len(t.encode()) if t else 0 for t in values], n, [x > limit for x in n]]

    kind = docs.schema[key].dataType.simpleString()
    return map_columns(docs, count, f"{key} {kind}, n_bytes long, n_tokens long, over_limit boolean", [key, text])


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of every whole text of documents under the 32k piece vocabulary."""
    return count_tokens(table(spark, sf_dir, "documents"))


QUERIES = {"op2_token_counts": op2_token_counts}
