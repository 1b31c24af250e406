"""Byte-level BPE encoding through an index of pair occurrences, and decoding.

The distinct words of a partition's block lie end to end in one array of symbols. An index maps each adjacent pair to
all its positions. Ranks that occur are taken in ascending order; all positions of a pair are merged at once and the
lists of the pairs so broken and made are brought up to date. Words already seen are kept in tables of bounded bytes.

Null and empty texts give no tokens. Strings of special tokens inside a text become the special token, as the
tokenizers library does by default. Texts of any length are handled whole, in blocks of bounded size.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import re
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import table, tokenizer_path

# fixed values: how byte-level vocabularies split text, and the bytes that stand for themselves in their entries
WORDS = regex.compile(r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+""")
#: a space beside other white space, or at an end
TANGLED = re.compile(r"\A | \s|\s | \Z")
PRINTABLE = [*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAC + 1), *range(0xAE, 0xFF + 1)]


def byte_alphabet() -> dict[str, int]:
    """The character that stands for each byte: itself where printable, else the next code point from 256 on."""
    rest = [b for b in range(256) if b not in set(PRINTABLE)]
    return {chr(b): b for b in PRINTABLE} | {chr(256 + i): b for i, b in enumerate(rest)}


ONE = np.ones(1, bool)


class ByteBpe:
    def __init__(self, path: str, room: int = 48_000_000, block_bytes: int = 24_000_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet, vocab = byte_alphabet(), spec["model"]["vocab"]
        entry = {i: bytes(alphabet[c] for c in piece) for piece, i in vocab.items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.bytes_of = entry | {i: s.encode() for s, i in self.special.items()}
        single = {b: i for i, b in entry.items() if len(b) == 1}
        self.of_byte = np.array([single[b"%c" % b] for b in range(256)], dtype=np.int64)
        self.size = max(self.bytes_of) + 1
        self.merges = [(vocab[a], vocab[b], vocab[a + b]) for a, b in spec["model"]["merges"]]
        self.rank_of = {a * self.size + b: r for r, (a, b, _) in enumerate(self.merges)}
        self.pairs = np.array(sorted(self.rank_of), dtype=np.int64)
        self.ranks = np.array([self.rank_of[p] for p in self.pairs.tolist()], dtype=np.int64)
        self.made = np.array([m for _, _, m in self.merges], dtype=np.int64)
        self.split = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.known: dict[str, bytes] = {}
        self.stems: dict[str, bytes] = {}
        self.room, self.block_bytes = [room, room], block_bytes

    def _active(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The rank of each pair, or -1."""
        code = left * self.size + right
        at = np.minimum(np.searchsorted(self.pairs, code), len(self.pairs) - 1)
        return np.where(self.pairs[at] == code, self.ranks[at], -1)

    def encode_words(self, words: list[str]) -> list[bytes]:
        """The ids of each word as little-endian unsigned 32-bit integers."""
        if not words:
            return []
        raw = [w.encode() for w in words]
        sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        joined = np.frombuffer(b"".join(raw), np.uint8)
        n = len(joined)
        symbol, ends = self.of_byte[joined], np.cumsum(sizes)
        following, before = np.arange(1, n + 1), np.arange(-1, n - 1)
        starts = ends - sizes
        following[ends - 1], before[starts] = -1, -1
        at = np.nonzero(following >= 0)[0]
        rank = self._active(symbol[at], symbol[at + 1])
        at, rank = at[rank >= 0], rank[rank >= 0]
        order = np.argsort(rank, kind="stable")
        at, rank = at[order], rank[order]
        cuts = np.flatnonzero(np.diff(rank)) + 1
        places: dict[int, list[np.ndarray]] = {int(r[0]): [p] for p, r in zip(np.split(at, cuts), np.split(rank, cuts), strict=True) if len(p)}
        heap = [*places]
        heapq.heapify(heap)
        alive = np.ones(n, bool)
        while heap:
            r = heapq.heappop(heap)
            a, b, made = self.merges[r]
            lists = places.pop(r)
            p = lists[0] if len(lists) == 1 else np.concatenate(lists)
            p = p[alive[p] & (symbol[p] == a)]
            if len(p) > 1:
                p = np.sort(p)
                p = p[np.concatenate((ONE, p[1:] != p[:-1]))]
            q = following[p]
            good = (q >= 0) & (symbol[q] == b)
            p, q = p[good], q[good]
            if a == b and len(p) > 1:  # of overlapping pairs the left one wins: keep every other of a run
                linked = np.r_[False, q[:-1] == p[1:]]
                run = np.arange(len(p)) - np.maximum.accumulate(np.where(linked, 0, np.arange(len(p))))
                p, q = p[run % 2 == 0], q[run % 2 == 0]
            if not len(p):
                continue
            symbol[p], alive[q] = made, False
            after, prior = following[q], before[p]
            following[p] = after
            before[after[after >= 0]] = p[after >= 0]
            new = np.concatenate((prior[prior >= 0], p[after >= 0]))
            got = self._active(symbol[new], symbol[following[new]])
            new, got = new[got >= 0], got[got >= 0]
            if len(new) == 0:
                continue
            if len(new) == 1 or (got == got[0]).all():
                groups = [(int(got[0]), new)]
            else:
                order = np.argsort(got, kind="stable")
                new, got = new[order], got[order]
                cuts = np.flatnonzero(np.diff(got)) + 1
                groups = [(int(g[0]), s) for s, g in zip(np.split(new, cuts), np.split(got, cuts), strict=True)]
            for g, s in groups:
                if g in places:
                    places[g].append(s)
                else:
                    places[g] = [s]
                    heapq.heappush(heap, g)
        out, left = symbol[alive].astype("<u4").tobytes(), np.r_[0, np.cumsum(alive)]
        bounds = (left[np.r_[0, ends]] * 4).tolist()
        return [out[x:y] for x, y in zip(bounds, bounds[1:], strict=False)]

    def encode_block(self, texts: list[str]) -> list[bytes]:
        """The ids of each text."""
        keys = [self._keys(t) for t in texts]
        fresh = {k for own in keys for k in own if k not in self.known}
        parts = {k: [w] if (w := k[1:]) in self.special and k[0] == " " else WORDS.findall(w if k[0] == " " else " " + k) for k in fresh if k}
        unseen = [*{w for own in parts.values() for w in own if w not in self.stems and w not in self.special}]
        table = dict(zip(unseen, self.encode_words(unseen), strict=True)) | {s: int(i).to_bytes(4, "little") for s, i in self.special.items()}
        get = _Both(self.stems, table).__getitem__
        made = {k: b"".join(map(get, own)) for k, own in parts.items()} | {"": b""}
        get = _Both(self.known, made).__getitem__
        out = [b"".join(map(get, own)) for own in keys]
        for i, (memo, new) in enumerate(((self.stems, table), (self.known, made))):
            sizes = np.cumsum([len(k) + len(v) + 100 for k, v in new.items()])  # with the overhead of an entry
            n = int(np.searchsorted(sizes, self.room[i], side="right"))
            memo.update(islice(new.items(), n))
            self.room[i] -= int(sizes[n - 1]) if n else 0
        return out

    def _keys(self, text: str) -> list[str]:
        """Parts of a text that are encoded one by one. A part that follows a single space goes without it; one that
        doesn't has a space put before it, which no part of the first kind holds."""
        if not text:
            return []
        if self.split is not None and any(s in text for s in self.special):
            return [" " + w for k, part in enumerate(self.split.split(text)) for w in ([part] if k % 2 else WORDS.findall(part))]
        if TANGLED.search(text):
            return [" " + w for w in WORDS.findall(text)]
        out = text.split(" ")
        out[0] = " " + out[0]
        return out

    def blocks(self, texts: list[str | None]) -> Iterator[tuple[int, list[bytes]]]:
        """The texts' ids, in blocks of bounded size: (position of the first text, ids of each)."""
        start = size = 0
        for i, t in enumerate(texts):
            size += len(t or "")
            if size >= self.block_bytes or i + 1 == len(texts):
                yield start, self.encode_block([x or "" for x in texts[start : i + 1]])
                start, size = i + 1, 0

    def decode(self, ids: bytes) -> str:
        """The text of ids, special tokens included; bytes that form no character become U+FFFD."""
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


class _Both(dict):
    def __init__(self, first: dict, second: dict):
        super().__init__(second)
        self.first = first

    def __missing__(self, key):
        return self.first[key]


_CODERS: dict[str, ByteBpe] = {}


def coder(vocabulary: str) -> ByteBpe:
    path = tokenizer_path(vocabulary)
    if path not in _CODERS:
        _CODERS[path] = ByteBpe(path)
    return _CODERS[path]


def _map_ids(docs: DataFrame, key: str, text: str, vocabulary: str, schema: str, finish) -> DataFrame:
    names = [part.split()[0] for part in schema.split(", ")]

    def run(batches):
        bpe = coder(vocabulary)
        for batch in batches:
            for start, ids in bpe.blocks(batch.column(1).to_pylist()):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(start, len(ids)), *map(pa.array, finish(bpe, ids))], names=names)

    return docs.select(key, text).mapInArrow(run, schema)


def encode(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and ``ids``, an array of token ids, for each row."""
    kind = docs.schema[key].dataType.simpleString()
    return _map_ids(docs, key, text, vocabulary, f"{key} {kind}, ids array<int>", lambda bpe, ids: [pa.array([np.frombuffer(x, "<u4").astype("i4") for x in ids], pa.list_(pa.int32()))])


def decode(rows: DataFrame, vocabulary: str = "byte_bpe_50k.json", key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """key and ``text`` for each row of ids; null ids give an empty text."""
    kind = rows.schema[key].dataType.simpleString()

    def run(batches):
        bpe = coder(vocabulary)
        for batch in batches:
            texts = [bpe.decode(np.asarray(x or [], "<u4").tobytes()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=[key, "text"])

    return rows.select(key, ids).mapInArrow(run, f"{key} {kind}, text string")


def op5_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every whole text of documents encoded and decoded, as counts and digests."""

    def digests(bpe: ByteBpe, ids: list[bytes]) -> list:
        sha = lambda x: hashlib.sha256(x).hexdigest()
        return [[len(x) // 4 for x in ids], [sha(x) for x in ids], [sha(bpe.decode(x).encode()) for x in ids]]

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    return _map_ids(table(spark, sf_dir, "documents"), "doc_id", "text", "byte_bpe_50k.json", schema, digests)


QUERIES = {"op5_bpe_round_trip": op5_bpe_round_trip}
