"""Harmonic packing of documents into token sequences.

A piece of n tokens belongs to the class floor(capacity / n); a sequence of class i takes a fixed number i of pieces,
so classes fill without looking at one another and each group of pieces packs on its own. Documents may be cut:

* ``cut="halves"`` (capacity a power of two): pieces are the powers of two that add up to the document. Each class then
  fills its sequences exactly, and what is left over in a class at the end forms sequences whose lengths are powers of
  two, so nothing is padded. Only the classes 1, 2, 4, ... are in use then, and a document has several pieces;
* ``cut="overlong"``: only documents longer than a sequence are cut; the classes are the plain harmonic ones, and a
  sequence of class i is padded by up to a share of 1 / (i + 1).

``figures`` reports classes, pieces a document and padding of both.

Null and empty texts have only the end token. Repeated rows are packed one by one. Very long texts are cut over many
sequences. An empty table gives no pieces. Columns of other names are not read. Groups are chosen by a hash of the
piece and hold about ``group_rows`` documents at any size of the corpus; only numbers are shuffled, never texts.
"""

from __future__ import annotations

import json
import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bpe import byte_alphabet
from .common import single_thread, table, tokenizer_path

#: separators that Arrow's split takes for white space and the vocabulary's pattern does not
ODD = "[\\x{1c}-\\x{1f}]"
#: characters that this module leaves to the library: number signs that aren't digits, İ, and all beyond the Latin blocks
RARE = "[\\x{b2}\\x{b3}\\x{b9}\\x{bc}-\\x{be}\\x{130}\\x{250}-\\x{10ffff}]|<\\|"
# fixed value: how the vocabulary splits words, for the characters that are left; and line ends
STEMS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\w\s]|_)+|\n")
NEVER = np.int32(2**31 - 1)


def _spread(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Positions of many ranges end to end."""
    ends = np.cumsum(n)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(first - ends + n, n)


def _bounds(sizes: np.ndarray) -> np.ndarray:
    return np.concatenate((np.zeros(1, np.int64), np.cumsum(sizes)))


class WordEncoder:
    """Ids of whole texts under a vocabulary that never merges across white space. The distinct words of a block are
    found on Arrow's columns, and their distinct stems merged together: each round takes the lowest pair of every stem
    that has one, the leftmost first. Nothing is kept from block to block, so memory is bounded by a block's bytes."""

    def __init__(self, path: str, widths: tuple[int, ...] = (8, 16, 32)):
        single_thread()
        from tokenizers import Tokenizer

        self.library, self.widths = Tokenizer.from_file(path), widths
        self.library.no_truncation()
        self.library.no_padding()
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab, suffix, alphabet = model["vocab"], model["end_of_word_suffix"], byte_alphabet()
        self.inner, self.last = np.zeros(256, np.int32), np.zeros(256, np.int32)
        for c, b in alphabet.items():
            self.inner[b], self.last[b] = vocab[c], vocab[c + suffix]
        self.size = max(vocab.values()) + 1
        merges = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        codes = np.array([vocab[a] * self.size + vocab[b] for a, b in merges], np.int64)
        order = np.argsort(codes)
        self.codes, self.ranks = codes[order], order.astype(np.int32)
        self.made = np.array([vocab[a + b] for a, b in merges], np.int32)

    def _ask(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, sizes) by the library."""
        found = [e.ids for k in range(0, len(texts), 20_000) for e in self.library.encode_batch_fast(texts[k : k + 20_000], add_special_tokens=False)]
        return np.array([i for ids in found for i in ids], np.uint32), np.array([*map(len, found)], np.int64)

    def _rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        code = a.astype(np.int64) * self.size + b
        at = np.minimum(np.searchsorted(self.codes, code), len(self.codes) - 1)
        return np.where((self.codes[at] == code) & (a >= 0) & (b >= 0), self.ranks[at], NEVER)

    def _merged(self, symbols: np.ndarray, ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, sizes) of stems given as rows of symbols, filled up with -1."""
        row, done = np.arange(len(symbols)), []
        while len(row):
            at = ranks.argmin(axis=1) if ranks.shape[1] else np.zeros(len(row), np.int64)
            best = ranks[np.arange(len(row)), at] if ranks.shape[1] else np.full(len(row), NEVER)
            end = best == NEVER
            if end.any():
                done.append((row[end], symbols[end]))
                go = ~end
                row, symbols, ranks, at, best = row[go], symbols[go], ranks[go], at[go], best[go]
            if not len(row):
                break
            own, wide = np.arange(len(row)), ranks.shape[1]
            stay = np.ones(symbols.shape, bool)
            stay[own, at + 1] = False
            symbols = symbols[stay].reshape(len(row), wide)
            symbols[own, at] = self.made[best]
            stay = np.ones(ranks.shape, bool)
            stay[own, at] = False
            ranks = ranks[stay].reshape(len(row), wide - 1)
            for near in (at - 1, at):
                some = np.flatnonzero((near >= 0) & (near < wide - 1))
                ranks[some, near[some]] = self._rank(symbols[some, near[some]], symbols[some, near[some] + 1])
        rows = np.concatenate([r for r, _ in done])
        sizes = np.concatenate([(s >= 0).sum(axis=1) for _, s in done])
        ids = np.concatenate([s[s >= 0] for _, s in done])
        starts = _bounds(sizes)
        back = np.argsort(rows)
        return ids[_spread(starts[back], sizes[back])].astype(np.uint32), sizes[back]

    def _stems(self, stems: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids, sizes) of distinct lower-cased stems."""
        raw = pa.concat_arrays([stems.cast(pa.large_binary())])
        _, spots, data = raw.buffers()
        starts = np.frombuffer(spots, np.int64)[raw.offset : raw.offset + len(raw) + 1]
        octets = np.frombuffer(data, np.uint8)[: starts[-1]] if data is not None else np.zeros(0, np.uint8)
        length = np.diff(starts)
        flat, full = self.inner[octets], length > 0
        flat[starts[1:][full] - 1] = self.last[octets[starts[1:][full] - 1]]
        parts, low = [], 0
        for width in self.widths:
            rows = np.flatnonzero((length > low) & (length <= width))
            for k in range(0, len(rows), 200_000):
                some = rows[k : k + 200_000]
                symbols = np.full((len(some), width), -1, np.int32)
                symbols[np.arange(width) < length[some][:, None]] = flat[_spread(starts[some], length[some])]
                ranks = self._rank(symbols[:, :-1], symbols[:, 1:])
                parts.append((some, *self._merged(symbols, ranks)))
            low = width
        long = np.flatnonzero(length > low)
        if len(long):
            parts.append((long, *self._ask(stems.take(pa.array(long)).to_pylist())))
        sizes = np.zeros(len(length), np.int64)
        for rows, _, n in parts:
            sizes[rows] = n
        out, at = np.zeros(int(sizes.sum()), np.uint32), _bounds(sizes)
        for rows, ids, n in parts:
            out[_spread(at[rows], n)] = ids
        return out, sizes

    def _words(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids, sizes) of distinct words."""
        rare = pc.match_substring_regex(words, RARE).to_numpy(zero_copy_only=False)
        plain = pc.utf8_is_alpha(words).to_numpy(zero_copy_only=False) & ~rare
        mixed = np.flatnonzero(~rare & ~plain)
        own = STEMS.findall("\n".join(pc.utf8_lower(words.take(pa.array(mixed))).to_pylist())) if len(mixed) else []
        ends = np.array([i for i, s in enumerate(own) if s == "\n"] + [len(own)], np.int64)
        per = np.diff(np.concatenate(([-1], ends))) - 1
        held = pa.array([s for s in own if s != "\n"], pa.large_string())
        lowered = pc.utf8_lower(words.filter(pa.array(plain))).cast(pa.large_string())
        stems = pa.concat_arrays([lowered, held]).dictionary_encode()
        ids, sizes = self._stems(stems.dictionary)
        starts, which = _bounds(sizes), stems.indices.to_numpy()
        n_stems = plain.astype(np.int64)  # stems of each word, and where the first stands in ``which``
        first = np.cumsum(plain) - plain
        n_stems[mixed], first[mixed] = per[: len(mixed)], len(lowered) + np.cumsum(per[: len(mixed)]) - per[: len(mixed)]
        asked, asked_sizes = self._ask(words.filter(pa.array(rare)).to_pylist())
        named = which[_spread(first, n_stems)]
        cuts = _bounds(sizes[named])
        at = _bounds(n_stems)
        out_sizes = cuts[at[1:]] - cuts[at[:-1]]
        out_sizes[rare] = asked_sizes
        out, spot = np.zeros(int(out_sizes.sum()), np.uint32), _bounds(out_sizes)
        out[_spread(spot[:-1][~rare], out_sizes[~rare])] = ids[_spread(starts[named], sizes[named])]
        out[_spread(spot[:-1][rare], asked_sizes)] = asked
        return out, out_sizes

    def encode_block(self, texts: pa.Array, tail: tuple[int, ...] = ()) -> tuple[np.ndarray, np.ndarray]:
        """(ids, bounds): the ids of all texts end to end, ``tail`` after each, and where each text's begin and end."""
        texts = texts.cast(pa.large_string()).fill_null("")
        odd = np.flatnonzero(pc.match_substring_regex(texts, ODD).to_numpy(zero_copy_only=False))
        asked, asked_sizes = self._ask(texts.take(pa.array(odd)).to_pylist()) if len(odd) else (np.zeros(0, np.uint32), np.zeros(0, np.int64))
        if len(odd):
            mask = np.zeros(len(texts), bool)
            mask[odd] = True
            texts = pc.if_else(pa.array(mask), "", texts)
        split = pc.utf8_split_whitespace(texts)
        ends = split.offsets.to_numpy()[1:] - split.offsets[0].as_py()
        coded = split.flatten().dictionary_encode()
        ids, sizes = self._words(coded.dictionary)
        # an odd text, left empty above, has one word: an entry of its own beyond the dictionary; the tail is one more
        words = coded.indices.to_numpy().astype(np.int64)
        words[ends[odd] - 1] = len(sizes) + np.arange(len(odd))
        words = np.insert(words, ends, len(sizes) + len(odd))
        ids, sizes = np.concatenate((ids, asked, np.array(tail, np.uint32))), np.concatenate((sizes, asked_sizes, [len(tail)]))
        starts, n = _bounds(sizes)[:-1], sizes[words]
        return ids[_spread(starts[words], n)], np.concatenate(([0], np.cumsum(n)[ends + np.arange(len(ends))]))

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        if not texts:
            return []
        ids, bounds = self.encode_block(pa.array(texts, pa.large_string()))
        return [ids[a:b].astype("<u4").tobytes() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]


_ENCODERS: dict[str, WordEncoder] = {}


def cuts(n: int, capacity: int, cut: str) -> list[int]:
    """The lengths of a document's pieces, in order."""
    whole, rest = [capacity] * (n // capacity), n % capacity
    if cut == "overlong":
        return whole + [rest] * bool(rest)
    return whole + [1 << k for k in range(rest.bit_length() - 1, -1, -1) if rest >> k & 1]


def pieces(docs: DataFrame, capacity: int, cut: str, vocabulary: str, end: int, key: str = "doc_id", text: str = "text", block_bytes: int = 16_000_000) -> DataFrame:
    """Every document's pieces: key, start, length, ids_crc32, doc_tokens."""
    names = [key, "start", "length", "ids_crc32", "doc_tokens"]

    def run(batches):
        path = tokenizer_path(vocabulary)
        if path not in _ENCODERS:
            _ENCODERS[path] = WordEncoder(path)
        for batch in batches:
            if not batch.num_rows:
                continue
            total = np.cumsum(pc.binary_length(batch.column(1)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64))
            # a block ends where the next text would take it past the limit; a text beyond the limit is one alone
            edges = [0]
            while edges[-1] < batch.num_rows:
                before = total[edges[-1] - 1] if edges[-1] else 0
                edges.append(max(edges[-1] + 1, int(np.searchsorted(total, before + block_bytes, side="right"))))
            for a, z in zip(edges[:-1], edges[1:], strict=True):
                ids, bounds = _ENCODERS[path].encode_block(batch.column(1).slice(a, z - a), (end,))
                octets = memoryview(ids.astype("<u4").tobytes())
                sizes = np.diff(bounds)
                parts = [cuts(n, capacity, cut) for n in sizes.tolist()]
                length = np.array([n for p in parts for n in p], np.int64)
                count = np.array([*map(len, parts)], np.int64)
                stop = np.cumsum(length)
                crc = [zlib.crc32(octets[4 * (e - n) : 4 * e]) for e, n in zip(stop.tolist(), length.tolist(), strict=True)]
                rows = np.repeat(np.arange(a, z), count)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows)), pa.array(stop - length - np.repeat(bounds[:-1], count)), pa.array(length), pa.array(crc, pa.int64()), pa.array(np.repeat(sizes, count))], names=names)

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(key, text).mapInArrow(run, f"{key} {kind}, start long, length long, ids_crc32 long, doc_tokens long")


def pack(docs: DataFrame, capacity: int = 4096, cut: str = "halves", vocabulary: str = "word_bpe_49k.json", end: int = 2, group_rows: int = 4000, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Pieces with ``sequence_id`` and ``offset``. The number of documents is counted first, from file footers."""
    if cut not in ("halves", "overlong") or capacity < 1 or cut == "halves" and capacity & (capacity - 1):
        raise ValueError("halves need a capacity that is a power of two")
    groups = max(1, -(-docs.count() // group_rows))
    own = pieces(docs, capacity, cut, vocabulary, end, key, text)
    own = own.withColumns({"__group": F.pmod(F.xxhash64(key, "start", "ids_crc32", "doc_tokens"), F.lit(groups)), "__class": F.expr(f"{capacity} div length")})
    spot = Window.partitionBy("__group", "__class")
    ranked = own.withColumns({"__r": F.row_number().over(spot.orderBy(F.col(key), "start", "ids_crc32", "doc_tokens")).cast("long") - 1, "__m": F.count("*").over(spot)})
    sequence = F.col("__group") * F.lit(capacity + 1) + F.col("__class")
    if cut == "overlong":
        ranked = ranked.withColumn("__s", F.expr("__r div __class"))
        before = Window.partitionBy("__group", "__class", "__s").orderBy("__r").rowsBetween(Window.unboundedPreceding, -1)
        ranked = ranked.withColumn("offset", F.coalesce(F.sum("length").over(before), F.lit(0)))
    else:
        ranked = ranked.withColumns({"__full": F.expr("__m div __class"), "__left": F.expr("__m % __class")})
        ranked = ranked.withColumn("__q", F.expr("__r - __full * __class"))
        # the rest, __left pieces, goes to runs of 2^j, one for each bit of __left from the top; j: the highest bit in which __q differs
        ranked = ranked.withColumn("__j", F.when(F.col("__q") >= 0, F.length(F.bin(F.col("__left").bitwiseXOR(F.col("__q")))) - 1))
        ranked = ranked.withColumn("__s", F.when(F.col("__q") < 0, F.expr("__r div __class")).otherwise(F.expr("__full + bit_count(shiftright(__left, __j + 1))")))
        ranked = ranked.withColumn("offset", F.col("length") * F.when(F.col("__q") < 0, F.expr("__r % __class")).otherwise(F.expr("__q - shiftleft(shiftright(__left, __j + 1), __j + 1)")))
    number = F.shiftleft(sequence, 24) + F.col("__s")
    return ranked.withColumn("sequence_id", number).select(key, "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


def figures(packed: DataFrame, capacity: int = 4096, key: str = "doc_id") -> DataFrame:
    """One row: pieces, documents, classes in use, sequences, tokens and padding (to the capacity, except at a power of two)."""
    held = packed.groupBy("sequence_id").agg(F.sum("length").alias("held"), F.count("*").alias("pieces"))
    fill = F.when(F.bit_count("held") == 1, 0).otherwise(F.lit(capacity) - F.col("held"))
    by = held.agg(F.sum("pieces").alias("pieces"), F.count("*").alias("sequences"), F.sum("held").alias("tokens"), F.sum(fill).cast("long").alias("padding"))
    whole = packed.agg(F.sum(F.when(F.col("start") == 0, 1).otherwise(0)).cast("long").alias("documents"), F.countDistinct(F.expr(f"{capacity} div length")).alias("classes"))
    return by.crossJoin(whole)  # one row each


def packing_figures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``figures`` of all documents under both ways to cut."""
    docs, out = table(spark, sf_dir, "documents"), None
    for cut in ("halves", "overlong"):
        row = figures(pack(docs, cut=cut)).withColumn("cut", F.lit(cut))
        out = row if out is None else out.unionByName(row)
    return out


def op10_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 4096 tokens, the end token included."""
    return pack(table(spark, sf_dir, "documents"))


QUERIES = {"op10_harmonic_packing": op10_harmonic_packing, "packing_figures": packing_figures}
