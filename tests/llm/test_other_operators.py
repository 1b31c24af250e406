from __future__ import annotations

import gzip
import random
import struct
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from curvetree.llm import common, embeddings, media, passages, registry, sharding, simhash, toxicity, urlfilter
from tests.oracle import assert_same, connect

from .conftest import TEXTS


@pytest.mark.parametrize("name", sorted(registry.ORACLE))
def test_same_as_sql(name, spark, sf_dir):
    assert_same(registry.QUERIES[name](spark, sf_dir), connect(sf_dir), registry.ORACLE[name])


# -- 1 ----------------------------------------------------------------------------------------------------------------
def jump(key: int, n: int) -> int:
    key, b, j = key % 2**64, -1, 0
    while j < n:
        b, key = j, (key * 2862933555777941757 + 1) % 2**64
        j = int((b + 1) * (2.0**31 / ((key >> 33) + 1)))
    return b


def test_jump_shards(spark):
    keys = [0, 1, -1, 2**63 - 1, -(2**63), None, *range(1000, 1200)]
    df = spark.createDataFrame([(k,) for k in keys], "k long")
    for n in (1, 2, 8, 70):
        got = {r[0]: r[1] for r in df.select("k", sharding.jump_shard(F.col("k"), n)).collect()}
        assert got == {k: jump(k or 0, n) for k in keys}
        assert all(jump(k or 0, n + 1) in (v, n) for k, v in got.items())


def test_slots_are_gapless(odd_docs, no_docs):
    rows = sharding.assign_shards(odd_docs, "doc_id", 3, buckets=4).collect()
    assert len(rows) == len(TEXTS) and sharding.assign_shards(no_docs, "doc_id", 3).count() == 0
    for s in range(3):
        own = sorted(r["slot"] for r in rows if r["shard"] == s)
        assert own == [*range(len(own))]


# -- 3 ----------------------------------------------------------------------------------------------------------------
def brute_fingerprint(text, k):
    words = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = [w for w in __import__("re").split(r"[\x20\x09-\x0D]+", words) if w]
    grams = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)] or ([" ".join(words)] if words else [])
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def components(nodes, linked):
    root = {n: n for n in nodes}

    def find(n):
        while root[n] != n:
            n = root[n]
        return n

    for a, b in linked:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    return {n: find(n) for n in nodes}


def test_fingerprints():
    for t in TEXTS:
        assert simhash.fingerprint(t, 4) % 2**64 == brute_fingerprint(t, 4)


@pytest.mark.parametrize(("distance", "segments"), [(4, 3), (4, 2), (8, 3), (4, 5), (1, 4)])
def test_links_are_complete(spark, distance, segments):
    rng = random.Random(1)
    fps = {rng.getrandbits(64) for _ in range(60)}
    for f in [*fps]:
        for _ in range(4):
            near = f
            for b in rng.sample(range(64), rng.randint(1, distance + 2)):
                near ^= 1 << b
            fps.add(near)
    signed = {i: f - 2**64 if f >= 2**63 else f for i, f in enumerate(sorted(fps))}
    got = {tuple(r) for r in simhash.links(spark.createDataFrame([*signed.items()], "node long, fp long"), distance, segments).collect()}
    values = {i: f % 2**64 for i, f in signed.items()}
    assert got == {(a, b) for a in values for b in values if a < b and (values[a] ^ values[b]).bit_count() <= distance}


def test_hubs_of_a_dense_group(spark):
    """Few links inside a dense group, all of them true; with the links between groups the components are those of all links."""
    rng = random.Random(3)
    centre = rng.getrandbits(64)
    fps = {rng.getrandbits(64) for _ in range(20)} | {centre ^ (1 << i) ^ (1 << j) for i in range(0, 64, 2) for j in range(1, 12, 2)}
    values = dict(enumerate(sorted(fps)))
    true = {(a, b) for a in values for b in values if a < b and (values[a] ^ values[b]).bit_count() <= 4}
    reps = spark.createDataFrame([(i, f - 2**64 if f >= 2**63 else f) for i, f in values.items()], "node long, fp long")
    hubs = [tuple(sorted(r)) for r in simhash.hub_links(reps, 4, 3).collect()]
    assert {*hubs} <= true and len(hubs) <= 4 * 3 * len(values) < len(true)
    group = components(values, hubs)
    grouped = spark.createDataFrame([(group[i], f) for i, f in reps.collect()], "group long, fp long")
    between = [tuple(r) for r in simhash.links(grouped, 4, 3, group="group").collect()]
    assert components(values, hubs + between) == components(values, true)


def test_simhash_query(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()
    fp = {r["doc_id"]: brute_fingerprint(r["text"], 4) for r in docs}
    want = components(fp, [(a, b) for a in fp for b in fp if a < b and (fp[a] ^ fp[b]).bit_count() <= 4])
    for r in simhash.op3_simhash_groups(spark, sf_dir).collect():
        assert (r["fingerprint"], r["component_id"]) == (f"{fp[r['doc_id']]:016x}", want[r["doc_id"]])


def test_keep_one(spark, odd_docs, no_docs):
    kept = simhash.keep_one(odd_docs)
    assert kept.columns == odd_docs.columns and simhash.keep_one(no_docs).count() == 0
    ids = [r["doc_id"] for r in kept.collect()]
    assert 5 in ids and 6 not in ids and None in ids
    again = simhash.keep_one(odd_docs.union(odd_docs.filter("doc_id = 5")))
    assert [r["doc_id"] for r in again.collect()].count(5) == 1


def test_components(spark):
    pairs = [(i, i + 1) for i in range(50)] + [(100, i) for i in range(101, 130)] + [(200, 200), (None, 3), (300, 299)]
    got = dict(map(tuple, common.connected_components(spark.createDataFrame(pairs, "src long, dst long")).collect()))
    assert got == {**dict.fromkeys(range(51), 0), **dict.fromkeys(range(100, 130), 100), 300: 299, 299: 299}


# -- 4 ----------------------------------------------------------------------------------------------------------------
def test_cascade_is_exact():
    rng = random.Random(2)
    listed, others = [[f"{p}{rng.random()}" for _ in range(n)] for p, n in (("a", 300), ("b", 5000))]
    first = urlfilter.Bloom(listed, 0.05, 0)
    cascade = urlfilter.Cascade.build(first, listed, [k for k in others if k in first])
    assert all(k in cascade for k in listed) and not any(k in cascade for k in others) and len(cascade.levels) > 2


def test_urls(spark):
    urls = [None, "", "nourl", "http://", "http://COM/", "http://x.com", "http://x.com/", "https://www.example.com/en/a?b#c", "http://a.www.example.com/en/", "http://example.com/en", "http://badexample.com/en/1", "http://a.net/es/", "ftp://net/fr/x://y.com/", "http://x.com?q=/en/", "http://x.com/", "http://x\ny.com/en/\n", "http://com./"]
    df = spark.createDataFrame([(i, u, "z") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r["page_id"]: r for r in urlfilter.judge_urls(df, urlfilter.PAGE_RULES).collect()}
    for i, u in enumerate(urls):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        cut = next((k for k, c in enumerate(rest) if c in "/?#"), len(rest))
        host, path = rest[:cut].lower(), rest[cut:].split("?")[0].split("#")[0]
        fit = [k for k in urlfilter.PAGE_RULES.verdicts if (host == k.split("/")[0] or host.endswith("." + k.split("/")[0])) and path.startswith(k[k.index("/") :])]
        rule = max(fit, key=len, default=None)
        assert (got[i]["host"], got[i]["path"], got[i]["rule"], got[i]["verdict"]) == (host, path, rule, urlfilter.PAGE_RULES.verdicts.get(rule, "allow"))
    assert urlfilter.judge_urls(df.filter("1 = 0"), urlfilter.PAGE_RULES).count() == 0


# -- 6 ----------------------------------------------------------------------------------------------------------------
def png() -> bytes:
    chunk = lambda n, d: struct.pack(">I", len(d)) + n + d + struct.pack(">I", zlib.crc32(n + d))
    return b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", 1, 1, 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(b"\0\0")) + chunk(b"IEND", b"")


GIF = b"GIF89a\x01\0\x01\0\x80\0\0\0\0\0\xff\xff\xff,\0\0\0\0\x01\0\x01\0\0\x02\x02D\x01\0;"
JPEG = b"\xff\xd8\xff\xe0\0\x04ab\xff\xda\0\x04cd\x12\xff\0\x34\xff\xd9"
PDF = b"%PDF-1.4\n1 0 obj\nendobj\nstartxref\n0\n%%EOF"


@pytest.mark.parametrize(("kind", "blob"), [("png", png()), ("gif", GIF), ("jpeg", JPEG), ("pdf", PDF), ("gzip", gzip.compress(b"hello")), ("wav", media.to_wav(b"abc"))])
def test_sniffing(kind, blob):
    assert media.sniff(blob) == (kind, len(blob), [])
    assert media.sniff(b"junk" + blob + b"tail")[2] == [(kind, 4, len(blob))]
    assert media.sniff(blob[:-1])[0] == "unknown" and media.sniff(blob[:-1])[2] == []


def flac(frames: int, total: int | None = None) -> bytes:
    """Mono, 16 bits, 192 constant samples a frame."""

    def crc(data: bytes, poly: int, bits: int) -> int:
        v = 0
        for x in data:
            v ^= x << bits - 8
            for _ in range(8):
                v = (v << 1 ^ (poly if v >> bits - 1 else 0)) & (1 << bits) - 1
        return v

    n = frames * 192 if total is None else total
    info = struct.pack(">HH", 192, 192) + b"\0" * 6 + (44100 << 44 | 0 << 41 | 15 << 36 | n).to_bytes(8, "big") + b"\0" * 16
    out = b"fLaC" + struct.pack(">I", 0x80 << 24 | 34) + info
    for i in range(frames):
        head = bytes([0xFF, 0xF8, 0x19, 0x08, i])
        frame = head + bytes([crc(head, 7, 8)]) + b"\0" + struct.pack(">h", 300 * i - 99)
        out += frame + struct.pack(">H", crc(frame, 0x8005, 16))
    return out


def riff(form: bytes, *chunks: tuple[bytes, bytes]) -> bytes:
    body = b"".join(n + struct.pack("<I", len(d)) + d + b"\0" * (len(d) % 2) for n, d in chunks)
    return b"RIFF" + struct.pack("<I", 4 + len(body)) + form + body


@pytest.mark.parametrize(("kind", "blob"), [("flac", flac(3)), ("flac", flac(1)), ("webp", riff(b"WEBP", (b"VP8L", b"/abcd"))), ("avi", riff(b"AVI ", (b"LIST", b"hdrlabcd"), (b"LIST", b"movi"))), ("pdf", PDF + b"\n1 0 obj\nendobj\nstartxref\n9\n%%EOF")])
def test_true_lengths(kind, blob):
    assert media.sniff(blob) == (kind, len(blob), [])
    assert media.sniff(b"junk" + blob + png() + b"tail")[2] == [(kind, 4, len(blob)), ("png", 4 + len(blob), len(png()))]


def test_empty_forms_are_no_media():
    for blob in (riff(b"WEBP"), riff(b"AVI "), riff(b"WEBP", (b"VP8 ", b"")), riff(b"WAVE", (b"data", b"ab")), flac(3)[:-9], flac(3, 999)):
        assert media.sniff(blob) == ("unknown", 0, [])
    unknown_total = flac(3, 0)
    assert media.sniff(unknown_total) == ("flac", len(unknown_total), [])


@pytest.mark.parametrize("text", [b"%PDF-1.4 startxref ", b"%PDF-", b"GIF89a!!!!!!!!!!!!!!!!!", b"GIF89a", b"\xff\xd8\xff\xe0\0\4ab\xff\xda\0\4cd", b"RIFF\x20\0\0\0WAVE", b"fLaC"])
def test_repeated_magic_takes_linear_time(text):
    import time

    blob = text * (5_000_000 // len(text))
    began = time.perf_counter()
    media.sniff(blob)
    assert time.perf_counter() - began < 15  # seconds; minutes if it were quadratic


def test_sniffing_an_empty_table(spark):
    assert media.sniff_column(spark.createDataFrame([], "id long, blob binary"), "id", "blob").count() == 0


def test_media_columns(spark):
    inside = media.to_wav(b"ab" + png() + GIF)
    rows = [(1, inside, "image/png"), (2, None, None), (3, b"", "wav"), (4, png(), "png"), (5, b"RIFF\xff\xff\xff\xffWAVE", "wav")]
    got = {r["id"]: r for r in media.sniff_column(spark.createDataFrame(rows, "id long, blob binary, said string"), "id", "blob", "said").collect()}
    assert (got[1]["media_type"], got[1]["corrected"], [(e["kind"], e["length"]) for e in got[1]["embedded"]]) == ("wav", True, [("png", len(png())), ("gif", len(GIF))])
    assert [got[i]["media_type"] for i in (2, 3, 4, 5)] == ["unknown", "unknown", "png", "unknown"] and not got[4]["corrected"]


def test_media_query(spark, sf_dir, odd_docs):
    docs = dict(map(tuple, spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()))
    import hashlib

    for r in media.op6_media(spark, sf_dir).collect():
        raw = (docs[r["doc_id"]] or "").encode()
        payload = media.padded(raw)
        assert len(payload) % 64 == 0 and payload.startswith(raw) and len(payload) - len(raw) < 65
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
    assert media.padded(b"") == b"\0" * 64
    stored = media.store_texts(odd_docs).collect()
    assert sorted(media.wav_samples(r["media"])[1] for r in stored) == sorted(media.padded((t or "").encode()) for t in TEXTS)


# -- 7 ----------------------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("block_rows", [8, 64])
def test_embedding_links(spark, block_rows):
    rng = np.random.default_rng(4)
    base = rng.normal(size=(40, 16))
    x = np.concatenate([base, base[:20] + rng.normal(size=(20, 16)) * 0.35, base[:5], base[:3] * 1e-30])
    rows = [(i, v.tolist(), 0) for i, v in enumerate(x)] + [(900, None, 1), (901, [0.0] * 16, 1), (902, [float("nan")] + [1.0] * 15, 1), (903, [None] + [1.0] * 15, 1), (904, [1.0, 2.0], 1), (905, [2.0, 4.0], 1), (906, [], 1), (907, [float("inf")] * 16, 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, node int").repartition(3)
    unit = x / np.linalg.norm(x / np.abs(x).max(axis=1)[:, None], axis=1)[:, None] / np.abs(x).max(axis=1)[:, None]
    close = [(i, j) for i in range(len(x)) for j in range(i) if unit[i] @ unit[j] >= 0.9] + [(904, 905)]
    ids = [r[0] for r in rows]
    want = components(ids, close)
    got = {r["vec_id"]: r for r in embeddings.embedding_links(df, block_rows=block_rows).collect()}
    for i in ids:
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (sum(i in p for p in close), want[i], want[i] == i)
    assert embeddings.embedding_links(df.filter("1 = 0")).count() == 0


def test_tile_bounds_lose_nothing():
    rng = np.random.default_rng(8)
    x = rng.normal(size=(300, 64))
    x[150:] = x[:150] + rng.normal(size=(150, 64)) * np.linspace(0.2, 0.8, 150)[:, None]
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    for t in (0.5, 0.8, 0.9):
        i, j, sure = embeddings.tile_links(embeddings.Coded.of(embeddings.units(x)), None, t)
        want = {(a, b) for a in range(300) for b in range(a + 1, 300) if (unit[a] * unit[b]).sum() >= t}
        found = set(zip(i.tolist(), j.tolist(), strict=True))
        assert want <= found and set(zip(i[sure].tolist(), j[sure].tolist(), strict=True)) <= want and (~sure).sum() <= 3


def test_links_at_the_ends_of_the_doubles(spark):
    """The least and the largest numbers: true cosines, no overflow, no underflow."""
    rows = [(1, [5e-324, 5e-324]), (2, [1.0, 0.0]), (3, [1.7e308, 1.7e308]), (4, [1.0, 1.0]), (5, [-1.7e308, 1.7e308]), (6, [1e-310, 0.0])]
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embeddings.embedding_links(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    assert got == {1: (2, 1), 3: (2, 1), 4: (2, 1), 2: (1, 2), 6: (1, 2), 5: (0, 5)}


def test_open_pairs_are_decided_exactly(spark):
    """Cosines a hair on either side of the threshold."""
    rows = [(0, [1.0] + [0.0] * 15)]
    for i, c in enumerate((0.9 - 1e-9, 0.9 - 1e-12, 0.9 + 1e-12, 0.9 + 1e-9), 1):
        rows.append((i, [c] + [0.0] * i + [float(np.sqrt(1 - c * c))] + [0.0] * (14 - i)))
    got = {r["vec_id"]: r["n_links"] for r in embeddings.embedding_links(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    assert got == {0: 2, 1: 0, 2: 0, 3: 1, 4: 1}


# -- 8 ----------------------------------------------------------------------------------------------------------------
def prose(rng, n):
    return " ".join("".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(n))


def test_passages(spark):
    rng = random.Random(6)
    shared, fuzzy = prose(rng, 80), prose(rng, 120).split()
    changed = [w if i % 11 else "other" for i, w in enumerate(fuzzy)]
    del changed[60]
    texts = {
        1: f"{prose(rng, 200)} {shared} {prose(rng, 50)}", 2: f"{prose(rng, 30)}\n{shared}\n{prose(rng, 300)}", 3: prose(rng, 400), 4: " ".join(fuzzy), 5: f"{prose(rng, 90)} {' '.join(changed)} {prose(rng, 90)}",
        6: prose(rng, 40), 9: None, 10: "", 11: "In. " * 500,
    }
    texts[7], texts[8] = texts[6], texts[3]
    rows = [(i, t, len(t or ""), "x") for i, t in texts.items()] + [(None, texts[3], 5, "x"), (2, texts[2], 0, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_chars long, rep string").repartition(3)
    found = {r["id"]: r["passages"] for r in passages.find_passages(docs).collect()}
    assert found.keys() == {2, 5, 8}
    s = found[2][0]
    assert texts[2][s["start"] : s["end"]] == shared and (s["match_id"], s["n_words"], s["share"]) == (1, 80, 1.0)
    assert found[5][0]["match_id"] == 4 and found[5][0]["n_words"] >= 110 and 0.8 <= found[5][0]["share"] < 1
    assert (found[8][0]["start"], found[8][0]["end"]) == (0, len(texts[3]))
    left = passages.drop_passages(docs)
    assert left.columns == docs.columns and left.count() == len(rows)
    by = {(r["doc_id"], r["n_chars"]): r["text"] for r in left.collect()}
    assert all(n == len(t or "") for (i, n), t in by.items() if i not in (None, 2))
    assert shared not in by[2, len(texts[2]) - 80 * 6 + 1 + 0] if (2, len(texts[2]) - 80 * 6 + 1) in by else True
    assert sum(shared in (t or "") for t in by.values()) == 1
    assert passages.drop_passages(docs.filter("1 = 0")).count() == 0


def test_seeds_guarantee():
    rng = random.Random(9)
    run = passages.word_hashes(prose(rng, 20))
    for _ in range(50):
        a, b = (np.concatenate([passages.word_hashes(prose(rng, rng.randint(0, 40))), run, passages.word_hashes(prose(rng, rng.randint(0, 40)))]) for _ in range(2))
        assert set(passages.seeds(a, 5, 16)[0]) & set(passages.seeds(b, 5, 16)[0])


def test_chaining_is_optimal():
    rng = random.Random(10)
    for _ in range(30):
        blocks = sorted((rng.randint(0, 60), rng.randint(0, 60), rng.randint(2, 6)) for _ in range(8))
        best = passages.chains(blocks, 0.1, 10**9)[0]

        def score(chain):
            return sum(n for _, _, n in chain) - 0.1 * sum(p - a - m + r - b - m for (a, b, m), (p, r, _) in zip(chain, chain[1:], strict=False))

        def longest(last, rest):
            own = [0.0] + [n - (0.1 * (p - last[0] - last[2] + r - last[1] - last[2]) if last else 0) + longest((p, r, n), rest[i + 1 :]) for i, (p, r, n) in enumerate(rest) if not last or (p >= last[0] + last[2] and r >= last[1] + last[2])]
            return max(own)

        assert score(best) == pytest.approx(longest(None, blocks))


# -- 9 ----------------------------------------------------------------------------------------------------------------
def test_classifier_learns_and_ignores_the_held_out_third(spark, odd_docs):
    rng = random.Random(11)
    rows = [(i, f"{prose(rng, 40)} {'idiot' if i % 4 == 0 else 'kind'} {prose(rng, 40)}") for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    wrong = spark.createDataFrame([(i, int((i % 4 == 0) ^ (zlib.crc32(str(i).encode()) % 3 == 1)), 1) for i in range(400)] + [(None, 1, 1)], "doc_id long, toxic int, quality int")
    model = toxicity.fit(docs, wrong)
    scored = toxicity.score_documents(docs, model).collect()
    assert sum(r["predicted"] == (r["doc_id"] % 4 == 0) for r in scored) >= 396
    assert all(0 <= r["score"] <= 1 for r in toxicity.score_documents(odd_docs, model).collect())
    kept = toxicity.drop_toxic(odd_docs, model)
    assert kept.columns == odd_docs.columns
    one_label = toxicity.fit(docs, wrong.filter("toxic = 0"))
    assert one_label.score("idiot") == one_label.score(None) < 0.01


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.1"
    scored = toxicity.op9_toxicity(spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").filter("held_out").collect()
    toxic = [r["predicted"] for r in scored if r["toxic"]]
    clean = [r["predicted"] for r in scored if not r["toxic"]]
    assert sum(toxic) / len(toxic) > 0.8 and sum(clean) / len(clean) < 0.01


# -- pipeline ---------------------------------------------------------------------------------------------------------
def test_pipeline_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    names, at = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = common.materialise(stage(spark, at, sf_dir), name)
        assert at.columns == names and 0 < at.count() <= docs.count()
    packed = corpus_pipeline.STAGES[-1][1](spark, at, sf_dir)
    assert packed.select("doc_id").distinct().count() == at.count()


def test_pipeline_on_odd_rows(spark, sf_dir, odd_docs, no_docs):
    for docs in (odd_docs, no_docs):
        at = docs
        for name, stage in corpus_pipeline.STAGES:
            at = common.materialise(stage(spark, at, sf_dir), name)
    assert at.count() == 0
