"""URL rules through a cascade of Bloom filters: exact membership without a join.

A rule names a host (and so all its subdomains) and a path prefix. The keys that a URL offers are every suffix of its
host at a dot together with every prefix of its path of a length that some rule has. The first level of the cascade
encodes the listed keys; the keys of the corpus that it lets through by mistake make the second level; the listed keys
that this one lets through make the third; and so on until a level makes no mistake. Over the corpus's complete key
universe the answer is therefore exact. A second cascade over the listed keys holds those that block.

The first level's size is set so that its mistakes number about as many as the rules, whatever the corpus: only they
reach the driver, and what each task carries is bounded by the rules. A URL that no listed key fits is allowed. Null
URLs, and those without ``://``, have an empty host and path and fit no rule. Repeated URLs get equal answers.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_columns, table


class Bloom:
    def __init__(self, keys: list[str], rate: float, salt: int):
        self.bits = max(8, math.ceil(-len(keys) * math.log(rate) / math.log(2) ** 2))
        self.hashes, self.salt = max(1, round(self.bits / max(1, len(keys)) * math.log(2))), salt
        field = np.zeros(self.bits, bool)
        for k in keys:
            field[self._spots(k)] = True
        self.field = np.packbits(field, bitorder="little").tobytes()

    def _spots(self, key: str) -> list[int]:
        h = xxhash.xxh3_128_intdigest(key.encode(), self.salt)
        a, b = h & (2**64 - 1), h >> 64 | 1
        return [((a + i * b) & (2**64 - 1)) % self.bits for i in range(self.hashes)]

    def __contains__(self, key: str) -> bool:
        return all(self.field[i >> 3] >> (i & 7) & 1 for i in self._spots(key))


@dataclass(frozen=True)
class Cascade:
    """Levels alternate between listed keys and the others' mistakes; exact on the universe it was built over."""

    levels: tuple[Bloom, ...]

    def __contains__(self, key: str) -> bool:
        for depth, level in enumerate(self.levels):
            if key not in level:
                return depth % 2 == 1
        return len(self.levels) % 2 == 1

    @staticmethod
    def build(first: Bloom, listed: list[str], mistakes: list[str], rate: float = 0.5) -> Cascade:
        levels, inside, outside = [first], sorted(listed), sorted(mistakes)
        while outside:
            levels.append(Bloom(outside, rate, len(levels)))
            inside, outside = outside, [k for k in inside if k in levels[-1]]
            # from here the roles swap: ``inside`` is encoded by the last level, ``outside`` passed it by mistake
        return Cascade(tuple(levels))


@dataclass(frozen=True)
class Rules:
    """host + path -> allow or block."""

    verdicts: dict[str, str]

    def lengths(self) -> list[int]:
        return sorted({len(k) - k.index("/") for k in self.verdicts}, reverse=True)


def key_candidates(host: str, path: str, lengths: list[int]) -> list[str]:
    """Every key that the URL offers, longest first; of equal length the longer host comes first."""
    labels = host.split(".") if host else []
    suffixes = [".".join(labels[i:]) for i in range(len(labels))]
    keys = [(s, path[:n]) for s in suffixes for n in lengths if n <= len(path)]
    return [s + p for s, p in sorted(keys, key=lambda k: (-len(k[0]) - len(k[1]), -len(k[0])))]


def split_url(url: F.Column) -> tuple[F.Column, F.Column]:
    after = F.regexp_extract(url, r"(?s)\A.*?://(.*)\z", 1)
    host = F.regexp_extract(after, r"(?s)\A([^/?#]*)", 1)
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    path = F.regexp_extract(after, r"(?s)\A[^/?#]*([^?#]*)", 1)
    return F.coalesce(F.translate(host, upper, upper.lower()), F.lit("")), F.coalesce(path, F.lit(""))


def build_cascades(parts: DataFrame, rules: Rules) -> tuple[Cascade, Cascade]:
    """From ``parts`` (host, path): one pass finds the first level's mistakes among the keys of all rows. Of a path only
    as much is shuffled as a rule can have."""
    lengths, listed = rules.lengths(), sorted(rules.verdicts)

    def offered(hosts, paths):
        return [[k for h, p in zip(hosts.to_pylist(), paths.to_pylist(), strict=True) for k in key_candidates(h, p, lengths)]]

    size, known = parts.count() * 8, frozenset(listed)  # rows from file footers; a URL offers a few keys
    universe = parts.select("host", F.substring("path", 1, max(lengths, default=0)).alias("path")).distinct()
    rate = min(0.5, max(1e-9, len(listed) * math.sqrt(0.5) / max(1, size)))
    while True:
        first = Bloom(listed, rate, 0)

        def passed(hosts, paths, first=first):
            keys = {k for own in offered(hosts, paths) for k in own}
            return [[k for k in keys if k not in known and k in first]]

        most = max(1000, 100 * len(listed))
        mistakes = [r[0] for r in map_columns(universe, passed, "key string", ["host", "path"]).distinct().limit(most + 1).collect()]
        if len(mistakes) <= most:  # about len(listed), at any size
            break
        rate /= 64
    blocked = [k for k in listed if rules.verdicts[k] == "block"]
    gate = Bloom(blocked or [""], 0.5, 0)
    return Cascade.build(first, listed, mistakes), Cascade.build(gate, blocked, [k for k in listed if rules.verdicts[k] != "block" and k in gate])


def judge_urls(pages: DataFrame, rules: Rules, key: str = "page_id", url: str = "url") -> DataFrame:
    """key, host, path, rule (null if none fits), verdict."""
    host, path = split_url(F.col(url))
    parts = pages.select(F.col(key).alias("__key"), host.alias("host"), path.alias("path"))
    listed, blocking = build_cascades(parts.select("host", "path"), rules)
    lengths = rules.lengths()

    def judge(keys, hosts, paths):
        found = [next((k for k in key_candidates(h, p, lengths) if k in listed), None) for h, p in zip(hosts.to_pylist(), paths.to_pylist(), strict=True)]
        return [keys, hosts, paths, pa.array(found, pa.string()), ["block" if k is not None and k in blocking else "allow" for k in found]]

    kind = pages.schema[key].dataType.simpleString()
    return map_columns(parts, judge, f"{key} {kind}, host string, path string, rule string, verdict string", ["__key", "host", "path"])


#: The rules of the registered query.
PAGE_RULES = Rules({"com/": "allow", "example.com/en/": "block", "www.example.com/en/": "allow", "net/es/": "block", "net/fr/": "block"})


def op4_url_verdicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page's URL under PAGE_RULES."""
    return judge_urls(table(spark, sf_dir, "pages"), PAGE_RULES)


ORACLE_OP4 = r"""WITH parts AS (SELECT page_id, coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), '') AS h,
    coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
  low AS (SELECT page_id, translate(h, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, path FROM parts),
  fits AS (SELECT *, CASE
    WHEN ('.' || host) LIKE '%.www.example.com' AND starts_with(path, '/en/') THEN 'www.example.com/en/'
    WHEN ('.' || host) LIKE '%.example.com' AND starts_with(path, '/en/') THEN 'example.com/en/'
    WHEN ('.' || host) LIKE '%.net' AND starts_with(path, '/es/') THEN 'net/es/'
    WHEN ('.' || host) LIKE '%.net' AND starts_with(path, '/fr/') THEN 'net/fr/'
    WHEN ('.' || host) LIKE '%.com' AND starts_with(path, '/') THEN 'com/' END AS rule FROM low)
SELECT page_id, host, path, rule, CASE WHEN rule IN ('example.com/en/', 'net/es/', 'net/fr/') THEN 'block' ELSE 'allow' END AS verdict FROM fits"""

QUERIES = {"op4_url_verdicts": op4_url_verdicts}
ORACLE = {"op4_url_verdicts": ORACLE_OP4}
