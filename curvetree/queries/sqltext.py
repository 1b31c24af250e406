"""SQL of the other engine (DuckDB) for clouds, codes, trees and brute-force searches."""

from __future__ import annotations

from ..functions.curves import orientation_table

DAY = "date_diff('day', DATE '1995-01-01', {0}::DATE)"
CLOUD = {
    "ship": f"SELECT row_number() OVER (ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_shipdate) - 1 AS pid, 20.0::DOUBLE * l_quantity AS x, l_extendedprice / 100.0::DOUBLE AS y, 0.4::DOUBLE * {DAY.format('l_shipdate')} AS z FROM lineitem",
    "order": f"SELECT o_orderkey AS pid, o_totalprice / 500.0::DOUBLE AS x, 0.4::DOUBLE * {DAY.format('o_orderdate')} AS y, o_custkey * 1000.0::DOUBLE / (SELECT count(*)::DOUBLE FROM customer) AS z FROM orders",
    "event": "SELECT event_id AS pid, (epoch_us(ts) - 1704067200000000) / 2592000000.0::DOUBLE AS x, 6.0::DOUBLE * user_id AS y, 2.0::DOUBLE * value AS z FROM events",
    "embed": "SELECT vec_id AS pid, 1000.0::DOUBLE * embedding[1]::DOUBLE AS x, 1000.0::DOUBLE * embedding[2]::DOUBLE AS y, 1000.0::DOUBLE * embedding[3]::DOUBLE AS z FROM embeddings",
    "text": "SELECT doc_id AS pid, n_chars / 10.0::DOUBLE AS x, len(string_split(text, ' '))::DOUBLE AS y, 10.0::DOUBLE * len(string_split(text, chr(10))) AS z FROM documents",
    "part": "SELECT p_partkey AS pid, 0.5::DOUBLE * p_partkey AS x, 20.0::DOUBLE * p_size AS y, 10.0::DOUBLE * (p_retailprice - 900.0::DOUBLE) AS z FROM part",
}
TWO21 = 1 << 21


def cells(cloud: str) -> str:
    """CTEs p (points), g (box), c (cells)."""
    box = ", ".join(f"min({a}) AS l{a}, max({a}) - min({a}) AS e{a}" for a in "xyz")
    cell = ", ".join(f"CASE WHEN e{a} <= 0 THEN 0 ELSE greatest(0, least(floor(({a} - l{a}) / e{a} * {TWO21}.0::DOUBLE)::BIGINT, {TWO21 - 1})) END AS c{a}" for a in "xyz")
    return f"p AS ({CLOUD[cloud]}), g AS (SELECT {box} FROM p), c AS (SELECT p.*, {cell} FROM p, g)"


def morton(cx: str = "cx", cy: str = "cy", cz: str = "cz") -> str:
    # the highest term is 2^62, so nothing overflows
    return " + ".join(f"(({a} >> {b}) & 1) * {1 << (3 * b + 2 - i)}" for b in range(21) for i, a in enumerate((cx, cy, cz)))


def coded(cloud: str, curve: str) -> str:
    """CTEs up to k (points with code and rank idx). Must stand after WITH RECURSIVE."""
    base = cells(cloud)
    if curve == "none":
        code = "SELECT *, 0::BIGINT AS code FROM c"
    elif curve == "morton":
        code = f"SELECT *, ({morton()})::BIGINT AS code FROM c"
    else:
        digit, following, _ = orientation_table()
        rows = ", ".join(f"({s}, {b}, {digit[s, b]}, {following[s, b]})" for s in range(len(digit)) for b in range(8))
        base += f""", turns(state, octant, digit, following) AS (VALUES {rows}),
walk AS (SELECT pid, cx, cy, cz, 20 AS bit, 0::BIGINT AS code, 0 AS state FROM c UNION ALL
  SELECT w.pid, w.cx, w.cy, w.cz, w.bit - 1, w.code * 8 + t.digit, t.following FROM walk w JOIN turns t
  ON t.state = w.state AND t.octant = ((w.cx >> w.bit) & 1) * 4 + ((w.cy >> w.bit) & 1) * 2 + ((w.cz >> w.bit) & 1) WHERE w.bit >= 0)"""
        code = "SELECT c.*, w.code FROM c JOIN walk w ON w.pid = c.pid AND w.bit = -1"
    return base + f", coded AS ({code}), k AS (SELECT *, row_number() OVER (ORDER BY code, pid) - 1 AS idx FROM coded)"


def tree(cloud: str, curve: str, bucket: int) -> str:
    """CTEs up to t (complete tree with ranges)."""
    return coded(cloud, curve) + f""", every AS (SELECT lv AS level, code >> (3 * (21 - lv)) AS prefix, count(*) AS cnt, min(idx) AS idx_lo, max(idx) + 1 AS idx_hi
  FROM k, (SELECT unnest(range(22))::INT AS lv) GROUP BY 1, 2),
full_ AS (SELECT e.* FROM every e LEFT JOIN every u ON u.level = e.level - 1 AND u.prefix = e.prefix >> 3 WHERE e.level = 0 OR u.cnt > {bucket}),
flagged AS (SELECT *, (cnt <= {bucket} OR level = 21) AS is_leaf FROM full_),
kids AS (SELECT level + 1 AS level, prefix * 8 + o AS prefix FROM flagged, (SELECT unnest(range(8)) AS o) WHERE NOT is_leaf),
hollow AS (SELECT kids.* FROM kids ANTI JOIN flagged USING (level, prefix)),
ended AS (SELECT h.*, (SELECT count(*) FROM k WHERE k.code < h.prefix << (3 * (21 - h.level))) AS pos FROM hollow h),
t AS (SELECT level, prefix, is_leaf, cnt, idx_lo, idx_hi FROM flagged UNION ALL SELECT level, prefix, true, 0, pos, pos FROM ended)"""


def sampled(n: int, where: str = "p") -> str:
    return f"q AS (SELECT pid AS cid, x AS qx, y AS qy, z AS qz FROM {where} ORDER BY (pid * 2654435761) % 4294967296, pid LIMIT {n})"


def share(of: float) -> str:
    return f"q AS (SELECT pid AS cid, x AS qx, y AS qy, z AS qz FROM p WHERE (pid * 2654435761) % 4294967296 < {of * 2**32!r}::DOUBLE)"


D2 = "((x - qx) * (x - qx) + (y - qy) * (y - qy) + (z - qz) * (z - qz))"


def hit(kernel: str, r: float) -> str:
    r_ = f"{float(r)!r}::DOUBLE"
    return {
        "sphere": f"{D2} < {r_} * {r_}",
        "circle": f"((x - qx) * (x - qx) + (y - qy) * (y - qy)) < {r_} * {r_}",
        "cube": f"abs(x - qx) < {r_} AND abs(y - qy) < {r_} AND abs(z - qz) < {r_}",
        "square": f"abs(x - qx) < {r_} AND abs(y - qy) < {r_}",
    }[kernel]


def by_id(step: int = 100, where: str = "p") -> str:
    """CTE q: the points whose id is divisible by ``step``."""
    return f"q AS (SELECT pid AS cid, x AS qx, y AS qy, z AS qz FROM {where} WHERE pid % {step} = 0)"


def classified(cloud: str, curve: str, bucket: int, r: float, step: int = 100) -> str:
    """CTEs up to walked (cid, level, prefix, cnt, is_leaf, place): the non-empty nodes that a pruning search with a sphere
    visits, those whose parent is neither outside nor wholly inside."""
    side = {a: f"(e{a} / (2.0::DOUBLE ** t.level))" for a in "xyz"}
    raw = ", ".join(f"l{a} + n{a} * {side[a]} AS lo{a}, l{a} + n{a} * {side[a]} + {side[a]} AS hi{a}" for a in "xyz")
    big = {a: f"(greatest(abs(lo{a}), abs(hi{a}), e{a}) * {8 * 2.0**-52!r}::DOUBLE)" for a in "xyz"}
    padded = ", ".join(f"lo{a} - {big[a]} AS u{a}, hi{a} + {big[a]} AS t{a}" for a in "xyz")
    gap = {a: f"greatest(u{a} - q{a}, q{a} - t{a}, 0.0::DOUBLE)" for a in "xyz"}
    far = {a: f"greatest(abs(q{a} - u{a}), abs(t{a} - q{a}))" for a in "xyz"}
    squares = lambda v: "(" + " + ".join(f"{v[a]} * {v[a]}" for a in "xyz") + ")"
    r_ = f"({float(r)!r}::DOUBLE * {float(r)!r}::DOUBLE)"
    cells_ = ", ".join(f"min(c{a} >> (21 - lv)) AS n{a}" for a in "xyz")
    return f"""WITH RECURSIVE {tree(cloud, curve, bucket)}, {by_id(step)},
corner AS (SELECT lv AS level, code >> (3 * (21 - lv)) AS prefix, {cells_} FROM k, (SELECT unnest(range(22))::INT AS lv) GROUP BY 1, 2),
raw AS (SELECT t.level, t.prefix, t.cnt, t.is_leaf, g.*, {raw} FROM t JOIN corner c ON c.level = t.level AND c.prefix = t.prefix, g WHERE t.cnt > 0),
boxes AS (SELECT level, prefix, cnt, is_leaf, {padded} FROM raw),
placed AS (SELECT cid, level, prefix, cnt, is_leaf, CASE WHEN {squares(gap)} >= {r_} THEN -1 WHEN {squares(far)} < {r_} THEN 1 ELSE 0 END AS place FROM q, boxes),
walked AS (SELECT a.* FROM placed a LEFT JOIN placed u ON u.cid = a.cid AND u.level = a.level - 1 AND u.prefix = a.prefix >> 3 WHERE a.level = 0 OR u.place = 0)"""


def radius(cloud: str, kernel: str, r: float, step: int = 100) -> str:
    return f"WITH p AS ({CLOUD[cloud]}), {by_id(step)} SELECT q.cid, count(p.pid) AS n, coalesce(sum(p.pid), 0)::BIGINT AS pid_sum FROM q LEFT JOIN p ON {hit(kernel, r)} GROUP BY q.cid"


def knn(k: int) -> str:
    """CTE n (cid, rank, pid) from p and q."""
    return f"n AS (SELECT cid, pid, d2, row_number() OVER (PARTITION BY cid ORDER BY d2, pid <> cid, pid) AS rank FROM (SELECT cid, pid, {D2} AS d2 FROM p, q) x QUALIFY rank <= {k})"
