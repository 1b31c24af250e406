"""Search structures inside one tile, in NumPy: linear octree, pointer octrees, kd-trees.

All answer the same queries exactly; they differ in layout and work. Their nodes are arrays, and a search moves a frontier
of (centre, node) pairs down the tree, so no centre and no node is handled one by one. ``radius`` gives (centre, first,
end) ranges over the tile's rows, ``hits`` gives (centre, row), both with counters; ``knn_batch`` gives the nearest of
many centres, ``knn`` those of one by best first.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np

from ..functions.curves import np_decode
from ..functions.grid import GridSpec
from ..functions.kernels import EPS8, Kernel, np_box_d2, np_d2

COUNTERS = ("nodes", "contained", "leaves", "tested", "bulk", "n_ranges")
CENTRES_AT_ONCE, TESTS_AT_ONCE, QUEUES_AT_ONCE = 2048, 1 << 20, 1024
#: centres of one block, and the most rows near it for which distances are a full matrix
BLOCK_CENTRES, BLOCK_ROWS = 32, 4096
NONE = np.zeros(0, np.int64)


def spread(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Positions of many ranges end to end."""
    ends = np.cumsum(n)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(first - ends + n, n)


def _expand(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of many ranges end to end, and which range each comes from."""
    n = np.maximum(hi - lo, 0)
    return spread(lo, n), np.repeat(np.arange(len(lo)), n)


def _portions(sizes: np.ndarray) -> list[slice]:
    """Successive entries whose sizes add up to about TESTS_AT_ONCE at most."""
    if not len(sizes):
        return []
    share = (np.cumsum(sizes) - sizes) // TESTS_AT_ONCE
    cuts = np.concatenate(([0], np.flatnonzero(np.diff(share)) + 1, [len(sizes)])).tolist()
    return [slice(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]


def coalesce(who: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ranges sorted by (who, lo), with touching ones of a centre put together."""
    order = np.lexsort((lo, who))
    who, lo, hi = who[order], lo[order], hi[order]
    if not len(who):
        return who, lo, hi
    new = np.ones(len(who), bool)
    new[1:] = (who[1:] != who[:-1]) | (lo[1:] != hi[:-1])
    at = np.flatnonzero(new)
    return who[at], lo[at], hi[np.concatenate((at[1:], [len(who)])) - 1]


def _far_d2(lo: np.ndarray, hi: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Squared distance to the farthest corner."""
    gap = np.maximum(np.abs(q - lo), np.abs(hi - q))
    return (gap * gap).sum(axis=1)


def _per_centre(centres: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first entry of each run of equal centres, and how many entries it has."""
    first = np.flatnonzero(np.concatenate(([True], centres[1:] != centres[:-1]))) if len(centres) else NONE
    return first, np.diff(np.append(first, len(centres)))


def _rows(d: np.ndarray, first: np.ndarray, n: np.ndarray, width: int) -> np.ndarray | None:
    """Runs of values as rows that end in infinities; None where runs are so uneven that rows would mostly be filling."""
    if len(n) * width > 4 * len(d) + TESTS_AT_ONCE:
        return None
    out = np.full((len(n), width), np.inf)
    out[np.repeat(np.arange(len(n)), n), np.arange(len(d)) - np.repeat(first, n)] = d
    return out


def _kth(d: np.ndarray, first: np.ndarray, n: np.ndarray, k: int) -> np.ndarray:
    """The k-th smallest of each run of values, infinite for shorter runs."""
    if not len(n):
        return np.zeros(0)
    rows = _rows(d, first, n, max(k, int(n.max())))
    if rows is None:
        ranked = d[np.lexsort((d, np.repeat(np.arange(len(n)), n)))]
        return np.where(n >= k, ranked[np.minimum(first + k, first + n) - 1], np.inf)
    rows.partition(k - 1, axis=1)
    return rows[:, k - 1]


def _ordered(d: np.ndarray, first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """What sorts each run of finite values; equal ones in any order."""
    rows = _rows(d, first, n, int(n.max())) if len(n) else None
    if rows is None:
        return np.lexsort((d, np.repeat(np.arange(len(n)), n)))
    at = np.argsort(rows, axis=1)
    return (at + first[:, None])[np.arange(rows.shape[1]) < n[:, None]]


class Walk:
    """What all structures share. Node 0 is the root; a node holds the rows ``members[lo:hi]`` (``members`` None: the rows
    lo to hi themselves). ``children`` gives the number of children of each internal node and their numbers end to end."""

    xyz: np.ndarray
    box_lo: np.ndarray
    box_hi: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    leaf: np.ndarray
    members: np.ndarray | None = None
    shortcut = False

    def children(self, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        raise NotImplementedError

    def rows_of(self, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All rows below each node, and which node each comes from."""
        at, which = _expand(self.lo[node], self.hi[node])
        return at if self.members is None else self.members[at], which

    # -- fixed radius -------------------------------------------------------------------------------------------------
    def _search(self, kernel: Kernel, q: np.ndarray, r: np.ndarray, shortcut: bool, contain_leaves: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(centre, node) taken whole, (centre, row) that passed the test, and counters."""
        work = np.zeros((len(q), len(COUNTERS)), np.int64)
        out: list[list[np.ndarray]] = [[NONE], [NONE], [NONE], [NONE]]
        for start in range(0, len(q) if len(self.lo) else 0, CENTRES_AT_ONCE):
            who = np.arange(start, min(start + CENTRES_AT_ONCE, len(q)))
            node = np.zeros(len(who), np.int64)
            while len(who):
                live = self.hi[node] > self.lo[node]
                who, node = who[live], node[live]
                np.add.at(work[:, 0], who, 1)
                place = kernel.np_classify(self.box_lo[node], self.box_hi[node], q[who], r[who])
                leaf = self.leaf[node]
                whole = (place == 1) & shortcut & (contain_leaves | ~leaf)
                np.add.at(work[:, 1], who[whole], 1)
                np.add.at(work[:, 4], who[whole], self.hi[node[whole]] - self.lo[node[whole]])
                out[0].append(who[whole])
                out[1].append(node[whole])
                test, go = leaf & (place != -1) & ~whole, ~leaf & (place != -1) & ~whole
                w, n = who[test], node[test]
                size = self.hi[n] - self.lo[n]
                np.add.at(work[:, 2], w, 1)
                np.add.at(work[:, 3], w, size)
                for part in _portions(size):
                    row, which = self.rows_of(n[part])
                    c = w[part][which]
                    hit = kernel.np_hits(self.xyz[row], q[c], r[c])
                    out[2].append(c[hit])
                    out[3].append(row[hit])
                who = who[go]
                count, node = self.children(node[go])
                who = np.repeat(who, count)
        return (*(np.concatenate(x) for x in out), work)

    def radius(self, kernel: Kernel, q: np.ndarray, r: np.ndarray, mode: str = "ranges", contain_leaves: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(centre, first, end) ranges of rows, coalesced, and counters (centre x COUNTERS). ``leafscan`` tests every touched
        leaf's points; other modes of the linear octree take contained octants whole, as ranges."""
        who, node, c, row, work = self._search(kernel, q, r, self.shortcut and mode != "leafscan", contain_leaves)
        if self.members is None:
            lo, hi = self.lo[node], self.hi[node]
        else:
            lo, which = self.rows_of(node)
            who, hi = who[which], lo + 1
        who, lo, hi = coalesce(np.concatenate((who, c)), np.concatenate((lo, row)), np.concatenate((hi, row + 1)))
        np.add.at(work[:, 5], who, 1)
        return who, lo, hi, work

    def hits(self, kernel: Kernel, q: np.ndarray, r: np.ndarray, mode: str = "prune", contain_leaves: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(centre, row) of every neighbour, by centre, and counters: contained octants' rows are listed one by one."""
        who, node, c, row, work = self._search(kernel, q, r, self.shortcut and mode != "leafscan", contain_leaves)
        rows, which = self.rows_of(node)
        who, rows = np.concatenate((who[which], c)), np.concatenate((rows, row))
        order = np.argsort(who, kind="stable")
        np.add.at(work[:, 5], who, 1)
        return who[order], rows[order], work

    # -- nearest neighbours -------------------------------------------------------------------------------------------
    def descend(self, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """For each centre a small node that holds k rows, and a squared distance within which they surely lie (infinite
        if there are no k rows): from the counts and boxes alone, no point is read."""
        node, far = np.zeros(len(q), np.int64), np.full(len(q), np.inf)
        if not len(self.lo) or self.hi[0] - self.lo[0] < k:
            return node, far
        far = _far_d2(self.box_lo[node], self.box_hi[node], q)
        live = np.arange(len(q))
        while True:
            live = live[~self.leaf[node[live]]]
            count, kid = self.children(node[live])
            who = np.repeat(live, count)
            ok = self.hi[kid] - self.lo[kid] >= k
            who, kid = who[ok], kid[ok]
            if not len(who):
                return node, far * (1 + 1e-12)
            reach = _far_d2(self.box_lo[kid], self.box_hi[kid], q[who])
            order = np.lexsort((reach, who))
            live, first = np.unique(who[order], return_index=True)
            best = order[first]
            node[live] = kid[best]
            far[live] = np.minimum(far[live], reach[best])

    def within(self, q: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(centre, leaf) of all leaves whose boxes come within the centre's squared distance."""
        out: list[list[np.ndarray]] = [[NONE], [NONE]]
        who = np.arange(len(q) if len(self.lo) else 0)
        node = np.zeros(len(who), np.int64)
        while len(who):
            near = (self.hi[node] > self.lo[node]) & (np_box_d2(self.box_lo[node], self.box_hi[node], q[who]) <= bound[who])
            who, node = who[near], node[near]
            leaf = self.leaf[node]
            out[0].append(who[leaf])
            out[1].append(node[leaf])
            count, node = self.children(node[~leaf])
            who = np.repeat(who[~leaf], count)
        return np.concatenate(out[0]), np.concatenate(out[1])

    def knn_batch(self, q: np.ndarray, k: int, key: np.ndarray, own: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(centre, d2, key) of the k nearest of each centre within its bound, in two phases: a small node with k rows gives
        the distance of its k-th nearest; then all leaves within that distance are read."""
        found: list[list[np.ndarray]] = [[NONE], [np.zeros(0)], [NONE]]
        for c, d, row in self._nearest(q, k, bound):
            item = key[row]
            begin, n = _per_centre(c, d)
            order = _ordered(d, begin, n)
            c, d, item = c[order], d[order], item[order]
            same = (c[1:] == c[:-1]) & (d[1:] == d[:-1])
            tied = np.flatnonzero(np.append(same, False) | np.append([False], same)[: len(c)])
            item[tied] = item[tied][np.lexsort((item[tied], item[tied] != own[c[tied]], d[tied], c[tied]))]
            top = np.arange(len(c)) - np.repeat(begin, n) < k
            for x, y in zip(found, (c, d, item), strict=True):
                x.append(y[top])
        return tuple(np.concatenate(x) for x in found)

    def kth_batch(self, q: np.ndarray, k: int, bound: np.ndarray) -> np.ndarray:
        """The squared distance of each centre's k-th nearest, or its bound where fewer lie within that."""
        out = bound.copy()
        for c, d, _ in self._nearest(q, k, bound):
            begin, n = _per_centre(c, d)
            if len(begin):
                out[c[begin[n >= k]]] = np.maximum.reduceat(d, begin)[n >= k]
        return out

    def _nearest(self, q: np.ndarray, k: int, bound: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(centre, d2, row), by centre, of those within the centre's bound that are no farther than the k-th nearest.

        Successive centres are taken in blocks: where they lie close together, the rows near a block are gathered once for
        all of them. Centres of other blocks are searched one by one."""
        single, held, n_held = [NONE], [], 0
        for block, rows in self._blocks(q, k, bound):
            if rows is None:
                single.append(np.arange(block.start, block.stop))
                continue
            x = self.xyz[rows]
            d = sum((x[None, :, i] - q[block, None, i]) ** 2 for i in range(3))
            limit = bound[block]
            if len(rows) >= k:
                limit = np.minimum(limit, np.partition(d, k - 1, axis=1)[:, k - 1])
            c, at = np.nonzero(d <= limit[:, None])
            held.append((c + block.start, d[c, at], rows[at]))
            n_held += len(c)
            if n_held > TESTS_AT_ONCE // 8:
                yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
                held, n_held = [], 0
        if held:
            yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
        single = np.concatenate(single)
        for c, d, row in self._nearest_singly(q[single], k, bound[single]):
            yield single[c], d, row

    def _blocks(self, q: np.ndarray, k: int, bound: np.ndarray) -> Iterator[tuple[slice, np.ndarray | None]]:
        """Blocks of successive centres, and all rows that can be among the k nearest of one of them within its bound; None
        where these are more than BLOCK_ROWS."""
        if not len(q):
            return
        first = np.arange(0, len(q), BLOCK_CENTRES)
        low, high = np.minimum.reduceat(q, first), np.maximum.reduceat(q, first)
        # what surely holds k rows near the block's middle does so for each of its centres, as far as the block is wide
        middle = (low + high) / 2
        # half the diagonal, and some units in the last place as the middle is rounded
        half = np.sqrt(((high - low) ** 2).sum(axis=1)) / 2 + 8 * np.spacing(np.maximum(np.abs(low), np.abs(high)).max(axis=1))
        reach = np.sqrt(self.descend(middle, k)[1]) + half
        reach = np.minimum(np.maximum.reduceat(bound, first), reach * reach * (1 + 1e-12))
        few = np.ones(len(first), bool)
        for step in range(2):  # the second time with the k-th nearest of a middle instead of what boxes and counts promise
            who, leaf = self.within_boxes(low, high, np.where(few, reach, -1.0))
            order = np.argsort(who, kind="stable")
            who, leaf = who[order], leaf[order]
            size = np.bincount(who, self.hi[leaf] - self.lo[leaf], len(first))
            few &= size <= (2 - step) * BLOCK_ROWS
            edges = np.searchsorted(who, np.arange(len(first) + 1))
            if step:
                break
            for i in np.flatnonzero(few & (size >= k)).tolist():
                row, _ = self.rows_of(leaf[edges[i] : edges[i + 1]])
                d = ((self.xyz[row] - middle[i]) ** 2).sum(axis=1)
                d.partition(k - 1)
                near = np.sqrt(d[k - 1]) + half[i]
                reach[i] = min(reach[i], near * near * (1 + 1e-12))
        for i, start in enumerate(first.tolist()):
            yield slice(start, min(start + BLOCK_CENTRES, len(q))), self.rows_of(leaf[edges[i] : edges[i + 1]])[0] if few[i] else None

    def within_boxes(self, low: np.ndarray, high: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(box, leaf) of all leaves whose boxes come within each box's squared distance."""
        out: list[list[np.ndarray]] = [[NONE], [NONE]]
        who = np.arange(len(low) if len(self.lo) else 0)
        node = np.zeros(len(who), np.int64)
        while len(who):
            gap = np.maximum(np.maximum(self.box_lo[node] - high[who], low[who] - self.box_hi[node]), 0.0)
            near = (self.hi[node] > self.lo[node]) & ((gap * gap).sum(axis=1) <= bound[who])
            who, node = who[near], node[near]
            leaf = self.leaf[node]
            out[0].append(who[leaf])
            out[1].append(node[leaf])
            count, node = self.children(node[~leaf])
            who = np.repeat(who[~leaf], count)
        return np.concatenate(out[0]), np.concatenate(out[1])

    def _nearest_singly(self, q: np.ndarray, k: int, bound: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        node, far = self.descend(q, k)
        bound = np.minimum(bound, far)
        sure = np.flatnonzero(np.isfinite(far))
        for part in _portions(self.hi[node[sure]] - self.lo[node[sure]]):
            some = sure[part]
            row, which = self.rows_of(node[some])
            d = np_d2(self.xyz[row], q[some[which]])
            bound[some] = np.minimum(bound[some], _kth(d, *_per_centre(which, d), k))
        for start in range(0, len(q), CENTRES_AT_ONCE):
            some = slice(start, start + CENTRES_AT_ONCE)
            who, leaf = self.within(q[some], bound[some])
            order = np.argsort(who, kind="stable")
            who, leaf = who[order] + start, leaf[order]
            first, _ = _per_centre(who, leaf)
            size = np.add.reduceat(self.hi[leaf] - self.lo[leaf], first) if len(first) else NONE
            stops = np.append(first, len(who))
            for part in _portions(size):  # whole centres at a time
                at = slice(stops[part.start], stops[part.stop])
                row, which = self.rows_of(leaf[at])
                c = who[at][which]
                d = np_d2(self.xyz[row], q[c])
                ok = d <= bound[c]
                c, d, row = c[ok], d[ok], row[ok]
                begin, n = _per_centre(c, d)
                ok = d <= np.repeat(_kth(d, begin, n, k), n)
                yield c[ok], d[ok], row[ok]

    def knn(self, q: np.ndarray, k: int, key: np.ndarray, own: int | None, bound: float = np.inf) -> list[tuple[float, int, int]]:
        """(d2, not own, key) of the k nearest of one centre by best first: one queue of octants and points keyed by squared distance."""
        queue: list[tuple] = [(0.0, 0, 0, 0)]
        out: list[tuple[float, int, int]] = []
        while queue and len(out) < k and len(self.lo):
            dist, kind, other, item = heapq.heappop(queue)
            if kind:
                out.append((dist, other, item))
            elif self.leaf[item]:
                rows, _ = self.rows_of(np.array([item]))
                for d, i in zip(np_d2(self.xyz[rows], q[None, :]).tolist(), key[rows].tolist(), strict=True):
                    if d <= bound:
                        heapq.heappush(queue, (d, 1, int(i != own), i))
            else:
                _, kids = self.children(np.array([item]))
                kids = kids[self.hi[kids] > self.lo[kids]]
                for d, i in zip(np_box_d2(self.box_lo[kids], self.box_hi[kids], q[None, :]).tolist(), kids.tolist(), strict=True):
                    if d <= bound:
                        heapq.heappush(queue, (d, 0, 0, i))
        return out

    def knn_bestfirst(self, q: np.ndarray, k: int, key: np.ndarray, own: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(centre, d2, key) like ``knn_batch``, by best first: each centre has a queue of its own, and in every round each
        takes the nearest node from it. A centre ends when that is farther than its k-th nearest point."""
        found: list[list[np.ndarray]] = [[NONE], [np.zeros(0)], [NONE]]
        for start in range(0, len(q) if len(self.lo) else 0, QUEUES_AT_ONCE):
            at, far = q[start : start + QUEUES_AT_ONCE], bound[start : start + QUEUES_AT_ONCE]
            mine, n = own[start : start + QUEUES_AT_ONCE], len(far)
            near, node, held = np.full((n, 16), np.inf), np.zeros((n, 16), np.int64), np.ones(n, np.int64)
            near[:, 0] = 0.0
            best = [np.full((n, k), np.inf), np.zeros((n, k), bool), np.zeros((n, k), key.dtype)]  # squared distance, not own, key
            live = np.arange(n)
            while len(live):
                spot = near[live].argmin(axis=1)
                go = np.isfinite(near[live, spot]) & (near[live, spot] <= best[0][live, -1])
                live, spot = live[go], spot[go]
                top = node[live, spot]
                held[live] -= 1
                last = held[live]  # the last entry moves to the place of what is taken
                near[live, spot], node[live, spot] = near[live, last], node[live, last]
                near[live, last] = np.inf
                leaf = self.leaf[top]
                count, kid = self.children(top[~leaf])
                who = np.repeat(live[~leaf], count)
                d = np_box_d2(self.box_lo[kid], self.box_hi[kid], at[who])
                ok = (self.hi[kid] > self.lo[kid]) & (d <= far[who]) & (d <= best[0][who, -1])
                who, kid, d = who[ok], kid[ok], d[ok]
                first, more = _per_centre(who, d)
                place = held[who] + np.arange(len(who)) - np.repeat(first, more)
                if len(place) and place.max() >= near.shape[1]:
                    wider = int(place.max()) + 1
                    near = np.concatenate((near, np.full((n, wider), np.inf)), axis=1)
                    node = np.concatenate((node, np.zeros((n, wider), np.int64)), axis=1)
                near[who, place], node[who, place] = d, kid
                held[who[first]] += more
                here, top = live[leaf], top[leaf]
                for part in _portions(self.hi[top] - self.lo[top]):
                    row, which = self.rows_of(top[part])
                    c = here[part][which]
                    d = np_d2(self.xyz[row], at[c])
                    ok = (d <= far[c]) & (d <= best[0][c, -1])
                    self._keep_nearest(best, k, c[ok], d[ok], key[row[ok]], mine)
            who, rank = np.nonzero(np.isfinite(best[0]))
            for x, y in zip(found, (who + start, best[0][who, rank], best[2][who, rank]), strict=True):
                x.append(y)
        return tuple(np.concatenate(x) for x in found)

    @staticmethod
    def _keep_nearest(best: list[np.ndarray], k: int, c: np.ndarray, d: np.ndarray, item: np.ndarray, own: np.ndarray) -> None:
        """Merges points, by centre, into the k best of their centres."""
        first, n = _per_centre(c, d)
        step = max(1, TESTS_AT_ONCE // (k + int(n.max(initial=0))))
        for lot in range(0, len(first), step):
            size, begin = n[lot : lot + step], first[lot : lot + step]
            mine = slice(begin[0], begin[-1] + size[-1])
            who = c[begin]
            row = np.repeat(np.arange(len(who)), size)
            column = k + np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
            wide = [np.concatenate((b[who], np.full((len(who), int(size.max())), empty, b.dtype)), axis=1) for b, empty in zip(best, (np.inf, False, 0), strict=True)]
            for w, v in zip(wide, (d[mine], item[mine] != own[c[mine]], item[mine]), strict=True):
                w[row, column] = v
            order = np.lexsort(wide[::-1], axis=1)[:, :k]
            for b, w in zip(best, wide, strict=True):
                b[who] = np.take_along_axis(w, order, axis=1)


class LinearOctree(Walk):
    """Arrays of nodes over sorted codes: counts by binary search, index ranges for every node, children found by
    arithmetic. ``boxes`` False keeps no boxes: they are decoded from the prefixes whenever a node is met."""

    shortcut = True

    def __init__(self, xyz: np.ndarray, codes: np.ndarray, grid: GridSpec, curve: str, bucket: int, root: tuple[int, int] = (0, 0), tight: bool = False):
        self.xyz = xyz
        level, prefix = [np.array([root[0]], np.int8)], [np.array([root[1]], np.int64)]
        lo, hi = [np.array([0])], [np.array([len(codes)])]
        at, depth = 0, root[0]
        first_child = []
        while True:
            size = hi[-1] - lo[-1]
            split = (size > bucket) & (depth < grid.levels)
            n = int(split.sum())
            base = at + len(size)
            first = np.full(len(size), -1)
            first[split] = base + 8 * np.arange(n)
            first_child.append(first)
            if not n:
                break
            kids = (prefix[-1][split][:, None] * 8 + np.arange(8)).ravel()
            depth += 1
            start = np.searchsorted(codes, kids << 3 * (grid.levels - depth))
            end = np.concatenate((start[1:], [0]))
            end[np.arange(7, 8 * n, 8)] = hi[-1][split]
            level.append(np.full(8 * n, depth, np.int8))
            prefix.append(kids)
            lo.append(start)
            hi.append(end)
            at = base
        self.level, self.prefix = np.concatenate(level), np.concatenate(prefix)
        self.lo, self.hi, self.first = np.concatenate(lo), np.concatenate(hi), np.concatenate(first_child)
        self.leaf = self.first < 0
        cells = np.zeros((len(self.level), 3), np.int64)
        for d in np.unique(self.level):
            m = self.level == d
            cells[m] = np_decode(self.prefix[m], curve, int(d)) if d else 0
        self.box_lo, self.box_hi = grid.np_boxes(self.level, cells)
        full = np.flatnonzero(self.hi > self.lo)
        if tight and len(full):
            # the last row of a node may be the first of the next: reduceat takes every other result
            edges = np.stack((self.lo[full], self.hi[full]), axis=1).ravel()
            padded = np.concatenate((xyz, xyz[-1:]))
            self.box_lo[full] = np.minimum.reduceat(padded, edges, axis=0)[::2]
            self.box_hi[full] = np.maximum.reduceat(padded, edges, axis=0)[::2]

    def children(self, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return np.full(len(node), 8), (self.first[node][:, None] + np.arange(8)).ravel()

    def node_bytes(self, centres: bool = True) -> int:
        """Bytes of the arrays held; without ``centres`` the boxes, which follow from the prefixes, are left out."""
        held = [self.level, self.prefix, self.lo, self.hi, self.first, self.leaf]
        return sum(a.nbytes for a in (held + [self.box_lo, self.box_hi] if centres else held))

    def bytes_of(self, nodes: int, centres: bool = True) -> int:
        """What ``node_bytes`` is with another number of nodes."""
        return self.node_bytes(centres) // len(self.lo) * nodes


class PointerTree(Walk):
    """A tree whose nodes name their children one by one, each with the scattered numbers of its rows.

    ``kind``: pointer (complete octree), noncomplete (empty children left out; contained branches taken whole if
    ``shortcut``), resolution (split down to a cell size, not to a count), kd (binary, by ``split``). Rows stay in the
    order given, whatever it is. All nodes of a level are split together.
    """

    def __init__(self, xyz: np.ndarray, box: tuple[np.ndarray, np.ndarray], kind: str = "pointer", bucket: int = 128, depth: int = 21, cell: float = 0.0, split: str = "median", shortcut: bool = False):
        self.xyz, self.kind, self.shortcut = xyz, kind, shortcut
        self.members = np.arange(len(xyz), dtype=np.int64 if kind == "pointer" else np.int32)
        los, his = [np.array([0])], [np.array([len(xyz)])]
        lows, highs = ([np.asarray(b, np.float64)[None, :]] for b in box)
        counts, level = [], 0
        while True:
            lo, hi, low, high = los[-1], his[-1], lows[-1], highs[-1]
            if kind == "kd":
                parent, start, end, low, high = self._halve(lo, hi, low, high, bucket, split)
            else:
                parent, start, end, low, high = self._octants(lo, hi, low, high, (high - low).max(axis=1) > cell if kind == "resolution" else hi - lo > bucket, level < depth)
            counts.append(np.bincount(parent, minlength=len(lo)))
            if not len(parent):
                break
            los.append(start)
            his.append(end)
            lows.append(low)
            highs.append(high)
            level += 1
        self.lo, self.hi, count = np.concatenate(los), np.concatenate(his), np.concatenate(counts)
        self.box_lo, self.box_hi = np.concatenate(lows), np.concatenate(highs)
        if kind != "kd":  # halving in reals may put a point an ulp outside its box
            wide = EPS8 * np.maximum(np.abs(self.box_lo), np.abs(self.box_hi)).max(axis=1, keepdims=True)
            self.box_lo, self.box_hi = self.box_lo - wide, self.box_hi + wide
        self.leaf = count == 0
        first = 1 + np.cumsum(count) - count
        if kind == "pointer":
            self.kid = np.where(self.leaf[:, None], -1, first[:, None] + np.arange(8))
        else:
            self.kid, self.kid_at, self.kid_n = np.arange(1, len(count)), (first - 1).astype(np.int64), count.astype(np.int8)

    def _octants(self, lo, hi, low, high, wanted, deeper):
        s = np.flatnonzero(wanted & (hi > lo)) if deeper else NONE
        if not len(s):
            return (s, *[NONE] * 4)
        mid = (low[s] + high[s]) / 2
        at, which = _expand(lo[s], hi[s])
        rows = self.members[at]
        octant = (self.xyz[rows] >= mid[which]) @ np.array([4, 2, 1])
        place = which * 8 + octant
        self.members[at] = rows[np.argsort(place, kind="stable")]
        size = np.bincount(place, minlength=8 * len(s))
        end = np.cumsum(size.reshape(-1, 8), axis=1).ravel() + np.repeat(lo[s], 8)
        up = np.array([[o >> 2 & 1, o >> 1 & 1, o & 1] for o in range(8)], bool)[None]
        below, above = (np.where(up, mid[:, None], low[s][:, None]).reshape(-1, 3), np.where(up, high[s][:, None], mid[:, None]).reshape(-1, 3))
        keep = np.ones(len(size), bool) if self.kind == "pointer" else size > 0
        return np.repeat(s, 8)[keep], (end - size)[keep], end[keep], below[keep], above[keep]

    def _halve(self, lo, hi, low, high, bucket, split):
        full = np.flatnonzero(hi > lo)
        if not len(full):
            return (full, *[NONE] * 4)
        least, most = self._extremes(lo[full], hi[full])
        low[full], high[full] = least, most
        span = most - least
        wide = (hi[full] - lo[full] > bucket) & span.any(axis=1)
        s, axis = full[wide], span[wide].argmax(axis=1)
        if not len(s):
            return (s, *[NONE] * 4)
        at, which = _expand(lo[s], hi[s])
        rows = self.members[at]
        v = self.xyz[rows, axis[which]]
        order = np.lexsort((v, which))
        self.members[at] = rows[order]
        size = hi[s] - lo[s]
        if split == "median":
            left = size // 2
        else:  # the middle of the box; where it parts nothing off, the plane slides to the nearest point
            i = np.arange(len(s))
            bottom, top = low[s][i, axis], high[s][i, axis]
            count = lambda test: np.bincount(which[test], minlength=len(s))
            left = count(v < ((bottom + top) / 2)[which])
            left = np.where(left == 0, count(v <= bottom[which]), left)
            left = np.where(left == size, count(v < top[which]), left)
        start = np.stack((lo[s], lo[s] + left), axis=1).ravel()
        end = np.stack((lo[s] + left, hi[s]), axis=1).ravel()
        least, most = self._extremes(start, end)
        return np.repeat(s, 2), start, end, least, most

    def _extremes(self, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at, _ = _expand(lo, hi)
        first = np.cumsum(hi - lo) - (hi - lo)
        points = self.xyz[self.members[at]]
        return np.minimum.reduceat(points, first, axis=0), np.maximum.reduceat(points, first, axis=0)

    def children(self, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.kind == "pointer":
            return np.full(len(node), 8), self.kid[node].ravel()
        n = self.kid_n[node].astype(np.int64)
        return n, self.kid[spread(self.kid_at[node], n)]

    def node_bytes(self) -> int:
        """Bytes of the arrays held, rows' numbers included."""
        held = [self.lo, self.hi, self.leaf, self.box_lo, self.box_hi, self.members, self.kid]
        return sum(a.nbytes for a in (held if self.kind == "pointer" else [*held, self.kid_at, self.kid_n]))

    def bytes_of(self, nodes: int, points: int) -> int:
        """What ``node_bytes`` is with other numbers of nodes and points: the root is the one node that is no child."""
        rows, kids = self.members.nbytes, self.kid.nbytes
        each = (self.node_bytes() - rows - kids) // len(self.lo)
        kids = self.kid.itemsize * (8 * nodes if self.kind == "pointer" else nodes - 1)
        return each * nodes + self.members.itemsize * points + kids


#: name -> (builder options); split rules and leaf sizes of the kd-trees are this library's choice
STRUCTURES = {
    "ranges": {}, "prune": {}, "leafscan": {},
    "pointer": {"kind": "pointer"},
    "noncomplete": {"kind": "noncomplete", "shortcut": True},
    "resolution": {"kind": "resolution"},
    "kd_small": {"kind": "kd", "bucket": 1},
    "kd_ten": {"kind": "kd", "bucket": 10},
    "kd_sliding": {"kind": "kd", "bucket": 10, "split": "middle"},
}
LINEAR = ("ranges", "prune", "leafscan")
#: the form in which a structure's search gives its result
OUTPUT = {"ranges": "ranges", "noncomplete": "coords"}


def build_local(structure: str, xyz: np.ndarray, codes: np.ndarray, grid: GridSpec, curve: str, bucket: int, root: tuple[int, int], box: tuple[np.ndarray, np.ndarray], cell: float = 0.0, tight: bool = False):
    if structure in LINEAR:
        return LinearOctree(xyz, codes, grid, curve, bucket, root, tight)
    options = {"bucket": bucket, "depth": grid.levels - root[0], "cell": cell} | STRUCTURES[structure]
    return PointerTree(xyz, box, **options)
