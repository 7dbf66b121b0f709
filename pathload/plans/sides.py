"""Loads of an undirected scope of two sides: few hubs, and many rims that have hubs alone as neighbours.

Customers and suppliers are such a scope, also with some edges inside a side: of each
edge one end is a hub. A path then goes from hub to hub over an edge or over one rim, so
levels of hubs are products with two small tables: edges between hubs, and numbers of rims
that two hubs share. Rims are met only as ends of paths, a tile of them at a time, and
their own loads come from one table of flows between hubs, as do the loads of their edges
but for paths that end there. As a path and its way back have
the same loads, a pair of rims is searched from its first one, a rim and a hub from the hub.
An edge that alone holds two large parts together is cut: each of its ends then stands for
all vertices behind it.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Rims that are unpacked at once; sources that a task takes at once.
RIMS, ROWS = 1024, 512
#: Cells of a product that take as long as picking one by itself; how many are picked at once.
PICKED, PICKS = 200, 1 << 20
#: Ends of edges that a task lists beside their bits.
LISTED = 20_000_000
#: Whole numbers below this are exact in four bytes.
EXACT = 1 << 24
#: Levels of a tree in which bridges are looked for.
LEVELS = 64


def hubs(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Which vertices are hubs: of each edge the end of more edges, so that no edge joins two of the others."""
    rank = (np.bincount(a, minlength=n) + np.bincount(b, minlength=n)) * n + np.arange(n)
    out = np.zeros(n, bool)
    out[np.where(rank[a] > rank[b], a, b)] = True
    return out


def bridges(n: int, a: np.ndarray, b: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """(edges that alone hold two parts of so many vertices or more together, vertices on their b's part) in a connected graph.

    A tree edge is one if every other edge from below it ends below it: then random numbers,
    added at one end of each other edge and taken off at the other, leave nothing below.
    Deep graphs get none.
    """
    depth, up, parent = np.full(n, -1), np.full(n, -1), np.full(n, -1)
    depth[0], level = 0, 0
    while (depth < 0).any():
        level += 1
        x, y = depth[a] >= 0, depth[b] >= 0
        e = np.flatnonzero(x != y)
        if level > LEVELS or not len(e):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        low = np.where(x[e], b[e], a[e])
        up[low] = e  # any of them
        low = np.unique(low)
        depth[low], parent[low] = level, a[up[low]] + b[up[low]] - low
    other = np.ones(len(a), bool)
    other[up[1:]] = False
    draw = np.random.default_rng(0).integers(0, 1 << 64, int(other.sum()), np.uint64)
    left, size = np.zeros(n, np.uint64), np.ones(n, np.int64)
    np.add.at(left, a[other], draw)
    np.subtract.at(left, b[other], draw)
    for k in range(level, 0, -1):
        low = np.flatnonzero(depth == k)
        np.add.at(left, parent[low], left[low])
        np.add.at(size, parent[low], size[low])
    low = np.flatnonzero((depth > 0) & (left == 0) & (size >= least) & (n - size >= least))
    return up[low], np.where(b[up[low]] == low, size[low], n - size[low])


@dataclass
class Sides:
    """order: vertices, rims first; weight: how many ends of paths each stands for; bits: a row of hubs for each rim; a, b: edges between hubs.

    For edge loads alone, rim and own: the ends of the other edges, in the order of rims; place: where these edges, then those between hubs, are among all.
    """

    order: np.ndarray
    weight: np.ndarray
    hubs: int
    bits: np.ndarray
    a: np.ndarray
    b: np.ndarray
    rim: np.ndarray | None = None
    own: np.ndarray | None = None
    place: np.ndarray | None = None

    @staticmethod
    def of(hub: np.ndarray, label: np.ndarray, a: np.ndarray, b: np.ndarray, weight: np.ndarray | None = None, edges: bool = False) -> Sides:
        """label: vertices of one label stand together, as tiles and sources that see the same hubs cost least."""
        n = len(hub)
        cross = hub[a] != hub[b]
        rim, own = np.where(hub[a], b, a)[cross], np.where(hub[a], a, b)[cross]
        least = np.full(n, n)
        np.minimum.at(least, rim, own)
        order = np.lexsort((np.arange(n), least, label, hub))
        at = np.empty(n, np.int64)
        at[order] = np.arange(n)
        p = n - int(hub.sum())
        rim, own = at[rim], at[own] - p
        sort = np.argsort(rim, kind="stable")
        rim, own = rim[sort], own[sort]
        bits = np.zeros((p, -(-(n - p) // 8)), np.uint8)
        for lo in range(0, p, RIMS):
            part = slice(*np.searchsorted(rim, (lo, lo + RIMS)))
            some = np.zeros((min(RIMS, p - lo), n - p), bool)
            some[rim[part] - lo, own[part]] = True
            bits[lo : lo + RIMS] = np.packbits(some, axis=1)
        out = Sides(order.astype(np.int32), np.ones(n) if weight is None else weight[order].astype(np.float64), n - p, bits, (at[a[~cross]] - p).astype(np.int32), (at[b[~cross]] - p).astype(np.int32))
        if edges:
            out.rim, out.own = rim.astype(np.int32), own.astype(np.int32)
            out.place = np.concatenate([np.flatnonzero(cross)[sort], np.flatnonzero(~cross)]).astype(np.int32)
        return out

    def jobs(self, step: int):
        """Ranges of sources, rims and hubs apart."""
        p = len(self.bits)
        for lo, hi in ((0, p), (p, p + self.hubs)):
            yield from ((s, min(hi, s + step)) for s in range(lo, hi, step))


class Flows:
    """Loads of some sources of a scope of two sides, added up."""

    def __init__(self, sides: Sides):
        self.sides, self.p, self.q = sides, len(sides.bits), sides.hubs
        self.hub = np.zeros(self.q)
        self.through = np.zeros((self.q, self.q))  # flows from hub to hub over the rims between them
        self.tied, place = np.unique(np.concatenate([sides.a, sides.b]), return_inverse=True)  # hubs with hubs as neighbours
        self.near = np.zeros((len(self.tied),) * 2)
        x, y = place[: len(sides.a)], place[len(sides.a) :]
        self.near[x, y] = self.near[y, x] = 1.0
        self.edges = sides.rim is not None
        if self.edges:
            self.x, self.y, self.direct = x, y, np.zeros(self.near.shape)  # flows from hub to hub over their edge
            self.first, self.end = np.searchsorted(sides.rim, np.arange(self.p + 1)), np.zeros(len(sides.rim))  # flows of paths that end at a rim
        self.joint = np.zeros((self.q, self.q))
        self.most = 1  # hubs of a rim
        self.lists: list | None = []  # (starts, rims) of each hub, a pair a tile
        listed = 0
        for _, rows in self._tiles(0):
            own = rows.sum(axis=1, dtype=np.int64)
            listed += int(own.sum())
            self.lists = None if self.lists is None or listed > LISTED else self.lists
            if self.lists is not None:
                at, hub = np.nonzero(rows)
                sort = np.argsort(hub, kind="stable")
                self.lists.append((np.searchsorted(hub[sort], np.arange(self.q + 1)).astype(np.int32), at[sort].astype(np.int32)))
            self.most = max(self.most, int(own.max()))
            if self._few(own):
                for _, pair in self._pairs(rows):
                    np.add.at(self.joint.reshape(-1), pair, 1.0)
            else:
                some = rows.astype(np.float32)  # a tile's numbers are exact in it
                self.joint += some.T @ some

    def _tiles(self, first: int):
        for lo in range(first // RIMS * RIMS, self.p, RIMS):
            yield lo, self._open(lo, lo + RIMS)

    def _open(self, lo: int, hi: int) -> np.ndarray:
        return np.unpackbits(self.sides.bits[lo:hi], axis=1, count=self.q)

    def _few(self, own: np.ndarray) -> bool:
        """Whether picking a rim's pairs of hubs is less work than a product over all hubs."""
        return int((own * own).sum()) * 4 * PICKED < len(own) * self.q * self.q

    def _pairs(self, rows: np.ndarray):
        """(rim, place of a pair of its hubs in a table) of all rims of a tile, so many pairs at once."""
        rim, hub = np.nonzero(rows)
        first = np.searchsorted(rim, np.arange(len(rows)))
        size = np.bincount(rim, minlength=len(rows))[rim]
        done, lo = np.cumsum(size), 0
        while lo < len(rim):
            before = done[lo] - size[lo]
            hi = max(lo + 1, int(np.searchsorted(done, before + PICKS, "right")))
            some = size[lo:hi]
            other = np.arange(int(done[hi - 1] - before)) + np.repeat(first[rim[lo:hi]] - (done[lo:hi] - some - before), some)
            yield np.repeat(rim[lo:hi], some), np.repeat(hub[lo:hi] * self.q, some) + hub[other]
            lo = hi

    def add(self, lo: int, hi: int) -> None:
        """Sources lo to hi, rims or hubs."""
        k, rim, weight = hi - lo, lo < self.p, self.sides.weight
        d = np.full((k, self.q), -1, np.int16)
        sigma = np.zeros(d.shape)
        if rim:
            start = self._open(lo, hi).astype(bool)
        else:
            start = np.zeros(d.shape, bool)
            start[np.arange(k), np.arange(lo, hi) - self.p] = True
        level = int(rim)
        d[start], sigma[start] = level, 1.0
        levels = {level: np.flatnonzero(start.any(axis=0))}  # the hubs that some source has there
        while len(levels[level]) or len(levels.get(level - 1, ())):
            level += 1
            reached = self._steps(d, sigma, levels, level - 1, level - 2)
            new = (d < 0) & (reached > 0)
            d[new], sigma[new] = level, reached[new]
            levels[level] = np.flatnonzero(new.any(axis=0))
            if (d >= 0).all():
                break
        ends = self._ends(lo, hi, d, sigma, levels)
        # What hubs get from below, as a share of their paths; as ends they count for hubs alone.
        share = np.zeros(d.shape)
        for level in sorted(levels, reverse=True):
            use = levels[level]
            if not len(use):
                continue
            way = d[:, use] == level
            paths = np.where(way, sigma[:, use], 0.0)
            below = np.where(way, (ends + self._steps(d, share, levels, level + 1, level + 2))[:, use], 0.0)
            if level:
                self.hub[use] += weight[lo:hi] @ (paths * below)
            if self.edges and rim and level == 1:
                flow, part = np.zeros(d.shape), slice(self.first[lo], self.first[hi])
                flow[:, use] = paths * below * weight[lo:hi, None]
                self.end[part] += flow[self.sides.rim[part] - lo, self.sides.own[part]]
            if self.edges and len(self.tied) and len(levels.get(level + 1, ())):
                tied = d[:, self.tied]
                self.direct += (np.where(tied == level, sigma[:, self.tied], 0.0) * weight[lo:hi, None]).T @ np.where(tied == level + 1, share[:, self.tied], 0.0)
            if len(far := levels.get(level + 2, ())):
                self.through[np.ix_(use, far)] += (paths * weight[lo:hi, None]).T @ np.where(d[:, far] == level + 2, share[:, far], 0.0)
            share[:, use] += below if rim else below + np.divide(weight[self.p + use], paths, out=np.zeros(paths.shape), where=way)

    def _steps(self, d: np.ndarray, x: np.ndarray, levels: dict[int, np.ndarray], one: int, two: int) -> np.ndarray:
        """For each source and hub the sum of x over hubs of level one an edge away, and of level two over a rim."""
        out = np.zeros(d.shape)
        if len(self.tied) and len(levels.get(one, ())):
            out[:, self.tied] += np.where(d[:, self.tied] == one, x[:, self.tied], 0.0) @ self.near
        if len(use := levels.get(two, ())):
            out += np.where(d[:, use] == two, x[:, use], 0.0) @ self.joint[use]
        return out

    def _bands(self, d: np.ndarray, sigma: np.ndarray, levels: dict[int, np.ndarray]):
        """(table, step, near, far): numbers of paths of successive levels of hubs, two levels in one table where that is exact.

        The near level's are times a power of two, of which all that the far one adds to a rim
        is a quarter at most.
        """
        order, i = [x for x in sorted(levels) if len(levels[x])], 0
        while i < len(order):
            near, far = (np.where(d == x, sigma, 0.0) for x in (order[i], order[min(i + 1, len(order) - 1)]))
            low, high = (x.max() * self.most for x in (near, far))
            kind = np.float32 if (low + 1) * self.most < EXACT >> 3 and high < EXACT else np.float64
            if i + 1 < len(order) and (kind == np.float32 or (low + 1) * self.most < 1 << 50 and high < 1 << 53):
                step = 2.0 ** np.ceil(np.log2(4 * high))
                yield (near * step + far).astype(kind), step, near, far
                i += 2
                continue
            yield near.astype(np.float32 if low < EXACT else np.float64), None, near, None
            i += 1

    def _ends(self, lo: int, hi: int, d: np.ndarray, sigma: np.ndarray, levels: dict[int, np.ndarray]) -> np.ndarray:
        """For each source and hub the shares of the rims one level below it as ends of paths, both ways counted."""
        both, weight = 2 * self.sides.weight, self.sides.weight[lo:hi, None]
        bands = [(*x, np.zeros(d.shape), np.zeros(d.shape) if x[3] is not None else None, np.nonzero(x[2]), np.count_nonzero(x[2], axis=0)) for x in self._bands(d, sigma, levels)]
        spare = np.empty((2, (hi - lo) * RIMS))
        for at, rows in self._tiles(lo if lo < self.p else 0):
            left = np.arange(at, at + len(rows)) > np.arange(lo, hi)[:, None] if lo < self.p and at < hi else None  # None: all
            use = np.flatnonzero(rows.any(axis=0))
            if len(use) * 4 > self.q * 3:
                use = slice(None)
            else:
                rows = rows[:, use]
            full = rows.astype(np.float64)
            room, share = (x[: (hi - lo) * len(rows)].reshape(hi - lo, -1) for x in spare)
            for table, step, near, far, by_near, by_far, pairs, count in bands:
                paths = table[:, use] @ rows.astype(table.dtype).T
                if far is not None:
                    seen = room.reshape(-1).view(table.dtype)[: room.size].reshape(room.shape)
                    np.rint(np.multiply(paths, table.dtype.type(1 / step), out=seen), out=seen)  # by the near level
                    lower = seen == 0
                    paths = np.add(np.multiply(paths, lower, out=paths), seen, out=paths)
                more = not paths.all()
                if more:
                    none = paths == 0
                    paths[none] = np.inf
                np.divide(both[at : at + len(rows)], paths, out=share)
                if left is not None:
                    share *= left
                lists = self.lists[at // RIMS] if self.lists else None
                if lists is not None and int(count @ np.diff(lists[0])) * PICKED < full.size * len(share):
                    by_near[pairs] += self._picked(share, lists, *pairs)
                else:
                    by_near[:, use] += share @ full  # what a near hub's rims get comes from the near level alone
                if self.edges:
                    flow = share.T @ (near * weight)
                if far is not None:
                    share *= lower
                    by_far[:, use] += share @ full
                    if self.edges:
                        flow += share.T @ (far * weight)
                if self.edges:
                    part = slice(self.first[at], self.first[at + len(rows)])
                    self.end[part] += flow[self.sides.rim[part] - at, self.sides.own[part]]
                if not more:
                    break
                left = none if left is None else left & none
                if not left.any():
                    break
        out = np.zeros(d.shape)
        for _, _, near, far, by_near, by_far, *_ in bands:
            out += np.where(near > 0, by_near, 0.0)
            if far is not None:
                out += np.where(far > 0, by_far, 0.0)
        return out

    @staticmethod
    def _picked(share: np.ndarray, lists: tuple[np.ndarray, np.ndarray], source: np.ndarray, hub: np.ndarray) -> np.ndarray:
        """For some pairs of a source and a hub the sum of the source's shares over the hub's rims in a tile."""
        first, rim = lists
        size, out = (first[1:] - first[:-1])[hub], np.zeros(len(hub))
        own = np.flatnonzero(size)
        if len(own):
            size, start = size[own], first[hub[own]]
            done = np.cumsum(size)
            at = rim[np.arange(int(done[-1])) + np.repeat(start - done + size, size)]
            at += np.repeat(source[own] * share.shape[1], size)
            out[own] = np.add.reduceat(share.reshape(-1)[at], done - size)
        return out

    def edge_loads(self) -> np.ndarray:
        """Of all edges, in the scope's order."""
        both, inner = self.through + self.through.T, np.empty(len(self.end))
        for lo, rows in self._tiles(0):
            part = slice(self.first[lo], self.first[lo + len(rows)])
            inner[part] = (rows.astype(np.float64) @ both)[self.sides.rim[part] - lo, self.sides.own[part]]
        out = np.empty(len(self.sides.place))
        out[self.sides.place] = np.concatenate([self.end + inner, self.direct[self.x, self.y] + self.direct[self.y, self.x]])
        return out

    def loads(self) -> np.ndarray:
        """Of all vertices, in the scope's order."""
        rims = np.zeros(self.p)
        for lo, rows in self._tiles(0):
            if self._few(rows.sum(axis=1, dtype=np.int64)):
                for rim, pair in self._pairs(rows):
                    rims[lo : lo + len(rows)] += np.bincount(rim, self.through.reshape(-1)[pair], len(rows))
            else:
                some = rows.astype(np.float64)
                rims[lo : lo + len(rows)] = ((some @ self.through) * some).sum(axis=1)
        out = np.empty(self.p + self.q)
        out[self.sides.order] = np.concatenate([rims, self.hub])
        return out
