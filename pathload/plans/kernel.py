"""Path state of a block of sources, built and repaired in lockstep over numpy arrays.

For each source of the block and each vertex: distance d (-1: unreachable), number
of shortest paths sigma, dependency delta. All sources of a block advance together:
frontiers are arrays of (source, vertex) keys, so one numpy pass serves the level of
every source. An update first sorts sources by the gap between the edge's ends,
skips those with gap 0, repairs distances, then path counts level by level downward,
then dependencies upward, and returns load differences.

Repairs come in two strategies with equal results: `uniform` rebuilds what is dirty;
`cases` takes the way that the case allows (additive counts where no distance moved,
a fixed step of one where a sibling holds the far end up, plain removal where a part
comes loose, and dependencies by differences of flows where a vertex keeps its place).
"""

from __future__ import annotations

from collections import Counter

import numpy as np

INF = np.int32(1 << 30)
#: Arcs that one pass of a static run unfolds at once: a level of many sources goes in parts, as a dense graph has far more arcs than cells.
PASS_ARCS = 1_000_000
#: A level that has more than one in so many of all sources' arcs is read whole, row by row in order, which costs an arc about a tenth of picking it out.
WHOLE_SHARE = 8
CASES_ADD = ("skip", "flat_add", "rise", "attach")
CASES_REMOVE = ("skip", "flat_remove", "drop_one", "drop", "detach")


class Net:
    """Edges with fixed numbers, and neighbour lists of both directions."""

    def __init__(self, n: int, src: np.ndarray, dst: np.ndarray, directed: bool = False):
        self.n, self.directed = n, directed
        self.src, self.dst = np.asarray(src, np.int64), np.asarray(dst, np.int64)
        self.alive = np.ones(len(self.src), bool)
        self._index()

    def _index(self) -> None:
        e = np.flatnonzero(self.alive)
        tail, head = self.src[e], self.dst[e]
        if self.directed:
            self.out = self._lists(tail, head, e)
            self.into = self._lists(head, tail, e)
        else:
            self.out = self.into = self._lists(np.concatenate([tail, head]), np.concatenate([head, tail]), np.concatenate([e, e]))

    def _lists(self, a: np.ndarray, b: np.ndarray, e: np.ndarray):
        order = np.lexsort((b, a))
        return np.searchsorted(a[order], np.arange(self.n + 1)), b[order], e[order]

    def find(self, u: int, v: int) -> int:
        hit = (self.src == u) & (self.dst == v)
        if not self.directed:
            hit |= (self.src == v) & (self.dst == u)
        hit = np.flatnonzero(hit & self.alive)
        return int(hit[0]) if len(hit) else -1

    def add(self, u: int, v: int) -> int:
        if u == v or self.find(u, v) >= 0:
            raise ValueError("a new edge joins two different vertices that have none")
        if not self.directed and u > v:
            u, v = v, u
        self.src, self.dst, self.alive = np.append(self.src, u), np.append(self.dst, v), np.append(self.alive, True)
        e = len(self.src) - 1
        if self.directed:
            self.out, self.into = self._with(self.out, u, v, e), self._with(self.into, v, u, e)
        else:
            self.out = self.into = self._with(self._with(self.out, u, v, e), v, u, e)
        return e

    def remove(self, u: int, v: int) -> int:
        e = self.find(u, v)
        if e < 0:
            raise ValueError("no such edge")
        self.alive[e] = False
        a, b = int(self.src[e]), int(self.dst[e])
        if self.directed:
            self.out, self.into = self._without(self.out, a, b), self._without(self.into, b, a)
        else:
            self.out = self.into = self._without(self._without(self.out, a, b), b, a)
        return e

    @staticmethod
    def _place(lists, a: int, b: int) -> int:
        at, to, _ = lists
        return int(at[a] + np.searchsorted(to[at[a] : at[a + 1]], b))

    @staticmethod
    def _with(lists, a: int, b: int, e: int):
        """New lists with one arc more, without a sort."""
        at, to, edge = lists
        k = Net._place(lists, a, b)
        return at + (np.arange(len(at)) > a), np.insert(to, k, b), np.insert(edge, k, e)

    @staticmethod
    def _without(lists, a: int, b: int):
        at, to, edge = lists
        k = Net._place(lists, a, b)
        return at - (np.arange(len(at)) > a), np.delete(to, k), np.delete(edge, k)

    def copy(self) -> Net:
        """A net that changes on its own; lists are never changed in place, so both share them."""
        other = Net.__new__(Net)
        other.n, other.directed, other.src, other.dst, other.alive, other.out, other.into = self.n, self.directed, self.src, self.dst, self.alive.copy(), self.out, self.into
        return other

    def grow(self, n: int) -> None:
        self.n = n
        self._index()

    @staticmethod
    def spans(lists, v: np.ndarray, most: int | None = None):
        """Slices of v with at most so many arcs each, or one vertex."""
        at = lists[0]
        total = np.cumsum(at[v + 1] - at[v])
        lo, most = 0, most or PASS_ARCS
        while lo < len(v):
            hi = max(lo + 1, int(np.searchsorted(total, (total[lo - 1] if lo else 0) + most, "right")))
            yield slice(lo, hi)
            lo = hi

    @staticmethod
    def expand(lists, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(which of v, neighbour, edge) for all arcs of v."""
        at, to, edge = lists
        size = at[v + 1] - at[v]
        which = np.repeat(np.arange(len(v)), size)
        place = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size) + np.repeat(at[v], size)
        return which, to[place], edge[place]


class Block:
    """The path state of some sources over one net."""

    def __init__(self, net: Net, sources: np.ndarray, state: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None, predecessors: bool = False, dependencies: bool = True):
        self.net, self.sources = net, np.asarray(sources, np.int64)
        self.predecessors = [] if predecessors else None
        self.lists = None
        self.arcs_read = 0
        if state is None:
            self.search()
            if dependencies:
                self.accumulate()
        else:
            self.d, self.sigma, self.delta = (self._wide(x, f) for x, f in zip(state, (-1, 0.0, 0.0), strict=True))
        if predecessors:
            self.lists = self._path_arcs()

    def _wide(self, x: np.ndarray, fill) -> np.ndarray:
        """Rows stored before vertices came: the missing tail is unreachable."""
        if x.shape[1] < self.net.n:
            x = np.concatenate([x, np.full((len(x), self.net.n - x.shape[1]), fill, x.dtype)], axis=1)
        return np.array(x, np.int32 if fill == -1 else np.float64)

    # -- static -----------------------------------------------------------------

    def search(self) -> None:
        b, n = len(self.sources), self.net.n
        self.d = np.full((b, n), -1, np.int32)
        self.sigma = np.zeros((b, n))
        d, sigma = self.d.reshape(-1), self.sigma.reshape(-1)
        key = np.arange(b) * n + self.sources
        d[key], sigma[key], level = 0, 1.0, 0
        while len(key):
            level += 1
            if self._wide_level(self.net.out, key):
                reached = self._sums_of_neighbours(self.net.into, np.where(self.d == level - 1, self.sigma, 0.0))
                new = (self.d < 0) & (reached > 0)
                self.d[new], self.sigma[new] = level, reached[new]
                key = np.flatnonzero(new)
                continue
            found, upper, lower = [], [], []
            for part in Net.spans(self.net.out, key % n):  # what one part reaches first is at this level for the parts after it too
                some = key[part]
                which, to, _ = Net.expand(self.net.out, some % n)
                self.arcs_read += len(to)
                target = (some - some % n)[which] + to
                new = target[d[target] < 0]
                d[new] = level
                found.append(np.unique(new))
                down = d[target] == level
                low, up = target[down], some[which[down]]
                np.add.at(sigma, low, sigma[up])
                if self.predecessors is not None:
                    upper.append(up)
                    lower.append(low)
            if self.predecessors is not None:
                self.predecessors.append((np.concatenate(upper), np.concatenate(lower)))
            key = np.concatenate(found)

    def accumulate(self) -> None:
        """Dependencies from the deepest level up; by kept predecessor lists, or by scanning neighbours one level up."""
        n = self.net.n
        self.delta = np.zeros(self.d.shape)
        d, sigma, delta = self.d.reshape(-1), self.sigma.reshape(-1), self.delta.reshape(-1)
        for level in range(int(d.max(initial=0)), 0, -1):
            if self.predecessors is not None:
                up, low = self.predecessors[level - 1]
                np.add.at(delta, up, sigma[up] / sigma[low] * (1 + delta[low]))
                continue
            key = np.flatnonzero(d == level)
            if self._wide_level(self.net.into, key):
                below = np.zeros(self.d.shape)
                below.reshape(-1)[key] = (1 + delta[key]) / sigma[key]
                below = self._sums_of_neighbours(self.net.out, below).reshape(-1)
                up = np.flatnonzero(d == level - 1)
                delta[up] = sigma[up] * below[up]
                continue
            for up, low, _ in self._arcs_above(key):
                np.add.at(delta, up, sigma[up] / sigma[low] * (1 + delta[low]))

    def _wide_level(self, lists, key: np.ndarray) -> bool:
        """Whether some keys have so many arcs that reading all arcs of all sources is less work."""
        if self.predecessors is not None:
            return False
        at, v = lists[0], key % self.net.n
        return int((at[v + 1] - at[v]).sum()) * WHOLE_SHARE > len(self.sources) * int(at[-1]) > 0

    def _sums_of_neighbours(self, lists, x: np.ndarray) -> np.ndarray:
        """For each source and vertex the sum of x over the vertex's list."""
        at, to, _ = lists
        out = np.zeros(x.shape)
        own = np.flatnonzero(np.diff(at))
        rows = max(1, PASS_ARCS // max(1, len(to)))
        self.arcs_read += len(x) * len(to)
        for part in Net.spans(lists, own):
            v = own[part]
            lo, hi = at[v[0]], at[v[-1] + 1]
            for i in range(0, len(x), rows):
                out[i : i + rows, v] = np.add.reduceat(np.take(x[i : i + rows], to[lo:hi], axis=1), at[v] - lo, axis=1)
        return out

    def _edge_sums(self) -> np.ndarray:
        """Each edge's flows of all sources, every edge read for every source."""
        src, dst, directed = self.net.src, self.net.dst, self.net.directed
        d = np.where(self.d < 0, -9, self.d)
        share = np.divide(1 + self.delta, self.sigma, out=np.zeros(self.sigma.shape), where=self.sigma > 0)
        out = np.zeros(len(src))
        self.arcs_read += len(d) * int(self.net.into[0][-1])
        rows = max(1, PASS_ARCS // max(1, len(src)))
        for lo in range(0, len(src), PASS_ARCS):
            a, b = src[lo : lo + PASS_ARCS], dst[lo : lo + PASS_ARCS]
            for i in range(0, len(d), rows):
                step = np.take(d[i : i + rows], b, axis=1) - np.take(d[i : i + rows], a, axis=1)
                s, t = self.sigma[i : i + rows], share[i : i + rows]
                out[lo : lo + PASS_ARCS] += np.where(step == 1, np.take(s, a, axis=1) * np.take(t, b, axis=1), 0.0).sum(axis=0)
                if not directed:
                    out[lo : lo + PASS_ARCS] += np.where(step == -1, np.take(s, b, axis=1) * np.take(t, a, axis=1), 0.0).sum(axis=0)
        return out

    def _arcs_above(self, key: np.ndarray):
        """(upper key, lower key, edge) of the path graphs' arcs into some keys, a bounded number of arcs at once."""
        n, d = self.net.n, self.d.reshape(-1)
        for part in Net.spans(self.net.into, key % n):
            some = key[part]
            which, to, edge = Net.expand(self.net.into, some % n)
            self.arcs_read += len(to)
            low = some[which]
            up = low - low % n + to
            use = d[up] == d[low] - 1
            yield up[use], low[use], edge[use]

    def state_bytes(self) -> int:
        lists = sum(8 * len(x) for x in self.lists) if self.lists is not None else 0
        return self.d.size * 20 + lists

    def _path_arcs(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(lower key, upper key, edge) of every arc of every source's path graph: the predecessor lists."""
        n, d = self.net.n, self.d.reshape(-1)
        low = np.flatnonzero(d > 0)
        which, to, edge = Net.expand(self.net.into, low % n)
        self.arcs_read += len(to)
        low = low[which]
        up = low - low % n + to
        use = d[up] == d[low] - 1
        return low[use], up[use], edge[use]

    def _relist(self, rows: np.ndarray, work: Block) -> None:
        """The lists of some rows made anew, as their sources were touched; all keys move if vertices came."""
        n = self.net.n
        touched = np.zeros(len(self.sources), bool)
        touched[rows] = True
        low, up, edge = self.lists
        stay = ~touched[low // n]
        l2, u2, e2 = work._path_arcs()
        shift = (rows - np.arange(len(rows))) * n
        self.lists = np.concatenate([low[stay], l2 + shift[l2 // n]]), np.concatenate([up[stay], u2 + shift[u2 // n]]), np.concatenate([edge[stay], e2])

    def flows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(edge, source row, flow) of every arc of every source's path graph."""
        sigma, delta = self.sigma.reshape(-1), self.delta.reshape(-1)
        low, up, edge = self.lists if self.lists is not None else self._path_arcs()
        return edge, low // self.net.n, sigma[up] / sigma[low] * (1 + delta[low])

    def loads(self, kind: str = "both") -> tuple[np.ndarray, np.ndarray]:
        """This block's part of the vertex loads and edge loads; zeros for those that kind leaves out."""
        vertex, edges = np.zeros(self.net.n), np.zeros(len(self.net.src))
        if kind != "edge":
            at = np.arange(len(self.sources)), self.sources
            own, self.delta[at] = self.delta[at], 0
            vertex = self.delta.sum(axis=0)
            self.delta[at] = own
        if kind != "vertex":
            sigma, delta = self.sigma.reshape(-1), self.delta.reshape(-1)
            if self.lists is not None:
                edge, _, flow = self.flows()
                edges += np.bincount(edge, flow, len(edges))
                return vertex, edges
            key = np.flatnonzero(self.d.reshape(-1) > 0)
            if self.net.alive.all() and self._wide_level(self.net.into, key):
                return vertex, self._edge_sums()
            for up, low, edge in self._arcs_above(key):
                np.add.at(edges, edge, sigma[up] / sigma[low] * (1 + delta[low]))
        return vertex, edges

    # -- updates ----------------------------------------------------------------

    def triage(self, op: str, u: int, v: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(near, far, gap, affected) of each source; unreachable counts as infinitely far."""
        du, dv = (np.where(self.d[:, x] < 0, INF, self.d[:, x]) for x in (u, v))
        if self.net.directed:
            near, far, gap = np.full(len(du), u), np.full(len(du), v), np.maximum(dv - du, 0)
            gap = np.where(du == INF, 0, gap)
            return near, far, gap, gap == 1 if op == "remove" else gap >= 1
        flip = du > dv
        near, far = np.where(flip, v, u), np.where(flip, u, v)
        gap = np.abs(du - dv)
        return near, far, gap, gap >= 1

    def cases(self, op: str, u: int, v: int) -> np.ndarray:
        """Each source's case by distances alone; a removal with neither another upper neighbour nor a sibling is drop_more."""
        near, far, gap, affected = self.triage(op, u, v)
        rows, n, d = np.flatnonzero(affected), self.net.n, self.d.reshape(-1)
        out = np.full(len(self.sources), "skip", object)
        key = rows * n + far[rows]
        if op == "add":
            out[rows] = np.where(gap[rows] == 1, "flat_add", np.where(d[key] < 0, "attach", "rise"))
            return out
        which, to, _ = Net.expand(self.net.into, far[rows])
        other = (rows * n)[which] + to
        level = np.where(d[other] < 0, INF, d[other]) - d[key[which]]
        upper = np.bincount(which, (level == -1) & (to != near[rows][which]), len(rows)) > 0
        sibling = np.bincount(which, level == 0, len(rows)) > 0
        out[rows] = np.where(upper, "flat_remove", np.where(sibling, "drop_one", "drop_more"))
        return out

    def apply(self, op: str, u: int, v: int, strategy: str = "uniform") -> dict:
        """One update. Returns vertex and edge load differences, cases, and work counts."""
        net, n = self.net, self.net.n
        near, far, gap, affected = self.triage(op, u, v)
        rows = np.flatnonzero(affected)
        edge = net.add(u, v) if op == "add" else net.find(u, v)
        if edge < 0:
            raise ValueError("no such edge")
        old_out, old_into = (net.out, net.into)
        if op == "remove":
            net.remove(u, v)
        cases = np.full(len(self.sources), "skip", object)
        vertex, edges = np.zeros(n), np.zeros(len(net.src))
        if not len(rows):
            return {"vertex": vertex, "edge": edges, "edge_id": edge, "cases": Counter(cases.tolist()), "case": cases, "touched": 0, "rows": rows}
        d0, s0, t0 = self.d[rows].copy(), self.sigma[rows].copy(), self.delta[rows].copy()
        work = Block.__new__(Block)
        work.net, work.sources, work.predecessors, work.lists, work.arcs_read = net, self.sources[rows], None, None, 0
        work.d, work.sigma, work.delta = d0.copy(), s0.copy(), t0.copy()
        base = np.arange(len(rows)) * n
        farthest, nearest = base + far[rows], base + near[rows]
        if op == "add":
            jump = gap[rows] > 1
            cases[rows] = np.where(jump, np.where(d0.reshape(-1)[farthest] < 0, "attach", "rise"), "flat_add")
            moved = work._rise(farthest[jump], nearest[jump])
        else:
            moved, kind = work._fall(farthest, strategy)
            cases[rows] = kind
        flat = np.isin(cases[rows], ("flat_add", "flat_remove"))
        if strategy == "cases":
            work._push_counts(d0, s0, farthest[flat], nearest[flat], 1.0 if op == "add" else -1.0)
            work._recount(d0, moved, farthest[~flat])
        else:
            work._recount(d0, moved, farthest)
        if strategy == "cases":
            touched, gained = work._move_dependencies(d0, s0, t0, nearest, farthest, (old_out, old_into), edge, op)
        else:
            touched = work._redepend(d0, s0, t0, moved, nearest, farthest, (old_out, old_into))
            changed = (work.d != d0) | (work.sigma != s0) | (work.delta != t0)
            gained = work._flow_difference(d0, s0, t0, changed.reshape(-1), edge, op)
        edges += gained
        gain = work.delta - t0
        gain[np.arange(len(rows)), work.sources] = 0
        vertex += gain.sum(axis=0)
        self.d[rows], self.sigma[rows], self.delta[rows] = work.d, work.sigma, work.delta
        if self.lists is not None:
            self._relist(rows, work)
        return {"vertex": vertex, "edge": edges, "edge_id": edge, "cases": Counter(cases.tolist()), "case": cases, "touched": int(touched), "rows": rows, "arcs": work.arcs_read}

    def _rise(self, far: np.ndarray, near: np.ndarray) -> np.ndarray:
        """The far ends move up to one below the near ends, and pull others with them. Returns all moved keys."""
        n, d = self.net.n, self.d.reshape(-1)
        d[far] = d[near] + 1
        key, moved = far, [far]
        while len(key):
            which, to, _ = Net.expand(self.net.out, key % n)
            self.arcs_read += len(to)
            target = (key - key % n)[which] + to
            want = d[key[which]] + 1
            closer = (d[target] < 0) | (d[target] > want)
            new, first = np.unique(target[closer], return_index=True)
            d[new] = want[closer][first]
            moved.append(new)
            key = new
        return np.unique(np.concatenate(moved))

    def _has_upper(self, key: np.ndarray, orphan: np.ndarray) -> np.ndarray:
        """Whether a neighbour one level up is there that is no orphan."""
        n, d = self.net.n, self.d.reshape(-1)
        which, to, _ = Net.expand(self.net.into, key % n)
        self.arcs_read += len(to)
        other = (key - key % n)[which] + to
        good = (d[other] >= 0) & (d[other] == d[key[which]] - 1) & ~orphan[other]
        return np.bincount(which, good, len(key)) > 0

    def orphans(self, far: np.ndarray) -> np.ndarray:
        """Keys that lose all their upper neighbours, level by level from the far ends."""
        n, d = self.net.n, self.d.reshape(-1)
        orphan = np.zeros(d.shape, bool)
        key = far[~self._has_upper(far, orphan)]
        found = [key]
        while len(key):
            orphan[key] = True
            which, to, _ = Net.expand(self.net.out, key % n)
            self.arcs_read += len(to)
            target = (key - key % n)[which] + to
            target = np.unique(target[(d[target] == d[key[which]] + 1) & ~orphan[target]])
            key = target[~self._has_upper(target, orphan)]
            found.append(key)
        return np.unique(np.concatenate(found))

    def find_anchors(self, orphans: np.ndarray) -> np.ndarray:
        """Keys that keep their distance and have an orphan among the vertices they lead to."""
        n, d = self.net.n, self.d.reshape(-1)
        inside = np.zeros(d.shape, bool)
        inside[orphans] = True
        which, to, _ = Net.expand(self.net.into, orphans % n)
        self.arcs_read += len(to)
        other = (orphans - orphans % n)[which] + to
        return np.unique(other[(d[other] >= 0) & ~inside[other]])

    def _fall(self, far: np.ndarray, strategy: str) -> tuple[np.ndarray, np.ndarray]:
        """Distances after a removal. Returns moved keys and each source's case."""
        n, d = self.net.n, self.d.reshape(-1)
        kind = np.full(len(far), "flat_remove", object)
        orphans = self.orphans(far)
        if not len(orphans):
            return orphans, kind
        row = orphans // n
        lost = np.zeros(len(far), bool)
        lost[row] = True
        which, to, _ = Net.expand(self.net.into, far % n)
        other = (far - far % n)[which] + to
        sibling = np.bincount(which, (d[other] == d[far[which]]), len(far)) > 0
        # A sibling keeps its distance, so it holds the far end one step lower and all orphans with it: no search for anchors.
        by_one = lost & sibling & (not self.net.directed)
        one = by_one[row]
        held = np.zeros(len(far), bool)
        if not one.all():
            held[np.unique(self.find_anchors(orphans[~one]) // n)] = True
        kind[lost] = np.where(by_one, "drop_one", np.where(held, "drop", "detach"))[lost]
        if strategy == "cases":
            loose = (lost & ~by_one & ~held)[row]
            d[orphans[one]] += 1
            d[orphans[loose]] = -1
            self._settle(orphans[~one & ~loose])
        else:
            self._settle(orphans)
        return orphans, kind

    def _settle(self, orphans: np.ndarray) -> None:
        """Distances of orphans from the anchors around them; what no anchor reaches is unreachable."""
        n, d = self.net.n, self.d.reshape(-1)
        d[orphans] = INF
        which, to, _ = Net.expand(self.net.into, orphans % n)
        self.arcs_read += len(to)
        other = (orphans - orphans % n)[which] + to
        good = (d[other] >= 0) & (d[other] < INF)
        np.minimum.at(d, orphans[which[good]], d[other[good]] + 1)
        key = orphans[d[orphans] < INF]
        while len(key):
            which, to, _ = Net.expand(self.net.out, key % n)
            self.arcs_read += len(to)
            target = (key - key % n)[which] + to
            want = d[key[which]] + 1
            closer = d[target] > want
            np.minimum.at(d, target[closer], want[closer])
            key = np.unique(target[closer])
        d[orphans[d[orphans] == INF]] = -1

    def _push_counts(self, d0, s0, far, near, sign: float) -> None:
        """Counts where no distance moved: the difference enters at the far end and runs down, each level once complete."""
        if not len(far):
            return
        n, d, sigma = self.net.n, self.d.reshape(-1), self.sigma.reshape(-1)
        more = np.zeros(d.shape)
        more[far] = sign * sigma[near]
        key = far
        while len(key):
            sigma[key] += more[key]
            which, to, _ = Net.expand(self.net.out, key % n)
            self.arcs_read += len(to)
            target = (key - key % n)[which] + to
            down = d[target] == d[key[which]] + 1
            np.add.at(more, target[down], more[key[which[down]]])
            key = np.unique(target[down])

    def _recount(self, d0: np.ndarray, moved: np.ndarray, far: np.ndarray) -> None:
        """Counts rebuilt for moved vertices and whatever hangs below a change, in rising levels."""
        if not len(far) and not len(moved):
            return
        n, d, sigma, before = self.net.n, self.d.reshape(-1), self.sigma.reshape(-1), d0.reshape(-1)
        which, to, _ = Net.expand(self.net.out, moved % n)
        near = (moved - moved % n)[which] + to
        x = moved[which]
        below = ((before[x] >= 0) & (before[near] == before[x] + 1)) | ((d[x] >= 0) & (d[near] == d[x] + 1))
        dirty = np.zeros(d.shape, bool)
        for part in (moved, far, near[below]):
            dirty[part] = True
        gone = np.flatnonzero(dirty & (d < 0))
        sigma[gone] = 0
        dirty[gone] = False
        todo = np.flatnonzero(dirty)
        level = int(d[todo].min()) if len(todo) else 0
        while len(todo):
            here = todo[d[todo] == level]
            rest = todo[d[todo] > level]
            new_below = np.zeros(0, np.int64)
            if len(here):
                which, to, _ = Net.expand(self.net.into, here % n)
                self.arcs_read += len(to)
                up = (here - here % n)[which] + to
                use = (d[up] >= 0) & (d[up] == level - 1)
                total = np.bincount(which[use], sigma[up[use]], len(here))
                if level == 0:
                    total = sigma[here]
                other = here[(total != sigma[here]) | (d[here] != before[here])]
                sigma[here] = total
                which, to, _ = Net.expand(self.net.out, other % n)
                target = (other - other % n)[which] + to
                new_below = target[d[target] == level + 1]
            todo = np.unique(np.concatenate([rest, new_below]))
            level += 1

    def _redepend(self, d0, s0, t0, moved, near, far, old) -> int:
        """Dependencies rebuilt from the deepest dirty level up. Returns how many keys were looked at."""
        n, d, sigma, delta = self.net.n, self.d.reshape(-1), self.sigma.reshape(-1), self.delta.reshape(-1)
        bd, bs, bt = d0.reshape(-1), s0.reshape(-1), t0.reshape(-1)
        changed = np.flatnonzero((d != bd) | (sigma != bs))
        dirty = np.zeros(d.shape, bool)
        for part in (changed, near, far):
            dirty[part] = True
        for lists in (old[1], self.net.into):
            which, to, _ = Net.expand(lists, changed % n)
            self.arcs_read += len(to)
            up = (changed - changed % n)[which] + to
            x = changed[which]
            above = ((bd[x] > 0) & (bd[up] == bd[x] - 1)) | ((d[x] > 0) & (d[up] == d[x] - 1))
            dirty[up[above]] = True
        gone = np.flatnonzero(dirty & (d < 0))
        delta[gone] = 0
        dirty[gone] = False
        seen = len(gone)
        todo = np.flatnonzero(dirty)
        level = int(d[todo].max()) if len(todo) else -1
        while level >= 0 and len(todo):
            here = todo[d[todo] == level]
            rest = todo[d[todo] < level]
            above = np.zeros(0, np.int64)
            if len(here):
                seen += len(here)
                which, to, _ = Net.expand(self.net.out, here % n)
                self.arcs_read += len(to)
                low = (here - here % n)[which] + to
                use = d[low] == level + 1
                x = here[which[use]]
                total = np.bincount(which[use], sigma[x] / sigma[low[use]] * (1 + delta[low[use]]), len(here))
                other = here[(total != delta[here]) | (sigma[here] != bs[here]) | (d[here] != bd[here])]
                delta[here] = total
                which, to, _ = Net.expand(self.net.into, other % n)
                up = (other - other % n)[which] + to
                above = up[(d[up] >= 0) & (d[up] == level - 1)]
            todo = np.unique(np.concatenate([rest, above]))
            level -= 1
        return seen

    def _move_dependencies(self, d0, s0, t0, near, far, old, edge: int, op: str) -> tuple[int, np.ndarray]:
        """Dependencies by differences of flows: (keys looked at, edge load differences).

        Where neither distance nor count changed, a vertex starts from its old
        dependency and gets, for each lower vertex whose flow is another, the new flow
        less the old one; the other lower vertices are never read. Where one of them
        changed, it is added up anew. What a moved vertex gave to its former upper
        neighbours is taken back first, as its new level may lie on either side of
        theirs. The same differences are those of the edges' loads.
        """
        n, net = self.net.n, self.net
        d, sigma, delta = self.d.reshape(-1), self.sigma.reshape(-1), self.delta.reshape(-1)
        bd, bs, bt = d0.reshape(-1), s0.reshape(-1), t0.reshape(-1)
        out = np.zeros(len(net.src))
        other = (d != bd) | (sigma != bs)
        changed = np.flatnonzero(other)
        parts = [changed, far]
        for lists, at in ((old[0], bd), (net.out, d)):  # arcs below a changed vertex carry something else
            which, to, _ = Net.expand(lists, changed % n)
            self.arcs_read += len(to)
            x = changed[which]
            low = x - x % n + to
            parts.append(low[(at[x] >= 0) & (at[low] == at[x] + 1)])
        todo = np.unique(np.concatenate(parts))

        def give(up: np.ndarray, e: np.ndarray, amount: np.ndarray) -> np.ndarray:
            """Adds flows to edges and to upper vertices that are not added up anew; returns those."""
            nonlocal out
            out += np.bincount(e, amount, len(out))
            use = ~other[up] & (amount != 0)
            np.add.at(delta, up[use], amount[use])
            return up[use]

        moved = todo[(d[todo] != bd[todo]) & (bd[todo] > 0)]
        which, to, e = Net.expand(old[1], moved % n)
        self.arcs_read += len(to)
        low = moved[which]
        up = low - low % n + to
        use = (bd[up] >= 0) & (bd[up] == bd[low] - 1)
        low, up, e = low[use], up[use], e[use]
        lost = [give(up, e, -bs[up] / bs[low] * (1 + bt[low]))]
        if op == "remove":  # where the far end stays, its list no longer has the arc
            use = (d[far] == bd[far]) & (bd[far] > 0) & (bd[near] == bd[far] - 1)
            x, y = near[use], far[use]
            lost.append(give(x, np.full(len(x), edge), -bs[x] / bs[y] * (1 + bt[y])))
        todo = np.unique(np.concatenate([todo, *lost]))
        gone = todo[d[todo] < 0]
        delta[gone] = 0
        todo = todo[d[todo] >= 0]
        seen = len(gone)
        level = int(d[todo].max()) if len(todo) else -1
        while level >= 0 and len(todo):
            here = todo[d[todo] == level]
            rest = todo[d[todo] < level]
            above = np.zeros(0, np.int64)
            if len(here):
                seen += len(here)
                anew = here[other[here]]
                if len(anew):
                    which, to, _ = Net.expand(net.out, anew % n)
                    self.arcs_read += len(to)
                    low = (anew - anew % n)[which] + to
                    use = d[low] == level + 1
                    x = anew[which[use]]
                    delta[anew] = np.bincount(which[use], sigma[x] / sigma[low[use]] * (1 + delta[low[use]]), len(anew))
                if level:
                    which, to, e = Net.expand(net.into, here % n)
                    self.arcs_read += len(to)
                    low = here[which]
                    up = low - low % n + to
                    now = d[up] == level - 1
                    before = (bd[low] == level) & (bd[up] == level - 1)
                    if op == "add":
                        before &= e != edge
                    use = now | before
                    low, up, e, now, before = low[use], up[use], e[use], now[use], before[use]
                    with np.errstate(divide="ignore", invalid="ignore"):
                        new = np.where(now, sigma[up] / sigma[low] * (1 + delta[low]), 0.0)
                        was = np.where(before, bs[up] / bs[low] * (1 + bt[low]), 0.0)
                    above = give(up, e, new - was)
            todo = np.unique(np.concatenate([rest, above]))
            level -= 1
        return seen, out

    def _flow_difference(self, d0, s0, t0, changed: np.ndarray, edge: int, op: str) -> np.ndarray:
        """New minus old flow of every arc at a changed vertex; the updated edge has only one side."""
        n, net = self.net.n, self.net
        out = np.zeros(len(net.src))

        def flow(x, y, d, s, t):
            """From x over the arc to y."""
            down = (d[x] >= 0) & (d[y] == d[x] + 1)
            with np.errstate(divide="ignore", invalid="ignore"):
                return np.where(down, s[x] / s[y] * (1 + t[y]), 0.0)

        new = self.d.reshape(-1), self.sigma.reshape(-1), self.delta.reshape(-1)
        old = d0.reshape(-1), s0.reshape(-1), t0.reshape(-1)
        key = np.flatnonzero(changed)
        seen = []
        for lists in (net.out,) if not net.directed else (net.out, net.into):
            which, to, e = Net.expand(lists, key % n)
            self.arcs_read += len(to)
            x = key[which]
            y = x - x % n + to
            use = e != edge
            x, y, e = x[use], y[use], e[use]
            if net.directed and lists is net.into:
                x, y = y, x
                once = ~changed[x]  # arcs whose tail changed were met already
            else:
                once = ~changed[y] | (x < y) if not net.directed else np.ones(len(x), bool)
            seen.append((x[once], y[once], e[once]))
        for x, y, e in seen:
            gain = flow(x, y, *new) - flow(x, y, *old)
            if not net.directed:
                gain += flow(y, x, *new) - flow(y, x, *old)
            out += np.bincount(e, gain, len(out))
        base = np.arange(len(self.d)) * n
        x, y = base + net.src[edge], base + net.dst[edge]
        side, sign = (new, 1.0) if op == "add" else (old, -1.0)
        own = flow(x, y, *side) + (0 if net.directed else flow(y, x, *side))
        out[edge] += sign * own.sum()
        return out


def grown(block: Block, n: int) -> None:
    """A block after vertices came: unreachable until edges reach them."""
    if block.lists is not None:
        raise ValueError("lists are kept for a fixed number of vertices")
    block.net.grow(n)
    block.d, block.sigma, block.delta = (block._wide(x, f) for x, f in ((block.d, -1), (block.sigma, 0.0), (block.delta, 0.0)))
