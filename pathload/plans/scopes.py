"""Loads without path state, one connected scope at a time.

No shortest path leaves its component, so each component is searched on its own, small
ones several together. Trees are counted and not searched: what a vertex or an edge holds
together follows from the sizes of the parts that it keeps apart. A sparse scope takes the
kernel's lists; a dense one is a matrix of
bits, whose levels are matrix products over a few rows unpacked at a time; one of few hubs
and many vertices beside them takes products over the hubs (plans/sides.py). Partial loads
travel as pieces of positions, are added up by piece, and get their ids at the end; the
driver holds the edges' ends as positions and no loads. Memory grows with the edges and
never with pairs of vertices.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from pathload.operators.components import cut_lineage
from pathload.operators.graph import ID_BYTES, Graph
from pathload.plans.blocks import TASK_CELLS, Loads, sources_at_once
from pathload.plans.kernel import Block, Net
from pathload.plans.sides import ROWS, Flows, Sides, bridges, hubs

#: Vertices of small components that share one scope.
SHARED = 512
#: A scope is dense from one arc in so many pairs on, up to so many vertices (50 MB of bits).
DENSE, DENSE_MOST = 32, 20_000
#: A scope has two sides from one arc in so many pairs of a hub and a rim on, where hubs are a quarter of it at most, and up to so many hubs (three tables of 134 MB).
TWO_SIDED, HUBS_MOST = 64, 4096
#: Rows of a bit matrix that are unpacked at once; positions of a piece of partial loads.
TILE, PIECE = 512, 1 << 16
#: Bytes of an edge on the driver while edges are sorted; of the ends of a graph there.
EDGE_BYTES, ENDS_MOST = 40, 1 << 30
#: Edges whose ends a task looks up at once.
LOOKED_UP = 1 << 20
#: Bytes of all tasks' edge loads before they are added up, where more tasks than cores would share the work.
EDGE_MOST = 1 << 28


@dataclass
class Ends:
    """A graph as positions: ids in order, edges sorted by (src, dst)."""

    ids: list[str]
    src: np.ndarray
    dst: np.ndarray
    directed: bool


def ends_bytes(graph: Graph) -> int:
    """Bytes of the graph's ends on the driver, from counts."""
    return graph.edges.count() * EDGE_BYTES + graph.vertices.count() * 2 * ID_BYTES


def ends_of(graph: Graph) -> Ends:
    """Positions are looked up in the tasks, so the driver gets eight bytes an edge; refuses what would not fit there."""
    if (need := ends_bytes(graph)) > ENDS_MOST:
        raise MemoryError(f"graph of {need} bytes on the driver")
    ids = sorted(graph.vertices.toArrow().column(0).to_pylist())
    sent = graph.spark.sparkContext.broadcast(ids)

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, some, size = pa.array(sent.value, pa.string()), [], 0
        for b in itertools.chain(batches, (None,)):
            if b is not None:
                some.append(b)
                size += b.num_rows
            if some and (b is None or size >= LOOKED_UP):  # each call makes its table of all names anew
                yield from pa.Table.from_arrays([pc.index_in(x, names) for x in pa.Table.from_batches(some).columns], ["a", "b"]).combine_chunks().to_batches()
                some, size = [], 0

    found = graph.edges.select("src", "dst").mapInArrow(look_up, "a int, b int").toArrow()
    return Ends(ids, *_in_order(*(found.column(i).to_numpy() for i in (0, 1)), len(ids)), graph.directed)


def _in_order(a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    key = a.astype(np.int64) * n + b
    key.sort()
    return (key // max(n, 1)).astype(np.int32), (key % max(n, 1)).astype(np.int32)


def edited(ends: Ends, work: list[tuple[str, str, str]], new_vertices: tuple[str, ...] = (), gone: str | None = None) -> Ends:
    """The graph after updates (op, u, v), checked in turn; those that don't fit it are left out, as a session rejects them. gone: a vertex that leaves with its edges."""
    ids = sorted({*ends.ids, *new_vertices})
    at = np.searchsorted(np.array(ids, dtype=object), np.array(ends.ids, dtype=object)).astype(np.int32) if len(ids) > len(ends.ids) else np.arange(len(ids), dtype=np.int32)
    place, n = {v: i for i, v in enumerate(ids)}, len(ids)
    key = at[ends.src].astype(np.int64) * n + at[ends.dst]  # positions move in order, so keys stay sorted
    now: dict[int, bool] = {}
    for op, u, v in work:
        if u == v or u not in place or v not in place:
            continue
        k = place[u] * n + place[v] if ends.directed or u < v else place[v] * n + place[u]
        i = int(np.searchsorted(key, k))
        if now.get(k, i < len(key) and key[i] == k) != (op == "add"):
            now[k] = op == "add"
    key = key[~np.isin(key, list(now))]
    key = np.sort(np.append(key, np.array([k for k, there in now.items() if there], np.int64)))
    src, dst = (key // max(n, 1)).astype(np.int32), (key % max(n, 1)).astype(np.int32)
    if gone in place:
        x = place[gone]
        use = (src != x) & (dst != x)
        src, dst = (y[use] - (y[use] > x).astype(np.int32) for y in (src, dst))
        ids = ids[:x] + ids[x + 1 :]
    return Ends(ids, src, dst, ends.directed)


def distances(ends: Ends, source: int) -> np.ndarray:
    """Each vertex's distance from one source, -1 where there is no way: a pass over a level's arcs a level."""
    a, b, n = ends.src, ends.dst, len(ends.ids)
    if not ends.directed:
        a, b = np.concatenate([a, b]), np.concatenate([b, a])
    order = np.argsort(a, kind="stable")
    at, to = np.searchsorted(a[order], np.arange(n + 1)), b[order]
    del a, b, order
    out, now, level = np.full(n, -1, np.int32), np.array([source]), 0
    while len(now):
        out[now] = level
        level += 1
        size = at[now + 1] - at[now]
        near = to[np.arange(int(size.sum())) + np.repeat(at[now] - np.cumsum(size) + size, size)]
        now = np.unique(near[out[near] < 0])
    return out


def distances_from(graph: Graph, source: str) -> DataFrame:
    """(s, t, d) of all vertices that one source reaches, searched in one task: as many rounds of Spark for a long chain as for a short one."""
    sent = graph.spark.sparkContext.broadcast((ends_of(graph), source))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _ in batches:
            ends, source = sent.value
            d = distances(ends, int(np.searchsorted(np.array(ends.ids, dtype=object), source)))
            there = np.flatnonzero(d >= 0)
            for lo in range(0, len(there), PIECE):
                some = there[lo : lo + PIECE]
                yield pa.RecordBatch.from_arrays([pa.array([source] * len(some), pa.string()), pa.array([ends.ids[i] for i in some.tolist()], pa.string()), pa.array(d[some])], ["s", "t", "d"])

    return cut_lineage(graph.spark.range(0, 1, 1, 1).mapInArrow(run, "s string, t string, d int"))


def labels(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least vertex of each vertex's component: least labels over edges, then jumps, until nothing moves."""
    out = np.arange(n)
    while len(a):
        x, y = out[a], out[b]
        if (x == y).all():
            break
        low = np.minimum(x, y)
        np.minimum.at(out, x, low)
        np.minimum.at(out, y, low)
        while (out[out] != out).any():
            out = out[out]
    return out


def scopes(n: int, label: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """(vertices in scope order, ranges of them): a component, or small ones up to SHARED vertices together."""
    order = np.argsort(label, kind="stable")
    starts = np.flatnonzero(np.append(True, label[order][1:] != label[order][:-1])) if n else np.zeros(0, np.int64)
    ranges, lo = [], 0
    for a, b in zip(starts.tolist(), [*starts[1:].tolist(), n][: len(starts)], strict=True):
        if b - lo > SHARED and a > lo:
            ranges.append((lo, a))
            lo = a
    if n:
        ranges.append((lo, n))
    return order, ranges


def tree_loads(n: int, a: np.ndarray, b: np.ndarray, kind: str) -> np.ndarray:
    """Exact loads of a kind of an undirected graph of trees: leaves are taken off, round by round, and leave their size to what they hang on.

    A vertex is on the way of all ordered pairs of others but those that stay in one part
    without it, an edge on that of all pairs of its two parts.
    """
    degree = np.bincount(a, minlength=n) + np.bincount(b, minlength=n)
    near = np.zeros(n, np.int64)  # exclusive or of all neighbours: of the last one, where one is left
    edge = np.zeros(n, np.int64)  # likewise of edges
    for x, y in ((a, b), (b, a)):
        np.bitwise_xor.at(near, x, y.astype(np.int64))
        np.bitwise_xor.at(edge, x, np.arange(len(a)))
    size, squares, up, rounds = np.ones(n, np.int64), np.zeros(n), np.arange(n), []
    leaves = np.flatnonzero(degree == 1)
    while len(leaves):
        on = near[leaves]
        use = (degree[on] > 1) | (leaves < on)  # of two that are left alone with each other, one stays
        leaves, on = leaves[use], on[use]
        up[leaves] = on
        rounds.append(leaves)
        np.add.at(size, on, size[leaves])
        np.add.at(squares, on, size[leaves].astype(np.float64) ** 2)
        np.subtract.at(degree, on, 1)
        np.bitwise_xor.at(near, on, leaves)
        np.bitwise_xor.at(edge, on, edge[leaves])
        degree[leaves] = 0
        on = np.unique(on)
        leaves = on[degree[on] == 1]
    whole = size.copy()  # of the tree, from its root downward
    for leaves in reversed(rounds):
        whole[leaves] = whole[up[leaves]]
    if kind == "vertex":
        return (whole - 1.0) ** 2 - squares - (whole - size).astype(np.float64) ** 2
    out, low = np.zeros(len(a)), np.concatenate([np.zeros(0, np.int64), *rounds])
    out[edge[low]] = 2.0 * size[low] * (whole - size)[low]
    return out


def bit_rows(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row a has bit b for each arc; a is sorted."""
    out = np.zeros((n, -(-n // 8)), np.uint8)
    for lo in range(0, n, TILE):
        part = slice(*np.searchsorted(a, (lo, lo + TILE)))
        some = np.zeros((min(TILE, n - lo), n), bool)
        some[a[part] - lo, b[part]] = True
        out[lo : lo + TILE] = np.packbits(some, axis=1)
    return out


class Dense:
    """All levels of some sources over a matrix of bits."""

    def __init__(self, n: int, out: np.ndarray, into: np.ndarray, directed: bool):
        self.n, self.out, self.into, self.directed = n, out, into, directed

    def _open(self, bits: np.ndarray) -> np.ndarray:
        return np.unpackbits(bits, axis=1, count=self.n)

    def _sums(self, x: np.ndarray, lists: np.ndarray) -> np.ndarray:
        """For each source and vertex the sum of x over the vertex's row of lists."""
        y = np.empty(x.shape)
        for lo in range(0, self.n, TILE):
            y[:, lo : lo + TILE] = x @ self._open(lists[lo : lo + TILE]).astype(np.float64).T
        return y

    def add(self, sources: np.ndarray, vertex: np.ndarray, edge: np.ndarray, kind: str) -> None:
        """Adds some sources' loads of a kind in place; edges are in the order of (src, dst)."""
        at = np.arange(len(sources)), sources
        d = np.full((len(sources), self.n), -1, np.int16)
        sigma = np.zeros(d.shape)
        d[at], sigma[at], level = 0, 1.0, 0
        while True:
            level += 1
            reached = self._open(self.out[sources]).astype(np.float64) if level == 1 else self._sums(np.where(d == level - 1, sigma, 0.0), self.into)
            new = (d < 0) & (reached > 0)
            if not new.any():
                break
            d[new], sigma[new] = level, reached[new]
            if (d >= 0).all():
                level += 1
                break
        delta = np.zeros(d.shape)
        for k in range(level - 1, 1, -1):  # what comes to the source itself is nobody's load
            share = np.divide(1 + delta, sigma, out=np.zeros(d.shape), where=d == k)
            delta += np.where(d == k - 1, sigma * self._sums(share, self.out), 0.0)
        if kind == "vertex":
            vertex += delta.sum(axis=0)
        else:
            self._edges(sources, d, sigma, delta, level, edge)

    def _edges(self, sources: np.ndarray, d: np.ndarray, sigma: np.ndarray, delta: np.ndarray, level: int, edge: np.ndarray) -> None:
        share = np.divide(1 + delta, sigma, out=np.zeros(d.shape), where=sigma > 0)
        at = 0
        first = np.where(d == 1, share, 0.0)  # what leaves the sources needs no product
        for lo in range(0, self.n, TILE):
            tile = slice(lo, lo + TILE)
            flow = np.zeros((min(TILE, self.n - lo), self.n))
            own = np.flatnonzero((sources >= lo) & (sources < lo + TILE))
            flow[sources[own] - lo] += first[own]
            if not self.directed:
                flow[:, sources] += first[:, tile].T
            for k in range(1, level - 1):
                flow += np.where(d[:, tile] == k, sigma[:, tile], 0.0).T @ np.where(d == k + 1, share, 0.0)
                if not self.directed:
                    flow += np.where(d[:, tile] == k + 1, share[:, tile], 0.0).T @ np.where(d == k, sigma, 0.0)
            there = self._open(self.out[tile]).astype(bool)
            if not self.directed:
                there &= np.arange(self.n) > np.arange(lo, lo + len(there))[:, None]
            part = flow[there]
            edge[at : at + len(part)] += part
            at += len(part)


@dataclass
class Trees:
    """A scope of trees: the ends of its edges."""

    a: np.ndarray
    b: np.ndarray


def _hubs_of(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray | None:
    """The hubs of an undirected scope of two sides, if it is one with few of them and products over them are less work than lists."""
    hub = hubs(n, a, b)
    q = int(hub.sum())
    return hub if n > SHARED and 0 < q <= min(HUBS_MOST, n // 4) and q * (n - q) <= min(2 * len(a) * TWO_SIDED, DENSE_MOST**2) else None


def parted(n: int, label: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Components of an undirected graph, trees aside, cut at edges between large parts, where all parts have two sides.

    Returns labels, the edges that stay, how many vertices each vertex stands for, and its
    load of paths between vertices of which one at least stands behind it.
    """
    label, stay, weight, behind = label.copy(), np.ones(len(a), bool), np.ones(n), np.zeros(n)
    members, by = np.argsort(label, kind="stable"), np.argsort(label[a], kind="stable")
    roots, count = np.unique(label, return_counts=True)
    first, ends, at = np.cumsum(count) - count, label[a][by], np.zeros(n, np.int64)
    arcs = np.bincount(np.searchsorted(roots, label[a]), minlength=len(roots))
    for i in np.flatnonzero((count > 2 * SHARED) & (arcs >= count)).tolist():  # trees are counted as they are
        own, size = members[first[i] : first[i] + count[i]], int(count[i])
        at[own] = np.arange(size)
        e = by[slice(*np.searchsorted(ends, (roots[i], roots[i] + 1)))]
        x, y = at[a[e]], at[b[e]]
        cut, far = bridges(size, x, y, SHARED + 1)
        if not len(cut):
            continue
        rest = np.ones(len(e), bool)
        rest[cut] = False
        part = labels(size, x[rest], y[rest])
        parts = np.unique(part)
        if len(parts) != len(cut) + 1:  # a cut edge was no bridge
            continue
        fits = True
        for r in parts.tolist():
            inside = part == r
            place = np.cumsum(inside) - 1
            use = rest & inside[x]
            fits = fits and _hubs_of(int(inside.sum()), place[x[use]], place[y[use]]) is not None
        if not fits:
            continue
        mass, squares = np.zeros(size), np.zeros(size)
        for end, beyond in ((x[cut], far), (y[cut], size - far)):
            np.add.at(mass, end, beyond)
            np.add.at(squares, end, beyond.astype(np.float64) ** 2)
        label[own], stay[e[cut]] = own[part], False
        weight[own] += mass
        behind[own] = mass**2 - squares + 2 * mass * (size - 1 - mass)
    return label, stay, weight, behind


def _pieces(kind: str, first: int, x: np.ndarray) -> Iterator[pa.RecordBatch]:
    """x from position first on, cut where a piece ends."""
    at = 0
    while at < len(x):
        size = min(len(x) - at, PIECE - (first + at) % PIECE)
        yield pa.RecordBatch.from_arrays([pa.array([kind]), pa.array([(first + at) // PIECE]), pa.array([(first + at) % PIECE]), pa.ListArray.from_arrays(pa.array([0, size], pa.int32()), pa.array(x[at : at + size]))], ["kind", "piece", "first", "part"])
        at += size


def loads_of(spark, ends: Ends, kind: str = "vertex") -> Loads:
    """Exact loads of a kind (vertex or edge) by a search from every vertex, or by counting in scopes of trees; the other frame is None."""
    n, m = len(ends.ids), len(ends.src)
    label, src, dst, weight, behind = labels(n, ends.src, ends.dst), ends.src, ends.dst, None, None
    sided = not ends.directed
    if sided and kind == "vertex":
        label, stay, weight, behind = parted(n, label, src, dst)
        src, dst = src[stay], dst[stay]
    order, ranges = scopes(n, label)
    to = np.empty(n, np.int32)
    to[order] = np.arange(n, dtype=np.int32)  # within a component order stays, so src stays before dst
    src, dst = to[src], to[dst]
    if len(ranges) > 1:
        src, dst = _in_order(src, dst, n)
    cut = np.searchsorted(src, [lo for lo, _ in ranges] + [n])
    first = np.flatnonzero(np.append(True, np.diff(label[order]) != 0)) if n else np.zeros(0, np.int64)
    trees = np.diff(np.searchsorted(first, [lo for lo, _ in ranges] + [n]))  # components of each scope
    graphs, jobs = [], []
    for i, (lo, hi) in enumerate(ranges):
        a, b, size = src[cut[i] : cut[i + 1]] - lo, dst[cut[i] : cut[i + 1]] - lo, hi - lo
        arcs = len(a) * (1 if ends.directed else 2)
        if not ends.directed and len(a) == size - trees[i] and (weight is None or (weight[order[lo:hi]] == 1).all()):
            graphs.append(Trees(a, b))
            jobs.append((i, 0, size, size))
            continue
        if sided and (hub := _hubs_of(size, a, b)) is not None:
            cross = hub[a] != hub[b]
            sides = Sides.of(hub, labels(size, a[cross], b[cross]), a, b, None if weight is None else weight[order[lo:hi]], kind == "edge")
            graphs.append(sides)
            p, q = len(sides.bits), sides.hubs
            jobs += [(i, s, e, (q * (p - s if s < p else p) // TWO_SIDED + size) * (e - s)) for s, e in sides.jobs(max(1, min(ROWS, 2 * TASK_CELLS // q)))]
            continue
        if SHARED < size <= DENSE_MOST and arcs * DENSE > size * size:
            out = bit_rows(size, a, b)
            back = np.zeros_like(out)
            for x in range(0, size, 8 * TILE):  # columns as rows
                back[x : x + 8 * TILE] = np.packbits(np.unpackbits(out[:, x // 8 : x // 8 + TILE], axis=1, count=min(8 * TILE, size - x)).T, axis=1)
            graphs.append((out, back) if ends.directed else (out | back,) * 2)
            step, work = max(1, 2 * TASK_CELLS // size), size * size // 24
        else:
            graphs.append((a, b))
            step, work = sources_at_once(size, 0, False), 2 * arcs + size
        jobs += [(i, s, min(size, s + step), work * (min(size, s + step) - s)) for s in range(0, size, step)]
    # Successive jobs share a task, about evenly by work, so that a scope's loads are added up before they move.
    cores = spark.sparkContext.defaultParallelism
    most = 4 * cores if kind == "vertex" else max(cores, min(4 * cores, EDGE_MOST // max(1, 8 * m)))
    parts = min(len(jobs), max(most, 1)) or 1
    done = np.cumsum([w for *_, w in jobs]) if jobs else np.zeros(0)
    tasks = np.split(np.arange(len(jobs)), np.searchsorted(done, np.arange(1, parts) * (done[-1] / parts))) if jobs else []
    plan = [[jobs[j][:3] for j in t.tolist()] for t in tasks if len(t)]
    sent = spark.sparkContext.broadcast((ranges, cut.tolist(), graphs, plan, ends.directed))
    del graphs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where, edges_at, nets, todo, directed = sent.value
        for batch in batches:
            for t in batch.column(0).to_pylist():
                now, net, v, e = -1, None, None, None
                for i, a, b in [*todo[t], (-1, 0, 0)]:
                    if i != now:
                        if isinstance(net, Flows):
                            v, e = (net.loads(), e) if kind == "vertex" else (v, net.edge_loads())
                        if now >= 0:
                            yield from _pieces("v", where[now][0], v) if kind == "vertex" else _pieces("e", edges_at[now], e)
                        if i < 0:
                            break
                        size, now = where[i][1] - where[i][0], i
                        v, e = np.zeros(size), np.zeros(edges_at[i + 1] - edges_at[i] if kind == "edge" else 0)
                        if isinstance(nets[i], Trees):
                            net = nets[i]
                        elif isinstance(nets[i], Sides):
                            net = Flows(nets[i])
                        else:
                            net = Dense(size, *nets[i], directed) if nets[i][0].ndim == 2 else Net(size, *nets[i], directed)
                    if isinstance(net, Trees):
                        got = tree_loads(b, net.a, net.b, kind)
                        v, e = (got, e) if kind == "vertex" else (v, got)
                        continue
                    if isinstance(net, Flows):
                        net.add(a, b)
                        continue
                    if isinstance(net, Dense):
                        net.add(np.arange(a, b), v, e, kind)
                        continue
                    got = Block(net, np.arange(a, b)).loads(kind)
                    if kind == "vertex":
                        v += got[0]
                    else:
                        e += got[1]

    rows = spark.range(0, len(plan), 1, max(1, len(plan))).mapInArrow(run, "kind string, piece bigint, first bigint, part array<double>")
    names = spark.sparkContext.broadcast((ends.ids, order, behind, *((src, dst) if kind == "edge" else (None, None))))

    def add(rows: pa.Table) -> pa.Table:
        ids, order, behind, src, dst = names.value
        lo = rows.column("piece")[0].as_py() * PIECE
        size = min(PIECE, (m if kind == "edge" else n) - lo)
        total = np.zeros(size)
        for first, part in zip(rows.column("first").to_pylist(), rows.column("part"), strict=True):
            x = part.values.to_numpy(zero_copy_only=False)
            total[first : first + len(x)] += x
        name = lambda at: pa.array([ids[i] for i in order[at].tolist()], pa.string())
        if kind == "vertex":
            total += 0 if behind is None else behind[order[lo : lo + size]]
            return pa.table({"id": name(np.arange(lo, lo + size)), "vbc": total})
        return pa.table({"src": name(src[lo : lo + size]), "dst": name(dst[lo : lo + size]), "ebc": total})

    summed = rows.groupBy("kind", "piece").applyInArrow(add, "id string, vbc double" if kind == "vertex" else "src string, dst string, ebc double")
    return Loads(summed, None) if kind == "vertex" else Loads(None, summed)
