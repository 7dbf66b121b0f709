"""The block plan: contiguous ranges of sources, each one task over a broadcast graph.

A block's task runs the kernel for all its sources and sums its loads before
anything is shuffled, so the shuffle carries a row for each (block, vertex or edge).
Path state leaves a task as one row a source, in Arrow batches of a few rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from pathload.operators.components import cut_lineage
from pathload.operators.graph import Csr, Graph, edge_bytes, to_csr
from pathload.plans import level
from pathload.plans.kernel import Block, Net

#: A graph of more bytes than this takes the level plan.
BROADCAST_BYTES = 1 << 30
#: Cells (sources times vertices) that a task's arrays hold at once.
TASK_CELLS = 1_000_000
#: Arcs of all sources of a repair or of kept predecessor lists, each of which may be unfolded at once.
TASK_ARCS = 3_000_000
#: Sources times edges from which the block plan searches a connected scope at a time (plans/scopes.py), where neither state nor lists are kept.
SCOPES_FROM = 100_000_000
ROW_SCHEMA = "kind string, a string, b string, part double, block int, s bigint, d array<int>, sigma array<double>, delta array<double>"
_ARROW = pa.schema([("kind", pa.string()), ("a", pa.string()), ("b", pa.string()), ("part", pa.float64()), ("block", pa.int32()), ("s", pa.int64()), ("d", pa.list_(pa.int32())), ("sigma", pa.list_(pa.float64())), ("delta", pa.list_(pa.float64()))])


@dataclass
class Loads:
    """vertex: (id, vbc); edge: (src, dst, ebc); state: packed rows (block, s, d, sigma, delta) or None."""

    vertex: DataFrame
    edge: DataFrame
    state: DataFrame | None = None


def sources_at_once(n: int, m: int, unfolded: bool = True) -> int:
    """Sources of a graph of n vertices and m edges that a task takes at once."""
    return max(1, min(TASK_CELLS // max(n, 1), TASK_ARCS // max(2 * m, 1) if unfolded else TASK_CELLS))


def block_ranges(n: int, n_blocks: int) -> list[tuple[int, int]]:
    cut = np.linspace(0, n, max(1, min(n_blocks, max(n, 1))) + 1).astype(int)
    return [(int(a), int(b)) for a, b in zip(cut[:-1], cut[1:], strict=True)]


def rows_of_loads(ids: np.ndarray, src: np.ndarray, dst: np.ndarray, vertex: np.ndarray, edge: np.ndarray) -> pa.RecordBatch:
    """Partial loads as rows; zeros stay at home."""
    v, e = np.flatnonzero(vertex), np.flatnonzero(edge)
    n = len(v) + len(e)
    none = lambda t: pa.nulls(n, t)
    return pa.RecordBatch.from_arrays(
        [
            pa.array(["v"] * len(v) + ["e"] * len(e)),
            pa.array([*ids[v].tolist(), *ids[src[e]].tolist()], pa.string()),
            pa.array([None] * len(v) + ids[dst[e]].tolist(), pa.string()),
            pa.array(np.concatenate([vertex[v], edge[e]])),
            *(none(_ARROW.field(i).type) for i in range(4, 9)),
        ],
        schema=_ARROW,
    )


def rows_of_state(block: int, state: Block, rows: np.ndarray | None = None) -> Iterator[pa.RecordBatch]:
    """Packed state rows, a bounded number of cells a batch."""
    rows = np.arange(len(state.sources)) if rows is None else rows
    step = max(1, 1_000_000 // max(1, state.net.n))
    for at in range(0, len(rows), step):
        r = rows[at : at + step]
        lists = lambda x: pa.array(list(x[r]), _ARROW.field("d" if x is state.d else "sigma").type)  # noqa: B023, E731
        k = len(r)
        yield pa.RecordBatch.from_arrays(
            [pa.array(["s"] * k), pa.nulls(k, pa.string()), pa.nulls(k, pa.string()), pa.nulls(k, pa.float64()), pa.array([block] * k, pa.int32()), pa.array(state.sources[r]), lists(state.d), lists(state.sigma), lists(state.delta)],
            schema=_ARROW,
        )


def run_blocks(csr: Csr, spark, n_blocks: int, predecessors: bool = False, keep_state: bool = True, sources: np.ndarray | None = None, kind: str = "both") -> DataFrame:
    """Rows of partial loads (kind v, e) and path state (kind s)."""
    picked = np.arange(len(csr.ids)) if sources is None else sources
    ranges = block_ranges(len(picked), n_blocks)
    sent = spark.sparkContext.broadcast((csr, picked, ranges))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph, all_sources, parts = sent.value
        n = len(graph.ids)
        net = Net(n, graph.src, graph.dst, graph.directed)
        for b in batches:
            for k in b.column(0).to_pylist():
                lo, hi = parts[k]
                vertex, edge = np.zeros(n), np.zeros(len(graph.src))
                step = sources_at_once(n, len(graph.src), predecessors)
                for at in range(lo, hi, step):
                    one = Block(net, all_sources[at : min(hi, at + step)], predecessors=predecessors)
                    v, e = one.loads(kind)
                    vertex += v
                    edge += e
                    if keep_state:
                        yield from rows_of_state(k, one)
                yield rows_of_loads(graph.ids, graph.src, graph.dst, vertex, edge)

    return spark.range(0, len(ranges), 1, len(ranges)).mapInArrow(run, ROW_SCHEMA)


def source_cases(graph: Graph, work: list[tuple[str, str, str]]) -> DataFrame:
    """(i, s, case): each source's case of each update (op, u, v), all of them on the graph as it is. Distances live and end in the tasks."""
    spark = graph.spark
    csr = to_csr(graph)
    todo = [(op, csr.position(u), csr.position(v)) for op, u, v in work]
    ranges = block_ranges(len(csr.ids), max(spark.sparkContext.defaultParallelism, -(-len(csr.ids) // 1000)))
    sent = spark.sparkContext.broadcast((csr, todo, ranges))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph, todo, parts = sent.value
        net = Net(len(graph.ids), graph.src, graph.dst, graph.directed)
        step = sources_at_once(net.n, len(graph.src), False)
        for b in batches:
            for k in b.column(0).to_pylist():
                lo, hi = parts[k]
                for at in range(lo, hi, step):
                    block = Block(net, np.arange(at, min(hi, at + step)), dependencies=False)
                    names = pa.array(graph.ids[block.sources].tolist(), pa.string())
                    for i, (op, u, v) in enumerate(todo):
                        yield pa.RecordBatch.from_arrays([pa.array([i] * len(names), pa.int32()), names, pa.array(block.cases(op, u, v).tolist(), pa.string())], ["i", "s", "case"])

    return spark.range(0, len(ranges), 1, len(ranges)).mapInArrow(run, "i int, s string, case string")


def sum_loads(rows: DataFrame, graph: Graph) -> Loads:
    """Partial loads added up, with every vertex and edge in the result."""
    v = rows.where("kind = 'v'").groupBy(F.col("a").alias("id")).agg(F.sum("part").alias("vbc"))
    e = rows.where("kind = 'e'").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("part").alias("ebc"))
    vertex = graph.vertices.join(v, "id", "left").select("id", F.coalesce("vbc", F.lit(0.0)).alias("vbc"))
    edge = graph.edges.join(e, ["src", "dst"], "left").select("src", "dst", F.coalesce("ebc", F.lit(0.0)).alias("ebc"))
    return Loads(vertex, edge, rows.where("kind = 's'").select("block", "s", "d", "sigma", "delta"))


def normalized(loads: Loads, graph: Graph, how: str) -> Loads:
    """'half': an undirected pair counts once; 'pairs': shares of all ordered pairs."""
    if how == "none":
        return loads
    n = graph.vertices.count()
    v = e = 0.5
    if how == "pairs":
        v, e = 1 / max(1, (n - 1) * (n - 2)), 1 / max(1, n * (n - 1))
    return Loads(loads.vertex.withColumn("vbc", F.col("vbc") * v), loads.edge.withColumn("ebc", F.col("ebc") * e), loads.state)


_NO_VERTEX = lambda spark: spark.createDataFrame([], "id string, vbc double")
_NO_EDGE = lambda spark: spark.createDataFrame([], "src string, dst string, ebc double")


def static_betweenness(graph: Graph, plan: str = "auto", predecessors: bool = False, n_blocks: int | None = None, keep_state: bool = False, normalize: str = "none", kind: str = "both", sources: int | None = None, seed: int = 0) -> Loads:
    """Vertex and edge loads from scratch.

    plan: 'block', 'level', or 'auto' by the graph's counted size. kind: 'both',
    'vertex' or 'edge'; the loads that are not asked for are neither added up nor
    shuffled, their frame is empty. From SCOPES_FROM on each frame is searched when it is
    read, as it is for its own kind. sources: a number of sampled sources, with loads
    scaled to all; None is exact.
    """
    if kind not in ("both", "vertex", "edge"):
        raise ValueError(f"no such kind of load: {kind}")
    spark = graph.spark
    graph = Graph(cut_lineage(graph.edges), graph.directed, None if graph.extra is None else cut_lineage(graph.extra))
    if plan == "auto":
        plan = "block" if edge_bytes(graph) <= BROADCAST_BYTES else "level"
    picked = None
    if sources is not None:
        picked = graph.vertices.orderBy(F.md5(F.concat_ws(":", "id", F.lit(seed))), "id").limit(sources)
    if plan == "level":
        state = level.dependency_state(level.shortest_path_state(graph, picked), graph)
        loads = Loads(level.vertex_load(state, graph.vertices) if kind != "edge" else _NO_VERTEX(spark), level.edge_load(state, graph) if kind != "vertex" else _NO_EDGE(spark), state)
    else:
        if not (keep_state or predecessors or n_blocks or sources) and graph.vertices.count() * graph.edges.count() >= SCOPES_FROM:
            from pathload.plans import scopes  # which needs this module

            if scopes.ends_bytes(graph) <= scopes.ENDS_MOST:
                ends = scopes.ends_of(graph)
                vertex = scopes.loads_of(spark, ends, "vertex").vertex if kind != "edge" else _NO_VERTEX(spark)
                edge = scopes.loads_of(spark, ends, "edge").edge if kind != "vertex" else _NO_EDGE(spark)
                return normalized(Loads(vertex, edge), graph, normalize)
        csr = to_csr(graph, None)
        chosen = None if picked is None else np.array(sorted(csr.position(r[0]) for r in picked.collect()), np.int64)
        parts = n_blocks or max(spark.sparkContext.defaultParallelism, -(-len(csr.ids) // 1000))
        loads = sum_loads(cut_lineage(run_blocks(csr, spark, parts, predecessors, keep_state, chosen, kind)), graph)
        loads = Loads(loads.vertex if kind != "edge" else _NO_VERTEX(spark), loads.edge if kind != "vertex" else _NO_EDGE(spark), loads.state)
    if sources is not None:
        scale = graph.vertices.count() / max(1, min(sources, graph.vertices.count()))
        loads = Loads(loads.vertex.withColumn("vbc", F.col("vbc") * scale), loads.edge.withColumn("ebc", F.col("ebc") * scale), loads.state)
    return normalized(loads, graph, normalize)


def sampled_betweenness(graph: Graph, sources: int, seed: int = 0) -> DataFrame:
    """(id, vbc, error): the estimate from sampled sources scaled to all, and its standard error from the spread of the sources' parts."""
    n = graph.vertices.count()
    k = min(sources, n)
    state = static_betweenness(graph, "level", sources=sources, seed=seed).state
    part = state.where("s <> t").groupBy(F.col("t").alias("id")).agg(F.sum("delta").alias("x"), F.sum(F.col("delta") * F.col("delta")).alias("xx"))
    both = graph.vertices.join(part, "id", "left").select("id", F.coalesce("x", F.lit(0.0)).alias("x"), F.coalesce("xx", F.lit(0.0)).alias("xx"))
    spread = F.greatest((F.col("xx") - F.col("x") * F.col("x") / k) / max(1, k - 1), F.lit(0.0))
    return both.select("id", (F.col("x") * (n / max(1, k))).alias("vbc"), (n * F.sqrt(spread / max(1, k) * (1 - k / max(1, n)))).alias("error"))


def long_state(state: DataFrame, ids: list[str]) -> DataFrame:
    """(s, t, d, sigma, delta) with ids, from packed rows; unreachable pairs are absent."""
    spark = state.sparkSession
    names = spark.createDataFrame([(i, v) for i, v in enumerate(ids)], "pos int, id string")
    each = state.select("s", F.posexplode(F.arrays_zip("d", "sigma", "delta")).alias("pos", "x")).where("x.d >= 0")
    each = each.join(names.toDF("s_pos", "s_id"), F.col("s") == F.col("s_pos")).join(names.toDF("t_pos", "t_id"), F.col("pos") == F.col("t_pos"))
    return each.select(F.col("s_id").alias("s"), F.col("t_id").alias("t"), F.col("x.d").alias("d"), F.col("x.sigma").alias("sigma"), F.col("x.delta").alias("delta"))
