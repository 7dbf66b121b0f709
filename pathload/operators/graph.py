"""Graphs as frames: edges, arcs, dense positions, statistics and components."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pathload.operators.components import component_roots, cut_lineage


@dataclass(frozen=True)
class Graph:
    """A simple unweighted graph. edges: (src, dst), src < dst where it is undirected; tail and head where it is directed."""

    edges: DataFrame
    directed: bool = False
    extra: DataFrame | None = None  # (id): vertices that may have no edge

    @staticmethod
    def from_edges(rows: DataFrame, src: str = "src", dst: str = "dst", directed: bool = False, vertices: DataFrame | None = None) -> Graph:
        """Loops, doubles and incomplete rows go; undirected edges get their canonical order."""
        a, b = F.col(src), F.col(dst)
        pairs = rows.where(a.isNotNull() & b.isNotNull() & (a != b))
        pairs = pairs.select(a.alias("src"), b.alias("dst")) if directed else pairs.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"))
        return Graph(pairs.distinct(), directed, vertices)

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def vertices(self) -> DataFrame:
        ends = self.edges.select(F.explode(F.array("src", "dst")).alias("id"))
        return (ends if self.extra is None else ends.unionByName(self.extra.select("id"))).distinct()

    @property
    def arcs(self) -> DataFrame:
        """(u, v): both directions of an undirected edge."""
        out = self.edges.select(F.col("src").alias("u"), F.col("dst").alias("v"))
        return out if self.directed else out.unionByName(self.edges.select(F.col("dst").alias("u"), F.col("src").alias("v")))

    def adjacency(self) -> DataFrame:
        """(v, nbrs): sorted neighbour lists."""
        return self.arcs.groupBy(F.col("u").alias("v")).agg(F.sort_array(F.collect_set("v")).alias("nbrs"))

    def register(self, name: str) -> None:
        """Views <name>_edges, <name>_arcs and <name>_vertices for SQL."""
        for part in ("edges", "arcs", "vertices"):
            getattr(self, part).createOrReplaceTempView(f"{name}_{part}")


def dense_index(graph: Graph) -> DataFrame:
    """(id, pos): positions 0..n-1 in the order of ids, by range partitions and offsets of their counts."""
    ranged = graph.vertices.repartitionByRange("id").withColumn("p", F.spark_partition_id())
    counts = ranged.groupBy("p").count()
    before = counts.select("p", (F.sum("count").over(Window.orderBy("p")) - F.col("count")).alias("before"))  # one row a partition
    within = F.row_number().over(Window.partitionBy("p").orderBy("id")) - 1
    return ranged.withColumn("i", within).join(F.broadcast(before), "p").select("id", (F.col("before") + F.col("i")).alias("pos"))


@dataclass
class Csr:
    """A graph on the driver: sorted ids, edge ends as positions."""

    ids: np.ndarray
    src: np.ndarray
    dst: np.ndarray
    directed: bool

    def position(self, ident) -> int:
        at = np.flatnonzero(self.ids == ident)  # ids that came later stand behind, unsorted
        if not len(at):
            raise KeyError(ident)
        return int(at[0])


#: Bytes that Python adds to each id on the driver: the object, its place in a list and in a dictionary.
ID_BYTES = 200


def edge_bytes(graph: Graph) -> int:
    """Bytes of the graph on the driver from counts: ids with their characters, both ends of each edge as they come and as positions, loads."""
    n = graph.vertices.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.octet_length(F.col("id").cast("string"))), F.lit(0)).alias("b")).first()
    m = graph.edges.agg(F.count(F.lit(1)).alias("m"), F.coalesce(F.sum(F.octet_length(F.col("src").cast("string")) + F.octet_length(F.col("dst").cast("string"))), F.lit(0)).alias("b")).first()
    return n["b"] + n["n"] * (ID_BYTES + 16) + m["b"] + m["m"] * 64


def to_csr(graph: Graph, max_bytes: int | None = 1 << 30) -> Csr:
    """The graph's arrays on the driver. Refuses graphs beyond max_bytes: those take the level plan."""
    if max_bytes is not None and (need := edge_bytes(graph)) > max_bytes:
        raise MemoryError(f"graph of {need} bytes; the block plan takes at most {max_bytes}")
    ids = np.array(sorted(graph.vertices.toArrow().column(0).to_pylist()), dtype=object)
    e = graph.edges.select("src", "dst").toArrow()
    names = pa.array(ids.tolist(), e.column(0).type)
    src, dst = (pc.index_in(e.column(i), names).to_numpy().astype(np.int64) if e.num_rows else np.zeros(0, np.int64) for i in (0, 1))
    order = np.lexsort((dst, src))
    return Csr(ids, src[order], dst[order], graph.directed)


def degrees(graph: Graph) -> DataFrame:
    """(id, degree): distinct neighbours of every vertex, isolated ones included."""
    both = graph.arcs if not graph.directed else graph.arcs.unionByName(graph.arcs.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct()
    d = both.groupBy(F.col("u").alias("id")).agg(F.count(F.lit(1)).alias("degree"))
    return graph.vertices.join(d, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))


def components(graph: Graph) -> DataFrame:
    """(id, component): the least id of each vertex's component, edge directions ignored."""
    roots = component_roots(graph.edges, "src", "dst")
    return graph.vertices.join(roots, "id", "left").select("id", F.coalesce("root", "id").alias("component"))


def largest_component(graph: Graph) -> Graph:
    """The component of most vertices; of equal ones that with the least id."""
    parts = components(graph)
    top = parts.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1)
    inside = parts.join(F.broadcast(top), "component").select("id")
    edges = graph.edges.join(inside.withColumnRenamed("id", "src"), "src", "left_semi")
    return Graph(edges.select("src", "dst"), graph.directed, inside)


def triangles(graph: Graph) -> DataFrame:
    """(a, b, c), a < b < c: edges meet at wedges whose middle has the lesser degree rank."""
    e = graph.edges
    ab, bc, ac = e.toDF("a", "b"), e.toDF("b", "c"), e.toDF("a", "c")
    return ab.join(bc, "b").join(ac, ["a", "c"], "left_semi").select("a", "b", "c")


#: Bytes of neighbour bits that counting by bits may read in all (edges times vertices, an eighth); beyond, triangles are joined.
BIT_WORK = 1 << 38
#: Bytes of a task's piece of the neighbour matrix before its bits are packed, and of the rows it compares at once.
BIT_BYTES = 1 << 25


def _common_bits(n: int, src: np.ndarray, dst: np.ndarray, lo: int, hi: int) -> np.ndarray:
    """Common neighbours of the ends of the edges lo to hi, a range of columns of the neighbour matrix at once."""
    out = np.zeros(hi - lo, np.int64)
    width = max(8, BIT_BYTES // max(n, 1))
    for c in range(0, n, width):
        near = np.zeros((n, min(width, n - c)), bool)
        for a, b in ((src, dst), (dst, src)):
            use = (b >= c) & (b < c + width)
            near[a[use], b[use] - c] = True
        bits = np.packbits(near, axis=1)
        del near
        step = max(1, BIT_BYTES // bits.shape[1] // 4)
        for i in range(lo, hi, step):
            j = min(hi, i + step)
            out[i - lo : j - lo] += np.bitwise_count(bits[src[i:j]] & bits[dst[i:j]]).sum(axis=1, dtype=np.int64)
    return out


def corners(graph: Graph) -> DataFrame:
    """(id, triangles) of vertices in triangles: counted by neighbour bits, without a row a wedge; joined where that reads too much."""
    n, m = graph.vertices.count(), graph.edges.count()
    if graph.directed or n * m // 8 > BIT_WORK or edge_bytes(graph) > 1 << 30:
        return triangles(graph).select(F.explode(F.array("a", "b", "c")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("triangles"))
    spark = graph.spark
    index = cut_lineage(dense_index(graph).select("id", F.col("pos").cast("int").alias("pos")))
    ids = np.array(index.orderBy("pos").select("id").toArrow().column(0).to_pylist(), dtype=object)
    ends = graph.edges.join(index.toDF("src", "a"), "src").join(index.toDF("dst", "b"), "dst").select("a", "b").toArrow()  # numbers alone come to the driver
    sent = spark.sparkContext.broadcast((ids, ends.column("a").to_numpy(), ends.column("b").to_numpy()))
    parts = spark.sparkContext.defaultParallelism
    cut = np.linspace(0, m, parts + 1).astype(int).tolist()
    del ends

    def count(batches):
        ids, src, dst = sent.value
        for batch in batches:
            for k in batch.column(0).to_pylist():
                lo, hi = cut[k], cut[k + 1]
                common = _common_bits(len(ids), src, dst, lo, hi)
                twice = np.zeros(len(ids), np.int64)
                np.add.at(twice, src[lo:hi], common)
                np.add.at(twice, dst[lo:hi], common)
                at = np.flatnonzero(twice)
                yield pa.RecordBatch.from_arrays([pa.array(ids[at].tolist(), pa.string()), pa.array(twice[at])], ["id", "twice"])

    rows = spark.range(0, parts, 1, parts).mapInArrow(count, "id string, twice bigint")
    return rows.groupBy("id").agg((F.sum("twice") / 2).cast("bigint").alias("triangles"))  # a triangle is met at two edges of each corner


def clustering(graph: Graph) -> DataFrame:
    """(id, triangles, clustering): share of neighbour pairs that are linked; 0 for degrees under 2."""
    corner = corners(graph)
    d = degrees(graph).join(corner, "id", "left").withColumn("triangles", F.coalesce("triangles", F.lit(0)))
    share = F.when(F.col("degree") < 2, F.lit(0.0)).otherwise(2 * F.col("triangles") / (F.col("degree") * (F.col("degree") - 1)))
    return d.select("id", "triangles", share.alias("clustering"))


def stats(graph: Graph) -> DataFrame:
    """One row: n, m, average degree, mean clustering."""
    c = clustering(graph).agg(F.count(F.lit(1)).alias("n"), F.avg("clustering").alias("clustering"))
    m = graph.edges.agg(F.count(F.lit(1)).alias("m"))
    return c.crossJoin(m).select("n", "m", (2 * F.col("m") / F.col("n")).alias("average_degree"), "clustering")


def without_edge(graph: Graph, a: str, b: str) -> Graph:
    return Graph(graph.edges.where(~((F.col("src") == F.least(F.lit(a), F.lit(b))) & (F.col("dst") == F.greatest(F.lit(a), F.lit(b))))), graph.directed, graph.vertices)
