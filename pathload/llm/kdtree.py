"""Exact top-k search by inner product over KD-trees, one for each shard of the vectors.

Shards are regions of space: median splits of the widest dimension, from a bounded
sample, part the vectors; a region of too many vectors is dealt to several shards by
a hash. Each shard's tree is built once, splits at medians in the same way, and is
kept as a row; every node has a tight box. A query's inner product with anything in
a box is at most the sum of its components' better products with the box's two
sides. Nodes are opened best bound first, and a search ends where the best bound
left is below the kth score so far.

The kth score is propagated: a first pass searches the region of each query's best
bound; the kth score there is what another region's box must reach for the query to
travel to it at all, and what the search there starts from. Queries go to a shard in
blocks, and a shard's tree goes once to each of its blocks.

Contracts: vectors that are null or hold null or non-finite components take no part
as query or candidate; only vectors of equal length meet; ties go to the smaller
id; a query's own id is never its candidate; repeated rows are candidates each, a
repeated query id is asked once (its first vector in array order); an empty table
gives an empty result; rows with a null id take no part. Scores are exact as long as
they stay below 2**53.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pathload.llm.common import staged, table

#: Vectors of a shard, queries of a block, vectors of a leaf, queries that a search advances together.
SHARD, QUERIES, LEAF, TOGETHER = 1 << 13, 1 << 14, 128, 4096
#: Rows that the regions are fitted on (those of least id hash) and most regions; with that many, their boxes are a few MB.
SAMPLE, REGIONS = 1 << 14, 1 << 12


def _halves(x: np.ndarray) -> tuple[int, np.ndarray] | None:
    """The widest dimension and an order whose halves lie on either side of its median; None where all rows are equal."""
    if not x.shape[1]:
        return None
    spread = x.max(axis=0) - x.min(axis=0)
    wide = int(np.argmax(spread))
    return (wide, np.argpartition(x[:, wide], len(x) // 2)) if spread[wide] > 0 else None


class Regions:
    """Median splits of space, fitted on a sample; every vector of the sample's length has one region."""

    def __init__(self, x: np.ndarray, rows: int, shard: int):
        self.nodes: list[tuple[int, float, int, int]] = []  # dimension, threshold, nodes or (from -1 down) regions on either side
        self.count = 0
        self.top = self._add(x, min(REGIONS, -(-rows // shard)))

    def _add(self, x: np.ndarray, regions: int) -> int:
        split = _halves(x) if regions > 1 and len(x) >= 4 else None
        if split is None:
            self.count += 1
            return -self.count
        wide, order = split
        cut = float(x[order[len(x) // 2], wide])
        low = x[:, wide] < cut
        if not low.any():  # half of the vectors have the least value
            cut = float(x[x[:, wide] > cut, wide].min())
            low = x[:, wide] < cut
        me = len(self.nodes)
        self.nodes.append((wide, cut, 0, 0))
        self.nodes[me] = (wide, cut, self._add(x[low], regions // 2), self._add(x[~low], regions - regions // 2))
        return me

    def of(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x), np.int32)
        todo = [(self.top, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            if node < 0:
                out[rows] = -node - 1
                continue
            wide, cut, left, right = self.nodes[node]
            low = x[rows, wide] < cut
            todo += [(left, rows[low]), (right, rows[~low])]
        return out


def bounds(q: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Upper bounds of queries (rows) over boxes (columns)."""
    return np.maximum(q, 0) @ high.T + np.minimum(q, 0) @ low.T


class KdTree:
    """A tree over integer vectors: the boxes of all nodes, their children, and their ranges of the reordered vectors."""

    FIELDS = (("x", np.float64), ("ids", np.int64), ("low", np.float64), ("high", np.float64), ("child", np.int32), ("span", np.int32))

    def __init__(self, x: np.ndarray, ids: np.ndarray, leaf: int = LEAF):
        x = x.astype(np.float64)
        order = np.arange(len(ids))
        low, high, child, span = [], [], [], []
        todo = [(0, len(ids), -1, 0)] if len(ids) else []
        while todo:
            a, b, parent, side = todo.pop()
            me = len(low)
            if parent >= 0:
                child[parent][side] = me
            part = x[order[a:b]]
            low.append(part.min(axis=0)), high.append(part.max(axis=0)), child.append([-1, -1]), span.append((a, b))
            split = _halves(part) if b - a > leaf else None
            if split is not None:
                order[a:b] = order[a:b][split[1]]
                half = a + (b - a) // 2
                todo += [(a, half, me, 0), (half, b, me, 1)]
        d = x.shape[1] if x.ndim == 2 else 0
        self.x, self.ids = x[order], np.asarray(ids, np.int64)[order]
        self.low, self.high = np.array(low).reshape(len(low), d), np.array(high).reshape(len(high), d)
        self.child, self.span = np.array(child, np.int32).reshape(-1, 2), np.array(span, np.int32).reshape(-1, 2)

    def to_row(self) -> dict[str, bytes]:
        return {name: np.ascontiguousarray(getattr(self, name), kind).tobytes() for name, kind in self.FIELDS}

    @classmethod
    def from_row(cls, row: dict) -> KdTree:
        tree = cls.__new__(cls)
        for name, kind in cls.FIELDS:
            setattr(tree, name, np.frombuffer(row[name], kind))
        n, nodes = len(tree.ids), len(tree.child) // 2
        d = len(tree.x) // max(n, 1)
        tree.x, tree.low, tree.high = tree.x.reshape(n, d), tree.low.reshape(nodes, d), tree.high.reshape(nodes, d)
        tree.child, tree.span = tree.child.reshape(-1, 2), tree.span.reshape(-1, 2)
        return tree

    def search(self, q: np.ndarray, own: np.ndarray, k: int, least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Scores and ids of the k best of each query (-inf, -1 where there are fewer).

        least: what the kth score is known to reach already. Queries advance together,
        TOGETHER at a time. Each keeps its open nodes by bound; the best one is replaced
        by its children, and a leaf is scored for all queries that reached it.
        """
        n = len(q)
        score, ident = np.full((n, k), -np.inf), np.full((n, k), -1, np.int64)
        for at in range(0, n, TOGETHER) if len(self.ids) else ():
            s = slice(at, at + TOGETHER)
            self._advance(q[s], own[s], k, least[s], score[s], ident[s])
        return score, ident

    def _advance(self, q, own, k, least, score, ident) -> None:
        state = np.full((len(q), len(self.low)), -np.inf)  # bounds of open nodes
        state[:, 0] = bounds(q, self.low[:1], self.high[:1])[:, 0]
        active = np.arange(len(q))
        while len(active):
            best = state[active].argmax(axis=1)
            bound = state[active, best]
            go = (bound > -np.inf) & (bound >= np.maximum(score[active, -1], least[active]))
            active, best = active[go], best[go]
            for node in np.unique(best).tolist():
                at = active[best == node]
                state[at, node] = -np.inf
                kids = self.child[node]
                if kids[0] >= 0:
                    state[np.ix_(at, kids)] = bounds(q[at], self.low[kids], self.high[kids])
                    continue
                a, b = self.span[node]
                s = q[at] @ self.x[a:b].T
                ids = np.broadcast_to(self.ids[a:b], s.shape)
                s = np.where(ids == own[at][:, None], -np.inf, s)
                all_s, all_i = np.concatenate([score[at], s], axis=1), np.concatenate([ident[at], np.where(s > -np.inf, ids, -1)], axis=1)
                order = np.lexsort((all_i, -all_s), axis=1)[:, :k]
                score[at], ident[at] = np.take_along_axis(all_s, order, 1), np.take_along_axis(all_i, order, 1)


def _rows(col) -> np.ndarray:
    col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
    return col.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(col), len(col[0])) if len(col) else np.zeros((0, 0))


def exact_top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, key: str = "vec_id", vector: str = "v", shard: int = SHARD, block: int = QUERIES) -> DataFrame:
    """(query_id, rank, key, score): the k best of the vectors for each query; integer vectors (arrays of long)."""
    v = staged(vectors.select(F.col(key).cast("long").alias("id"), F.col(vector).alias("x"), F.size(vector).alias("d")).where("id is not null and x is not null"))
    q = staged(queries.where(F.col(key).isNotNull() & F.col(vector).isNotNull()).groupBy(F.col(key).cast("long").alias("qid")).agg(F.min(vector).alias("q")).withColumn("d", F.size("q")))
    common = v.groupBy("d").count().orderBy(F.desc("count"), "d").first()
    main, rows = (common["d"], common["count"]) if common else (-1, 0)
    sample = v.where(F.col("d") == main).orderBy(F.xxhash64("id"), "id").limit(SAMPLE).select("x").toArrow()
    regions = Regions(_rows(sample.column(0)), rows, shard)  # the driver holds SAMPLE vectors

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Regions of the most common length; other lengths have one region each."""
        for b in batches:
            d = b.column(2).to_numpy()
            out = np.zeros(b.num_rows, np.int32)
            use = np.flatnonzero(d == main)
            if len(use):
                out[use] = regions.of(_rows(b.column(1).take(pa.array(use))))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out)], [*b.schema.names, "region"])

    def build(name: tuple, there: pa.Table) -> pa.Table:
        tree = KdTree(_rows(there.column("x")), there.column("id").to_numpy())
        return pa.Table.from_pylist([{"d": name[0].as_py(), "region": name[1].as_py(), "sub": name[2].as_py(), **tree.to_row()}], tree_schema)

    tree_schema = pa.schema([("d", pa.int32()), ("region", pa.int32()), ("sub", pa.int32()), *((name, pa.binary()) for name, _ in KdTree.FIELDS)])
    put = v.mapInArrow(place, "id bigint, x array<bigint>, d int, region int")
    subs = staged(put.groupBy("d", "region").agg(F.ceil(F.count(F.lit(1)) / shard).cast("int").alias("subs")))
    dealt = put.join(subs, ["d", "region"]).withColumn("sub", F.pmod(F.xxhash64("id"), F.col("subs")).cast("int"))
    trees = staged(dealt.select("d", "region", "sub", "id", "x").groupBy("d", "region", "sub").applyInArrow(build, "d int, region int, sub int, " + ", ".join(f"{name} binary" for name, _ in KdTree.FIELDS)))

    def box(name: tuple, there: pa.Table) -> pa.Table:
        low, high = (np.array([np.frombuffer(x.as_buffer(), np.float64)[:main] for x in there.column(c)]) for c in ("low", "high"))
        return pa.table({"region": pa.array([name[0].as_py()], pa.int32()), "low": pa.array([low.min(axis=0).tobytes()], pa.binary()), "high": pa.array([high.max(axis=0).tobytes()], pa.binary())})

    first_nodes = trees.where((F.col("d") == main) & (F.col("d") > 0)).select("region", *(F.substring(c, 1, 8 * max(main, 0)).alias(c) for c in ("low", "high")))
    found = first_nodes.groupBy("region").applyInArrow(box, "region int, low binary, high binary").collect()  # at most REGIONS rows
    names = np.array([r["region"] for r in found], np.int32)
    low, high = (np.array([np.frombuffer(r[c], np.float64) for r in found]).reshape(len(found), max(main, 0)) for c in ("low", "high"))

    def routed(asked: DataFrame, home: bool) -> DataFrame:
        """(qid, q, d, least, region): the region of the best bound, or all others whose bound reaches what is known."""

        def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                d = b.column(2).to_numpy()
                row, region = [np.flatnonzero(d != main) if home else np.zeros(0, np.int64)], []
                region.append(np.zeros(len(row[0]), np.int32))
                use = np.flatnonzero(d == main)
                if len(use) and len(names):
                    bound = bounds(_rows(b.column(1).take(pa.array(use))), low, high) if main > 0 else np.zeros((len(use), len(names)))
                    best = bound.argmax(axis=1)
                    if home:
                        i, j = np.arange(len(use)), best
                    else:
                        bound[np.arange(len(use)), best] = -np.inf
                        known = b.column(3).to_numpy().astype(np.float64)[use]
                        i, j = np.nonzero((bound >= known[:, None]) & (bound > -np.inf))
                    row.append(use[i]), region.append(names[j])
                row = np.concatenate(row)
                yield pa.RecordBatch.from_arrays([*(c.take(pa.array(row)) for c in b.columns), pa.array(np.concatenate(region).astype(np.int32))], [*b.schema.names, "region"])

        return asked.mapInArrow(route, "qid bigint, q array<bigint>, d int, least bigint, region int")

    def search(there: pa.Table, asked: pa.Table) -> pa.Table:
        if not there.num_rows or not asked.num_rows:
            return pa.table({"qid": pa.array([], pa.int64()), "id": pa.array([], pa.int64()), "score": pa.array([], pa.int64())})
        tree = KdTree.from_row(there.select([name for name, _ in KdTree.FIELDS]).to_pylist()[0])
        own = asked.column("qid").to_numpy()
        score, ident = tree.search(_rows(asked.column("q")), own, k, asked.column("least").to_numpy().astype(np.float64))
        i, j = np.nonzero(score > -np.inf)
        return pa.table({"qid": own[i], "id": ident[i, j], "score": score[i, j].astype(np.int64)})

    def met(asked: DataFrame) -> DataFrame:
        """Queries at all shards of their regions, in blocks."""
        n = staged(asked.groupBy("d", "region").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks")).join(subs, ["d", "region"]))
        each = asked.join(n, ["d", "region"]).withColumn("block", F.pmod(F.xxhash64("qid", F.lit(3)), F.col("blocks")).cast("int"))
        each = each.withColumn("sub", F.explode(F.sequence(F.lit(0), F.col("subs") - 1))).select("d", "region", "sub", "block", "qid", "q", "least")
        here = trees.join(n.drop("subs"), ["d", "region"]).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks")
        by = ["d", "region", "sub", "block"]
        return here.groupBy(*by).cogroup(each.groupBy(*by)).applyInArrow(search, "qid bigint, id bigint, score bigint")

    best = Window.partitionBy("qid").orderBy(F.desc("score"), "id")
    low_score = F.lit(np.iinfo(np.int64).min)
    first = staged(met(routed(q.withColumn("least", low_score), True)))
    known = first.withColumn("r", F.row_number().over(best)).where(F.col("r") == k).select("qid", F.col("score").alias("least"))
    start = q.join(known, "qid", "left").select("qid", "q", "d", F.coalesce("least", low_score).alias("least"))
    everything = first.unionByName(met(routed(staged(start), False)))
    ranked = everything.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    return ranked.select(F.col("qid").alias("query_id"), "rank", F.col("id").alias(key), "score")


def integer_vectors(vectors: DataFrame, key: str = "vec_id", embedding: str = "embedding", scale: int = 256) -> DataFrame:
    """(key, v): floor(scale * component) of the vectors whose components are all there and finite."""
    fine = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    good = vectors.where(F.col(key).isNotNull() & F.col(embedding).isNotNull() & F.coalesce(F.forall(embedding, fine), F.lit(False)))
    return good.select(key, F.transform(embedding, lambda x: F.floor(scale * x.cast("double"))).alias("v"))


def op3_kdtree(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = integer_vectors(table(spark, sf_dir, "embeddings"))
    return exact_top_k(v, v.where("vec_id % 50 = 0"))


ORACLE = """
WITH v AS MATERIALIZED (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
s AS (SELECT q.vec_id AS query_id, v.vec_id, list_inner_product(q.e, v.e)::BIGINT AS score FROM v q JOIN v ON q.vec_id <> v.vec_id AND len(q.e) = len(v.e) WHERE q.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 5
"""
