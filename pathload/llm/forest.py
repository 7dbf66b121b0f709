"""Embedding near-dedup by a forest of random-projection trees.

Each node of each tree has a random direction of its own and splits at the median of
its vectors' projections, with a margin: vectors near a split go to both sides.
Directions follow from a seed, thresholds come from a bounded sample (and below the
sample's reach from the median of all of the level's projections), so a tree is a
small table that travels with the task while every vector is put into its leaves.
Vectors that share a leaf and a label are compared by cosine in double precision. A
pair counts in the smallest leaf that it shares, so it counts once over all trees
without being emitted; links reach the union step as stars.

Vectors of equal components and label are one class with a multiplicity. A leaf of
more than `block` classes is compared in pairs of blocks by several tasks.

Contracts: vectors that are null, zero, or hold null or non-finite components, and
vectors with a null label, have no links; only vectors of equal length are
compared; equal rows link with each other; a null id is its own component (null);
an empty table gives an empty result.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm.common import staged, table
from pathload.operators.components import component_roots

#: Rows that the trees are fitted on (those of least id hash), trees, rows of a leaf, spill margin in standard deviations, rows of a block.
SAMPLE, TREES, LEAF, SPILL, BLOCK_ROWS = 16_384, 8, 1024, 0.12, 8192
#: Levels whose nodes have directions and thresholds of their own; nodes further down take those of the node with equal lower bits.
TABLE_LEVELS = 12
_DEPTH_BITS = 40  # a leaf's number: tree above these bits, path below


class Forest:
    """Thresholds and margins of some trees over vectors of one length; directions come from the seed."""

    def __init__(self, sample: np.ndarray, rows: int, trees: int = TREES, leaf: int = LEAF, spill: float = SPILL, seed: int = 7):
        self.trees, self.seed, self.dim = trees, seed, sample.shape[1] if len(sample) else 0
        self.depth = int(max(0, np.ceil(np.log2(max(rows, 1) / leaf)))) if len(sample) else 0
        self.margins = np.zeros((trees, self.depth))
        self.thresholds: list[list[np.ndarray]] = []
        for t in range(trees):
            node = np.zeros(len(sample), np.int64)
            levels = []
            for d in range(self.depth):
                p = self.project(sample, t, d, node)
                self.margins[t, d] = spill * p.std()
                cut = np.full(1 << min(d, TABLE_LEVELS), np.median(p))
                own = node & (len(cut) - 1)
                order = np.lexsort((p, own))
                nodes, at, n = np.unique(own[order], return_index=True, return_counts=True)
                for v, a, c in zip(nodes, at, n, strict=True):
                    if c >= 32:
                        cut[v] = np.median(p[order[a : a + c]])
                levels.append(cut)
                node = node * 2 + (p >= cut[own])
            self.thresholds.append(levels)

    def project(self, x: np.ndarray, tree: int, level: int, node: np.ndarray) -> np.ndarray:
        """Each vector's projection on its node's direction."""
        n = 1 << min(level, TABLE_LEVELS)
        directions = _directions(self.seed, tree, level, n, self.dim)
        own = node & (n - 1)
        order = np.argsort(own, kind="stable")
        cuts = np.flatnonzero(np.diff(own[order])) + 1
        out = np.empty(len(x))
        for part in np.split(order, cuts) if len(x) else ():
            out[part] = x[part] @ directions[own[part[0]]]
        return out

    def leaves(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf) of every vector's leaves in all trees."""
        rows, leaves = [], []
        for t in range(self.trees if self.depth else 1):
            row, node = np.arange(len(x)), np.zeros(len(x), np.int64)
            for d in range(self.depth):
                cut = self.thresholds[t][d]
                p = self.project(x[row], t, d, node)
                edge = cut[node & (len(cut) - 1)]
                low, high = p < edge + self.margins[t, d], p >= edge - self.margins[t, d]
                row, node = np.concatenate([row[low], row[high]]), np.concatenate([node[low] * 2, node[high] * 2 + 1])
            rows.append(row)
            leaves.append(node + (np.int64(t) << _DEPTH_BITS))
        return np.concatenate(rows), np.concatenate(leaves)


@functools.lru_cache(maxsize=512)
def _directions(seed: int, tree: int, level: int, n: int, dim: int) -> np.ndarray:
    x = np.random.default_rng((seed, tree, level)).standard_normal((n, dim))
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def usable(embedding: str = "embedding"):
    """Whether a vector is there, not zero, and all its components are finite."""
    e = F.col(embedding)
    fine = lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))
    return e.isNotNull() & F.coalesce(F.forall(e, fine), F.lit(False)) & F.coalesce(F.exists(e, lambda v: v != 0), F.lit(False))


def _matrix(col) -> np.ndarray:
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    flat = col.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    x = flat.reshape(len(col), -1) if len(col) else np.zeros((0, 0))
    with np.errstate(over="ignore"):
        x = x / np.maximum(np.abs(x).max(axis=1, keepdims=True, initial=0), 1e-300)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def local_roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least member of each place's component under links a-b."""
    root = np.arange(n)
    while True:
        least = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], least)
        np.minimum.at(new, root[b], least)
        np.minimum.at(new, a, least)
        np.minimum.at(new, b, least)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def compare_leaf(leaf: int, x: np.ndarray, ids: np.ndarray, weight: np.ndarray, paths: list[np.ndarray], block: np.ndarray, pair: tuple[int, int], least: float) -> tuple[np.ndarray, np.ndarray]:
    """(linked vectors that count in this leaf, least linked id) of each row; ids rise."""
    n = len(x)
    width = max((len(p) for p in paths), default=0)
    own = np.full((n, width), -1, np.int64)
    for i, p in enumerate(paths):
        own[i, : len(p)] = p
    count = np.zeros(n, np.int64)
    la, lb = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    left = np.flatnonzero(block == pair[0])
    right = np.flatnonzero(block == pair[1])
    for i in range(0, len(left), 512):
        for j in range(0, len(right), 512):
            p, q = left[i : i + 512], right[j : j + 512]
            a, b = np.nonzero(x[p] @ x[q].T >= least)
            a, b = p[a], q[b]
            if pair[0] == pair[1]:
                a, b = a[a < b], b[a < b]
            for k in range(0, len(a), 20_000):
                u, v = a[k : k + 20_000], b[k : k + 20_000]
                both = (own[u][:, :, None] == own[v][:, None, :]) & (own[u] >= 0)[:, :, None]
                shared = np.where(both.any(axis=2), own[u], np.iinfo(np.int64).max).min(axis=1, initial=np.iinfo(np.int64).max)
                here = shared == leaf
                np.add.at(count, u[here], weight[v[here]])
                np.add.at(count, v[here], weight[u[here]])
            roots = local_roots(n, a, b)  # a block's links as stars
            moved = np.flatnonzero(roots != np.arange(n))
            la.append(moved), lb.append(roots[moved])
    return count, ids[local_roots(n, np.concatenate(la), np.concatenate(lb))]


def near_duplicates(vectors: DataFrame, least: float = 0.98, key: str = "vec_id", embedding: str = "embedding", label: str = "label", trees: int = TREES, leaf: int = LEAF, block: int = BLOCK_ROWS) -> DataFrame:
    """(key, n_links, component_id, kept) of every vector."""
    spark = vectors.sparkSession
    every = vectors.select(F.col(key).alias("id"), F.col(embedding).alias("e"), F.col(label).alias("label"))
    good = every.where(usable("e") & F.col("label").isNotNull() & F.col("id").isNotNull())
    name = [F.xxhash64("e").alias("h1"), F.xxhash64(F.lit(1), "e", F.size("e")).alias("h2")]
    classes = staged(good.withColumns({"h1": name[0], "h2": name[1]}).groupBy("label", "h1", "h2").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("weight"), F.first("e").alias("e")))
    sizes = {r["d"]: r["count"] for r in classes.groupBy(F.size("e").alias("d")).count().orderBy(F.desc("count"), "d").limit(64).collect()}
    main = next(iter(sizes), 0)
    sample = classes.where(F.size("e") == main).orderBy(F.xxhash64("first"), "first").limit(SAMPLE).select("e").toArrow()
    forest = Forest(_matrix(sample.column(0)), sizes.get(main, 0), trees, leaf)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = b.schema.get_field_index("e")
            n = np.array([len(e) for e in b.column(at)], np.int64)
            lists: list[list[int]] = [[-1 - int(k)] for k in n]  # other lengths meet in one leaf of their own
            use = np.flatnonzero(n == main)
            if len(use):
                row, where = forest.leaves(_matrix(b.column(at).take(pa.array(use))))
                order = np.lexsort((where, row))
                row, where = row[order], where[order]
                cut = np.searchsorted(row, np.arange(len(use) + 1))
                for i, r in enumerate(use.tolist()):
                    lists[r] = where[cut[i] : cut[i + 1]].tolist()
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(lists, pa.list_(pa.int64()))], [*b.schema.names, "leaves"])

    put = classes.select("label", "first", "weight", "e")
    kind = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in put.schema)
    put = staged(put.mapInArrow(assign, f"{kind}, leaves array<bigint>"))
    rows = put.select("*", F.explode("leaves").alias("leaf"))
    big = staged(rows.groupBy("leaf", "label").count().where(F.col("count") > block).select("leaf", "label", F.ceil(F.col("count") / block).cast("int").alias("blocks")))
    dealt = rows.join(big, ["leaf", "label"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    dealt = dealt.withColumn("block", F.pmod(F.xxhash64("first"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.withColumns({"b1": F.least("block", "other"), "b2": F.greatest("block", "other")})

    def compare(name_: tuple, rows_: pa.Table) -> pa.Table:
        rows_ = rows_.sort_by("first")
        leaf_, b1, b2 = name_[0].as_py(), name_[2].as_py(), name_[3].as_py()
        ids = rows_.column("first").to_numpy()
        count, root = compare_leaf(leaf_, _matrix(rows_.column("e")), ids, rows_.column("weight").to_numpy(), [np.array(p, np.int64) for p in rows_.column("leaves").to_pylist()], rows_.column("block").to_numpy(), (b1, b2), least)
        use = (count > 0) | (root != ids)
        return pa.table({"first": ids[use], "n": count[use], "root": root[use].astype(np.int64)})

    found = staged(dealt.select("leaf", "label", "b1", "b2", "first", "weight", "e", "leaves", "block").groupBy("leaf", "label", "b1", "b2").applyInArrow(compare, "first bigint, n bigint, root bigint"))
    counted = found.groupBy("first").agg(F.sum("n").alias("n"))
    roots = component_roots(found.where("first <> root"), "first", "root").select(F.col("id").alias("first"), "root")
    joined = classes.select("label", "h1", "h2", "first", "weight").join(counted, "first", "left").join(roots, "first", "left")
    placed = joined.select("label", "h1", "h2", (F.coalesce("n", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("root", "first").alias("component_id"))
    own = F.when(usable("e") & F.col("label").isNotNull() & F.col("id").isNotNull(), F.struct(*name))
    result = every.select("id", "label", own.alias("n")).select("id", "label", "n.h1", "n.h2").join(placed, ["label", "h1", "h2"], "left")
    result = result.select(F.col("id").alias(key), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "id").cast("long").alias("component_id"))
    return result.withColumn("kept", F.col(key).eqNullSafe(F.col("component_id")))


def op5_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))


ORACLE = """
WITH RECURSIVE v AS MATERIALIZED (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings WHERE embedding IS NOT NULL AND label IS NOT NULL
  AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
links AS MATERIALIZED (SELECT a.vec_id AS x, b.vec_id AS y FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= 0.98),
reach AS (SELECT x AS vec_id, x AS r FROM links UNION SELECT reach.vec_id, links.y FROM reach JOIN links ON links.x = reach.r),
least AS (SELECT vec_id, min(r) AS r FROM reach GROUP BY 1),
n AS (SELECT x AS vec_id, count(*) AS n FROM links GROUP BY 1)
SELECT e.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, least(e.vec_id, coalesce(l.r, e.vec_id))::BIGINT AS component_id, e.vec_id = least(e.vec_id, coalesce(l.r, e.vec_id)) AS kept
FROM embeddings e LEFT JOIN n USING (vec_id) LEFT JOIN least l USING (vec_id)
"""
