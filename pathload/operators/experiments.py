"""Experiments on updates: modes, measured times, replays, scaling, and how structure bears on work.

Times are taken inside the tasks and added up over them, as a cluster's cumulative time;
wall times are the caller's. Every run also gives counts (sources affected, keys looked
at, arcs read), which are the same on every machine.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from pathload.operators.graph import Csr, Graph, to_csr
from pathload.operators.update import Session, Update
from pathload.plans.blocks import block_ranges, sources_at_once
from pathload.plans.kernel import Block, Net

MODES = ("MP", "MO", "DO")
MEASURED = "mode string, seq bigint, op string, block int, t_full double, t_update double, affected bigint, touched bigint, arcs bigint, state_bytes bigint"


def measured_blocks(graph: Graph, updates: list[Update], n_blocks: int, mode: str = "MO", strategy: str = "cases", sources: int | None = None) -> DataFrame:
    """A row for each block and update (MEASURED). MP keeps predecessor lists, MO does not; both hold state in the task,
    of as many of the block's sources at once as fit it. All updates go to these sources before the next ones are taken; times and counts add up.

    t_full is the block's static time from scratch, the same on all its rows. sources: how many the first blocks take, for runs of a part.
    """
    csr = to_csr(graph)
    place = {v: i for i, v in enumerate(csr.ids.tolist())}
    work = [(x.op, place[x.u], place[x.v], x.seq) for x in updates]
    spark = graph.spark
    sent = spark.sparkContext.broadcast((csr, work, block_ranges(min(sources or len(csr.ids), len(csr.ids)), n_blocks)))
    fields = [x.split() for x in MEASURED.split(", ")]
    kinds = {"string": pa.string(), "bigint": pa.int64(), "int": pa.int32(), "double": pa.float64()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g, todo, ranges = sent.value
        for b in batches:
            for k in b.column(0).to_pylist():
                lo, hi = ranges[k]
                at = time.perf_counter()
                net = Net(len(g.ids), g.src, g.dst, g.directed)
                full = time.perf_counter() - at
                sums = np.zeros((len(todo), 5))
                step = sources_at_once(net.n, len(g.src) + len(todo))
                for first in range(lo, hi, step):
                    at = time.perf_counter()
                    block = Block(net.copy(), np.arange(first, min(hi, first + step)), predecessors=mode == "MP")
                    block.loads()
                    full += time.perf_counter() - at
                    for i, (op, u, v, _) in enumerate(todo):
                        at = time.perf_counter()
                        got = block.apply(op, u, v, strategy)
                        spent = time.perf_counter() - at
                        sums[i] += spent, len(got["rows"]), got["touched"], got.get("arcs", 0), block.state_bytes()
                rows = [(mode, seq, op, k, full, float(t), *map(int, counts)) for (op, _, _, seq), (t, *counts) in zip(todo, sums, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(c, kinds[t]) for c, (_, t) in zip(zip(*rows, strict=True), fields, strict=True)] if rows else [pa.array([], kinds[t]) for _, t in fields], [n for n, _ in fields])

    ranges = sent.value[2]
    return spark.range(0, len(ranges), 1, len(ranges)).mapInArrow(run, MEASURED)


def cumulative(measured: DataFrame) -> DataFrame:
    """(mode, seq, op, t_full, t_update, speedup, affected, touched, arcs): summed over the blocks, that is the cluster's cumulative time."""
    total = measured.groupBy("mode", "seq", "op").agg(*(F.sum(c).alias(c) for c in ("t_full", "t_update", "affected", "touched", "arcs")))
    return total.withColumn("speedup", F.col("t_full") / F.col("t_update"))


def stored_run(graph: Graph, updates: list[Update], n_blocks: int, strategy: str = "cases") -> tuple[Session, list[dict]]:
    """Mode DO: one update at a time through a session's store; (session, rows with wall seconds and counts)."""
    at = time.perf_counter()
    session = Session.start(graph, n_blocks, strategy)
    full = time.perf_counter() - at
    rows = []
    for x in updates:
        at = time.perf_counter()
        session = session.apply([x])
        rows.append({"mode": "DO", "seq": x.seq, "op": x.op, "t_full": full, "t_update": time.perf_counter() - at, "affected": session.read_rows, "touched": session.counts.get((x.seq, "touched"), 0)})
    return session, rows


def with_measured_times(updates: DataFrame, rows: list[dict]) -> DataFrame:
    """(seq, t_i, t_u): arrivals (seq, ts) with the seconds until the next one and the measured update time."""
    spark = updates.sparkSession
    took = spark.createDataFrame([(int(r["seq"]), float(r["t_update"])) for r in rows], "seq bigint, t_u double")
    gap = F.timestamp_diff("MICROSECOND", F.col("ts"), F.lead("ts").over(Window.orderBy("ts", "seq"))) / 1e6  # the updates of one run
    return updates.withColumn("t_i", gap).join(took, "seq").where("t_i IS NOT NULL").select("seq", "t_i", "t_u")


def scaling_runs(graph: Graph, updates: list[Update], workers: tuple[int, ...], per_worker: bool = False) -> DataFrame:
    """(workers, updates, seconds, longest): task seconds in all and of the slowest block, for as many blocks as workers.

    per_worker: the updates grow with the workers (weak scaling); else they stay (strong scaling).
    """
    out = None
    for w in workers:
        some = updates[: max(1, len(updates) * w // max(workers))] if per_worker else updates
        each = measured_blocks(graph, some, w).groupBy("block").agg(F.sum("t_update").alias("t"))
        one = each.agg(F.sum("t").alias("seconds"), F.max("t").alias("longest")).select(F.lit(w).alias("workers"), F.lit(len(some)).alias("updates"), "seconds", "longest")
        out = one if out is None else out.unionByName(one)
    return out


def biconnected(csr: Csr) -> tuple[np.ndarray, np.ndarray]:
    """(component of each edge, vertices of each component) of an undirected graph that the driver holds, by one depth-first search."""
    n = len(csr.ids)
    net = Net(n, csr.src, csr.dst)
    start, to, edge = net.out
    low, order, component = np.full(n, -1), np.full(n, -1), np.full(len(csr.src), -1)
    at, met, parts = start[:-1].copy(), 0, 0
    for root in range(n):
        if order[root] >= 0:
            continue
        order[root] = low[root] = met
        met += 1
        path, held = [(root, -1)], []
        while path:
            v, came = path[-1]
            if at[v] < start[v + 1]:
                w, e = int(to[at[v]]), int(edge[at[v]])
                at[v] += 1
                if e == came:
                    continue
                if order[w] < 0:
                    held.append(e)
                    order[w] = low[w] = met
                    met += 1
                    path.append((w, e))
                elif order[w] < order[v]:
                    held.append(e)
                    low[v] = min(low[v], order[w])
                continue
            path.pop()
            if path:
                u = path[-1][0]
                low[u] = min(low[u], low[v])
                if low[v] >= order[u]:  # u parts what hangs below it
                    while True:
                        e = held.pop()
                        component[e] = parts
                        if e == came:
                            break
                    parts += 1
    ends = np.unique(np.concatenate([component * np.int64(n) + csr.src, component * np.int64(n) + csr.dst])) if len(csr.src) else np.zeros(0, np.int64)
    return component, np.bincount(ends // max(n, 1), minlength=parts)


def cycle_scope(graph: Graph) -> DataFrame:
    """(src, dst, scope): vertices that a method which recomputes the cycles through an edge would have to look at."""
    csr = to_csr(graph)
    component, size = biconnected(csr)
    ids = csr.ids
    table = pa.table({"src": pa.array(ids[csr.src].tolist(), pa.string()), "dst": pa.array(ids[csr.dst].tolist(), pa.string()), "scope": pa.array(size[component] if len(component) else np.zeros(0, np.int64), pa.int64())})
    return graph.spark.createDataFrame(table)


def bridges(graph: Graph) -> DataFrame:
    """(src, dst): edges that are a biconnected component by themselves."""
    return cycle_scope(graph).where("scope = 2").select("src", "dst")
