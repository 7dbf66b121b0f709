"""Updates as a stream over stateful blocks: each key is a range of sources whose path state lives in Spark's state store.

Every update goes to all blocks; a block builds its state from the graph when it first
hears of an update, applies updates in order of seq, and puts out differences of loads.
State and offsets are committed together, so a restart goes on where the last micro-batch
ended. Batches come in order; within one, updates are sorted.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from pathload.operators.components import cut_lineage, shared_folder
from pathload.operators.graph import Graph, to_csr
from pathload.plans.blocks import Loads, block_ranges
from pathload.plans.kernel import Block, Net

PART = "kind string, a string, b string, part double"


def run_stateful_blocks(updates: DataFrame, graph: Graph, n_blocks: int = 4, strategy: str = "cases", checkpoint: str | None = None, out: str | None = None) -> Loads:
    """Consumes a stream of (seq, op, u, v) over known vertices; loads after what is there.

    out and checkpoint: folders of the differences and of the stream's state; the same two again go on from there.
    """
    spark = updates.sparkSession
    csr = to_csr(Graph(cut_lineage(graph.edges), graph.directed, cut_lineage(graph.vertices)))
    sent = spark.sparkContext.broadcast((csr, block_ranges(len(csr.ids), n_blocks)))
    out = out or shared_folder(spark)

    def parts(ids: list[str], src, dst, vertex: np.ndarray, edge: np.ndarray) -> pd.DataFrame:
        v, e = np.flatnonzero(vertex), np.flatnonzero(edge)
        return pd.DataFrame({"kind": ["v"] * len(v) + ["e"] * len(e), "a": [*(ids[i] for i in v), *(ids[src[i]] for i in e)], "b": [*[None] * len(v), *(ids[dst[i]] for i in e)], "part": np.concatenate([vertex[v], edge[e]])})

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        g, ranges = sent.value
        ids = g.ids.tolist()
        place = {x: i for i, x in enumerate(ids)}
        if state.exists:
            block: Block = pickle.loads(state.get[0])  # written by this function alone
        else:
            block = Block(Net(len(ids), g.src, g.dst, g.directed), np.arange(*ranges[key[0]]))
            yield parts(ids, block.net.src, block.net.dst, *block.loads())
        for x in pd.concat(frames).sort_values("seq").itertuples():
            u, v = place.get(x.u), place.get(x.v)
            if x.op is None or u is None or v is None or u == v or (x.op == "add") == (block.net.find(u, v) >= 0):
                continue  # the start's row, and what does not fit the graph
            got = block.apply(x.op, u, v, strategy)
            yield parts(ids, block.net.src, block.net.dst, got["vertex"], got["edge"])
        state.update((pickle.dumps(block),))

    each = updates.select("seq", "op", "u", "v", F.explode(F.sequence(F.lit(0), F.lit(len(sent.value[1]) - 1))).alias("block"))
    changes = each.groupBy("block").applyInPandasWithState(step, PART, "held binary", "append", GroupStateTimeout.NoTimeout)
    query = changes.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint or shared_folder(spark)).outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.schema(PART).parquet(out)
    vertex = rows.where("kind = 'v'").groupBy(F.col("a").alias("id")).agg(F.sum("part").alias("vbc"))
    edge = rows.where("kind = 'e'").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("part").alias("ebc")).where(F.abs("ebc") > 1e-7)  # a removed edge's parts add up to rounding
    return Loads(graph.vertices.join(vertex, "id", "left").select("id", F.coalesce("vbc", F.lit(0.0)).alias("vbc")), edge)
