"""Keeping loads exact while edges and vertices come and go.

A session holds the graph and the loads as arrays on the driver, whose size is checked
before, and the path state in the shared store. A batch first reads the distance column
alone: sources whose distances to both ends of every update are equal are skipped, and
nothing else of them is read or written. The other sources' rows go to the kernel where
they lie, without a shuffle, each for itself; a task adds up its load differences and
puts out the state rows that changed, which make the next version. One sum over the
parts gives the new loads.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pathload.operators.components import cut_lineage, shared_folder
from pathload.operators.graph import Csr, Graph, to_csr
from pathload.operators.state import StateStore
from pathload.plans.blocks import _ARROW, ROW_SCHEMA, TASK_CELLS, Loads, rows_of_state, run_blocks, sources_at_once
from pathload.plans.kernel import Block, Net

#: Versions of a lineage after which a session writes its whole state anew.
COMPACT_AFTER = 16


@dataclass(frozen=True)
class Update:
    op: str  # add or remove
    u: str
    v: str
    seq: int = 0


@dataclass
class Session:
    """Loads and state of a graph after some updates. log: (seq, case, sources), (seq, 'touched', keys)."""

    spark: SparkSession
    csr: Csr
    vbc: np.ndarray
    ebc: np.ndarray  # beside csr.src and csr.dst
    store: StateStore
    lineage: tuple[int, ...]
    n_blocks: int
    strategy: str = "cases"
    predecessors: bool = False
    dead: frozenset = frozenset()  # vertices that went; their positions stay
    ops: tuple[str, ...] = ("add", "remove")  # a restricted method takes additions alone
    counts: dict = field(default_factory=dict)
    rejected: list[tuple[Update, str]] = field(default_factory=list)
    read_rows: int = 0  # sources whose whole rows the last batch read

    @staticmethod
    def start(graph: Graph, n_blocks: int | None = None, strategy: str = "cases", predecessors: bool = False, path: str | None = None, ops: tuple[str, ...] = ("add", "remove")) -> Session:
        """Offline step: loads and state by a static run. path: of the store, a fresh folder by default."""
        spark = graph.spark
        graph = Graph(cut_lineage(graph.edges), graph.directed, cut_lineage(graph.vertices))
        csr = to_csr(graph)
        parts = n_blocks or max(2, -(-len(csr.ids) // 1000))
        store = StateStore(spark, path or shared_folder(spark))
        version = store.write(run_blocks(csr, spark, parts, predecessors))
        place = {v: i for i, v in enumerate(csr.ids.tolist())}
        edge = {(a, b): i for i, (a, b) in enumerate(zip(csr.src.tolist(), csr.dst.tolist(), strict=True))}
        vbc, ebc = np.zeros(len(csr.ids)), np.zeros(len(csr.src))
        for r in store.rows([version], "v", "e").groupBy("a", "b").agg(F.sum("part").alias("part")).toArrow().to_pylist():  # a row for each vertex and edge that the driver holds
            if r["b"] is None:
                vbc[place[r["a"]]] = r["part"]
            else:
                ebc[edge[place[r["a"]], place[r["b"]]]] = r["part"]
        store.seal(version)
        return Session(spark, csr, vbc, ebc, store, (version,), parts, strategy, predecessors, ops=ops)

    # -- what it holds, as frames -------------------------------------------------

    @property
    def graph(self) -> Graph:
        return Graph(self._edges().select("src", "dst"), self.csr.directed, self._vertices().select("id"))

    @property
    def loads(self) -> Loads:
        return Loads(self._vertices(), self._edges())

    @property
    def state(self) -> DataFrame:
        return self.store.read(lineage=self.lineage)

    @property
    def log(self) -> DataFrame:
        return self.spark.createDataFrame([(seq, case, int(n)) for (seq, case), n in self.counts.items()], "seq bigint, case string, n bigint")

    def _vertices(self) -> DataFrame:
        there = np.array([v not in self.dead for v in self.csr.ids.tolist()], bool)
        return self.spark.createDataFrame(pa.table({"id": pa.array(self.csr.ids[there].tolist(), pa.string()), "vbc": pa.array(self.vbc[there])}))

    def _edges(self) -> DataFrame:
        a, b = self.csr.ids[self.csr.src], self.csr.ids[self.csr.dst]
        if not self.csr.directed:
            a, b = np.where(a < b, a, b) if len(a) else a, np.where(a < b, b, a) if len(a) else b
        return self.spark.createDataFrame(pa.table({"src": pa.array(a.tolist(), pa.string()), "dst": pa.array(b.tolist(), pa.string()), "ebc": pa.array(self.ebc)}))

    def heaviest(self) -> tuple[str, str, float] | None:
        """The edge of most load, rounded so that noise can't choose; ties go to the least ids."""
        if not len(self.ebc):
            return None
        load = np.round(self.ebc + 1e-9, 6)
        ends = [tuple(self.csr.ids[[self.csr.src[i], self.csr.dst[i]]].tolist()) for i in np.flatnonzero(load == load.max()).tolist()]
        return (*min(e if self.csr.directed else tuple(sorted(e)) for e in ends), float(load.max()))

    # -- batches ------------------------------------------------------------------

    def validate(self, updates: list[Update], new_vertices: tuple[str, ...] = ()) -> tuple[list[Update], list[tuple[Update, str]]]:
        """Updates that fit the graph as it is when they come, and the others with reasons."""
        ids = self.csr.ids.tolist()
        key = (lambda a, b: (a, b)) if self.csr.directed else (lambda a, b: (min(a, b), max(a, b)))
        there = {key(ids[a], ids[b]) for a, b in zip(self.csr.src.tolist(), self.csr.dst.tolist(), strict=True)}
        known = (set(ids) - self.dead) | set(new_vertices)
        good, bad = [], []
        for x in updates:
            e = key(x.u, x.v)
            why = "loop" if x.u == x.v else "unknown operation" if x.op not in self.ops else ""
            why = why or ("edge exists" if x.op == "add" and e in there else "no such edge" if x.op == "remove" and e not in there else "")
            why = why or ("unknown vertex" if not {x.u, x.v} <= known else "")
            if why:
                bad.append((x, why))
                continue
            good.append(x)
            (there.add if x.op == "add" else there.remove)(e)
        return good, bad

    def touched_sources(self, work: list[tuple[str, int, int, int]]) -> DataFrame:
        """(s, version): the latest rows of sources that some update of the batch touches, from the distance column alone.

        A source that the first updates skip keeps its distances, so one look at the
        stored ones tells whether the whole batch skips it.
        """
        at = lambda i: F.coalesce(F.try_element_at("d", F.lit(i + 1)), F.lit(-1))

        def hit(op: str, u: int, v: int):
            if not self.csr.directed:
                return at(u) != at(v)
            return (at(u) >= 0) & ((at(v) < 0) | (at(v) > at(u)) if op == "add" else at(v) == at(u) + 1)

        some = F.lit(False)
        for op, u, v, _ in work:
            some = some | hit(op, u, v)
        seen = self.store.rows(self.lineage, "s").select("s", "version", some.alias("hit"))
        if len(self.lineage) > 1:
            seen = seen.groupBy("s").agg(F.max(F.struct("version", "hit")).alias("x")).select("s", "x.version", "x.hit")
        return seen.where("hit").select("s", "version")

    def apply(self, updates: list[Update], new_vertices: tuple[str, ...] = (), batch: int | None = None) -> Session:
        """The session after a batch. New vertices come without edges first; their sources are a block of their own."""
        known = set(self.csr.ids.tolist())
        back = frozenset(v for v in new_vertices if v in self.dead)
        fresh = tuple(sorted({v for v in new_vertices if v not in known}))
        good, bad = self.validate(updates, (*fresh, *back))
        ids = np.array([*self.csr.ids.tolist(), *fresh], dtype=object)
        place = {v: i for i, v in enumerate(ids.tolist())}
        work = [(x.op, place[x.u], place[x.v], x.seq) for x in good]
        n = len(ids)
        after = replace(self, rejected=[*self.rejected, *bad], dead=self.dead - back, counts=dict(self.counts))
        after.csr = Csr(ids, self.csr.src, self.csr.dst, self.csr.directed)
        after.vbc = np.append(self.vbc, np.zeros(len(fresh)))
        if not work and not fresh:
            if batch is not None:
                version = self.store.write(self.store.rows(self.lineage[-1:], "s").where("false").drop("version"))
                after.lineage = (*self.lineage, version)
                self.store.seal(version, self.lineage, batch, after.note())
            return after
        picked = self.touched_sources(work).toArrow()  # two numbers a source; the driver holds more than that of the graph
        chosen = self.spark.createDataFrame(picked) if picked.num_rows else None
        sent = self.spark.sparkContext.broadcast((n, self.csr.src, self.csr.dst, self.csr.directed, work, self.strategy))

        def repair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            n, src, dst, directed, todo, strategy = sent.value
            vertex, edge = np.zeros(n), np.zeros(len(src) + len(todo))
            counts: dict[tuple[int, str], float] = {}
            step = sources_at_once(n, len(src) + len(todo))
            start = Net(n, src, dst, directed)
            for whole in batches:
                for lo in range(0, whole.num_rows, step):
                    rows = whole.slice(lo, step)
                    wide = lambda name, fill, kind: _dense(rows.column(name), n, fill, kind)  # noqa: B023, E731
                    s, blocks = rows.column("s").to_numpy(), rows.column("block").to_numpy()
                    block = Block(start.copy(), s, (wide("d", -1, np.int32), wide("sigma", 0.0, np.float64), wide("delta", 0.0, np.float64)))
                    changed = np.zeros(len(s), bool)
                    for op, u, v, seq in todo:
                        got = block.apply(op, u, v, strategy)
                        vertex += got["vertex"]
                        edge[: len(got["edge"])] += got["edge"]
                        changed[got["rows"]] = True
                        for case, k in (*got["cases"].items(), ("touched", got["touched"])):
                            counts[seq, case] = counts.get((seq, case), 0) + k
                    for b in np.unique(blocks[changed]).tolist():
                        yield from rows_of_state(b, block, np.flatnonzero(changed & (blocks == b)))
            yield _numbered("v", vertex)
            yield _numbered("e", edge)
            if counts:
                yield _counted(counts)

        rows = None
        if chosen is not None:
            rows = self.store.rows(self.lineage, "s").join(F.broadcast(chosen), ["s", "version"]).select("s", "block", "d", "sigma", "delta").mapInArrow(repair, ROW_SCHEMA)
        if fresh:
            own = self._own_rows(len(self.csr.ids), n).mapInArrow(repair, ROW_SCHEMA) if work else self._own_rows(len(self.csr.ids), n).selectExpr("'s' AS kind", "CAST(NULL AS string) AS a", "CAST(NULL AS string) AS b", "CAST(NULL AS double) AS part", "block", "s", "d", "sigma", "delta")
            if work:  # rows that no update changed are new all the same
                idle = self._own_rows(len(self.csr.ids), n).where(~F.col("s").isin(sorted({x for _, u, v, _ in work for x in (u, v)})))
                own = own.unionByName(idle.selectExpr("'s' AS kind", "CAST(NULL AS string) AS a", "CAST(NULL AS string) AS b", "CAST(NULL AS double) AS part", "block", "s", "d", "sigma", "delta"))
            rows = own if rows is None else rows.unionByName(own)
            after.n_blocks += 1
        if rows is None:
            rows = self.store.rows(self.lineage[-1:], "s").where("false").drop("version")
        version = self.store.write(rows)
        net = Net(n, self.csr.src, self.csr.dst, self.csr.directed)
        for op, u, v, _ in work:
            (net.add if op == "add" else net.remove)(u, v)
        gain = self.store.rows([version], "v", "e").groupBy("kind", "s").agg(F.sum("part").alias("part")).toArrow()
        which, at, part = (gain.column(c).to_numpy(zero_copy_only=False) for c in ("kind", "s", "part"))
        total = np.append(self.ebc, np.zeros(len(net.src) - len(self.ebc)))
        after.vbc[at[which == "v"]] += part[which == "v"]
        total[at[which == "e"]] += part[which == "e"]
        live = np.flatnonzero(net.alive)
        after.csr, after.ebc = Csr(ids, net.src[live], net.dst[live], self.csr.directed), total[live]
        met = {}
        for r in self.store.rows([version], "c").groupBy("a", "b").agg(F.sum("part").alias("n")).collect():  # a row for each update and case
            met[int(r["a"]), r["b"]] = int(r["n"])
        skipped = len(self.csr.ids) - picked.num_rows
        for _, _, _, seq in work:
            met[seq, "skip"] = met.get((seq, "skip"), 0) + skipped
            if not met[seq, "skip"]:
                del met[seq, "skip"]
            met.setdefault((seq, "touched"), 0)
        after.counts.update(met)
        after.lineage, after.read_rows = (*self.lineage, version), picked.num_rows
        self.store.seal(version, self.lineage, batch, "" if batch is None else after.note())
        if len(after.lineage) > COMPACT_AFTER:
            whole = self.store.write(self.store.read(lineage=after.lineage))
            self.store.seal(whole, (), batch, "" if batch is None else after.note())
            after.lineage = (whole,)
        return after

    def _own_rows(self, first: int, n: int) -> DataFrame:
        """State rows of new sources: each reaches itself alone."""
        own = self.spark.range(first, n).select(F.lit(self.n_blocks).alias("block"), F.col("id").alias("s"))
        at = lambda yes, no: F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.when(i == F.col("s"), F.lit(yes)).otherwise(F.lit(no)))
        return own.select("s", "block", at(0, -1).alias("d"), at(1.0, 0.0).alias("sigma"), at(0.0, 0.0).alias("delta"))

    # -- after a restart ------------------------------------------------------------

    def note(self) -> str:
        """Where the driver's arrays of this state are: a folder of the shared store, written with the version."""
        to = shared_folder(self.spark)
        table = pa.table({"name": ["ids", "dead", "directed", "vbc", "ebc", "src", "dst", "blocks"], "value": [_packed_words(self.csr.ids.tolist()), _packed_words(sorted(self.dead)), bytes([self.csr.directed]), self.vbc.tobytes(), self.ebc.tobytes(), self.csr.src.astype(np.int64).tobytes(), self.csr.dst.astype(np.int64).tobytes(), int(self.n_blocks).to_bytes(8, "little")]})
        self.spark.createDataFrame(table).coalesce(1).write.parquet(to)
        return to

    @staticmethod
    def resume(spark: SparkSession, path: str, strategy: str = "cases") -> tuple[Session, int] | None:
        """The session of the store's last whole batch, and that batch's number; None where no batch was committed."""
        store = StateStore(spark, path)
        if not store.versions():
            return None
        last = store.manifest().where("note <> ''").orderBy(F.desc("batch"), F.desc("number")).first()
        if last is None:
            return None
        got = {r["name"]: bytes(r["value"]) for r in spark.read.parquet(last["note"]).collect()}
        ids = np.array(_unpacked_words(got["ids"]), dtype=object)
        csr = Csr(ids, np.frombuffer(got["src"], np.int64), np.frombuffer(got["dst"], np.int64), bool(got["directed"][0]))
        session = Session(spark, csr, np.frombuffer(got["vbc"], np.float64).copy(), np.frombuffer(got["ebc"], np.float64).copy(), store, tuple(last["lineage"]), int.from_bytes(got["blocks"], "little"), strategy, dead=frozenset(_unpacked_words(got["dead"])))
        return session, last["batch"]

    # -- vertices, drift --------------------------------------------------------------

    def add_vertex(self, vertex: str, neighbours: list[str], seq: int = 0) -> Session:
        return self.apply([Update("add", vertex, v, seq + i) for i, v in enumerate(neighbours)], (vertex,))

    def remove_vertex(self, vertex: str, seq: int = 0) -> Session:
        """Its edges go one by one; then it is no vertex any more, until it is added again."""
        ids = self.csr.ids.tolist()
        at = self.csr.position(vertex) if vertex in ids else -1
        own = [(ids[a], ids[b]) for a, b in zip(self.csr.src.tolist(), self.csr.dst.tolist(), strict=True) if at in (a, b)]
        after = self.apply([Update("remove", a, b, seq + i) for i, (a, b) in enumerate(sorted(own))])
        after.dead = after.dead | ({vertex} & set(ids))
        return after

    def rebase(self) -> Session:
        """Vertex loads added up anew from the stored dependencies, without any search; rounding drift goes."""
        n = len(self.csr.ids)

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(n)
            for b in batches:
                for lo in range(0, b.num_rows, max(1, TASK_CELLS // max(n, 1))):
                    rows = b.slice(lo, max(1, TASK_CELLS // max(n, 1)))
                    delta = _dense(rows.column("delta"), n, 0.0, np.float64)
                    delta[np.arange(len(delta)), rows.column("s").to_numpy()] = 0
                    total += delta.sum(axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(n)), pa.array(total)], ["t", "part"])

        summed = self.store.read(("delta",), lineage=self.lineage).select("s", "delta").mapInArrow(add, "t bigint, part double").groupBy("t").agg(F.sum("part").alias("vbc")).toArrow()
        after = replace(self, vbc=np.zeros(n))
        after.vbc[summed.column("t").to_numpy()] = summed.column("vbc").to_numpy()
        return after


def _packed_words(words: list[str]) -> bytes:
    raw = [w.encode() for w in words]
    return b"".join(len(r).to_bytes(4, "little") + r for r in raw)


def _unpacked_words(data: bytes) -> list[str]:
    out, at = [], 0
    while at < len(data):
        n = int.from_bytes(data[at : at + 4], "little")
        out.append(data[at + 4 : at + 4 + n].decode())
        at += 4 + n
    return out


def _numbered(kind: str, part: np.ndarray) -> pa.RecordBatch:
    """Differences that are not zero, by position in the column s."""
    at = np.flatnonzero(part)
    k = len(at)
    none = lambda i: pa.nulls(k, _ARROW.field(i).type)
    return pa.RecordBatch.from_arrays([pa.array([kind] * k, pa.string()), none(1), none(2), pa.array(part[at]), none(4), pa.array(at), none(6), none(7), none(8)], schema=_ARROW)


def _counted(counts: dict[tuple[int, str], float]) -> pa.RecordBatch:
    k = len(counts)
    return pa.RecordBatch.from_arrays(
        [pa.array(["c"] * k), pa.array([str(s) for s, _ in counts]), pa.array([c for _, c in counts]), pa.array(list(map(float, counts.values()))), *(pa.nulls(k, _ARROW.field(i).type) for i in range(4, 9))],
        schema=_ARROW,
    )


def _dense(col, n: int, fill, kind) -> np.ndarray:
    """A list column as a matrix; rows from before a vertex came are shorter."""
    out = np.full((len(col), n), fill, kind)
    off = np.asarray(col.offsets)
    flat = col.values.to_numpy(zero_copy_only=False)
    size = np.diff(off)
    if len(size) and (size == size[0]).all():
        out[:, : size[0]] = flat[off[0] : off[-1]].reshape(len(col), size[0])
    else:
        for i, (a, b) in enumerate(zip(off[:-1], off[1:], strict=True)):
            out[i, : b - a] = flat[a:b]
    return out


def updates_from(frame: DataFrame) -> list[Update]:
    """Updates in order of seq; a batch is small by definition."""
    return [Update(r["op"], r["u"], r["v"], int(r["seq"])) for r in frame.select("seq", "op", "u", "v").orderBy("seq").collect()]


def last_by_pair(updates: DataFrame) -> DataFrame:
    """The last operation of every pair."""
    w = Window.partitionBy(F.least("u", "v"), F.greatest("u", "v")).orderBy(F.desc("seq"))
    return updates.withColumn("r", F.row_number().over(w)).where("r = 1").drop("r")
