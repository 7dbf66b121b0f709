"""Path state in the shared store: versions of Parquet rows, and a manifest.

A version holds what one run or batch put out: rows of path state of the sources that
changed (kind s), its parts of the loads (kinds v and e) and its counts (kind c). The
manifest of a version is written last, so a version without one is not there. Readers
take, for each source, the row of the latest version of their lineage; distances are a
column of their own and are read without the counts and dependencies.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, functions as F

ROW = "kind string, a string, b string, part double, block int, s bigint, d array<int>, sigma array<double>, delta array<double>"
#: Bytes of a row group: small, so that a reader of few sources skips most of a file.
GROUP_BYTES = 8 << 20


@dataclass
class StateStore:
    spark: SparkSession
    path: str

    def _fs(self):
        jvm = self.spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(self.path)
        return at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), jvm.org.apache.hadoop.fs.Path

    def versions(self) -> list[int]:
        """Versions whose manifest is whole."""
        fs, path = self._fs()
        top = path(f"{self.path}/manifest")
        if not fs.exists(top):
            return []
        names = [x.getPath().getName() for x in fs.listStatus(top)]
        return sorted(int(n.split("=")[1]) for n in names if n.startswith("version=") and fs.exists(path(f"{self.path}/manifest/{n}/_SUCCESS")))

    def manifest(self) -> DataFrame:
        """(number, batch, lineage, note) of whole versions: the stream batch it came from (-1: none) and the versions it stands on."""
        return self.spark.read.schema("number int, batch bigint, lineage array<int>, note string").parquet(*(f"{self.path}/manifest/version={v}" for v in self.versions()))

    def write(self, rows: DataFrame) -> int:
        """Rows as the next version; it counts once `seal` has written its manifest."""
        fs, path = self._fs()
        top = path(f"{self.path}/state")
        have = [int(x.getPath().getName().split("=")[1]) for x in fs.listStatus(top)] if fs.exists(top) else []
        version = max(have, default=-1) + 1
        names = [f.split()[0] for f in ROW.split(", ")]
        full = rows if "kind" in rows.columns else rows.select(F.lit("s").alias("kind"), *(F.lit(None).cast(t).alias(n) for n, t in (("a", "string"), ("b", "string"), ("part", "double"))), "block", "s", "d", "sigma", "delta")
        full.select(*names).write.option("parquet.block.size", GROUP_BYTES).partitionBy("kind").parquet(f"{self.path}/state/version={version}")
        return version

    def seal(self, version: int, lineage: tuple[int, ...] = (), batch: int | None = None, note: str = "") -> None:
        mark = self.spark.createDataFrame([(version, -1 if batch is None else batch, [*lineage, version], note)], "number int, batch bigint, lineage array<int>, note string")
        mark.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/manifest/version={version}")

    def commit(self, rows: DataFrame, batch: int | None = None) -> int:
        """Writes changed rows (block, s, d, sigma, delta) as the next version. A batch number that was committed is not written again."""
        have = self.versions()
        if batch is not None and have and (done := self.manifest().where(F.col("batch") == batch).first()):
            return done["number"]
        version = self.write(rows)
        self.seal(version, tuple(have), batch)
        return version

    def rows(self, versions: list[int] | tuple[int, ...], *kinds: str) -> DataFrame:
        """All rows of some versions with their version; of some kinds."""
        every = self.spark.read.schema(f"{ROW}, version int").option("basePath", f"{self.path}/state").parquet(*(f"{self.path}/state/version={v}" for v in versions))
        return every.where(F.col("kind").isin(*kinds))

    def read(self, columns: tuple[str, ...] = ("d", "sigma", "delta"), version: int | None = None, lineage: tuple[int, ...] | None = None) -> DataFrame:
        """(block, s, columns) as of a version or of a lineage; only the named columns are scanned."""
        use = list(lineage) if lineage is not None else [v for v in self.versions() if version is None or v <= version]
        every = self.rows(use, "s")
        if len(use) == 1:
            return every.select("block", "s", *columns)
        latest = every.groupBy("s").agg(F.max("version").alias("version"))
        return every.join(latest, ["s", "version"]).select("block", "s", *columns)

    def compact(self, lineage: tuple[int, ...] | None = None) -> int:
        """All rows as one new version, which stands on its own; older ones can be deleted by their owner afterwards."""
        version = self.write(self.read(lineage=lineage))
        self.seal(version)
        return version
