"""Size-tiered shard storage with versioned manifests. DataFrame functions only on the executors."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from .shared import shared_folder


class ManifestConflict(RuntimeError):
    """Another writer has committed this version."""


class ShardStore:
    """Immutable Parquet shards under one folder and the manifest that names the current ones.

    A manifest ``_manifest/v<n>.json`` is written under another name and renamed, which fails if the version exists; readers see one
    version or the next. Shards that no manifest names are leftovers of failed tasks and writers and don't count.
    """

    def __init__(self, spark: SparkSession, root: str, arrival_bytes: int = 1 << 20, target_bytes: int = 16 << 20, fan: int = 4, most_runs: int = 256):
        self.spark, self.root, self.arrival, self.target, self.fan, self.most_runs = spark, root.rstrip("/"), arrival_bytes, target_bytes, fan, most_runs
        self.jvm = spark.sparkContext._jvm.org.apache.hadoop.fs

    def _fs(self, path: str):
        p = self.jvm.Path(path)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), p

    def version(self) -> int:
        fs, p = self._fs(f"{self.root}/_manifest")
        return max([0, *(int(x.getPath().getName()[1:-5]) for x in fs.listStatus(p) if x.getPath().getName().startswith("v"))]) if fs.exists(p) else 0

    def shards(self, version: int | None = None) -> list[dict]:
        """Path, rows, bytes and tier of each shard of a version, in the order they were added."""
        n = self.version() if version is None else version
        return json.loads(self.spark.read.text(f"{self.root}/_manifest/v{n}.json", wholetext=True).first()[0])["shards"] if n else []

    def commit(self, base: int, shards: list[dict]) -> int:
        fs, tmp = self._fs(f"{self.root}/_manifest/.{uuid.uuid4().hex}")
        out = fs.create(tmp, False)
        out.write(bytearray(json.dumps({"version": base + 1, "shards": shards}).encode()))
        out.close()
        final = self.jvm.Path(f"{self.root}/_manifest/v{base + 1}.json")
        if fs.exists(final) or not fs.rename(tmp, final):
            fs.delete(tmp, False)
            raise ManifestConflict(f"version {base + 1} exists")
        return base + 1

    def tier(self, size: int) -> int:
        """0 for the smallest shards, one more for each factor of ``fan``."""
        n = 0
        while size >= self.arrival * self.fan ** (n + 1):
            n += 1
        return n

    def _written(self, folder: str) -> list[dict]:
        fs, p = self._fs(folder)
        if not fs.exists(p):
            return []
        df = self.spark.read.option("recursiveFileLookup", "true").parquet(folder) if any(x.isDirectory() or x.getPath().getName().endswith(".parquet") for x in fs.listStatus(p)) else None
        if df is None:
            return []
        rows = df.groupBy(F.col("_metadata.file_path").alias("path"), F.col("_metadata.file_size").alias("bytes")).agg(F.count(F.lit(1)).alias("rows")).orderBy("path").collect()
        return [{"path": r["path"], "rows": r["rows"], "bytes": r["bytes"], "tier": self.tier(r["bytes"])} for r in rows]

    def append(self, df: DataFrame, row_bytes: int) -> int:
        """Add rows as small shards, without a shuffle; ``row_bytes`` is about what a row takes on disk. Gives the new version."""
        folder = f"{self.root}/data/a-{uuid.uuid4().hex}"
        df.write.option("compression", "zstd").option("maxRecordsPerFile", max(1, self.arrival // max(1, row_bytes))).parquet(folder)
        base = self.version()
        return self.commit(base, self.shards(base) + self._written(folder))

    def plan(self) -> DataFrame:
        """(path, run): neighbouring shards of one tier that are below the target, gathered up to the target; runs of at least ``fan`` shards or of target size."""
        listed = [(i, s["path"], s["bytes"], s["tier"]) for i, s in enumerate(self.shards()) if s["bytes"] < self.target // 2]
        rows = self.spark.createDataFrame(listed, "seq long, path string, bytes long, tier int")
        order = Window.partitionBy("tier").orderBy("seq")
        rows = rows.withColumn("part", F.floor((F.sum("bytes").over(order) - F.col("bytes")) / self.target))
        run = Window.partitionBy("tier", "part")
        rows = rows.withColumn("n", F.count(F.lit(1)).over(run)).where(F.col("n") >= self.fan)
        return rows.select("path", F.concat_ws("-", "tier", "part").alias("run"))

    def _keys(self, n: int) -> list[int]:
        """``n`` numbers that a shuffle into ``n`` partitions sends to different ones."""
        place = F.pmod(F.hash("id"), F.lit(n))
        return [r["k"] for r in self.spark.range(64 * n).groupBy(place.alias("p")).agg(F.min("id").alias("k")).collect()]

    def compact_once(self) -> bool:
        """Merge at most ``most_runs`` runs, each a task of its own, and commit; False if there is nothing to merge."""
        base, plan = self.version(), self.plan().orderBy("run", "path").collect()
        chosen = sorted({r["run"] for r in plan})[: self.most_runs]
        moved = [(r["path"], r["run"]) for r in plan if r["run"] in set(chosen)]
        if not moved:
            return False
        old = self.shards(base)
        folder = f"{self.root}/data/m-{uuid.uuid4().hex}"
        # One commit's runs are bounded, and with them this list.
        keys = self._keys(len(chosen))
        key = {run: keys[i % len(keys)] for i, run in enumerate(chosen)}
        runs = self.spark.createDataFrame([(p, r, key[r]) for p, r in moved], "path string, run string, key long")
        df = self.spark.read.parquet(*[p for p, _ in moved])
        merged = df.select(F.struct(*df.columns).alias("row"), F.col("_metadata.file_path").alias("path")).join(F.broadcast(runs), "path")
        merged.repartition(len(chosen), "key").select("row.*", F.col("run").alias("_run")).write.option("compression", "zstd").partitionBy("_run").parquet(folder)
        gone = {p for p, _ in moved}
        self.commit(base, [s for s in old if s["path"] not in gone] + self._written(folder))
        return True

    def compact(self) -> int:
        while self.compact_once():
            pass
        return self.version()

    def vacuum(self) -> int:
        """Delete shards that earlier versions name and the current one doesn't; gives their number."""
        now, gone = {s["path"] for s in self.shards()}, set()
        for n in range(1, self.version()):
            gone |= {s["path"] for s in self.shards(n)} - now
        for path in gone:
            fs, p = self._fs(path)
            fs.delete(p, False)
        return len(gone)

    def read(self, version: int | None = None) -> DataFrame | None:
        """All rows of a version with the column ``_metadata`` of their files; None if it has no shard."""
        paths = [s["path"] for s in self.shards(version)]
        return self.spark.read.parquet(*paths) if paths else None


def shard(docs: DataFrame, id_col: str = "doc_id", root: str | None = None, text_col: str = "text", **how) -> DataFrame:
    """Store all rows, with all their columns, compact them, and give one row per document: id, ``shard_id``, ``shard_rows``, ``shard_bytes``, ``tier``, ``n_bytes``, ``version``.

    ``shard_id`` is the shard's place in the manifest, ``n_bytes`` the length of the text read back (null: 0). Rows that repeat an id are stored as
    they are. Columns named ``_run`` or ``_metadata`` are refused. An empty table gives an empty result.
    """
    spark = docs.sparkSession
    if clash := {c.lower() for c in docs.columns} & {"_run", "_metadata"}:
        raise ValueError(f"columns {clash} clash with the store's")
    store = ShardStore(spark, root or f"{shared_folder(spark)}/shards-{uuid.uuid4().hex}", **how)
    width = docs.agg(F.coalesce(F.avg(F.octet_length(F.col(text_col))), F.lit(0)).cast("long")).first()[0] + 32
    store.append(docs, width // 2)
    store.compact()
    store.vacuum()
    listed = [(i, s["path"], s["rows"], s["bytes"], s["tier"], store.version()) for i, s in enumerate(store.shards())]
    df = store.read()
    if df is None:
        return docs.select(F.col(id_col).cast("long").alias(id_col), *[F.lit(0).cast("long").alias(c) for c in ("shard_id", "shard_rows", "shard_bytes")], F.lit(0).alias("tier"), F.lit(0).cast("long").alias("n_bytes"), F.lit(0).alias("version")).limit(0)
    shards = spark.createDataFrame(listed, "shard_id long, path string, shard_rows long, shard_bytes long, tier int, version int")
    rows = df.select(F.col(id_col).cast("long").alias(id_col), F.coalesce(F.octet_length(F.col(text_col)), F.lit(0)).cast("long").alias("n_bytes"), F.col("_metadata.file_path").alias("path"))
    return rows.join(shards, "path").select(id_col, "shard_id", "shard_rows", "shard_bytes", "tier", "n_bytes", "version")
