"""Streams of new objects and of attributes."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.index import RangeIndex
from ..operators.segment import segment_of


class IndexWriter:
    """Adds the batches of a stream to a stored index. Each batch writes the shards that it touches, as new files, and a manifest ``<root>/v<batch>`` that names these and the
    untouched ones; a batch that runs again after a failure finds its version and does nothing."""

    def __init__(self, root: str):
        self.root = root.rstrip("/")

    def _fs(self, spark: SparkSession, path: str):
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p

    def start(self, index: RangeIndex) -> None:
        index.save(f"{self.root}/v-1")

    def versions(self, spark: SparkSession) -> list[int]:
        """Versions whose manifest is written, which comes last."""
        fs, p = self._fs(spark, self.root)
        names = [x.getPath().getName() for x in fs.listStatus(p)]
        return sorted(int(n[1:]) for n in names if n.startswith("v") and fs.exists(self._fs(spark, f"{self.root}/{n}/manifest/_SUCCESS")[1]))

    def current(self, spark: SparkSession) -> RangeIndex:
        return RangeIndex.load(spark, f"{self.root}/v{self.versions(spark)[-1]}")

    def __call__(self, batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        if number in self.versions(spark):
            return
        fs, p = self._fs(spark, f"{self.root}/v{number}")
        fs.delete(p, True)
        base = RangeIndex.load(spark, f"{self.root}/v{[v for v in self.versions(spark) if v < number][-1]}")
        base.append(batch, folder=f"{self.root}/shards").commit(f"{self.root}/v{number}")


def ingest(stream: DataFrame, writer: IndexWriter, checkpoint: str) -> StreamingQuery:
    """Insert a stream (vid, vec, attr); takes what is there and ends."""
    return stream.writeStream.foreachBatch(writer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_counts(stream: DataFrame, bounds: list[float], late: str = "1 hour", window: str = "1 day") -> DataFrame:
    """(window, seg, n) of a stream (ts, attr): what a drift check compares with the index's histogram."""
    seg = segment_of(F.col("attr"), bounds)
    return stream.withWatermark("ts", late).groupBy(F.window("ts", window), seg.alias("seg")).agg(F.count(F.lit(1)).alias("n"))


def drift_monitor(stream: DataFrame, reference: list[int], bounds: list[float], threshold: float) -> DataFrame:
    """(key, seen, psi, drifted): counts per segment are kept as state; each batch gives the stability index of all seen so far against ``reference``.

    Tasks count their own rows first, so that one row of counts for each of them meets the state.
    """
    import numpy as np
    import pandas as pd

    n = len(reference)

    def count(batches):
        total = np.zeros(n, np.int64)
        for pdf in batches:
            total += np.bincount(pdf.seg[pdf.seg >= 0], minlength=n)[:n]
        yield pd.DataFrame({"key": [0], "counts": [total.tolist()]})

    def update(key, parts, state):
        counts = np.array(json.loads(state.get[0])) if state.exists else np.zeros(n)
        for pdf in parts:
            counts = counts + np.stack(pdf.counts.to_numpy()).sum(axis=0)
        state.update((json.dumps(counts.tolist()),))
        a, b = np.array(reference) + 0.5, counts + 0.5
        a, b = a / a.sum(), b / b.sum()
        psi = float(((b - a) * np.log(b / a)).sum())
        yield pd.DataFrame({"key": [key[0]], "seen": [int(counts.sum())], "psi": [psi], "drifted": [psi > threshold]})

    rows = stream.select(segment_of(F.col("attr"), bounds).alias("seg")).mapInPandas(count, "key int, counts array<long>")
    return rows.groupBy("key").applyInPandasWithState(update, "key int, seen long, psi double, drifted boolean", "counts string", "update", "NoTimeout")


def late_counts(stream: DataFrame, late: str, window: str, folder: str, checkpoint: str) -> StreamingQuery:
    """Counts by window of a stream (ts); rows whose window has ended before the watermark are dropped. Each batch writes the windows that it changed to ``folder``."""
    counts = stream.withWatermark("ts", late).groupBy(F.window("ts", window)).agg(F.count(F.lit(1)).alias("n"))

    def write(batch: DataFrame, number: int) -> None:
        batch.select(F.col("window.start").alias("start"), "n").write.mode("overwrite").parquet(f"{folder}/batch={number}")

    return counts.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def folder_result(df: DataFrame, root: str) -> DataFrame:
    """Run a bounded stream of appended rows to its end into files under ``root``, for results of any size: no row passes the driver, and state lies in RocksDB beside the heap."""
    spark, key = df.sparkSession, "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        q = df.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start()
    finally:
        spark.conf.set(key, before)
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{root}/out")


def memory_result(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a bounded stream to its end into memory, for small results."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)
