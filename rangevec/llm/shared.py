"""What several operators need: durable cut points, skew-proof joins, and Arrow text kernels."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

#: A key with more than one part in so many of all rows is joined by broadcast; there are at most so many such keys.
HOT_PARTS = 1024
HOT_LEAST = 64
SLICE_BYTES = 4 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where the session names none (tests), a local master gets a temporary folder and any other master a folder of the warehouse.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        if spark.sparkContext.getCheckpointDir() is None:
            spark.sparkContext.setCheckpointDir(named)
        return named
    if (known := spark.sparkContext.getCheckpointDir()) is None:
        local = spark.sparkContext.master.split("[")[0] == "local"
        folder = tempfile.mkdtemp(prefix="rangevec-") if local else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints"
        spark.sparkContext.setCheckpointDir(folder)
        known = spark.sparkContext.getCheckpointDir()
    return known


def settle(df: DataFrame) -> DataFrame:
    """Write a frame of narrow rows to the shared folder and go on from there; a lost executor doesn't lose it."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def tidy(spark: SparkSession, rounds: int = 1) -> None:
    """Let the driver find what nothing refers to any more: only then do shuffle and checkpoint files of earlier steps go.

    What a step's frames held is found in the second round, after a pause.
    """
    for i in range(rounds):
        if i:
            time.sleep(0.5)
        gc.collect()
        spark.sparkContext._jvm.System.gc()


def unsized(df: DataFrame) -> DataFrame:
    """A settled frame without the size that Spark guesses from the plan it came from: in a loop of joins those guesses are multiplied at each turn until the planner is lost in long numbers."""
    spark = df.sparkSession
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(df._jdf.queryExecution().toRdd(), df._jdf.schema(), False), spark)


def unclear(docs: DataFrame, id_col: str) -> bool:
    """Whether some id is missing or on several rows, so that ids alone don't name the rows."""
    ids = docs.groupBy(F.col(id_col).cast("long").alias("_id")).agg(F.count(F.lit(1)).alias("_n"))
    return not ids.where("_id IS NULL OR _n > 1").isEmpty()


def null_safe(left: str, right: str, keys: list[str]) -> Column:
    """The condition that two aliased frames have equal keys; null equals null."""
    same = F.lit(True)
    for c in keys:
        same = same & F.col(f"{left}.{c}").eqNullSafe(F.col(f"{right}.{c}"))
    return same


def join_hot(facts: DataFrame, groups: DataFrame, keys: list[str], size: str) -> DataFrame:
    """Inner join of many rows with one row per key, where one key may hold any share of the rows.

    ``groups[size]`` is the number of fact rows of the key. Keys above 1/HOT_PARTS of all rows are at most
    HOT_PARTS in number, so their group rows are broadcast; the others shuffle, none of them large.
    Both inputs are read twice: settle them first. Null keys match nothing.
    """
    total = groups.agg(F.sum(size)).first()[0] or 0
    limit = max(total // HOT_PARTS, HOT_LEAST)
    hot, cold = groups.where(F.col(size) > limit), groups.where(F.col(size) <= limit)
    few = facts.join(F.broadcast(hot), keys)
    many = facts.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(cold, keys)
    return few.unionByName(many)


def release() -> None:
    """Give freed memory back to the system: a worker waits for its next task with what its last one left."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def slices(batches: Iterator[pa.RecordBatch], column: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``most`` bytes of text; one longer text is a batch of its own."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        ends, start = np.cumsum(sizes), 0
        while start < len(sizes):
            base = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, base + most, "right")))
            yield batch.slice(start, stop - start)
            start = stop
        del batch
    release()


class Words:
    """Words ``[^\\x20\\x09-\\x0D]+`` of some texts: ``vocab[codes[offsets[i]:offsets[i + 1]]]`` are those of text i. Null counts as empty."""

    def __init__(self, texts: pa.Array, lower: bool = True):
        texts = pc.fill_null(texts, "")
        if lower:
            texts = pc.ascii_lower(texts)
        if isinstance(texts, pa.ChunkedArray):
            texts = texts.combine_chunks()
        lists = pc.ascii_split_whitespace(pc.ascii_trim_whitespace(texts))
        flat = lists.flatten()
        full = pc.binary_length(flat).to_numpy(zero_copy_only=False) > 0
        ends = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)
        self.offsets = np.concatenate([[0], np.cumsum(full)]).astype(np.int64)[ends]
        coded = flat.filter(pa.array(full)).dictionary_encode()
        self.codes = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
        self.vocab: list[str] = coded.dictionary.to_pylist()


def hashes(words: list[str]) -> np.ndarray:
    """Stable 64-bit hashes."""
    from xxhash import xxh3_64_intdigest as h

    return np.fromiter((h(w.encode("utf-8", "surrogatepass")) for w in words), np.uint64, len(words))


def by_row(values: np.ndarray, offsets: np.ndarray, reduce=np.add) -> np.ndarray:
    """Reduce each row's values; a row without any gives zero."""
    out = np.zeros((len(offsets) - 1, *values.shape[1:]), values.dtype)
    full = offsets[1:] > offsets[:-1]
    if full.any():
        out[full] = reduce.reduceat(values, offsets[:-1][full], axis=0)
    return out
