"""Cut points that outlive executors, and ranks without a single-partition sort."""

from __future__ import annotations

import json
import shutil
import tempfile
import uuid
from pathlib import Path
from urllib.parse import urlparse

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window, functions as F


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where none is named, a temporary folder under a local master and a folder of the warehouse elsewhere."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if named is None:
        named = tempfile.mkdtemp(prefix="rangevec-") if sc.master.split("[")[0] == "local" else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints"
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(named)
    return sc.getCheckpointDir()


def settle(df: DataFrame) -> DataFrame:
    """Write to the shared folder and go on from there."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def unsized(df: DataFrame) -> DataFrame:
    """A settled frame without the size guessed from its plan; in loops of joins those guesses grow without bound."""
    spark = df.sparkSession
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(df._jdf.queryExecution().toRdd(), df._jdf.schema(), False), spark)


def ranked(df: DataFrame, order: list[str], name: str = "rank") -> DataFrame:
    """Adds the place, from 0, of each row in the order: one range shuffle, then ranks within partitions shifted by the rows before them.

    The rows are settled in between, since a second sampling may cut the ranges elsewhere. The table of partition sizes is one row per partition.
    """
    cut = settle(df.repartitionByRange(*order).withColumn("_p", F.spark_partition_id()))
    sizes = cut.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.withColumn("_before", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    inside = Window.partitionBy("_p").orderBy(*order)
    return cut.withColumn("_r", F.row_number().over(inside) - 1).join(F.broadcast(before.select("_p", "_before")), "_p").withColumn(name, (F.col("_before") + F.col("_r")).cast("long")).drop("_p", "_r", "_before")


def _local(path: str) -> str | None:
    return urlparse(path).path if urlparse(path).scheme in ("", "file") else None


def store_arrays(folder: str, name: str, arrays: dict[str, np.ndarray]) -> str:
    """Write arrays one behind another into a new file of a shared folder; gives its path. A task that runs twice leaves a file that nothing names."""
    path = f"{folder.rstrip('/')}/{name}-{uuid.uuid4().hex}.arrays"
    at, listed, kept = 0, [], {k: np.ascontiguousarray(a) for k, a in arrays.items()}
    for k, a in kept.items():
        listed.append((k, a.dtype.str, a.shape, at))
        at += -(-a.nbytes // 64) * 64
    head = json.dumps(listed).encode()
    head = len(head).to_bytes(8, "little") + head
    head += bytes(-len(head) % 64)
    if (local := _local(path)) is not None:
        Path(local).parent.mkdir(parents=True, exist_ok=True)
        stream = open(local, "wb")  # noqa: SIM115
    else:
        from pyarrow import fs

        system, inside = fs.FileSystem.from_uri(path)
        system.create_dir(inside.rsplit("/", 1)[0])
        stream = system.open_output_stream(inside)
    with stream as f:
        f.write(head)
        for a in kept.values():
            f.write(a.tobytes())
            f.write(bytes(-a.nbytes % 64))
    return path


def open_arrays(path: str) -> dict[str, np.ndarray]:
    """The arrays of a file, mapped where the folder has a path, so that what isn't touched isn't read; from other stores they are read whole."""
    if (local := _local(path)) is not None:
        raw = np.memmap(local, np.uint8, "r")
    else:
        from pyarrow import fs

        system, inside = fs.FileSystem.from_uri(path)
        with system.open_input_stream(inside) as f:
            raw = np.frombuffer(f.read(), np.uint8)
    n = int.from_bytes(raw[:8].tobytes(), "little")
    base = -(-(8 + n) // 64) * 64
    out = {}
    for k, kind, shape, at in json.loads(raw[8 : 8 + n].tobytes()):
        kind = np.dtype(kind)
        out[k] = raw[base + at : base + at + kind.itemsize * int(np.prod(shape))].view(kind).reshape(shape)
    return out


def copy_file(path: str, folder: str) -> str:
    """Copy a file into a folder under its own name."""
    target = f"{folder.rstrip('/')}/{path.rsplit('/', 1)[1]}"
    if (a := _local(path)) is not None and (b := _local(target)) is not None:
        Path(b).parent.mkdir(parents=True, exist_ok=True)
        own = Path(f"{b}.{uuid.uuid4().hex}")
        shutil.copyfile(a, own)
        own.replace(b)
    else:
        from pyarrow import fs

        fs.copy_files(path, target)
    return target
