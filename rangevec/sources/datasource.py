"""``spark.read.format("rangevec")``: the vectors of a stored index, one partition per shard, with attribute bounds pushed down."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from .durable import open_arrays

SCHEMA = "vid long, vec array<double>, attr double, seg int, shard int"


class ShardPartition(InputPartition):
    def __init__(self, shard: int, path: str):
        super().__init__((shard, path))


class IndexReader(DataSourceReader):
    """Reads the shards that meet [lo, hi]."""

    def __init__(self, path: str, lo: float = float("-inf"), hi: float = float("inf")):
        self.path, self.lo, self.hi = path, lo, hi

    def partitions(self) -> list[ShardPartition]:
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(self.path if "://" in self.path or self.path.startswith("file:") else f"file://{self.path}")
        text = next(x.path for x in system.get_file_info(fs.FileSelector(f"{root}/manifest")) if x.base_name.startswith("part-") and x.size)
        with system.open_input_stream(text) as f:
            manifest = json.loads(f.read())
        ends = [float("-inf"), *manifest["outer"], float("inf")]
        files = {shard: path for shard, path, _ in manifest["parts"]}
        return [ShardPartition(i, files[i]) for i, (a, b) in enumerate(zip(ends, ends[1:], strict=False)) if a <= self.hi and self.lo < b and i in files]

    def read(self, partition: ShardPartition) -> Iterator[tuple]:
        import numpy as np

        shard, path = partition.value
        a = open_arrays(path)
        for i in np.flatnonzero((a["attr"] >= self.lo) & (a["attr"] <= self.hi)):
            yield int(a["vid"][i]), a["x"][i].tolist(), float(a["attr"][i]), int(a["seg"][i]), shard


class PushedReader(IndexReader):
    """The same, with bounds taken from the query's filters."""

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Bounds of attr choose shards and rows; every filter is applied again by Spark."""
        for f in filters:
            if getattr(f, "attribute", None) == ("attr",) and isinstance(getattr(f, "value", None), (int, float)):
                if isinstance(f, (GreaterThan, GreaterThanOrEqual, EqualTo)):
                    self.lo = max(self.lo, float(f.value))
                if isinstance(f, (LessThan, LessThanOrEqual, EqualTo)):
                    self.hi = min(self.hi, float(f.value))
            yield f


class IndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "rangevec"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> IndexReader:
        kind = PushedReader if self.options.get("pushdown", "false") == "true" else IndexReader
        return kind(self.options["path"], float(self.options.get("lo", "-inf")), float(self.options.get("hi", "inf")))


def load(spark: SparkSession, path: str, lo: float = float("-inf"), hi: float = float("inf")):
    """The vectors of an index with attributes in [lo, hi]. Spark refuses readers that take filters unless the session allows them."""
    spark.dataSource.register(IndexSource)
    allowed = spark.conf.get("spark.sql.python.filterPushdown.enabled", "false")
    df = spark.read.format("rangevec").option("path", path).option("pushdown", allowed).option("lo", str(lo)).option("hi", str(hi)).load()
    return df.where(df.attr.between(lo, hi))
