"""Joins on the nearest earlier value."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from .segment import fit, segment_of


def asof(left: DataFrame, right: DataFrame, on: str, take: str, key: str, segments: int = 64) -> DataFrame:
    """``left`` with ``take`` of the right row with the largest ``on`` that isn't above its own; null without one. Of equal right rows the one with the largest ``key`` counts.

    Both sides are cut into segments of the right side, ordered within each, and what a segment lacks at its start comes from the segments before
    it, one row each. So no task sorts everything.
    """
    bounds = fit(right.select(F.col(key).alias("vid"), F.col(on).alias("attr")), segments)
    seg = segment_of(F.col(on), bounds).alias("_seg")
    r = right.select(seg, F.col(on).alias("_v"), F.lit(0).alias("_kind"), F.col(key).cast("string").alias("_key"), F.col(take).alias("_take"), F.lit(None).cast(left.select(F.struct("*")).schema[0].dataType).alias("_row"))
    a = left.select(seg, F.col(on).alias("_v"), F.lit(1).alias("_kind"), F.lit(None).cast("string").alias("_key"), F.lit(None).cast(right.schema[take].dataType).alias("_take"), F.struct(*left.columns).alias("_row"))
    inside = Window.partitionBy("_seg").orderBy("_v", "_kind", "_key").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = r.unionByName(a).withColumn("_last", F.last("_take", True).over(inside)).where("_kind = 1")
    ends = r.where("_v IS NOT NULL").groupBy("_seg").agg(F.max(F.struct("_v", "_key", "_take")).getField("_take").alias("_end"))
    all_segs = left.sparkSession.range(len(bounds) + 1).select(F.col("id").cast("int").alias("_seg"))
    before = Window.orderBy("_seg").rowsBetween(Window.unboundedPreceding, -1)
    carried = all_segs.join(ends, "_seg", "left").withColumn("_before", F.last("_end", True).over(before)).select("_seg", "_before")
    return found.join(F.broadcast(carried), "_seg", "left").select("_row.*", F.coalesce("_last", "_before").alias(take))
