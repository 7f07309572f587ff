"""Hybrid search of many queries at once as joins: for batches too large, or graphs too large, for one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.columns import in_range, l2
from ..sources.durable import settle, unsized
from .exact import top
from .segment import intersecting


def frontier_search(base: DataFrame, edges: DataFrame, queries: DataFrame, segments: DataFrame, ef: int = 50, m: int = 16, starts: int = 4, width: int = 4) -> DataFrame:
    """(qid, rnk, vid, dist). Each hop expands, for every query, its ``width`` nearest nodes not yet expanded that are within its ef best; chunks of the
    range's segments are looked at, the first ceil(m / segments) of each. It ends when no query has such a node, which each hop brings nearer, since none is expanded twice. State is at most ef results, ef routing nodes and the
    visited ids of each query.
    """
    hit = intersecting(queries, segments).select("qid", "seg")
    share = hit.groupBy("qid").agg(F.ceil(F.lit(m) / F.count(F.lit(1))).alias("share"))
    q = settle(queries.select("qid", "qvec", "lo", "hi", "k"))
    vec = base.select("vid", "vec", "attr", "seg")
    first = top(hit.join(vec.select("vid", "seg"), "seg").withColumn("h", F.xxhash64("vid")), ["qid"], F.lit(starts), ["h", "vid"])

    def measured(pairs: DataFrame) -> DataFrame:
        near = pairs.join(q, "qid").join(vec, "vid")
        return near.select("qid", "vid", l2("vec", "qvec").alias("dist"), in_range("attr", "lo", "hi").alias("ok"), F.lit(False).alias("done"))

    state = unsized(settle(measured(first.select("qid", "vid"))))
    while True:
        rank = Window.partitionBy("qid", "ok").orderBy("dist", "vid")
        beam = state.withColumn("_r", F.row_number().over(rank))
        worst = beam.where(F.col("ok") & (F.col("_r") == ef)).select("qid", F.col("dist").alias("worst"))
        open_ = beam.join(worst, "qid", "left").where(~F.col("done") & (F.coalesce(F.col("dist") <= F.col("worst"), F.lit(True))))
        now = unsized(settle(top(open_.select("qid", "vid", "dist"), ["qid"], F.lit(width)).select("qid", "vid")))
        if now.isEmpty():
            break
        look = now.withColumnRenamed("vid", "src").join(edges.select("src", "chunk", "dst", "rnk"), "src").join(hit.withColumnRenamed("seg", "chunk"), ["qid", "chunk"]).join(share, "qid").where(F.col("rnk") <= F.col("share"))
        new = look.select("qid", F.col("dst").alias("vid")).distinct().join(state.select("qid", "vid"), ["qid", "vid"], "left_anti")
        kept = state.join(now.withColumn("_now", F.lit(True)), ["qid", "vid"], "left").select("qid", "vid", "dist", "ok", (F.col("done") | F.coalesce("_now", F.lit(False))).alias("done"))
        state = unsized(settle(kept.unionByName(measured(new))))
    return top(state.where("ok").join(q.select("qid", "k"), "qid"), ["qid"], F.col("k")).select("qid", "rnk", "vid", "dist")
