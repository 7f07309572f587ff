"""Attribute segments of about equal size."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Row, functions as F

from ..functions.columns import uniform
from ..sources.durable import ranked, settle


def fit(base: DataFrame, s: int, method: str = "exact", sample: float = 0.1, seed: int = 0) -> list[float]:
    """Inner boundaries, at most s - 1, rising: segment j holds attributes from boundary j - 1 on and below boundary j; the outer ones are open.

    ``exact`` ranks all objects, ``sample`` a share of them chosen by a hash of the id, ``sketch`` uses approximate percentiles. Equal
    attributes fall together, so ties give fewer segments. The result is s - 1 numbers.
    """
    rows = base.where(F.col("attr").isNotNull() & ~F.isnan(F.col("attr").cast("double"))).select("vid", F.col("attr").cast("double").alias("attr"))
    if method == "sketch":
        found = rows.agg(F.percentile_approx("attr", [j / s for j in range(1, s)], 10_000)).first()[0] if s > 1 else []
        return sorted(set(found or []))
    if method == "sample":
        rows = rows.where(uniform("vid", f"sample:{seed}") < sample)
    elif method != "exact":
        raise ValueError(f"no method {method}")
    have = ranked(rows, ["attr", "vid"], "rank")
    n = have.count()
    if not n:
        return []
    starts = {-(-j * n // s) for j in range(1, s)} - {0}
    first = have.agg(F.min("attr")).first()[0]
    found = {r["attr"] for r in have.where(F.col("rank").isin([int(x) for x in starts if x < n])).select("attr").collect()}
    return sorted(found - {first})


def fit_nested(base: DataFrame, shards: int, s: int, method: str = "exact") -> tuple[list[float], list[list[float]]]:
    """Boundaries of ``shards`` shards, and of ``s`` segments in each: ``fit`` for all of them in the same few passes, however many there are."""
    rows = base.where(F.col("attr").isNotNull() & ~F.isnan(F.col("attr").cast("double"))).select("vid", F.col("attr").cast("double").alias("attr"))
    if method == "sketch":
        outer = fit(base, shards, method)
        cut = F.percentile_approx("attr", [j / s for j in range(1, s)], 10_000) if s > 1 else F.array().cast("array<double>")
        got = {r["shard"]: r["cut"] for r in rows.groupBy(segment_of(F.col("attr"), outer).alias("shard")).agg(cut.alias("cut")).collect()}
        return outer, [sorted(set(got.get(i) or [])) for i in range(len(outer) + 1)]
    if method == "sample":
        rows = rows.where(uniform("vid", "sample:0") < 0.1)
    elif method != "exact":
        raise ValueError(f"no method {method}")
    have = settle(ranked(rows, ["attr", "vid"], "rank").select("rank", "attr"))
    n = have.count()
    if not n:
        return [], [[]]

    def at(ranks: set[int]) -> dict[int, float]:
        # One row for each boundary.
        wanted = have.sparkSession.createDataFrame([(int(r),) for r in sorted(ranks)], "rank long")
        return {r["rank"]: r["attr"] for r in have.join(F.broadcast(wanted), "rank").collect()}

    found = at({-(-j * n // shards) for j in range(shards) if -(-j * n // shards) < n})
    outer = sorted(set(found.values()) - {found[0]})
    # Equal attributes fall together: a shard begins at the first of its boundary's rank.
    edges = have.sparkSession.createDataFrame([(b,) for b in outer], "attr double")
    first = {r["attr"]: r["rank"] for r in have.join(F.broadcast(edges), "attr").groupBy("attr").agg(F.min("rank").alias("rank")).collect()}
    starts = [0, *(first[b] for b in outer)]
    ends = [*starts[1:], n]
    picks = [[a + -(-j * (b - a) // s) for j in range(s) if a + -(-j * (b - a) // s) < b] for a, b in zip(starts, ends, strict=True)]
    value = at({r for p in picks for r in p})
    return outer, [sorted({value[r] for r in p} - {value[p[0]]}) for p in picks]


def segment_of(attr: Column, bounds: list[float]) -> Column:
    """Segment number, from 0; -1 without an attribute."""
    if not bounds:
        return F.when(attr.isNull() | F.isnan(attr.cast("double")), -1).otherwise(0)
    passed = F.size(F.filter(F.array(*[F.lit(float(b)) for b in bounds]), lambda b: b <= attr.cast("double")))
    return F.when(attr.isNull() | F.isnan(attr.cast("double")), -1).otherwise(passed).cast("int")


def table(base: DataFrame, bounds: list[float]) -> DataFrame:
    """(seg, lo, hi, n) with open outer bounds as nulls."""
    edges = [None, *bounds, None]
    spark = base.sparkSession
    empty = spark.createDataFrame([Row(seg=j, lo=a, hi=b) for j, (a, b) in enumerate(zip(edges, edges[1:], strict=False))], "seg int, lo double, hi double")
    counts = base.select(segment_of(F.col("attr"), bounds).alias("seg")).groupBy("seg").agg(F.count(F.lit(1)).alias("n"))
    return empty.join(counts, "seg", "left").select("seg", "lo", "hi", F.coalesce("n", F.lit(0)).alias("n"))


def bounds_of(segments: DataFrame) -> list[float]:
    return [r["lo"] for r in segments.where("lo is not null").orderBy("seg").collect()]


def assign(base: DataFrame, segments: DataFrame | list[float]) -> DataFrame:
    bounds = segments if isinstance(segments, list) else bounds_of(segments)
    return base.withColumn("seg", segment_of(F.col("attr"), bounds))


def intersecting(queries: DataFrame, segments: DataFrame) -> DataFrame:
    """(qid, seg, covered): segments that a range meets, and whether it covers them. Segments are few and fixed by the index."""
    s = F.broadcast(segments.select("seg", F.col("lo").alias("s_lo"), F.col("hi").alias("s_hi")))
    meets = F.coalesce(F.col("hi") >= F.col("s_lo"), F.lit(True)) & F.coalesce(F.col("lo") < F.col("s_hi"), F.lit(True))
    left = F.col("lo").isNull() | F.coalesce(F.col("lo") <= F.col("s_lo"), F.lit(False))
    right = F.col("hi").isNull() | F.coalesce(F.col("hi") >= F.col("s_hi"), F.lit(False))
    return queries.join(s, meets).select("qid", "seg", (left & right).alias("covered"))
