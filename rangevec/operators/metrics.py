"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F


def recall(found: DataFrame, truth: DataFrame, y: DataFrame, k: int | None = None) -> DataFrame:
    """(qid, y, recall): of the min(k, y) nearest objects the share found; 1 for an empty range. ``y`` is (qid, y), and holds k unless given."""
    size = F.least(F.col("y"), F.lit(k) if k is not None else F.col("k"))
    hits = found.select("qid", "vid").join(truth.select("qid", "vid"), ["qid", "vid"], "left_semi").groupBy("qid").agg(F.count(F.lit(1)).alias("hits"))
    return y.join(hits, "qid", "left").select("qid", "y", F.when(size > 0, F.coalesce("hits", F.lit(0)) / size).otherwise(F.lit(1.0)).alias("recall"))


def summary(recalls: DataFrame, by: list[str] = ()) -> DataFrame:
    """Mean recall with and without empty ranges, and how many those are."""
    return recalls.groupBy(*by).agg(F.avg("recall").alias("recall"), F.avg(F.when(F.col("y") > 0, F.col("recall"))).alias("recall_nonempty"), F.sum((F.col("y") == 0).cast("long")).alias("n_empty"), F.count(F.lit(1)).alias("queries"))


def best_at(sweep: DataFrame, target: float, by: list[str], rate: str = "qps") -> DataFrame:
    """The best rate of any setting that reaches a recall; null where none does."""
    return sweep.groupBy(*by).agg(F.max(F.when(F.col("recall") >= target, F.col(rate))).alias("best"))


def frontier(sweep: DataFrame, by: list[str], rate: str = "qps") -> DataFrame:
    """Settings that no other beats in both recall and rate."""
    w = Window.partitionBy(*by).orderBy(F.col("recall").desc(), F.col(rate).desc()).rowsBetween(Window.unboundedPreceding, -1)
    return sweep.withColumn("_best", F.max(rate).over(w)).where(F.col("_best").isNull() | (F.col(rate) > F.col("_best"))).drop("_best")


def mean_levels(m: int) -> float:
    """Expected layers of a node under the decay rule."""
    return 1 / (1 - 1 / m)


def space_units(n: Column | float, s: Column | int, m: Column | int, levels: Column | float | None = None) -> Column | float:
    """32-bit units of the graph: n nodes on so many layers, each with m * s edges, as many mask bits and one successor."""
    return n * ((mean_levels(m) if levels is None else levels) * (33 / 32 * m * s + 1))


def many_graph_penalty(s: Column, n: Column) -> Column:
    """Cost of searching s graphs of n / s objects over that of one graph of n."""
    return s * (1 - F.log(s) / F.log(n))


def combinations_of(s: Column, contiguous: bool = False) -> Column:
    return s * (s + 1) / 2 if contiguous else F.pow(F.lit(2.0), s) - 1


def build_model(segments: DataFrame, s: int) -> DataFrame:
    """(searches, bound) of a build over segments (n): each of all objects searches the graphs of all ``s`` segments, the sum of log n_j, at most s log n, for each object."""
    ln = F.when(F.col("n") > 1, F.log("n")).otherwise(F.lit(0.0))
    total = segments.agg(F.sum("n").alias("n"), F.sum(ln).alias("one"))
    return total.select("n", (F.col("n") * F.col("one")).alias("searches"), (F.col("n") * s * F.log("n")).alias("bound"))


def search_model(queries: DataFrame, n: int, tau_a: float = 0.01, tau_b: float = 0.5) -> DataFrame:
    """(qid, strategy, cost) of queries (qid, y, hit), ``hit`` objects being in the segments that a range meets: y + log n before, log n after, log of the hit ones during the search."""
    from ..plans.planner import choose

    how = choose(F.col("y"), n, tau_a, tau_b)
    ln = F.log(F.lit(float(n)))
    return queries.select("qid", how.alias("strategy"), F.when(how == "pre", F.col("y") + ln).when(how == "post", ln).otherwise(F.log(F.greatest("hit", F.lit(2)).cast("double"))).alias("cost"))


def log_slope(df: DataFrame, size: str, cost: str) -> DataFrame:
    """Slope and fit of a cost against the logarithm of a size."""
    return df.agg(F.regr_slope(cost, F.log(size)).alias("slope"), F.regr_r2(cost, F.log(size)).alias("r2"))
