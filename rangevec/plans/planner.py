"""Which strategy a range gets: cardinality estimates, the rule, its calibration, and drift."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from ..operators.exact import cardinality
from ..operators.segment import fit, table


def histogram(base: DataFrame, buckets: int = 64, method: str = "exact") -> DataFrame:
    """(seg, lo, hi, n) with the smallest and largest attribute as outer bounds; ``buckets`` rows."""
    rows = base.where("attr is not null")
    ends = rows.agg(F.min("attr").alias("a"), F.max("attr").alias("b")).first()
    h = table(rows, fit(rows, buckets, method))
    return h.select("seg", F.coalesce("lo", F.lit(ends["a"])).cast("double").alias("lo"), F.coalesce("hi", F.lit(ends["b"])).cast("double").alias("hi"), "n")


def estimate(queries: DataFrame, hist: DataFrame) -> DataFrame:
    """(qid, y_est): of each bucket the share that the range covers, as if attributes lay evenly in it; a bucket of one value counts whole."""
    h = F.broadcast(hist.select(F.col("lo").alias("b_lo"), F.col("hi").alias("b_hi"), "n"))
    a, b = F.greatest(F.coalesce("lo", "b_lo"), "b_lo"), F.least(F.coalesce("hi", "b_hi"), "b_hi")
    meets = F.coalesce(F.col("hi") >= F.col("b_lo"), F.lit(True)) & F.coalesce(F.col("lo") <= F.col("b_hi"), F.lit(True))
    share = F.when(F.col("b_hi") > F.col("b_lo"), (b - a) / (F.col("b_hi") - F.col("b_lo"))).otherwise(F.lit(1.0))
    sums = queries.join(h, meets).groupBy("qid").agg(F.sum(F.col("n") * share).alias("y_est"))
    return queries.select("qid").join(sums, "qid", "left").select("qid", F.coalesce("y_est", F.lit(0.0)).alias("y_est"))


def estimate_sample(base: DataFrame, queries: DataFrame, keep: Column, share: float) -> DataFrame:
    """(qid, y_est) from the rows that ``keep`` chooses, a share of all."""
    return cardinality(base.where(keep), queries).select("qid", (F.col("y") / share).alias("y_est"))


def choose(y: Column, n: Column | int, tau_a: float = 0.01, tau_b: float = 0.5) -> Column:
    """``pre`` up to a share tau_a of all objects, ``post`` from tau_b, else ``hybrid``."""
    share = y / (F.lit(n) if isinstance(n, int) else n)
    return F.when(share <= tau_a, "pre").when(share >= tau_b, "post").otherwise("hybrid")


def turning_points(log: DataFrame, recall_target: float, cost: str = "n_dist", buckets: int = 20) -> DataFrame:
    """(tau_a, tau_b) as shares, from a log (qid, share, strategy, recall, <cost>).

    Runs that meet the target count. In each bucket of the share the strategy with the least mean cost wins. tau_a is the upper end of
    the first run of buckets that ``pre`` wins, tau_b the lower end of the last run that ``post`` wins. Without such a run they are 0 and 1.
    """
    good = log.where(F.col("recall") >= recall_target).withColumn("b", F.least(F.floor(F.col("share") * buckets), F.lit(buckets - 1)))
    means = good.groupBy("b", "strategy").agg(F.avg(cost).alias("c"))
    won = means.groupBy("b").agg(F.min_by("strategy", F.struct("c", "strategy")).alias("won"))
    up, down = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, 0), Window.orderBy("b").rowsBetween(0, Window.unboundedFollowing)
    runs = won.select("b", F.min((F.col("won") == "pre").cast("int")).over(up).alias("pre"), F.min((F.col("won") == "post").cast("int")).over(down).alias("post"))
    a = F.coalesce(F.max(F.when(F.col("pre") == 1, (F.col("b") + 1) / buckets)), F.lit(0.0))
    b = F.coalesce(F.min(F.when(F.col("post") == 1, F.col("b") / buckets)), F.lit(1.0))
    return runs.agg(a.alias("tau_a"), F.greatest(a, b).alias("tau_b"))


def calibrate(index, base: DataFrame, queries: DataFrame, recall_target: float = 0.95, cost: str = "n_dist", k: int = 10, ef: int = 100, m: int = 16) -> tuple[DataFrame, DataFrame]:
    """Run the queries, objects of the base with random ranges, under all three strategies; gives the log and the turning points."""
    from ..operators.exact import range_knn_blocks
    from ..operators.metrics import recall
    from ..sources.durable import settle

    n = index.manifest.rows
    truth = settle(range_knn_blocks(base, queries, k))
    y = settle(cardinality(base, queries))
    log = None
    for strategy in ("pre", "post", "hybrid"):
        best, spent = index.work(index.search(queries, strategy, k, ef, m, counters=True), queries, k)
        part = recall(best, truth, y, k).join(spent.drop("strategy"), "qid").select("qid", "y", (F.col("y") / n).alias("share"), F.lit(strategy).alias("strategy"), "recall", "n_dist", "latency_ms")
        log = part if log is None else log.unionByName(part)
    log = settle(log)
    return log, turning_points(log, recall_target, cost)


def drift(old: DataFrame, new: DataFrame) -> DataFrame:
    """(psi, ks) between two histograms over the same segments: population stability index, with half a count for empty ones, and the largest gap of shares."""
    j = old.select("seg", F.col("n").alias("a")).join(new.select("seg", F.col("n").alias("b")), "seg", "full").na.fill(0)
    every = Window.partitionBy(F.lit(0))
    j = j.withColumn("pa", (F.col("a") + 0.5) / (F.sum("a").over(every) + 0.5 * F.count(F.lit(1)).over(every))).withColumn("pb", (F.col("b") + 0.5) / (F.sum("b").over(every) + 0.5 * F.count(F.lit(1)).over(every)))
    run = Window.partitionBy(F.lit(0)).orderBy("seg")
    j = j.withColumn("gap", F.abs(F.sum("a").over(run) / F.sum("a").over(every) - F.sum("b").over(run) / F.sum("b").over(every)))
    return j.agg(F.sum((F.col("pb") - F.col("pa")) * F.log(F.col("pb") / F.col("pa"))).alias("psi"), F.max("gap").alias("ks"))


def drifted(old: DataFrame, new: DataFrame, threshold: float = 0.2) -> bool:
    """Whether the stability index asks for new thresholds."""
    return (drift(old, new).first()["psi"] or 0.0) > threshold


def adapt(index, old: DataFrame, base: DataFrame, threshold: float = 0.2, sample: float = 0.05, **how):
    """The index with new thresholds if the attributes of ``base`` have drifted from the histogram ``old`` beyond ``threshold``, else the index as it is.

    Objects of the updated base, chosen by a hash, become queries with random ranges and are run under all strategies.
    """
    from dataclasses import replace

    from ..functions.columns import uniform
    from ..operators.index import RangeIndex
    from ..operators.segment import bounds_of
    from ..sources.durable import settle
    from ..sources.tables import rank_ranges

    if not drifted(old, table(base.where("attr is not null"), bounds_of(old)), threshold):
        return index
    q = base.where(uniform("vid", "recalibration") < sample).select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"))
    _, points = calibrate(index, base, settle(rank_ranges(base, q, how.get("k", 10), salt="recalibration")), **how)
    p = points.first()
    return RangeIndex(index.spark, replace(index.manifest, tau=(p["tau_a"], p["tau_b"])))


def narrowest(queries: DataFrame, estimates: dict[str, DataFrame]) -> DataFrame:
    """(qid, attribute, y_est): of several attributes the one whose range holds the fewest objects drives the search."""
    out = None
    for name, est in estimates.items():
        part = est.select("qid", F.lit(name).alias("attribute"), "y_est")
        out = part if out is None else out.unionByName(part)
    best = out.groupBy("qid").agg(F.min(F.struct("y_est", "attribute")).alias("m"))
    return queries.select("qid").join(best, "qid").select("qid", "m.attribute", "m.y_est")


# SQL surface.
def register_udtf(spark: SparkSession, index, name: str = "range_ann", ef: int = 100, m: int = 16) -> None:
    """``SELECT ... FROM q, LATERAL range_ann(q.qvec, q.lo, q.hi, q.k)``: workers map the shards' files, so nothing of the index goes out."""
    from pyspark.sql.functions import udtf

    from ..operators.index import _arrays
    from ..operators.kernel import Graph, estimated

    s, params, outer, inner, (tau_a, tau_b) = index.manifest.s, index.params, index.manifest.outer, index.manifest.inner, index.manifest.tau
    paths = {shard: path for shard, path, _ in index.manifest.parts}

    @udtf(returnType="vid long, dist double")
    class RangeAnn:
        def eval(self, qvec, lo: float, hi: float, k: int):
            import numpy as np

            x, found = np.asarray(qvec, np.float64), []
            lo, hi, beam = (-np.inf if lo is None else lo), (np.inf if hi is None else hi), max(ef, k)
            for shard in range(int(np.searchsorted(outer, lo, "right")), int(np.searchsorted(outer, hi, "right")) + 1):
                if shard not in paths:
                    continue
                a = _arrays(paths[shard])
                g, cuts = Graph.of_arrays(a, s, params), inner[shard]
                share = estimated(a["histogram"], np.array([lo]), np.array([hi]))[0] / max(1, g.size)
                segs = range(int(np.searchsorted(cuts, lo, "right")), int(np.searchsorted(cuts, hi, "right")) + 1)
                got = g.pre(x, lo, hi, k) if share <= tau_a else g.post(x, lo, hi, k, beam) if share >= tau_b else g.hybrid(x, lo, hi, k, beam, segs, m)
                found += [(d, int(g.vid[v])) for d, v in got]
            for d, v in sorted(found)[:k]:
                yield v, float(d)

    spark.udtf.register(name, RangeAnn)
