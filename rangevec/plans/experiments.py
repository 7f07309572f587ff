"""Experiments as grids: a task for each configuration and shard; tables and queries lie in the shared folder as arrays, so nothing passes the driver."""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions.columns import level
from ..operators.competitors import METHODS, Degraded, Shard, common_edges
from ..operators.kernel import Params
from ..operators.segment import fit, segment_of
from ..sources.durable import open_arrays, settle, shared_folder, store_arrays
from ..sources.tables import held_out, rank_ranges, width_class

#: Rows of a measured shard, which a task holds whole, and queries of a block.
SHARD_ROWS, BLOCK = 20_000, 4096
SETTING = "name string, method string, setting string, ef int, m int, k int"
FOUND = f"config int, {SETTING}, shard int, qid long, y long, found array<struct<d:double,v:long>>, best array<struct<d:double,v:long>>, n_dist double, latency_ms double, build_s double, build_dist long, index_bytes long, rows long, inclusiveness double"


def _stored(df: DataFrame, key: str, columns: list[str], name: str) -> list[str]:
    """The rows of each key as one file of arrays; gives the paths in the order of the keys."""
    folder = f"{shared_folder(df.sparkSession)}/measured-{uuid.uuid4().hex}"

    def write(table: pa.Table) -> pa.Table:
        out = {}
        for c in columns:
            col = table.column(c).combine_chunks()
            if pa.types.is_list(col.type):
                out[c] = np.asarray(col.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(col), -1)
            else:
                out[c] = col.to_numpy(zero_copy_only=False)
        k = table.column(key)[0].as_py()
        return pa.table({"key": pa.array([k], pa.int64()), "path": [store_arrays(folder, f"{name}-{k}", out)]})

    got = df.select(F.col(key).cast("long").alias(key), *columns).groupBy(key).applyInArrow(write, "key long, path string").collect()
    return [r["path"] for r in sorted(got)]


def shards_of(base: DataFrame, m: int = 16, most: int = SHARD_ROWS) -> list[str]:
    """A table's rows as arrays, in attribute ranges of about ``most`` rows."""
    rows = base.where("attr is not null").select("vid", F.col("vec").cast("array<double>").alias("vec"), F.col("attr").cast("double").alias("attr"), level("vid", m).cast("long").alias("level"))
    n = max(1, -(-rows.count() // most))
    bounds = fit(rows, n) if n > 1 else []
    return _stored(rows.withColumn("shard", segment_of(F.col("attr"), bounds)), "shard", ["vid", "vec", "attr", "level"], "shard")


def query_rows(queries: DataFrame) -> list[str]:
    """Queries as arrays, in blocks."""
    rows = queries.select("qid", F.col("qvec").cast("array<double>").alias("qvec"), F.col("lo").cast("double").alias("lo"), F.col("hi").cast("double").alias("hi"))
    n = max(1, -(-rows.count() // BLOCK))
    return _stored(rows.withColumn("block", F.pmod(F.xxhash64("qid"), F.lit(n))), "block", ["qid", "qvec", "lo", "hi"], "queries")


def shard_at(path: str) -> Shard:
    a = open_arrays(path)
    return Shard.of(a["vid"], a["vec"], a["attr"], a["level"])


def _best(s: Shard, q: np.ndarray, lo: float, hi: float, k: int) -> list[tuple[float, int]]:
    a, b = s.range(lo, hi)
    d = np.sqrt(((s.x[a:b] - q) ** 2).sum(axis=1))
    return [(float(d[i]), int(s.vid[a + i])) for i in np.lexsort([s.vid[a:b], d])[:k]]


def runs(spark: SparkSession, shards: list[str], queries: list[str], configs: Iterable[dict], each: bool = False, truth: bool = True) -> DataFrame:
    """One row per configuration, search setting, shard and query that meets it: results, the exact ones unless ``truth`` is off, and what the search took.

    A configuration holds ``method`` and may hold ``name``, ``how`` (the method's options), ``params`` (the graph's) and ``searches``: (ef, m, k) triples.
    Queries are timed side by side, and one by one with ``each``. Distances don't count the exact scan.
    """

    def run(batches):
        import time

        for pdf in batches:
            for number, text, shard, path in zip(pdf.config, pdf.text, pdf["shard"], pdf["path"], strict=True):
                c, s = json.loads(text), shard_at(path)
                began = time.perf_counter()
                method = METHODS[c["method"]](s, Params(**{"m": 16, **c.get("params", {})}), **c.get("how", {}))
                took, setting = time.perf_counter() - began, json.dumps({**c.get("how", {}), **c.get("params", {})}, sort_keys=True)
                for ef, m, k in c.get("searches", [(100, 16, 10)]):
                    for block in queries:
                        a = open_arrays(block)
                        lo, hi = np.nan_to_num(a["lo"], nan=-np.inf, neginf=-np.inf, posinf=np.inf), np.nan_to_num(a["hi"], nan=np.inf, neginf=-np.inf, posinf=np.inf)
                        y = np.searchsorted(s.attr, hi, "right") - np.searchsorted(s.attr, lo, "left")
                        at = np.flatnonzero(y > 0) if len(shards) > 1 else np.arange(len(y))
                        if not len(at):
                            continue
                        x, ms = a["qvec"][at], np.zeros(len(at))
                        t = time.perf_counter()
                        found = method.many(x, lo[at], hi[at], k, max(ef, k), m)
                        ms[:] = (time.perf_counter() - t) * 1000 / len(at)
                        spent = method.spent
                        for i in range(len(at)) if each else ():
                            t = time.perf_counter()
                            method.many(x[i : i + 1], lo[at[i : i + 1]], hi[at[i : i + 1]], k, max(ef, k), m)
                            ms[i] = (time.perf_counter() - t) * 1000
                        struct = lambda rows: [{"d": d, "v": v} for d, v in rows]
                        yield pd.DataFrame({
                            "config": number, "name": c.get("name", ""), "method": c["method"], "setting": setting, "ef": ef, "m": m, "k": k, "shard": shard, "qid": a["qid"][at], "y": y[at],
                            "found": [struct(f) for f in found], "best": [struct(_best(s, q, l, h, k)) if truth else [] for q, l, h in zip(x, lo[at], hi[at], strict=True)], "n_dist": np.asarray(spent, np.float64), "latency_ms": ms,
                            "build_s": took, "build_dist": int(method.build_dist), "index_bytes": int(method.size()), "rows": len(s.vid), "inclusiveness": getattr(method, "measured", None),
                        })

    rows = [(i, json.dumps(c), j, p) for i, c in enumerate(configs) for j, p in enumerate(shards)]
    # A task for each configuration and shard.
    work = spark.createDataFrame(rows, "config int, text string, shard int, path string").repartition(max(1, len(rows)))
    return work.mapInPandas(run, FOUND)


def answers(found: DataFrame) -> DataFrame:
    """One row per configuration, setting and query: the shards' results merged, with recall against the merged exact ones."""
    keys = ["config", *(c.split()[0] for c in SETTING.split(", ")), "qid"]
    merge = lambda c: F.slice(F.array_sort(F.flatten(F.collect_list(c))), 1, F.max("k"))
    one = found.groupBy(*keys).agg(F.sum("y").alias("y"), merge("found").alias("found"), merge("best").alias("best"), F.sum("n_dist").alias("n_dist"), F.sum("latency_ms").alias("latency_ms"), F.first("inclusiveness").alias("inclusiveness"))
    hits = F.size(F.array_intersect(F.transform("found", lambda x: x.v), F.transform("best", lambda x: x.v)))
    return one.withColumn("recall", F.when(F.size("best") > 0, hits / F.size("best")).otherwise(F.lit(1.0)))


def results(found: DataFrame) -> DataFrame:
    """(qid, rnk, vid, dist) of the first configuration."""
    one = answers(found).where("config = 0").select("qid", F.posexplode("found").alias("i", "e"))
    return one.select("qid", (F.col("i") + 1).alias("rnk"), F.col("e.v").alias("vid"), F.col("e.d").alias("dist"))


def measure(spark: SparkSession, shards: list[str], queries: list[str], configs: Iterable[dict], each: bool = False) -> DataFrame:
    """One row per configuration, search setting and width class (small, medium, large, all): recall, distances, latency with its median and 99th percentile, queries a second
    of one core, and what the build took and holds."""
    found = settle(runs(spark, shards, queries, configs, each))
    built = found.select("config", "shard", "build_s", "build_dist", "index_bytes", "rows").distinct().groupBy("config").agg(*[F.sum(c).alias(c) for c in ("build_s", "build_dist", "index_bytes", "rows")])
    one = answers(found).join(F.broadcast(built), "config")
    one = one.withColumn("width", F.explode(F.array(F.lit("all"), width_class(F.col("y") / F.col("rows")))))
    keys = ["config", *(c.split()[0] for c in SETTING.split(", ")), "width"]
    mean = F.avg("latency_ms")
    return one.groupBy(*keys).agg(
        F.count(F.lit(1)).alias("queries"), F.avg("recall").alias("recall"), F.avg("n_dist").alias("n_dist"), mean.alias("latency_ms"), F.percentile("latency_ms", 0.5).alias("p50_ms"), F.percentile("latency_ms", 0.99).alias("p99_ms"),
        (1000 / F.nullif(mean, F.lit(0.0))).alias("qps"), *[F.first(c).alias(c) for c in ("build_s", "build_dist", "index_bytes", "rows", "inclusiveness")],
    ).drop("config")


def workload(base_all: DataFrame, k: int = 10, low: float = 0.001, high: float = 1.0, salt: str = "range") -> tuple[DataFrame, DataFrame]:
    """Base and queries of a table: a tenth of its objects held out, mixed range widths."""
    base, q = held_out(base_all)
    return base, rank_ranges(base, q, k, low, high, salt)


BASELINES = ("index", "pq_cost_planner", "partitioned_pq", "fused_distance_graph", "graph_postfilter", "vecdb_postfilter", "interval_edge_graph")


def overall(ks=(10, 100), efs=(20, 50, 100, 200)) -> list[dict]:
    """Recall against cost of all methods."""
    return [{"name": "overall", "method": m, "searches": [(ef, 16, k) for k in ks for ef in efs]} for m in BASELINES]


def build_table() -> list[dict]:
    """Build cost and size."""
    return [{"name": "build", "method": m} for m in BASELINES]


def classes(efs=(20, 50, 100, 200, 400)) -> list[dict]:
    """Nine arms over small, medium and large ranges."""
    arms = [("index", {"strategy": s}) for s in ("pre", "post", "hybrid", "auto")] + [(m, {}) for m in ("pq_pre", "btree_pre", "hnsw_post", "interval_edge_graph", "dedicated")]
    return [{"name": "classes", "method": m, "how": h, "searches": [(ef, 16, 10) for ef in efs]} for m, h in arms]


def inclusivity(levels=(30, 40, 60, 80)) -> list[dict]:
    """The index thinned to measured levels of inclusiveness, beside a graph built for each range and one graph a segment."""
    arms = [("degraded_index", {"strategy": "hybrid", "inclusiveness": x}) for x in levels] + [("optimal_hnsw", {}), ("multi_segment_hnsw", {})]
    return [{"name": "inclusivity", "method": m, "how": h, "searches": [(50, 32, 10)]} for m, h in arms]


def picks(ms=(8, 16, 32)) -> list[dict]:
    return [{"name": "picks", "method": "index", "how": {"strategy": "hybrid", "pick": p}, "searches": [(100, m, 10) for m in ms]} for p in ("chunk", "distance")]


def build_grid(ss=(1, 2, 4, 8, 16, 32), ms=(4, 8, 16, 32, 48), efs=(16, 64, 128, 500)) -> list[dict]:
    """One build parameter at a time."""
    rows = [{"how": {"segments": s, "strategy": "hybrid"}, "params": {}} for s in ss]
    rows += [{"how": {"strategy": "hybrid"}, "params": {"m": m}} for m in ms] + [{"how": {"strategy": "hybrid"}, "params": {"ef_cons": e}} for e in efs]
    return [{"name": "build_grid", "method": "index", **r} for r in rows]


def search_grid(efs=(10, 20, 50, 100, 200, 400), ms=(4, 8, 16, 32, 64)) -> list[dict]:
    return [{"name": "search_grid", "method": "index", "how": {"strategy": "hybrid"}, "searches": [(ef, 16, 10) for ef in efs] + [(100, m, 10) for m in ms]}]


def k_grid(ks=(1, 10, 20, 50, 100)) -> list[dict]:
    return [{"name": "k_grid", "method": "index", "searches": [(100, 16, k) for k in ks]}]


def tuning(ss=(4, 8, 16), ms=(8, 16, 32), efs=(20, 50, 100, 200)) -> list[dict]:
    """Grids from which defaults are chosen: the index over S and M, and the parameters of the others."""
    rows = [{"method": "index", "how": {"segments": s}, "params": {"m": m}} for s in ss for m in ms]
    rows += [{"method": "hnsw_post", "params": {"m": m}} for m in ms] + [{"method": "interval_edge_graph", "params": {"m": m}} for m in ms]
    rows += [{"method": "fused_distance_graph", "how": {"weight": w}} for w in (0.1, 0.5, 1.0, 2.0)]
    rows += [{"method": "partitioned_pq", "how": {"partitions": p}} for p in (4, 8, 16)] + [{"method": "pq_cost_planner", "how": {"rerank": r}} for r in (2, 4, 8)]
    return [{"name": "tuning", "searches": [(ef, 16, 10) for ef in efs], **r} for r in rows]


def at_targets(measured: DataFrame, targets: tuple[float, ...] = (0.9, 0.95, 0.99), rate: str = "qps") -> DataFrame:
    """(method, setting, width, target, best): the best rate of any search setting that reaches each target; null where none does."""
    wanted = measured.withColumn("target", F.explode(F.array(*map(F.lit, targets))))
    return wanted.groupBy("method", "setting", "width", "target").agg(F.max(F.when(F.col("recall") >= F.col("target"), F.col(rate))).alias("best"), F.min(F.when(F.col("recall") >= F.col("target"), F.col("n_dist"))).alias("least_dist"))


def tuned(measured: DataFrame, target: float = 0.9) -> DataFrame:
    """Of each method the setting with the least distances among those that reach the target."""
    w = Window.partitionBy("method").orderBy("n_dist", "setting", "ef")
    return measured.where((F.col("width") == "all") & (F.col("recall") >= target)).withColumn("_r", F.row_number().over(w)).where("_r = 1").drop("_r")


def spans(spark: SparkSession, shards: list[str], segments: int = 8, lengths=(1, 2, 4, 6, 8), m: int = 16, ef_cons: int = 500) -> DataFrame:
    """(segments, first, common, total, inclusiveness) for every run of neighbouring segments of some lengths, over the shards of a table."""

    def run(batches):
        params = Params(m=m, ef_cons=ef_cons)
        for pdf in batches:
            for path in pdf["path"]:
                s = shard_at(path)
                index = METHODS["index"](s, params, segments=segments)
                seg, out = np.searchsorted(index.cuts, s.attr, "right"), []
                for n in (x for x in lengths if x <= segments):
                    for a in range(segments - n + 1):
                        common, total = common_edges(index.g, s, np.flatnonzero((seg >= a) & (seg < a + n)), params)
                        out.append((n, a, common, total))
                yield pd.DataFrame(out, columns=["segments", "first", "common", "total"])

    rows = spark.createDataFrame([(p,) for p in shards], "path string").repartition(len(shards))
    sums = rows.mapInPandas(run, "segments int, first int, common long, total long").groupBy("segments", "first").agg(F.sum("common").alias("common"), F.sum("total").alias("total"))
    return sums.withColumn("inclusiveness", F.when(F.col("total") > 0, 100.0 * F.col("common") / F.col("total")).otherwise(F.lit(100.0)))


def incremental(spark: SparkSession, shards: list[str], queries: list[str], rounds: int = 5, m: int = 16, ef_cons: int = 100, k: int = 10, efs: tuple[int, ...] = (20, 50, 100, 200), target: float = 0.95) -> DataFrame:
    """(method, round, rows, build_dist, build_s, ef, recall, n_dist, latency_ms): objects arrive in ``rounds`` equal parts by id, in each shard of the table. The index inserts each part; interval
    edges, which need attribute order, are built anew. Searches take the smallest of ``efs`` that reaches the target, or the largest."""

    def run(batches):
        import time

        for pdf in batches:
            for name, path in zip(pdf.method, pdf["path"], strict=True):
                s = shard_at(path)
                parts, out, method, before = np.array_split(s.by_id(), rounds), [], None, 0
                for r, part in enumerate(parts):
                    here, began = s.take(np.sort(np.concatenate(parts[: r + 1]))), time.perf_counter()
                    if name == "index" and method is not None:
                        # Boundaries come from the first part and stay.
                        method.g = method.g.grown(s.x[part], s.attr[part], s.vid[part], np.searchsorted(method.cuts, s.attr[part], "right"), s.level[part])
                        for v in range(method.g.size, len(method.g.vid)):
                            method.g.insert(v)
                        method.s, cost = here, method.g.dist
                    else:
                        method = METHODS[name](here, Params(m=m, ef_cons=ef_cons))
                        cost = method.build_dist
                    took = time.perf_counter() - began
                    for ef in efs:
                        rec, spent, ms = [], [], 0.0
                        for block in queries:
                            a = open_arrays(block)
                            t = time.perf_counter()
                            found = method.many(a["qvec"], a["lo"], a["hi"], k, ef, 16)
                            ms += (time.perf_counter() - t) * 1000
                            spent += list(method.spent)
                            for q, lo, hi, f in zip(a["qvec"], a["lo"], a["hi"], found, strict=True):
                                best = {v for _, v in _best(here, q, lo, hi, k)}
                                rec.append(len(best & {v for _, v in f}) / len(best) if best else 1.0)
                        if np.mean(rec) >= target:
                            break
                    out.append((name, r + 1, len(here.vid), int(cost), took, ef, float(np.mean(rec)), float(np.mean(spent)), ms / max(1, len(rec))))
                yield pd.DataFrame(out, columns=["method", "round", "rows", "build_dist", "build_s", "ef", "recall", "n_dist", "latency_ms"])

    rows = spark.createDataFrame([(name, p) for name in ("index", "interval_edge_graph") for p in shards], "method string, path string").repartition(2 * len(shards))
    got = rows.mapInPandas(run, "method string, round int, rows long, build_dist long, build_s double, ef int, recall double, n_dist double, latency_ms double")
    return got.groupBy("method", "round").agg(*[F.sum(c).alias(c) for c in ("rows", "build_dist", "build_s")], F.max("ef").alias("ef"), F.avg("recall").alias("recall"), F.sum("n_dist").alias("n_dist"), F.sum("latency_ms").alias("latency_ms"))
