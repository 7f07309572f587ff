"""Plans, the index, streams and registered queries on the given tables."""

import subprocess
import sys
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from rangevec.functions.columns import in_range, interleave, level, uniform
from rangevec.operators import exact, graphs, metrics, segment
from rangevec.operators.exact import cardinality, range_knn, range_knn_blocks
from rangevec.operators.index import RangeIndex
from rangevec.plans import experiments as ex, planner, vector_queries
from rangevec.sources import tables
from rangevec.sources.durable import ranked, settle


@pytest.fixture(scope="module")
def work(spark):
    base, q = ex.workload(tables.emb_price(spark, "/root/testdata/sf0.001"))
    return settle(base), settle(q)


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_ranked(spark):
    df = spark.createDataFrame([(i * 7 % 50, i) for i in range(200)], "a int, b int")
    got = ranked(df, ["a", "b"], "r").orderBy("r").collect()
    assert [r["r"] for r in got] == list(range(200)) and [(r["a"], r["b"]) for r in got] == sorted((i * 7 % 50, i) for i in range(200))


def test_range_rule(spark):
    df = spark.createDataFrame([(1.0, 0.0, 1.0), (1.0, 1.0, None), (1.0, None, 0.5), (None, None, None), (float("nan"), None, None), (2.0, None, None)], "a double, lo double, hi double")
    assert [r[0] for r in df.select(in_range("a", "lo", "hi")).collect()] == [True, True, False, False, False, True]


def test_exact_forms_agree(work):
    base, q = work
    a = rows(range_knn(base, q).select("qid", "rnk", "vid"))
    assert a == rows(range_knn_blocks(base, q).select("qid", "rnk", "vid")) == rows(range_knn(base, q, segments=segment.table(base, segment.fit(base, 4))).select("qid", "rnk", "vid"))
    y = {r["qid"]: r["y"] for r in cardinality(base, q).collect()}
    assert len(a) == sum(min(10, n) for n in y.values()) and y == {r["qid"]: r["y"] for r in q.collect()}


def test_ties_share_a_segment(spark):
    df = spark.createDataFrame([(i, float(i // 40)) for i in range(200)] + [(999, None)], "vid long, attr double")
    bounds = segment.fit(df, 8)
    got = segment.assign(df, bounds).groupBy("attr").agg(F.count_distinct("seg").alias("n"), F.min("seg").alias("s")).collect()
    assert all(r["n"] == 1 for r in got) and [r["s"] for r in got if r["attr"] is None] == [-1] and len(bounds) == 4
    assert segment.fit(df.limit(0), 8) == [] and segment.fit(df, 1) == []


def test_every_combination_is_in_the_chunked_graph(spark):
    """Also with equal vectors, of which ids choose."""
    v = spark.createDataFrame([(i, [float(i % 6), float(i % 4)], float(i)) for i in range(24)], "vid long, vec array<double>, attr double")
    base = settle(segment.assign(v, segment.fit(v, 3)))
    assert graphs.missing(graphs.exhaustive(base, 3, [0, 1, 2]), graphs.chunked(base, 3)).count() == 0
    assert len(graphs.subsets([0, 1, 2])) == 7 and len(graphs.subsets([0, 1, 2], True)) == 6


def test_graph_queries_take_all_rows(spark, sf):
    """Every priced vector is a source, and the full beams answer as a brute-force scan of the table."""
    v = settle(tables.emb_price(spark, sf))
    ids, found = {r["vid"] for r in v.select("vid").collect()}, vector_queries.QUERIES
    assert {r["src"] for r in found["knn_graph_full"](spark, sf).collect()} == ids == {r["vid"] for r in found["chain_links"](spark, sf).collect()}
    vec = {r["vid"]: np.array(r["vec"]) for r in v.collect()}
    near = {s: sorted((float(np.sqrt(((vec[o] - vec[s]) ** 2).sum())), o) for o in ids if o != s) for s in sorted(ids)[-3:]}
    filled = found["prune_filled"](spark, sf).toPandas().groupby("src").dst.apply(list)
    kept = found["prune_kept"](spark, sf).toPandas().groupby("src").dst.apply(set)
    assert set(filled.index) == ids == set(kept.index)
    for s, cands in near.items():
        want = []
        for d, o in cands:
            if len(want) < 4 and all(np.sqrt(((vec[e] - vec[o]) ** 2).sum()) >= d for e in want):
                want.append(o)
        assert kept[s] == set(want) and set(want) <= set(filled[s]) and len(filled[s]) == 4
    q = v.where("vid % 50 = 0").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"), F.lit(30000.0).alias("lo"), F.lit(250000.0).alias("hi"), F.lit(10).alias("k"))
    want = rows(range_knn(v, q).select("qid", "rnk", "vid"))
    assert want and all(rows(found[f"search_{how}_full_beam"](spark, sf).select("qid", "rnk", "vid")) == want for how in ("post", "hybrid"))


def test_query_sets_are_whole(spark, sf):
    """Ids divisible by 100 are queries, and each meets all rows."""
    ids, found = {r["vid"] for r in tables.embeddings(spark, sf).select("vid").collect()}, vector_queries.QUERIES
    asked = {i for i in ids if i % 100 == 0}
    for name in ("distance_l2", "distance_cosine", "distance_ip", "distance_sql_function"):
        assert {(r["a"], r["b"]) for r in found[name](spark, sf).select("a", "b").collect()} == {(a, b) for a in asked for b in ids}, name
    lines = tables.load(spark, sf, "lineitem").count()
    assert {r["qid"] for r in found["exact_range_knn_lines"](spark, sf).collect()} == set(range(0, lines, 100))


def test_growing_indexes_take_all_rows(spark, sf, monkeypatch):
    """Streamed and appended rows are all there over several shards, answers are exact, and appending gives the edges of a build at once."""
    monkeypatch.setattr(vector_queries, "SHARD_ROWS", 400)
    found, n = vector_queries.QUERIES, tables.load(spark, sf, "events").count()
    got = found["stream_ingest_final"](spark, sf).toPandas()
    assert set(got.qid) == set(range(0, n, 100)) and (got.rows == n).all() and (got.right == got.found).all()
    grown = found["append_rounds"](spark, sf).first()
    assert grown["rows"] == 450 and grown["only_appended"] == 0 == grown["only_at_once"] and grown["linked"]
    seen = []
    monkeypatch.setattr(vector_queries.planner, "adapt", lambda index, old, new, **how: seen.append((index.manifest.rows, new.count())) or index)
    found["drift_recalibrated"](spark, sf)
    assert seen == [(tables.emb_value(spark, sf).count(),) * 2] * 2


def test_zorder_index(spark, sf):
    """The index over interleaved keys answers a conjunction exactly."""
    found = vector_queries.QUERIES
    assert rows(found["zorder_index"](spark, sf)) == rows(found["and_two_attributes"](spark, sf))


def test_calibration_finds_turning_points(spark):
    """From a log in which scans win up to a quarter and the whole graph from seven tenths on, thresholds come out near these."""
    log = spark.createDataFrame([(i, i / 200, s, 1.0 if s != "post" or i > 60 else 0.5, {"pre": i * 2.0, "post": 120.0, "hybrid": 90.0 + i * 0.22}[s]) for i in range(200) for s in ("pre", "post", "hybrid")], "qid int, share double, strategy string, recall double, n_dist double")
    p = planner.turning_points(log, 0.9).first()
    assert 0.2 <= p["tau_a"] <= 0.3 and 0.6 <= p["tau_b"] <= 0.75


def test_levels_shrink(spark):
    n = {r["level"]: r["count"] for r in spark.range(20000).select(level("id", 16).alias("level")).groupBy("level").count().collect()}
    assert 0.92 < n[0] / 20000 < 0.955
    u = spark.range(5000).select(uniform("id", "x").alias("u")).agg(F.min("u"), F.max("u"), F.avg("u")).first()
    assert 0 < u[0] and u[1] < 1 and abs(u[2] - 0.5) < 0.02


def test_interleave(spark):
    got = [r[0] for r in spark.createDataFrame([(0, 0), (1, 0), (0, 1), (3, 3), (2, 1)], "a int, b int").select(interleave([F.col("a"), F.col("b")], 4)).collect()]
    assert got == [0, 1, 2, 15, 6]


def test_index(spark, work, tmp_path):
    base, q = work
    index = RangeIndex.build(base, 4, 8, 40)
    assert rows(index.search(q, "pre").select("qid", "rnk", "vid")) == rows(range_knn(base, q).select("qid", "rnk", "vid"))
    for how in ("post", "hybrid", "auto"):
        best, cost = index.work(index.search(q, how, ef=200, m=32, counters=True), q, 10)
        got = metrics.summary(metrics.recall(best, range_knn_blocks(base, q), q.select("qid", "y", "k"))).first()
        assert got["recall"] > (0.8 if how == "post" else 0.93), how
        assert cost.count() == q.count()
    # Blocks of queries change nothing, and there may be any number of queries.
    assert rows(index.search(q, "hybrid", block=3)) == rows(index.search(q, "hybrid"))
    e = index.edges().where("layer = 0")
    assert e.groupBy("src", "chunk").count().agg(F.max("count")).first()[0] <= 8
    assert rows(index.chain().where("layer = 0").select("vid", "next")) == rows(base.select("vid", F.expr("lead(vid) OVER (ORDER BY attr, vid)").alias("next")))
    assert e.groupBy("src").agg(F.sum(F.col("masked").cast("int")).alias("n")).agg(F.max("n")).first()[0] <= 8
    seg = {r["vid"]: r["seg"] for r in index.vectors().collect()}
    assert all(seg[r["dst"]] == r["chunk"] and r["src"] != r["dst"] for r in e.collect())
    again = RangeIndex.load(spark, index.save(f"file://{tmp_path}/i"))
    assert rows(again.search(q, "hybrid")) == rows(index.search(q, "hybrid"))
    for bad in ({"k": 0}, {"ef": 5}, {"m": 0}):
        with pytest.raises(ValueError):
            index.search(q, "hybrid", **bad)
    with pytest.raises(ValueError):
        RangeIndex.build(base.unionByName(base), 4)


def test_append_equals_build(spark, work):
    base, _ = work
    some = base.where("vid < 160")
    for shards in (1, 3):
        whole = RangeIndex.build(some, 3, 6, 30, shards=shards)
        part = RangeIndex._inserted(RangeIndex._checked(some.where("vid < 90"))[0], replace(whole.manifest, parts=[]))
        grown = part.append(some.where("vid >= 90"))
        assert rows(grown.edges()) == rows(whole.edges()) and rows(grown.entries()) == rows(whole.entries()) and rows(grown.chain()) == rows(whole.chain())
    # Shards that get no object keep their files.
    last = grown.append(base.where("vid >= 160").orderBy(F.col("attr").desc()).limit(1))
    assert len(set(last.manifest.parts) & set(grown.manifest.parts)) == 2 and last.manifest.rows == grown.manifest.rows + 1


def test_nested_boundaries(spark):
    """Fitting all shards at once gives what fitting them one by one does, ties included."""
    df = spark.createDataFrame([(i, float(i * i % 97)) for i in range(500)] + [(999, None)], "vid long, attr double")
    for shards, s in ((1, 4), (3, 4), (5, 2), (40, 3)):
        outer, inner = segment.fit_nested(df, shards, s)
        assert outer == segment.fit(df, shards) and len(inner) == len(outer) + 1
        placed = df.where("attr IS NOT NULL").withColumn("shard", segment.segment_of(F.col("attr"), outer))
        for i in range(min(3, len(inner))):
            assert inner[i] == segment.fit(placed.where(F.col("shard") == i), s)
    assert segment.fit_nested(df.limit(0), 3, 3) == ([], [[]])


def test_large_batches_are_split(spark, work, monkeypatch):
    """Beyond the broadcast bound, exact searches go by segments or in blocks, with the same results."""
    base, q = work
    want = rows(range_knn(base, q).select("qid", "rnk", "vid"))
    monkeypatch.setattr(exact, "MOST_BYTES", 15_000)
    assert exact.batch_blocks(q) > 1
    assert rows(range_knn_blocks(base, q).select("qid", "rnk", "vid")) == want == rows(range_knn(base, q).select("qid", "rnk", "vid"))


def test_open_and_tied_ranges_count(spark):
    df = spark.createDataFrame([(i, float(i // 4)) for i in range(40)] + [(90, None), (91, float("nan"))], "vid long, attr double")
    q = spark.createDataFrame([(0, 2.0, 3.0), (1, None, 3.0), (2, 2.0, None), (3, None, None), (4, 2.5, 2.6), (5, -5.0, -1.0), (6, 50.0, 60.0), (7, 2.5, 4.5)], "qid long, lo double, hi double")
    assert rows(cardinality(df, q)) == [(0, 8), (1, 16), (2, 32), (3, 40), (4, 0), (5, 0), (6, 0), (7, 8)]
    assert {r["y"] for r in cardinality(df.limit(0), q).collect()} == {0}


def test_nulls_stay_out(spark):
    v = tables.emb_retail(spark, "/root/testdata/sf0.001")
    index = RangeIndex.build(v.where("vid < 300"), 2, 6, 20)
    assert index.manifest.rows == v.where("vid < 300 AND attr IS NOT NULL").count() < 300


def test_planner(spark, work):
    base, q = work
    est = {r["qid"]: r["y_est"] for r in planner.estimate(q, planner.histogram(base, 32)).collect()}
    n = base.count()
    assert max(abs(est[r["qid"]] - r["y"]) for r in q.collect()) <= 2 * n / 32 + 2
    h = segment.table(base, segment.fit(base, 8))
    assert not planner.drifted(h, h) and planner.drifted(h, segment.table(base.where("attr > 150000"), segment.bounds_of(h)))
    log = spark.createDataFrame([(i, i / 100, s, 1.0, {"pre": i * 4.0, "post": 150.0, "hybrid": 80.0 + i}[s]) for i in range(1, 100) for s in ("pre", "post", "hybrid")], "qid int, share double, strategy string, recall double, n_dist double")
    t = planner.turning_points(log, 0.9).first()
    assert 0.2 <= t["tau_a"] <= 0.3 and 0.65 <= t["tau_b"] <= 0.75


def test_trends(spark, work):
    """More beam or more neighbours: more recall and more work. Picking by distance takes more distances than taking chunk heads."""
    base, q = work
    shard, asked = ex.shards_of(base), ex.query_rows(q)
    got = ex.measure(spark, shard, asked, ex.search_grid((10, 50, 200), (4, 16, 64))).where("width = 'all'").toPandas()
    by_ef, by_m = got[got.m == 16].drop_duplicates("ef").sort_values("ef"), got[got.ef == 100].sort_values("m")
    for g in (by_ef, by_m):
        assert (np.diff(g.recall) >= -0.02).all() and (np.diff(g.n_dist) > 0).all()
    # A table in several shards gives merged results; its exact arm finds all.
    split = ex.measure(spark, ex.shards_of(base, most=150), asked, [{"method": "btree_pre"}, {"method": "index"}]).where("width = 'all'").toPandas().set_index("method")
    assert split.recall["btree_pre"] == 1 and split.recall["index"] > 0.9 and (split.rows == base.count()).all() and (split.queries == q.count()).all()
    assert {"best", "target", "least_dist"} <= set(ex.at_targets(ex.measure(spark, shard, asked, ex.k_grid((10,)))).columns)
    picks = ex.measure(spark, shard, asked, ex.picks((16,))).where("width = 'all'").toPandas().set_index("setting").n_dist
    assert picks[picks.index.str.contains("distance")].iloc[0] > 2 * picks[picks.index.str.contains("chunk")].iloc[0]
    span = {r["segments"]: r["x"] for r in ex.spans(spark, shard).groupBy("segments").agg(F.avg("inclusiveness").alias("x")).collect()}
    assert span[1] > 60 and min(span.values()) > 40


def test_rounds_cost_the_same(spark, work):
    base, q = work
    got = ex.incremental(spark, ex.shards_of(base), ex.query_rows(q.limit(10)), 4, 8, 40).toPandas().sort_values("round")
    ours, theirs = got[got.method == "index"].build_dist.to_numpy(), got[got.method != "index"].build_dist.to_numpy()
    assert theirs[-1] / theirs[0] > ours[-1] / ours[0]


def test_udtf_and_datasource(spark, work):
    from rangevec.sources.datasource import load

    base, q = work
    index = RangeIndex.build(base, 3, 6, 30, shards=2)
    got = load(spark, index.save(), 50_000, 90_000)
    assert rows(got.select("vid")) == rows(base.where("attr BETWEEN 50000 AND 90000").select("vid"))
    planner.register_udtf(spark, index, "range_ann_test")
    q.createOrReplaceTempView("asked")
    assert spark.sql("SELECT qid, a.vid FROM asked, LATERAL range_ann_test(qvec, lo, hi, k) a").count() > 0


def test_entry(spark):
    assert __spark_entry__.entry(spark).columns == ["qid", "rnk", "vid", "dist"]


def test_registry():
    found = __spark_entry__.queries()
    assert set(__spark_entry__.oracle_sql()) <= set(found) and len(found) > 120
    assert set(vector_queries.QUERIES) <= set(found)


def test_core_needs_no_pipeline():
    """Without the pipeline's folder and file the entry module still imports."""
    code = "import sys, importlib.abc\nclass No(importlib.abc.MetaPathFinder):\n    def find_spec(self, name, path, target=None):\n        if name == 'corpus_pipeline' or name.startswith('rangevec.llm'):\n            raise ModuleNotFoundError(name=name)\nsys.meta_path.insert(0, No())\nimport __spark_entry__ as e\nassert len(e.queries()) > 100 and not any(n.startswith('op') for n in e.queries())"
    subprocess.run([sys.executable, "-c", code], check=True, cwd=__spark_entry__.__file__.rsplit("/", 1)[0])


def test_stream_results_are_files(spark, sf):
    """A stream's deduplicated rows lie in files, none in the driver's memory; the session's state store stays as it was."""
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    got = vector_queries.QUERIES["stream_dedup"](spark, sf)
    assert got.inputFiles()
    assert sorted(r[0] for r in got.collect()) == sorted(r[0] for r in tables.load(spark, sf, "events").select("event_id").collect())
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass") == before


@pytest.mark.parametrize(("metric", "spread"), [("l2", None), ("cosine", None), ("ip", None), ("l2", 3.0)])
def test_best_over_blocks(metric, spread, monkeypatch):
    """The k best by tiles and blocks are those of all distances, with ties, repeated and zero vectors, open ranges and different k; no tile is larger than its bound."""
    r, n, nq = np.random.default_rng(0), 700, 60
    v, x = np.round(r.normal(size=(n, 8)), 1), np.round(r.normal(size=(nq, 8)), 1)
    v[5], v[100:300] = 0, v[99]
    attr, lo, vid, ks = r.integers(0, 50, n) * 1.0, r.integers(0, 50, nq) * 1.0, r.permutation(n), r.integers(1, 12, nq)
    hi = lo + r.integers(0, 30, nq)
    if spread is None:
        lo[0], hi[1] = -np.inf, np.inf
    monkeypatch.setattr(exact._Best, "TILE", 1000)
    best, sizes = exact._Best(x, lo, hi, ks, metric, spread), []
    rough = best._rough
    best._rough = lambda at, *a: sizes.append((at.stop - at.start) * len(a[0])) or rough(at, *a)
    for i in range(0, n, 64):
        best.see(v[i : i + 64], attr[i : i + 64], vid[i : i + 64])
    assert max(sizes) <= 1000
    want = []
    for i in range(nq):
        with np.errstate(invalid="ignore"):
            dot = (v * x[i]).sum(axis=1)
            d = {"l2": np.sqrt(((v - x[i]) ** 2).sum(axis=1)), "ip": -dot, "cosine": 1 - dot / (np.sqrt((v**2).sum(axis=1)) * np.sqrt((x[i] ** 2).sum()))}[metric]
        if spread:
            d = d + np.maximum(np.abs(attr - (lo[i] + hi[i]) / 2) - (hi[i] - lo[i]) / 2, 0) / spread
        inside = np.flatnonzero((attr >= lo[i]) & (attr <= hi[i]) if spread is None else np.ones(n, bool))
        want += [(i, int(vid[a]), float(d[a])) for a in inside[np.lexsort([vid[inside], d[inside]])][: ks[i]]]
    got = [(int(a), int(b), float(c)) for a, b, c in zip(*best.rows(), strict=True)]
    assert [g[:2] for g in got] == [w[:2] for w in want] and np.allclose([g[2] for g in got], [w[2] for w in want], rtol=0, atol=1e-12, equal_nan=True)


@pytest.mark.parametrize("dim", [2, 4])
def test_best_by_boxes(dim, monkeypatch):
    """Going through boxes of objects gives what going through all gives, ties and copies included, and compares few of the pairs; queries with many lower bounds go through all."""
    r, n, nq = np.random.default_rng(dim), 6000, 2000
    v, x = np.round(r.random((n, dim)), 2), np.round(r.random((nq, dim)) * 1.5, 2)
    # All but two are flags.
    v[:, 2:], x[:, 2:] = np.round(v[:, 2:]), np.round(np.minimum(x[:, 2:], 1))
    v[3000:4000] = v[:1000]
    x = x[np.concatenate(exact._leaves(x, 64))]
    attr, vid, ks = r.integers(0, 50, n) * 1.0, r.permutation(n), r.integers(1, 12, nq)
    lo, hi = np.repeat([5.0, 20.0], nq // 2), np.full(nq, 30.0)
    monkeypatch.setattr(exact._Best, "LEAF", 64)
    monkeypatch.setattr(exact._Best, "SIDE", 64)
    near, whole, pairs = exact._Best(x, lo, hi, ks, "l2", None), exact._Best(x, lo, hi, ks, "l2", None), []
    monkeypatch.setattr(near, "_rough", lambda at, *a: pairs.append((at.stop - at.start) * len(a[0])) or exact._Best._rough(near, at, *a))
    assert near.boxed and not exact._Best(x, r.random(nq), hi, ks, "l2", None).boxed
    for i in range(0, n, 4000):
        near.near(v[i : i + 4000], attr[i : i + 4000], vid[i : i + 4000])
    for i in range(0, n, 512):
        whole.see(v[i : i + 512], attr[i : i + 512], vid[i : i + 512])
    assert sum(pairs) < n * nq / 2
    assert all((a == b).all() for a, b in zip(near.rows(), whole.rows(), strict=True))


@pytest.mark.parametrize("name", ["exact_cosine", "exact_half_bounded", "exact_knn_all", "fused_distance_exact"])
def test_exact_queries_go_by_products(spark, sf, name):
    """No join of every query with every object."""
    plan = vector_queries.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "NestedLoop" not in plan and "Cartesian" not in plan


def _scans(df):
    return df._jdf.queryExecution().executedPlan().toString().count("FileScan parquet")


def test_combinations_of_years(spark, sf):
    """The years of each customer's orders as segments, from the orders themselves."""
    got, o = vector_queries.QUERIES["combination_counts"](spark, sf), tables.load(spark, sf, "orders").toPandas()
    years = set(o.groupby("o_custkey").o_orderdate.apply(lambda d: d.dt.year.nunique()))
    assert _scans(got) and rows(got) == rows_of([(s, 2**s - 1, s * (s + 1) // 2) for s in years])


def rows_of(found):
    return sorted(found, key=str)


def test_penalty_of_priorities(spark, sf):
    """Tables as large as the orders of each priority."""
    got, o = vector_queries.QUERIES["multi_graph_penalty"](spark, sf), tables.load(spark, sf, "orders").toPandas()
    want = [(s, int(n), round(s * (1 - np.log(s) / np.log(n)), 6)) for s in (2, 4, 8, 16) for n in o.groupby("o_orderpriority").size()]
    assert _scans(got) and np.allclose(sorted(map(tuple, got.collect())), sorted(want), rtol=0, atol=2e-6)


def test_space_of_orders(spark, sf):
    """The model's size for as many objects as there are orders with a price."""
    got, n = vector_queries.QUERIES["space_model"](spark, sf), tables.load(spark, sf, "orders").count()
    want = [(s, m, metrics.space_units(n, s, m) * 4 / 1048576) for s in (1, 2, 4, 8, 16) for m in (8, 16, 32)]
    assert _scans(got) and np.allclose(sorted(map(tuple, got.collect())), sorted(want), rtol=0, atol=1e-4)


def test_shards_follow_rows(spark, sf, monkeypatch):
    """A larger table is built by more tasks, and queries that ask for several shards get them at least."""
    monkeypatch.setattr(vector_queries, "INDEX_ROWS", 100)
    index, base, _ = vector_queries._index(spark, sf, s=4, m=4, ef_cons=16)
    assert len(index.manifest.parts) == 5 and index.manifest.rows == base.count()
    assert len(vector_queries._index(spark, sf, s=4, m=4, ef_cons=16, least=7)[0].manifest.parts) == 7


@pytest.mark.parametrize("name", ["baseline_interval_graph", "baseline_optimal", "baseline_degraded", "baseline_dedicated"])
def test_slow_builds_are_dealt_to_shards(spark, sf, name, monkeypatch):
    """Shards of these methods stay small, however many rows the table has."""
    from rangevec.plans import vector_queries as vq

    seen, shards_of = [], vq.ex.shards_of
    monkeypatch.setattr(vq, "METHOD_ROWS", dict.fromkeys(vq.METHOD_ROWS, 60))
    monkeypatch.setattr(vq.ex, "shards_of", lambda *a, **how: seen.append(shards_of(*a, **how)) or seen[-1])
    got = vq.QUERIES[name](spark, sf).collect()
    assert len(seen[0]) >= 3 and all(r["good"] for r in got)


def test_bulk_backbone_compares_by_matrices(spark):
    """Copies, far ids and an empty chunk; the plan pairs no rows."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(60, 5))
    x[10:14] = x[10]
    vid, seg = np.arange(60) * 10**9 - 5, np.where(np.arange(60) % 3 == 0, 0, 2)
    base = spark.createDataFrame([(int(v), a.tolist(), int(s)) for v, a, s in zip(vid, x, seg, strict=True)], "vid long, vec array<double>, seg int")
    found = graphs.bulk_backbone(base, 4, 4)
    assert "MapInArrow" in found._jdf.queryExecution().toString()
    got = {(r["src"], r["chunk"]): r["dst"] for r in found.where("layer = 0 and rnk = 1").collect()}
    for i in range(60):
        for s in (0, 2):
            to = [j for j in np.flatnonzero(seg == s) if j != i]
            assert got[int(vid[i]), s] == vid[min(to, key=lambda j: (((x[i] - x[j]) ** 2).sum(), vid[j]))]
    assert graphs.bulk_backbone(base.limit(0), 4, 4).count() == 0


def test_zorder_search_asks_for_k_objects(spark, sf, monkeypatch):
    """An interval gives its k nearest objects of the rectangle, of several shards."""
    from rangevec.operators.index import RangeIndex
    from rangevec.plans import vector_queries as vq

    seen, search = [], RangeIndex.search
    monkeypatch.setattr(vq, "INDEX_ROWS", 120)
    monkeypatch.setattr(RangeIndex, "search", lambda self, *a, **how: seen.append((how["k"], len(self.manifest.outer))) or search(self, *a, **how))
    assert rows(vq.QUERIES["zorder_index"](spark, sf)) == rows(vq.QUERIES["and_two_attributes"](spark, sf))
    assert seen[0][0] == vq.K and seen[0][1] >= 2
