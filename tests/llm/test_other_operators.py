"""Vectors, classifiers, shards, components and the pipeline."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangevec.llm import embedding_dedup, langid, queries, sharding, toxicity
from rangevec.llm.components import components
from rangevec.llm.shared import join_hot

from .test_text_operators import EDGE, frame


def reach(n, links):
    comp = list(range(n))
    changed = True
    while changed:
        changed = False
        for a, b in links:
            m = min(comp[a], comp[b])
            if (comp[a], comp[b]) != (m, m):
                comp[a] = comp[b] = m
                changed = True
    return comp


@pytest.mark.parametrize("shape", ["random", "path", "star", "none"])
def test_components(spark, shape):
    rng = np.random.default_rng(3)
    links = {"random": rng.integers(0, 300, (250, 2)).tolist(), "path": [(i, i + 1) for i in range(60)], "star": [(299, i) for i in range(250)], "none": [(5, 5)]}[shape]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame([tuple(map(int, x)) for x in links] + [(None, 1)], "a long, b long")).collect()}
    comp = reach(300, links)
    assert got == {i: comp[i] for a, b in links if a != b for i in (a, b)}


def test_join_hot(spark):
    facts = spark.createDataFrame([(i % 7 if i % 3 else 0, i) for i in range(3000)], "k long, i long")
    groups = facts.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    assert join_hot(facts, groups, ["k"], "n").count() == 3000


def vectors(seed=0):
    rng = np.random.default_rng(seed)
    rows = []
    for g in range(40):
        c = rng.normal(size=16)
        for _ in range(int(rng.integers(1, 12))):
            rows.append((c + rng.normal(size=16) * 0.22).tolist())
    rows += [rows[0], rows[0], [2 * x for x in rows[1]]]
    rows += [None, [], [0.0] * 16, [None] + [1.0] * 15, [float("nan")] * 16, [float("inf")] + [1.0] * 15, [1.0, 2.0], [1.0, 2.0], [1e300] * 16, [1e-200] * 16]
    order = rng.permutation(len(rows))
    return [(int(i), rows[i], "label", 1.0) for i in order]


def brute_vectors(rows, t=0.9):
    ok = {i: np.array(v, float) for i, v, *_ in rows if v and None not in v and np.isfinite(np.array(v, float)).all() and np.any(v)}
    unit = {i: (v / abs(v).max()) / np.linalg.norm(v / abs(v).max()) for i, v in ok.items()}
    links = [(a, b) for a in ok for b in ok if a != b and len(ok[a]) == len(ok[b]) and unit[a] @ unit[b] >= t]
    n, comp = {i: 0 for i, *_ in rows}, reach(len(rows), links)
    for a, _ in links:
        n[a] += 1
    return {i: (n[i], comp[i], i == comp[i]) for i, *_ in rows}


@pytest.mark.parametrize("block", [(4, 8), (256, 4096)])
def test_vectors(spark, block, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "LEAST_BLOCK", block[0])
    monkeypatch.setattr(embedding_dedup, "MOST_BLOCK", block[1])
    rows = vectors()
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, key string, rep double")
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in embedding_dedup.near_vectors(df).collect()}
    assert got == brute_vectors(rows)
    assert embedding_dedup.near_vectors(df.limit(0)).collect() == []
    assert embedding_dedup.near_vectors(df.where("embedding IS NULL")).count() == 1


def test_vectors_that_repeat_ids(spark):
    """Each row is a vector of its own, also where several rows have one id or none."""
    rows = [(5, None), (5, [1.0, 0.0]), (6, [0.0, 1.0]), (6, [0.0, 2.0]), (None, [3.0, 0.1]), (None, None), (7, [0.0, 0.0])]
    got = embedding_dedup.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert sorted(map(tuple, got), key=str) == sorted([(5, 0, 5, True), (5, 1, 5, True), (6, 1, 6, True), (6, 1, 6, True), (None, 1, 5, False), (None, 0, None, True), (7, 0, 7, True)], key=str)


def test_cells_exclude_only_far_vectors():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 8))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    y = x + rng.normal(size=x.shape) * 0.1
    y /= np.linalg.norm(y, axis=1, keepdims=True)
    pivots = x[:20]
    reach_ = np.sqrt(0.2)
    hx, near = embedding_dedup._near_cells(x, pivots, reach_)
    hy, _ = embedding_dedup._near_cells(y, pivots, reach_)
    close = np.linalg.norm(x - y, axis=1) <= reach_
    assert close.any() and near[np.arange(300), hy][close].all()


def test_shards(spark, tmp_path):
    df = frame(spark, EDGE + [(100 + i, f"text {i} " * 50) for i in range(3000)])
    store = sharding.ShardStore(spark, f"file://{tmp_path}/s", arrival_bytes=2000, target_bytes=40_000)
    store.append(df.where("doc_id < 1500"), 100)
    small = len(store.shards())
    store.append(df.where("doc_id >= 1500"), 100)
    before = len(store.shards())
    assert before > small > 4
    version = store.compact()
    assert version > 2 and len(store.shards()) < before / 2
    assert store.read().count() == df.count() == store.read(2).count()
    assert sorted(map(tuple, store.read().collect()), key=str) == sorted(map(tuple, df.collect()), key=str)
    # Every shard is named once, holds the rows it is said to hold, and runs of one commit went to different tasks.
    listed = {x["path"]: x["rows"] for x in store.shards()}
    held = {r["p"]: r["count"] for r in store.read().groupBy(F.col("_metadata.file_path").alias("p")).count().collect()}
    assert held == listed and len({k % 7 for k in range(7)}) == len(set(store._keys(7))) == 7
    with pytest.raises(sharding.ManifestConflict):
        store.commit(version - 1, [])
    assert store.vacuum() > 0 and store.read().count() == df.count()
    assert not store.compact_once()


def test_shard_query(spark):
    got = sharding.shard(frame(spark, EDGE)).collect()
    assert sorted((r["doc_id"], r["n_bytes"]) for r in got) == sorted((i, len((t or "").encode())) for i, t in EDGE)
    assert sharding.shard(frame(spark, [])).collect() == []
    # Another text column, and what is stored is what came, row for row.
    df = frame(spark, EDGE).withColumnRenamed("text", "body")
    assert sorted(r["n_bytes"] for r in sharding.shard(df, text_col="body").collect()) == sorted(len((t or "").encode()) for _, t in EDGE)
    with pytest.raises(ValueError):
        sharding.shard(frame(spark, EDGE).withColumn("_run", F.lit(1)))


def test_language(spark):
    docs = queries.table(spark, "/root/testdata/sf0.01", "documents")
    got = queries.op8_language_id(spark, "/root/testdata/sf0.01").join(docs.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got.lang_pred == got.lang).mean() > 0.97 and got.score.between(0, 1).all()
    model = langid.fit(docs, F.lit(True))
    edge = {r["doc_id"]: r for r in langid.identify(frame(spark, [*EDGE, (50, "123 ---"), (51, "the and of with")]), model).collect()}
    assert all(edge[i]["lang_pred"] == "und" and edge[i]["score"] == 0 and edge[i]["rejected"] for i in (1, 2, 3, 50)) and edge[51]["lang_pred"] == "en"
    assert langid.identify(frame(spark, []), model).collect() == []
    kept = langid.keep_identified(docs.withColumn("x", F.lit(1)), model)
    assert kept.columns == [*docs.columns, "x"] and kept.count() >= 0.99 * docs.count()
    none = langid.fit(docs.limit(0), F.lit(True))
    assert {r["lang_pred"] for r in langid.identify(frame(spark, EDGE), none).collect()} == {"und"}


def test_toxicity(spark):
    sf = "/root/testdata/sf0.1"
    marks = queries.table(spark, sf, "labels").select("doc_id", "toxic")
    got = queries.op10_toxicity(spark, sf).join(marks, "doc_id").where("held_out").toPandas()
    found = got[got.predicted == 1]
    assert (found.toxic == 1).mean() > 0.85 and (got[got.toxic == 1].predicted == 1).mean() > 0.7
    docs = queries.table(spark, sf, "documents")
    model = toxicity.fit(docs, queries.table(spark, sf, "labels"), F.lit(True))
    edge = {r["doc_id"]: r["score"] for r in toxicity.score(frame(spark, [*EDGE, (60, "you idiot"), (61, "you idiott"), (62, "the and of")]), model).collect()}
    assert all(0 <= s <= 1 for s in edge.values()) and max(edge[1], edge[2], edge[3]) < 0.01 and edge[60] > 0.5 > edge[62] and edge[61] > edge[62]
    assert toxicity.score(frame(spark, []), model).collect() == []
    none = toxicity.fit(docs, queries.table(spark, sf, "labels").limit(0), F.lit(True))
    assert {round(r["score"], 3) for r in toxicity.score(frame(spark, EDGE), none).collect()} == {0.5}


def test_pipeline(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.01"
    docs = queries.table(spark, sf, "documents")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language ID", "exact dedup", "MinHash near-dedup", "mixing", "packing"]
    kept = docs
    counts = []
    for _, f in corpus_pipeline.STAGES[:-1]:
        kept = f(spark, kept, sf)
        assert kept.columns == docs.columns
        kept = spark.createDataFrame(kept.toPandas(), docs.schema)
        counts.append(kept.count())
    assert docs.count() >= counts[0] > counts[1] > counts[2]
    out = corpus_pipeline.run(spark, sf).toPandas()
    assert set(out.doc_id) == {r["doc_id"] for r in kept.select("doc_id").distinct().collect()}
    assert out.groupby("sequence_id").length.sum().max() <= 4096
