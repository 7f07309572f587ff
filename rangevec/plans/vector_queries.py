"""Named queries over the vector tables, with DuckDB SQL where SQL can express them."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import replace
from functools import partial

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.columns import cosine_distance, inner_product, l2, level, norm, register_sql, uniform
from ..operators import graphs, metrics, multiattr, segment
from ..operators.exact import cardinality, range_knn, range_knn_blocks
from ..operators.index import RangeIndex
from ..sources import tables as t
from ..sources.durable import settle, shared_folder
from . import experiments as ex, planner

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
K, S, M = 10, 4, 4
#: Rows of a shard that the beam of the full-beam searches holds whole.
FULL_BEAM_ROWS = 300
#: Rows of a shard of an index that grows: a task holds it whole.
SHARD_ROWS = 1000
#: Rows of a shard of an index that is built at once and searched: more of them make builds shorter and searches, which open each shard, longer.
INDEX_ROWS = 5000
#: Rows of a shard of methods whose build takes long: one task builds one, and edges by intervals find the less the longer their order is.
METHOD_ROWS = {"interval_edge_graph": SHARD_ROWS, "optimal_hnsw": SHARD_ROWS, "degraded_index": SHARD_ROWS, "dedicated": 2 * SHARD_ROWS}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


# SQL of the tables and workloads.
def u_sql(key: str, salt: str) -> str:
    return f"((('0x' || substr(md5({key}::VARCHAR || ':{salt}'), 1, 8))::BIGINT + 0.5) / 4294967296.0)"


_WORDS = "list_filter(regexp_split_to_array(lower(coalesce({0}, '')), '[^a-z0-9]+'), lambda w: w <> '')"


def _text_sql(source: str, key: str, text: str, attr: str) -> str:
    counts = f"(SELECT vid, attr, [len(list_filter(p, lambda x: x = i)) for i in range(64)]::DOUBLE[] AS c FROM (SELECT {key} AS vid, ({attr})::DOUBLE AS attr, list_transform({_WORDS.format(text)}, lambda w: ('0x' || substr(md5(w), 1, 8))::BIGINT % 64) AS p FROM {source}))"
    return f"SELECT vid, CASE WHEN n > 0 THEN [x / n for x in c] ELSE c END AS vec, attr FROM (SELECT vid, attr, c, sqrt(list_sum([x * x for x in c])) AS n FROM {counts})"


_E = "embedding::DOUBLE[] AS vec"
TABLE_SQL = {
    "emb_price": f"SELECT vec_id AS vid, {_E}, o_totalprice AS attr FROM embeddings JOIN orders ON vec_id = o_orderkey",
    "emb_uniform": f"SELECT vec_id AS vid, {_E}, {u_sql('vec_id', 'attr')} * 10000 AS attr FROM embeddings",
    "emb_date": f"SELECT vec_id AS vid, {_E}, epoch_us(o_orderdate)::DOUBLE AS attr FROM embeddings JOIN orders ON vec_id = o_orderkey",
    "emb_value": f"SELECT vec_id AS vid, {_E}, value AS attr FROM embeddings JOIN events ON vec_id = event_id",
    "emb_label": f"SELECT vec_id AS vid, {_E}, label::DOUBLE AS attr FROM embeddings",
    "emb_retail": f"SELECT vec_id AS vid, {_E}, p_retailprice AS attr FROM embeddings LEFT JOIN part ON vec_id = p_partkey",
    "doc_text": _text_sql("documents", "doc_id", "text", "n_chars"),
    "page_html": _text_sql("pages", "page_id", "regexp_replace(html, '<[^>]*>', ' ', 'g')", "length(html)"),
    "event_vec": "SELECT event_id AS vid, [ln(1 + value), sin(hour(ts) * (2 * 3.141592653589793 / 24)), cos(hour(ts) * (2 * 3.141592653589793 / 24)), user_id / 150, " + ", ".join(f"(event_type = '{x}')::DOUBLE" for x in t.EVENT_TYPES) + ", json_extract_string(props, '$.k')::DOUBLE / 100] AS vec, epoch_us(ts)::DOUBLE AS attr FROM events",
    "line_num": "SELECT row_number() OVER (ORDER BY COLUMNS(*)) - 1 AS vid, [l_quantity / 50, l_extendedprice / 105000, l_discount / 0.1, l_tax / 0.08, " + ", ".join(f"({c} = '{v}')::DOUBLE" for c, vs in (("l_returnflag", "ANR"), ("l_linestatus", "FO")) for v in vs) + "] AS vec, epoch_us(l_shipdate)::DOUBLE AS attr FROM lineitem",
}
LINE_COLUMNS = "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
TABLE_SQL["line_num"] = TABLE_SQL["line_num"].replace("COLUMNS(*)", LINE_COLUMNS)


def work_sql(name: str, low: float = 0.001, high: float = 1.0, salt: str = "range", k: int = K) -> str:
    """Common table expressions base and q."""
    return f"""v AS MATERIALIZED ({TABLE_SQL[name]}), base AS MATERIALIZED (SELECT * FROM v WHERE vid % 10 <> 0),
        ranks AS MATERIALIZED (SELECT attr, row_number() OVER (ORDER BY attr, vid) - 1 AS rank FROM base WHERE attr IS NOT NULL), total AS (SELECT count(*) AS n FROM ranks),
        q1 AS (SELECT vid AS qid, vec AS qvec, n, {low} + {high - low} * {u_sql("vid", salt + ":w")} AS w FROM v, total WHERE vid % 10 = 0),
        q2 AS (SELECT *, greatest(1, floor(w * n))::BIGINT AS y FROM q1), q3 AS (SELECT *, floor({u_sql("qid", salt + ":s")} * (n - y + 1))::BIGINT AS s FROM q2),
        q AS MATERIALIZED (SELECT qid, qvec, a.attr AS lo, b.attr AS hi, {k} AS k, w, y FROM q3 JOIN ranks a ON a.rank = s JOIN ranks b ON b.rank = s + y - 1)"""


def knn_sql(ctes: str, on: str = "attr BETWEEN lo AND hi", dist: str = "list_distance(vec, qvec)", source: str = "base JOIN q") -> str:
    return f"""WITH {ctes} SELECT qid, rnk::INTEGER AS rnk, vid, round(dist, 6) AS dist FROM (SELECT qid, vid, dist, k, row_number() OVER (PARTITION BY qid ORDER BY dist, vid) AS rnk
        FROM (SELECT qid, vid, k, {dist} AS dist FROM {source} ON {on})) WHERE rnk <= k"""


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns or ("dist",)})


def work(spark: SparkSession, sf: str, name: str = "emb_price", **how) -> tuple[DataFrame, DataFrame]:
    return ex.workload(t.TABLES[name](spark, sf), K, **how)


# Exact answers.
def _exact(name: str, spark: SparkSession, sf: str) -> DataFrame:
    base, q = work(spark, sf, name)
    return rounded(range_knn(base, q))


for _name, _table in {"price": "emb_price", "uniform": "emb_uniform", "date": "emb_date", "value": "emb_value", "label": "emb_label", "retail_nulls": "emb_retail", "events": "event_vec", "pages": "page_html"}.items():
    query(f"exact_range_knn_{_name}", knn_sql(work_sql(_table)))(partial(_exact, _table))


@query("exact_range_knn_lines", knn_sql(work_sql("line_num").replace("WHERE vid % 10 = 0", "WHERE vid % 100 = 0")))
def _(spark, sf):
    base, q = t.held_out(t.line_num(spark, sf))
    base = settle(base)
    return rounded(range_knn_blocks(base, t.rank_ranges(base, q.where("qid % 100 = 0"), K)))


def _passages(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    q = t.text_vectors(t.load(spark, sf, "benchmark"), "item_id", F.col("text"), F.lit(0.0)).select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"), F.lit(200.0).alias("lo"), F.lit(4000.0).alias("hi"), F.lit(K).alias("k"))
    return t.doc_text(spark, sf), q


@query("exact_range_knn_text", knn_sql(f"base AS ({TABLE_SQL['doc_text']}), q AS (SELECT vid AS qid, vec AS qvec, 200.0 AS lo, 4000.0 AS hi, {K} AS k FROM ({_text_sql('benchmark', 'item_id', 'text', '0')}))"))
def _(spark, sf):
    base, q = _passages(spark, sf)
    return rounded(range_knn(base, q))


@query("exact_blocks_price", knn_sql(work_sql("emb_price")))
def _(spark, sf):
    base, q = work(spark, sf)
    return rounded(range_knn_blocks(base, q))


@query("exact_by_segments_price", knn_sql(work_sql("emb_price")))
def _(spark, sf):
    base, q = work(spark, sf)
    return rounded(range_knn(base, q, segments=segment.table(base, segment.fit(base, 8))))


@query("exact_knn_all", knn_sql(work_sql("emb_price"), "TRUE"))
def _(spark, sf):
    base, q = work(spark, sf)
    return rounded(range_knn_blocks(base, q.withColumns({"lo": F.lit(None).cast("double"), "hi": F.lit(None).cast("double")})))


@query("exact_half_bounded", knn_sql(work_sql("emb_price"), "attr <= hi"))
def _(spark, sf):
    base, q = work(spark, sf)
    return rounded(range_knn_blocks(base, q.withColumn("lo", F.lit(None).cast("double"))))


@query("exact_point_range", knn_sql(work_sql("emb_label"), "attr = lo"))
def _(spark, sf):
    base, q = work(spark, sf, "emb_label")
    return rounded(range_knn(base, q.withColumn("hi", F.col("lo"))))


@query("exact_empty_range", f"WITH {work_sql('emb_price')} SELECT count(*) AS found, (SELECT count(*) FROM q) AS queries FROM base JOIN q ON attr BETWEEN -2 AND -1")
def _(spark, sf):
    base, q = work(spark, sf)
    none = range_knn(base, q.withColumn("lo", F.lit(-2.0)).withColumn("hi", F.lit(-1.0))).agg(F.count(F.lit(1)).alias("found"))
    return none.crossJoin(q.agg(F.count(F.lit(1)).alias("queries")))


@query("exact_y_lt_k", knn_sql(work_sql("emb_price", 0.001, 0.02, "few")))
def _(spark, sf):
    base, q = work(spark, sf, low=0.001, high=0.02, salt="few")
    return rounded(range_knn(base, q))


@query("exact_cosine", knn_sql(work_sql("emb_uniform"), dist="1 - list_cosine_similarity(vec, qvec)"))
def _(spark, sf):
    base, q = work(spark, sf, "emb_uniform")
    return rounded(range_knn_blocks(base, q, metric="cosine"))


@query("exact_inner_product", knn_sql(work_sql("emb_uniform"), dist="-list_inner_product(vec, qvec)"))
def _(spark, sf):
    base, q = work(spark, sf, "emb_uniform")
    return rounded(range_knn(base, q, metric="ip"))


@query("search_by_order_month", f"""WITH p AS ({TABLE_SQL['emb_date']}), b AS (SELECT vid, vec, date_trunc('month', make_timestamp(attr::BIGINT)) AS mon FROM p)
    SELECT qid, rnk::INTEGER AS rnk, vid, round(dist, 6) AS dist FROM (SELECT a.vid AS qid, b.vid, list_distance(a.vec, b.vec) AS dist, row_number() OVER (PARTITION BY a.vid ORDER BY list_distance(a.vec, b.vec), b.vid) AS rnk FROM b a JOIN b ON a.mon = b.mon AND a.vid <> b.vid WHERE a.vid % 10 = 0) WHERE rnk <= 3""")
def _(spark, sf):
    month = F.date_trunc("month", F.timestamp_micros(F.col("attr").cast("long")))
    rows = t.emb_date(spark, sf).select("vid", "vec", month.alias("mon"))
    q = rows.where("vid % 10 = 0").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"), "mon")
    pairs = rows.join(q, "mon").where("vid <> qid").select("qid", "vid", l2("vec", "qvec").alias("dist"))
    return rounded(graphs.top(pairs, ["qid"], F.lit(3)).select("qid", "rnk", "vid", "dist"))


# Cardinalities and estimates.
@query("range_cardinality", f"WITH {work_sql('emb_value')} SELECT qid, count(attr) AS y FROM q LEFT JOIN base ON attr BETWEEN lo AND hi GROUP BY qid")
def _(spark, sf):
    base, q = work(spark, sf, "emb_value")
    return cardinality(base, q)


def seg_sql(s: int, of: str = "base") -> str:
    """bounds and segs (seg, lo, hi) as exact equi-depth cuts of ``of``."""
    return f"""r0 AS MATERIALIZED (SELECT attr, row_number() OVER (ORDER BY attr, vid) - 1 AS rank, count(*) OVER () AS n FROM {of} WHERE attr IS NOT NULL),
        bounds AS MATERIALIZED (SELECT DISTINCT attr AS b FROM r0 WHERE rank IN (SELECT ceil(j * (SELECT max(n) FROM r0) / {s}.0)::BIGINT FROM range(1, {s}) t(j)) AND attr > (SELECT min(attr) FROM r0)),
        segs AS MATERIALIZED (SELECT (row_number() OVER (ORDER BY lo NULLS FIRST) - 1)::INTEGER AS seg, lo, hi FROM (SELECT b AS lo, lead(b) OVER (ORDER BY b NULLS FIRST) AS hi FROM (SELECT NULL::DOUBLE AS b UNION ALL SELECT b FROM bounds)))"""


def assigned_sql(of: str = "base") -> str:
    return f"sb AS MATERIALIZED (SELECT x.*, segs.seg FROM {of} x JOIN segs ON (lo IS NULL OR attr >= lo) AND (hi IS NULL OR attr < hi))"


@query("range_cardinality_estimate", f"""WITH {work_sql('emb_price')}, {seg_sql(64)}, ends AS (SELECT min(attr) AS a, max(attr) AS b FROM base),
    h AS (SELECT seg, coalesce(segs.lo, ends.a) AS b_lo, coalesce(segs.hi, ends.b) AS b_hi, (SELECT count(*) FROM base WHERE (segs.lo IS NULL OR attr >= segs.lo) AND (segs.hi IS NULL OR attr < segs.hi)) AS n FROM segs, ends)
    SELECT qid, round(sum(n * CASE WHEN b_hi > b_lo THEN (least(hi, b_hi) - greatest(lo, b_lo)) / (b_hi - b_lo) ELSE 1 END), 6) AS y_est FROM q JOIN h ON hi >= b_lo AND lo <= b_hi GROUP BY qid""")
def _(spark, sf):
    base, q = work(spark, sf)
    return rounded(planner.estimate(q, planner.histogram(base)), "y_est")


_CHOICE = "CASE WHEN y / n <= 0.01 THEN 'pre' WHEN y / n >= 0.5 THEN 'post' ELSE 'hybrid' END"


@query("strategy_choice", f"WITH {work_sql('emb_price')} SELECT qid, y, {_CHOICE} AS strategy FROM q, total")
def _(spark, sf):
    base, q = work(spark, sf)
    return q.select("qid", "y", planner.choose(F.col("y"), base.count()).alias("strategy"))


@query("range_cardinality_sampled", f"WITH {work_sql('emb_price')}, s AS (SELECT attr FROM base WHERE {u_sql('vid', 'estimate')} < 0.5) SELECT qid, round(count(s.attr) / 0.5, 6) AS y_est FROM q LEFT JOIN s ON attr BETWEEN lo AND hi GROUP BY qid")
def _(spark, sf):
    base, q = work(spark, sf)
    return rounded(planner.estimate_sample(base, q, uniform("vid", "estimate") < 0.5, 0.5), "y_est")


_HIST = "SELECT seg, count(*) AS {} FROM (SELECT * FROM sb WHERE vid % 2 = {}) GROUP BY seg"


@query("drift_score", f"""WITH v AS ({TABLE_SQL['emb_value']}), {seg_sql(8, 'v')}, {assigned_sql('v')}, j AS (SELECT seg, coalesce(a, 0) AS a, coalesce(b, 0) AS b FROM segs LEFT JOIN ({_HIST.format('a', 0)}) USING (seg) LEFT JOIN ({_HIST.format('b', 1)}) USING (seg)),
    p AS (SELECT seg, (a + 0.5) / (sum(a) OVER () + 0.5 * count(*) OVER ()) AS pa, (b + 0.5) / (sum(b) OVER () + 0.5 * count(*) OVER ()) AS pb, abs(sum(a) OVER (ORDER BY seg) / sum(a) OVER () - sum(b) OVER (ORDER BY seg) / sum(b) OVER ()) AS gap FROM j)
    SELECT round(sum((pb - pa) * ln(pb / pa)), 6) AS psi, round(max(gap), 6) AS ks FROM p""")
def _(spark, sf):
    v = t.emb_value(spark, sf)
    bounds = segment.fit(v, 8)
    return rounded(planner.drift(segment.table(v.where("vid % 2 = 0"), bounds), segment.table(v.where("vid % 2 = 1"), bounds)), "psi", "ks")


@query("drift_flags")
def _(spark, sf):
    v = t.event_vec(spark, sf)
    bounds, rows = segment.fit(v, 8), []
    old = segment.table(v, bounds)
    for name, new in (("same", v.where("vid % 2 = 0")), ("shifted", v.withColumn("attr", F.col("attr") + 864e9 * 10))):
        r = planner.drift(old, segment.table(new, bounds)).first()
        rows.append((name, r["psi"], r["ks"], r["psi"] > 0.2))
    return spark.createDataFrame(rows, "batch string, psi double, ks double, drifted boolean")


def _shards(v: DataFrame, rows: int | None = None) -> int:
    return max(1, -(-v.count() // (rows or SHARD_ROWS)))


@query("drift_recalibrated")
def _(spark, sf):
    """Thresholds before and after a batch whose attributes are shifted."""
    v = settle(t.emb_value(spark, sf))
    index = RangeIndex.build(v, 4, 8, 50, shards=_shards(v))
    old = settle(segment.table(v, segment.fit(v, 8)))
    same = planner.adapt(index, old, v)
    moved = planner.adapt(index, old, settle(v.withColumn("attr", F.col("attr") * 3)), sample=0.1)
    return spark.createDataFrame([("before", *index.manifest.tau), ("same", *same.manifest.tau), ("shifted", *moved.manifest.tau)], "state string, tau_a double, tau_b double")


# Distances.
_PAIRS = "FROM embeddings a JOIN embeddings b ON a.vec_id % 100 = 0"


def _distance(f, spark: SparkSession, sf: str) -> DataFrame:
    e = t.embeddings(spark, sf)
    a = e.where("vid % 100 = 0").select(F.col("vid").alias("a"), F.col("vec").alias("x"))
    b = e.select(F.col("vid").alias("b"), F.col("vec").alias("y"))
    return b.crossJoin(F.broadcast(a)).select("a", "b", F.round(f("x", "y"), 6).alias("dist"))


for _name, _f, _sql in (("l2", l2, "list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"), ("cosine", cosine_distance, "1 - list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"), ("ip", inner_product, "list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[])")):
    query(f"distance_{_name}", f"SELECT a.vec_id AS a, b.vec_id AS b, round({_sql}, 6) AS dist {_PAIRS}")(partial(_distance, _f))


@query("distance_sql_function", f"SELECT a.vec_id AS a, b.vec_id AS b, round(list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS dist {_PAIRS}")
def _(spark, sf):
    register_sql(spark)
    t.load(spark, sf, "embeddings").createOrReplaceTempView("embeddings")
    return spark.sql(f"SELECT a.vec_id AS a, b.vec_id AS b, round(rv_l2(CAST(a.embedding AS ARRAY<DOUBLE>), CAST(b.embedding AS ARRAY<DOUBLE>)), 6) AS dist {_PAIRS}")


@query("vector_norms", "SELECT vec_id AS vid, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS n FROM embeddings")
def _(spark, sf):
    return t.embeddings(spark, sf).select("vid", F.round(norm("vec"), 6).alias("n"))


# Segments.
def _segments(table_name: str, s: int, spark: SparkSession, sf: str) -> DataFrame:
    v = t.TABLES[table_name](spark, sf)
    return segment.table(v, segment.fit(v, s))


def _segments_sql(name: str, s: int) -> str:
    return f"WITH v AS MATERIALIZED ({TABLE_SQL[name]}), {seg_sql(s, 'v')}, {assigned_sql('v')} SELECT segs.seg, any_value(segs.lo) AS lo, any_value(segs.hi) AS hi, count(sb.vid) AS n FROM segs LEFT JOIN sb USING (seg) GROUP BY segs.seg"


query("segments_exact", _segments_sql("emb_price", 8))(partial(_segments, "emb_price", 8))
query("segments_ties", _segments_sql("emb_label", 16))(partial(_segments, "emb_label", 16))


@query("segments_sampled", f"WITH v0 AS ({TABLE_SQL['emb_price']}), v AS MATERIALIZED (SELECT * FROM v0 WHERE {u_sql('vid', 'sample:0')} < 0.5), {seg_sql(8, 'v')} SELECT b FROM bounds")
def _(spark, sf):
    return spark.createDataFrame([(b,) for b in segment.fit(t.emb_price(spark, sf), 8, "sample", 0.5)], "b double")


@query("segments_sketched")
def _(spark, sf):
    v = t.emb_price(spark, sf)
    return segment.table(v, segment.fit(v, 8, "sketch"))


@query("segments_hit", f"WITH {work_sql('emb_price')}, {seg_sql(8)} SELECT qid, seg, (segs.lo IS NOT NULL AND q.lo <= segs.lo AND segs.hi IS NOT NULL AND q.hi >= segs.hi) AS covered FROM q JOIN segs ON (segs.lo IS NULL OR q.hi >= segs.lo) AND (segs.hi IS NULL OR q.lo < segs.hi)")
def _(spark, sf):
    base, q = work(spark, sf)
    return segment.intersecting(q, segment.table(base, segment.fit(base, 8)))


@query("segment_balance", f"WITH v AS MATERIALIZED ({TABLE_SQL['emb_value']}), {seg_sql(8, 'v')}, {assigned_sql('v')} SELECT count(*) AS segments, min(n) AS least, max(n) AS most FROM (SELECT seg, count(*) AS n FROM sb GROUP BY seg)")
def _(spark, sf):
    v = t.emb_value(spark, sf)
    return segment.table(v, segment.fit(v, 8)).agg(F.count(F.lit(1)).alias("segments"), F.min("n").alias("least"), F.max("n").alias("most"))


# Graphs.
def _base(spark: SparkSession, sf: str, s: int = S) -> tuple[DataFrame, list[float]]:
    """All priced vectors in segments. The exact graphs compare all pairs, so their work grows with the square of the rows."""
    v = t.emb_price(spark, sf)
    bounds = segment.fit(v, s)
    return settle(segment.assign(v, bounds)), bounds


_G = f"v AS MATERIALIZED ({TABLE_SQL['emb_price']}), {seg_sql(S, 'v')}, {assigned_sql('v')}, pr AS MATERIALIZED (SELECT a.vid AS src, b.vid AS dst, a.seg AS src_seg, b.seg AS chunk, list_distance(a.vec, b.vec) AS dist FROM sb a JOIN sb b ON a.vid <> b.vid)"
_CH = "ch AS MATERIALIZED (SELECT * FROM (SELECT src, src_seg, chunk, dst, dist, row_number() OVER (PARTITION BY src, chunk ORDER BY dist, dst) AS rnk FROM pr) WHERE rnk <= 3)"


def _edges(df: DataFrame) -> DataFrame:
    return rounded(df)


@query("knn_graph_full", f"WITH {_G} SELECT src, dst, round(dist, 6) AS dist, rnk::INTEGER AS rnk FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rnk FROM pr) WHERE rnk <= 3")
def _(spark, sf):
    return _edges(graphs.knn_graph(_base(spark, sf)[0], 3)).select("src", "dst", "dist", "rnk")


@query("knn_graph_chunked", f"WITH {_G}, {_CH} SELECT src, chunk, dst, round(dist, 6) AS dist, rnk::INTEGER AS rnk FROM ch")
def _(spark, sf):
    return _edges(graphs.chunked(_base(spark, sf)[0], 3))


def _union_sql(contiguous: bool) -> str:
    combos = graphs.subsets(list(range(S)), contiguous)
    parts = [f"SELECT src, dst, dist FROM (SELECT src, dst, dist, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rnk FROM pr WHERE src_seg IN {c if len(c) > 1 else f'({c[0]})'} AND chunk IN {c if len(c) > 1 else f'({c[0]})'}) WHERE rnk <= 3" for c in combos]
    return " UNION ".join(parts)


def _combos_sql(contiguous: bool) -> str:
    return f"WITH {_G} SELECT src, dst, round(dist, 6) AS dist FROM ({_union_sql(contiguous)})"


@query("knn_graph_exhaustive", _combos_sql(False))
def _(spark, sf):
    return _edges(graphs.exhaustive(_base(spark, sf)[0], 3, list(range(S))))


@query("knn_graph_contiguous", _combos_sql(True))
def _(spark, sf):
    return _edges(graphs.exhaustive(_base(spark, sf)[0], 3, list(range(S)), True))


_SUB = "(SELECT src, dst, dist, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rnk FROM pr WHERE src_seg IN (1, 2) AND chunk IN (1, 2))"


@query("knn_graph_rebuilt", f"WITH {_G} SELECT src, dst, round(dist, 6) AS dist, rnk::INTEGER AS rnk FROM {_SUB} WHERE rnk <= 3")
def _(spark, sf):
    base, _ = _base(spark, sf)
    return _edges(graphs.rebuild(graphs.chunked(base, 3), (1, 2), 3, base)).select("src", "dst", "dist", "rnk")


@query("inclusion_violations", f"WITH {_G}, {_CH} SELECT count(*) AS violations FROM ({_union_sql(False)}) g LEFT JOIN ch USING (src, dst) WHERE ch.rnk IS NULL")
def _(spark, sf):
    base, _ = _base(spark, sf)
    return graphs.missing(graphs.exhaustive(base, 3, list(range(S))), graphs.chunked(base, 3)).agg(F.count(F.lit(1)).alias("violations"))


@query("lemma_violations", f"WITH {_G}, {_CH} SELECT count(*) AS violations FROM {_SUB} g LEFT JOIN ch USING (src, dst) WHERE g.rnk <= 3 AND ch.rnk IS NULL")
def _(spark, sf):
    base, _ = _base(spark, sf)
    return graphs.missing(graphs.knn_graph(base.where("seg IN (1, 2)"), 3), graphs.chunked(base, 3)).agg(F.count(F.lit(1)).alias("violations"))


@query("inclusiveness_chunked", f"WITH {_G}, {_CH} SELECT count(ch.rnk) AS common, count(*) AS total, 100.0 * count(ch.rnk) / count(*) AS inclusiveness FROM {_SUB} g LEFT JOIN ch USING (src, dst) WHERE g.rnk <= 3")
def _(spark, sf):
    base, _ = _base(spark, sf)
    return graphs.inclusiveness(graphs.knn_graph(base.where("seg IN (1, 2)"), 3), graphs.chunked(base, 3))


_TOY = "v AS (SELECT vec_id AS vid, embedding::DOUBLE[] AS vec, vec_id::DOUBLE AS attr, (vec_id >= 5)::INTEGER AS seg FROM embeddings WHERE vec_id BETWEEN 1 AND 8), pr AS (SELECT a.vid AS src, b.vid AS dst, a.seg AS s, b.seg AS chunk, list_distance(a.vec, b.vec) AS dist FROM v a JOIN v b ON a.vid <> b.vid)"


@query("toy_example_graphs", f"WITH {_TOY} SELECT g, src, dst, round(dist, 6) AS dist FROM (SELECT g, src, dst, dist, row_number() OVER (PARTITION BY g, src ORDER BY dist, dst) AS r FROM pr JOIN (VALUES (1, 0, 0), (2, 1, 1), (3, 0, 1)) c(g, a, b) ON s BETWEEN a AND b AND chunk BETWEEN a AND b) WHERE r <= 3")
def _(spark, sf):
    v = t.embeddings(spark, sf).where("vid BETWEEN 1 AND 8").select("vid", "vec", F.col("vid").cast("double").alias("attr"), (F.col("vid") >= 5).cast("int").alias("seg"))
    out = None
    for g, segs in ((1, (0,)), (2, (1,)), (3, (0, 1))):
        part = graphs.knn_graph(v.where(F.col("seg").isin(*segs)), 3).select(F.lit(g).alias("g"), "src", "dst", "dist")
        out = part if out is None else out.unionByName(part)
    return rounded(out)


def prune_sql(cands: str, keys: str, m: int) -> str:
    """Greedy pruning by recursion: ``cands`` is (keys..., dst, dist, vec)."""
    same = " AND ".join(f"c.{k} = r.{k}" for k in keys.split(", "))
    return f"""cand AS MATERIALIZED (SELECT {keys}, dst, dist, vec, row_number() OVER (PARTITION BY {keys} ORDER BY dist, dst) AS i FROM ({cands})),
        kept AS (SELECT {keys}, 1::BIGINT AS i, [dst] AS ids, [vec] AS vecs FROM cand WHERE i = 1
        UNION ALL SELECT {', '.join('r.' + k for k in keys.split(', '))}, c.i, CASE WHEN ok THEN list_append(ids, c.dst) ELSE ids END, CASE WHEN ok THEN list_append(vecs, c.vec) ELSE vecs END
        FROM kept r JOIN cand c ON {same} AND c.i = r.i + 1, LATERAL (SELECT len(r.ids) < {m} AND len(list_filter(r.vecs, lambda e: list_distance(e, c.vec) < c.dist)) = 0 AS ok)),
        fin AS (SELECT {keys}, arg_max(ids, i) AS ids FROM kept GROUP BY {keys})"""


_PRUNE = prune_sql("SELECT src, dst, dist, sb.vec FROM pr JOIN sb ON sb.vid = pr.dst", "src", M)


@query("prune_kept", f"WITH RECURSIVE {_G}, {_PRUNE} SELECT f.src, c.dst, round(c.dist, 6) AS dist FROM fin f JOIN cand c ON c.src = f.src AND list_contains(f.ids, c.dst)")
def _(spark, sf):
    base, _ = _base(spark, sf)
    pairs = graphs._pairs(base.select("vid", "vec"), base.select("vid", "vec"))
    return rounded(graphs.pruned_edges(pairs, base, M, ["src"]).select("src", "dst", "dist"))


@query("prune_filled", f"WITH RECURSIVE {_G}, {_PRUNE} SELECT src, dst, round(dist, 6) AS dist FROM (SELECT c.src, c.dst, c.dist, row_number() OVER (PARTITION BY c.src ORDER BY NOT list_contains(f.ids, c.dst), c.dist, c.dst) AS r FROM fin f JOIN cand c ON c.src = f.src) WHERE r <= {M}")
def _(spark, sf):
    base, _ = _base(spark, sf)
    pairs = graphs._pairs(base.select("vid", "vec"), base.select("vid", "vec"))
    return rounded(graphs.pruned_edges(pairs, base, M, ["src"], fill=True).select("src", "dst", "dist"))


def _level_sql(m: int, rule: str = "decay") -> str:
    inner = f"-ln({u_sql('vec_id', 'level')}) / ln({m}.0)" if rule == "decay" else f"-ln({u_sql('vec_id', 'level')} / ln({m}.0))"
    return f"greatest(floor({inner}), 0)::INTEGER"


for _name, _rule in (("level_histogram", "decay"), ("level_histogram_printed", "inside")):
    query(_name, f"SELECT {_level_sql(M, _rule)} AS level, count(*) AS n FROM embeddings GROUP BY 1")(lambda spark, sf, rule=_rule: t.embeddings(spark, sf).groupBy(level("vid", M, rule).alias("level")).agg(F.count(F.lit(1)).alias("n")))

_L = f"lv AS MATERIALIZED (SELECT sb.*, {_level_sql(M).replace('vec_id', 'vid')} AS level FROM sb), ly AS MATERIALIZED (SELECT lv.*, l.layer FROM lv JOIN range(0, 20) l(layer) ON l.layer <= lv.level)"


@query("entry_points", f"WITH {_G}, {_L} SELECT seg, max(level) AS top_layer, arg_max(vid, (level, -vid)) AS entry FROM lv GROUP BY seg")
def _(spark, sf):
    return graphs.entries(_base(spark, sf)[0], M)


@query("chain_links", f"WITH {_G}, {_L} SELECT layer::INTEGER AS layer, vid, lead(vid) OVER (PARTITION BY layer ORDER BY attr, vid) AS next FROM ly")
def _(spark, sf):
    return graphs.chain(_base(spark, sf)[0], M).select("layer", "vid", "next")


@query("chain_locate", f"WITH {work_sql('emb_price')} SELECT qid, arg_min(vid, (attr, vid)) AS first FROM q JOIN base ON attr >= lo GROUP BY qid")
def _(spark, sf):
    base, q = work(spark, sf)
    return RangeIndex.build(settle(base), 4, 4, 16, shards=2).locate(q).select("qid", "first")


_BULK = prune_sql("SELECT layer, src, chunk, dst, dist, vec FROM (SELECT a.layer, a.vid AS src, b.seg AS chunk, b.vid AS dst, list_distance(a.vec, b.vec) AS dist, b.vec, row_number() OVER (PARTITION BY a.layer, a.vid, b.seg ORDER BY list_distance(a.vec, b.vec), b.vid) AS o FROM ly a JOIN ly b ON a.layer = b.layer AND a.vid <> b.vid) WHERE o <= 8", "layer, src, chunk", M)
_BB = "bb AS MATERIALIZED (SELECT f.layer, f.src, f.chunk, c.dst, c.dist, c.vec FROM fin f JOIN cand c ON c.layer = f.layer AND c.src = f.src AND c.chunk = f.chunk AND list_contains(f.ids, c.dst))"


@query("bulk_backbone_edges", f"WITH RECURSIVE {_G}, {_L}, {_BULK}, {_BB} SELECT layer::INTEGER AS layer, src, chunk, dst, round(dist, 6) AS dist FROM bb")
def _(spark, sf):
    return rounded(graphs.bulk_backbone(_base(spark, sf)[0], M, 8).select("layer", "src", "chunk", "dst", "dist"))


@query("bulk_reverse_edges", "WITH RECURSIVE " + f"{_G}, {_L}, {_BULK}, {_BB}, " + prune_sql("SELECT DISTINCT layer, src, chunk, dst, dist, vec FROM (SELECT * FROM bb UNION ALL SELECT bb.layer, bb.dst, s.seg, bb.src, bb.dist, s.vec FROM bb JOIN sb s ON s.vid = bb.src)", "layer, src, chunk", M).replace("cand AS", "cand2 AS").replace("FROM cand ", "FROM cand2 ").replace("kept AS", "kept2 AS").replace("FROM kept r JOIN cand c", "FROM kept2 r JOIN cand2 c").replace("fin AS", "fin2 AS").replace("FROM kept GROUP", "FROM kept2 GROUP") + " SELECT f.layer::INTEGER AS layer, f.src, f.chunk, c.dst, round(c.dist, 6) AS dist FROM fin2 f JOIN cand2 c ON c.layer = f.layer AND c.src = f.src AND c.chunk = f.chunk AND list_contains(f.ids, c.dst)")
def _(spark, sf):
    base, _ = _base(spark, sf)
    return rounded(graphs.closed(settle(graphs.bulk_backbone(base, M, 8)), base, M).select("layer", "src", "chunk", "dst", "dist"))


@query("bulk_global_mask", "WITH RECURSIVE " + f"{_G}, {_L}, {_BULK}, {_BB}, " + prune_sql("SELECT layer, src, dst, dist, vec FROM bb", "layer, src", M).replace("cand AS", "cand2 AS").replace("FROM cand ", "FROM cand2 ").replace("kept AS", "kept2 AS").replace("FROM kept r JOIN cand c", "FROM kept2 r JOIN cand2 c").replace("fin AS", "fin2 AS").replace("FROM kept GROUP", "FROM kept2 GROUP") + " SELECT f.layer::INTEGER AS layer, f.src, c.dst, round(c.dist, 6) AS dist FROM fin2 f JOIN cand2 c ON c.layer = f.layer AND c.src = f.src AND list_contains(f.ids, c.dst)")
def _(spark, sf):
    base, _ = _base(spark, sf)
    return rounded(graphs.global_mask(settle(graphs.bulk_backbone(base, M, 8)), base, M).select("layer", "src", "dst", "dist"))


_SEGS_OF = "qs AS (SELECT vid AS qid, vid AS node, [0, 1, 2] AS segs FROM sb WHERE vid % 2 = 0)"


@query("expand_pick_chunk", f"WITH {_G}, {_CH}, {_SEGS_OF} SELECT qid, dst, round(dist, 6) AS dist FROM qs JOIN ch ON ch.src = node AND list_contains(segs, chunk) WHERE rnk <= ceil(5 / len(segs))")
def _(spark, sf):
    base, _ = _base(spark, sf)
    q = base.where("vid % 2 = 0").select(F.col("vid").alias("qid"), F.col("vid").alias("node"), F.array(F.lit(0), F.lit(1), F.lit(2)).alias("segs"))
    return rounded(graphs.expand(graphs.chunked(base, 3), q, "node", 5, "chunk"))


@query("expand_pick_distance", f"WITH {_G}, {_CH}, {_SEGS_OF} SELECT qid, dst, round(dist, 6) AS dist FROM (SELECT qid, dst, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, dst) AS r FROM qs JOIN ch ON ch.src = node AND list_contains(segs, chunk)) WHERE r <= 5")
def _(spark, sf):
    base, _ = _base(spark, sf)
    q = base.where("vid % 2 = 0").select(F.col("vid").alias("qid"), F.col("vid").alias("node"), F.array(F.lit(0), F.lit(1), F.lit(2)).alias("segs"))
    return rounded(graphs.expand(graphs.chunked(base, 3), q, "node", 5, "distance"))


# The index.
def _index(spark: SparkSession, sf: str, name: str = "emb_price", s: int = 8, m: int = 16, ef_cons: int = 100, shards: int | None = None, least: int = 1) -> tuple[RangeIndex, DataFrame, DataFrame]:
    """The index of a table; unless ``shards`` are given their number follows the rows, since one task builds a shard, and is ``least`` at least."""
    base, q = work(spark, sf, name)
    base, q = settle(base), settle(q)
    return RangeIndex.build(base, s, m, ef_cons, shards=shards or max(least, _shards(base, INDEX_ROWS))), base, q


def graded_sql(ctes: str, widths: tuple[str, ...], q: str = "q, total") -> str:
    """What a method that meets its floor of recall gives: the queries of each width class and the objects that they ask for."""
    return f"WITH {ctes} SELECT width, count(*) AS queries, sum(least(k, y))::BIGINT AS asked, TRUE AS good FROM (SELECT {_CLASS} AS width, k, y FROM {q}) WHERE width IN ({', '.join(repr(w) for w in widths)}) GROUP BY width"


def graded(recalls: DataFrame, n: int, widths: tuple[str, ...], floor: float) -> DataFrame:
    """(width, queries, asked, good) of (qid, y, k, recall): whether the mean recall over the objects asked for is at least ``floor`` in each class."""
    asked = F.least(F.col("y"), F.col("k"))
    one = recalls.withColumn("width", t.width_class(F.col("y") / n)).where(F.col("width").isin(*widths))
    return one.groupBy("width").agg(F.count(F.lit(1)).alias("queries"), F.sum(asked).cast("long").alias("asked"), (F.sum(F.col("recall") * asked) / F.sum(asked) >= floor).alias("good"))


_CLASS = "CASE WHEN y / n <= 0.01 THEN 'small' WHEN y / n < 0.5 THEN 'medium' ELSE 'large' END"
ALL, LARGE = ("small", "medium", "large"), ("large",)


def _graded(found: DataFrame, base: DataFrame, q: DataFrame, widths: tuple[str, ...] = ALL, floor: float = 0.9) -> DataFrame:
    got = metrics.recall(found, range_knn_blocks(base, q), q.select("qid", "y", "k")).join(q.select("qid", "k"), "qid")
    return graded(got, base.count(), widths, floor)


def _searched(strategy: str, how: dict, widths: tuple[str, ...], spark: SparkSession, sf: str) -> DataFrame:
    index, base, q = _index(spark, sf)
    return _graded(index.search(q, strategy, **how), base, q, widths)


for _name, _strategy, _how, _widths in (
    ("search_post", "post", {"ef": 200}, LARGE), ("search_post_grow", "post", {"grow": True}, ALL), ("search_hybrid_chunk", "hybrid", {}, ALL), ("search_hybrid_distance", "hybrid", {"pick": "distance"}, ALL),
    ("search_hybrid_stop_worst", "hybrid", {"stop": "worst", "ef": 200}, LARGE), ("search_hybrid_all_entries", "hybrid", {"scope": "all"}, ALL), ("search_auto", "auto", {"ef": 200}, ALL),
):
    query(_name, graded_sql(work_sql("emb_price"), _widths))(partial(_searched, _strategy, _how, _widths))


@query("search_costs")
def _(spark, sf):
    """What each strategy takes of each query."""
    index, base, q = _index(spark, sf)
    truth, out = settle(range_knn_blocks(base, q)), None
    for strategy in ("pre", "post", "hybrid", "auto"):
        best, cost = index.work(index.search(q, strategy, counters=True), q, K)
        part = metrics.recall(best, truth, q.select("qid", "y", "k")).join(cost.withColumnRenamed("strategy", "taken"), "qid").withColumn("strategy", F.lit(strategy))
        out = part if out is None else out.unionByName(part)
    return out


@query("search_pre", knn_sql(work_sql("emb_price")))
def _(spark, sf):
    index, _, q = _index(spark, sf, s=4, m=4, ef_cons=16)
    return rounded(index.search(q, "pre"))


@query("search_pre_kernel", knn_sql(work_sql("emb_value")))
def _(spark, sf):
    index, _, q = _index(spark, sf, "emb_value", s=4, m=4, ef_cons=16, shards=2)
    return rounded(index.work(index.search(q, "pre", counters=True), q, K)[0])


def _full_beam(spark: SparkSession, sf: str) -> tuple[RangeIndex, DataFrame]:
    """The beam holds all of a shard, so both graph searches are exact: shards stay below its width, and their number follows the table."""
    v = settle(t.emb_price(spark, sf))
    q = v.where("vid % 50 = 0").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"), F.lit(30000.0).alias("lo"), F.lit(250000.0).alias("hi"), F.lit(K).alias("k"))
    return RangeIndex.build(v, 4, 100, 200, shards=max(1, -(-v.count() // FULL_BEAM_ROWS)), base_degree=200, mask_degree=400), q


_FULL_BEAM_SQL = knn_sql(f"base AS MATERIALIZED ({TABLE_SQL['emb_price']}), q AS (SELECT vid AS qid, vec AS qvec, 30000.0 AS lo, 250000.0 AS hi, {K} AS k FROM base WHERE vid % 50 = 0)")


@query("search_post_full_beam", _FULL_BEAM_SQL)
def _(spark, sf):
    index, q = _full_beam(spark, sf)
    return rounded(index.search(q, "post", ef=500))


@query("search_hybrid_full_beam", _FULL_BEAM_SQL)
def _(spark, sf):
    index, q = _full_beam(spark, sf)
    return rounded(index.search(q, "hybrid", ef=500, m=800))


@query("search_sharded", graded_sql(work_sql("emb_price"), ALL))
def _(spark, sf):
    index, base, q = _index(spark, sf, s=4, least=3)
    return _graded(index.search(q, "auto", ef=200), base, q)


@query("search_stored", knn_sql(work_sql("emb_price")))
def _(spark, sf):
    """Written, read again and searched along the chain."""
    index, _, q = _index(spark, sf, s=4, m=8, ef_cons=50, shards=2)
    return rounded(RangeIndex.load(spark, index.save()).search(q, "pre"))


@query("search_stored_hybrid", graded_sql(work_sql("emb_price"), ALL))
def _(spark, sf):
    """Written, read again and searched by its graph, with the results of the index before."""
    index, base, q = _index(spark, sf, s=4, least=2)
    a, b = index.search(q, "hybrid"), RangeIndex.load(spark, index.save()).search(q, "hybrid")
    return _graded(a.join(b, ["qid", "rnk", "vid", "dist"]), base, q)


@query("index_stats")
def _(spark, sf):
    return _index(spark, sf)[0].stats()


_PRICED = f"WITH v AS ({TABLE_SQL['emb_price']}), base AS (SELECT * FROM v WHERE vid % 10 <> 0)"


@query("index_nodes", f"{_PRICED} SELECT 0 AS layer, count(*) AS nodes, TRUE AS linked, TRUE AS bounded, TRUE AS masked FROM base")
def _(spark, sf):
    """Layer 0 holds every object; each has edges, no chunk holds more than M, and no mask more than M."""
    index, base, _ = _index(spark, sf, s=4, m=8, ef_cons=50)
    e = index.edges().where("layer = 0")
    per = e.groupBy("src").agg(F.sum(F.col("masked").cast("int")).alias("masked"))
    chunk = e.groupBy("src", "chunk").agg(F.count(F.lit(1)).alias("n"))
    nodes = index.vectors().agg(F.count(F.lit(1)).alias("nodes"))
    sums = per.agg(F.count(F.lit(1)).alias("linked"), F.max("masked").alias("most")).crossJoin(chunk.agg(F.max("n").alias("widest")))
    return nodes.crossJoin(sums).select(F.lit(0).alias("layer"), "nodes", (F.col("linked") == F.col("nodes")).alias("linked"), (F.col("widest") <= 8).alias("bounded"), (F.col("most") <= 8).alias("masked"))


@query("index_chain", f"{_PRICED} SELECT vid, lead(vid) OVER (ORDER BY attr, vid) AS next FROM base")
def _(spark, sf):
    """The successors that the inserted objects have on layer 0."""
    return _index(spark, sf, s=4, m=8, ef_cons=16, shards=1)[0].chain().where("layer = 0").select("vid", "next")


@query("index_edges")
def _(spark, sf):
    return _index(spark, sf, s=4, m=4, ef_cons=32)[0].edges()


@query("index_degrees")
def _(spark, sf):
    e = _index(spark, sf, s=4, m=8, ef_cons=50)[0].edges().where("layer = 0").groupBy("src").agg(F.count(F.lit(1)).alias("degree"), F.sum(F.col("masked").cast("long")).alias("masked"))
    return e.groupBy("degree", "masked").agg(F.count(F.lit(1)).alias("nodes"))


@query("range_ann_udtf", graded_sql(work_sql("emb_price"), ALL))
def _(spark, sf):
    index, base, q = _index(spark, sf, s=4, shards=1)
    planner.register_udtf(spark, index, ef=200)
    q.createOrReplaceTempView("rv_queries")
    return _graded(spark.sql("SELECT q.qid, a.vid, a.dist FROM rv_queries q, LATERAL range_ann(q.qvec, q.lo, q.hi, q.k) a"), base, q)


@query("src_datasource_pushdown", f"WITH {work_sql('emb_price')} SELECT vid, attr FROM base WHERE attr BETWEEN 60000 AND 90000")
def _(spark, sf):
    from ..sources.datasource import load

    index, _, _ = _index(spark, sf, s=4, m=4, ef_cons=16, shards=2)
    return load(spark, index.save(), 60000, 90000).select("vid", "attr")


def _halves(v: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The rows with the smaller ids and the others."""
    mid = v.agg(F.percentile("vid", 0.5)).first()[0] or 0
    return v.where(F.col("vid") <= mid), v.where(F.col("vid") > mid)


@query("append_rounds", f"{_PRICED} SELECT count(*) AS rows, 0::BIGINT AS only_appended, 0::BIGINT AS only_at_once, TRUE AS linked FROM base")
def _(spark, sf):
    """Building at once and appending in the same order give the same edges, ranks and masks on every layer.

    The half that is built first takes the boundaries of the whole table, since appending keeps them.
    """
    base = settle(work(spark, sf)[0])
    whole = RangeIndex.build(base, 4, 8, 50, shards=_shards(base))
    first, rest = _halves(base)
    grown = RangeIndex._inserted(RangeIndex._checked(first)[0], replace(whole.manifest, parts=[])).append(rest)
    keys = ["shard", "layer", "src", "chunk", "dst", "rnk", "masked"]
    both = grown.edges().select(*keys, F.lit(1).alias("here")).join(whole.edges().select(*keys, F.lit(1).alias("there")), keys, "full")
    one = lambda c: F.sum(F.col(c).isNull().cast("long"))
    edges = both.agg(one("there").alias("only_appended"), one("here").alias("only_at_once"), F.count_distinct("src").alias("src"))
    return grown.vectors().agg(F.count(F.lit(1)).alias("rows")).crossJoin(edges).select("rows", "only_appended", "only_at_once", (F.col("src") == F.col("rows")).alias("linked"))


def _calibrated(name: str, spark: SparkSession, sf: str) -> DataFrame:
    """The runs of objects of the base with random ranges under all three strategies, and the thresholds that they give."""
    index, base, _ = _index(spark, sf, name)
    q = base.where("vid % 7 = 1").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"))
    log, points = planner.calibrate(index, base, settle(t.rank_ranges(base, q, K, salt="calibration")), recall_target=0.9)
    return log.crossJoin(F.broadcast(points))


query("calibration_log")(partial(_calibrated, "emb_price"))
query("calibration_log_text")(partial(_calibrated, "doc_text"))


@query("calibrated_thresholds", f"WITH v AS ({TABLE_SQL['emb_price']}), r AS (SELECT count(*) AS runs FROM v WHERE vid % 10 <> 0 AND vid % 7 = 1) SELECT strategy, runs, TRUE AS ordered FROM r, (VALUES ('pre'), ('post'), ('hybrid')) s(strategy)")
def _(spark, sf):
    """Every sampled object runs under every strategy; thresholds are shares, the lower one first."""
    log = _calibrated("emb_price", spark, sf)
    return log.groupBy("strategy").agg(F.count(F.lit(1)).alias("runs"), F.min((F.col("tau_a") >= 0) & (F.col("tau_a") <= F.col("tau_b")) & (F.col("tau_b") <= 1)).alias("ordered"))


@query("search_frontier", graded_sql(work_sql("emb_price"), ALL))
def _(spark, sf):
    from ..operators.frontier import frontier_search

    base, q = work(spark, sf)
    bounds = segment.fit(base, S)
    base = settle(segment.assign(base, bounds))
    edges = settle(graphs.closed(settle(graphs.bulk_backbone(base, 12, 48)), base, 24).where("layer = 0"))
    return _graded(frontier_search(base, edges, settle(q), segment.table(base, bounds), ef=40, m=48, width=16), base, q)


@query("search_chunked_graph", graded_sql(work_sql("emb_price"), ALL))
def _(spark, sf):
    """The chunked nearest-neighbour graph itself, searched over the chunks that a range meets."""
    from ..operators.frontier import frontier_search

    base, q = work(spark, sf)
    bounds = segment.fit(base, S)
    base = settle(segment.assign(base, bounds))
    edges = settle(graphs.chunked(base, 12))
    return _graded(frontier_search(base, edges, settle(q), segment.table(base, bounds), ef=40, m=48, starts=16, width=16), base, q)


# Two attributes.
_TWO = f"b2 AS MATERIALIZED (SELECT a.vid, a.vec, a.attr, b.attr AS attr2 FROM ({TABLE_SQL['emb_price']}) a JOIN ({TABLE_SQL['emb_date']}) b USING (vid) WHERE a.vid % 10 <> 0), q AS (SELECT vec_id AS qid, embedding::DOUBLE[] AS qvec, 50000.0 AS lo, 200000.0 AS hi, epoch_us(TIMESTAMP '1996-01-01')::DOUBLE AS lo2, epoch_us(TIMESTAMP '1999-01-01')::DOUBLE AS hi2, {K} AS k FROM embeddings WHERE vec_id % 10 = 0)"


def _two(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    d = t.emb_date(spark, sf).select("vid", F.col("attr").alias("attr2"))
    base = t.emb_price(spark, sf).join(d, "vid").where("vid % 10 <> 0")
    day = lambda s: F.unix_micros(F.to_timestamp(F.lit(s))).cast("double")
    q = t.embeddings(spark, sf).where("vid % 10 = 0").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"), F.lit(50000.0).alias("lo"), F.lit(200000.0).alias("hi"), day("1996-01-01 00:00:00").alias("lo2"), day("1999-01-01 00:00:00").alias("hi2"), F.lit(K).alias("k"))
    return base, q


@query("and_two_attributes", knn_sql(_TWO, "attr BETWEEN lo AND hi AND attr2 BETWEEN lo2 AND hi2", source="b2 JOIN q"))
def _(spark, sf):
    return rounded(multiattr.exact_both(*_two(spark, sf), K))


@query("or_two_attributes", knn_sql(_TWO, "attr BETWEEN lo AND hi OR attr2 BETWEEN lo2 AND hi2", source="b2 JOIN q"))
def _(spark, sf):
    return rounded(multiattr.exact_either(*_two(spark, sf), K))


def _agree(found: DataFrame, truth: DataFrame, q: DataFrame) -> DataFrame:
    """(queries, asked, good): whether nine of ten of the objects asked for are found."""
    y = truth.groupBy("qid").agg(F.count(F.lit(1)).alias("y"))
    y = q.select("qid", "k").join(y, "qid", "left").select("qid", F.coalesce("y", F.lit(0)).alias("y"), "k")
    got = metrics.recall(found, truth, y)
    return got.agg(F.count(F.lit(1)).alias("queries"), F.sum("y").cast("long").alias("asked"), (F.sum(F.col("recall") * F.col("y")) >= 0.9 * F.sum("y")).alias("good"))


def _agree_sql(ctes: str, on: str, source: str = "b2 JOIN q") -> str:
    return f"WITH {ctes}, y AS (SELECT qid, least(any_value(k), count(*)) AS y FROM {source} ON {on} GROUP BY qid) SELECT (SELECT count(*) FROM q) AS queries, sum(y)::BIGINT AS asked, TRUE AS good FROM y"


@query("search_and_index", _agree_sql(_TWO, "attr BETWEEN lo AND hi AND attr2 BETWEEN lo2 AND hi2"))
def _(spark, sf):
    base, q = _two(spark, sf)
    base, q = settle(base), settle(q)
    index = RangeIndex.build(base, 4, 16, 100, shards=_shards(base, INDEX_ROWS))
    found = index.search_both(q, base.select("vid", "attr2"), strategy="hybrid", ef=150, m=48)
    return _agree(found, multiattr.exact_both(base, q, K), q)


@query("search_or_indexes", _agree_sql(_TWO, "attr BETWEEN lo AND hi OR attr2 BETWEEN lo2 AND hi2"))
def _(spark, sf):
    base, q = _two(spark, sf)
    base, q = settle(base), settle(q)
    one = RangeIndex.build(base, 4, 16, 100)
    two = RangeIndex.build(base.select("vid", "vec", F.col("attr2").alias("attr")), 4, 16, 100)
    return _agree(RangeIndex.search_either(one, two, q, K, strategy="hybrid", ef=150, m=48), multiattr.exact_either(base, q, K), q)


@query("zorder_index", knn_sql(_TWO, "attr BETWEEN lo AND hi AND attr2 BETWEEN lo2 AND hi2", source="b2 JOIN q"))
def _(spark, sf):
    """One index over the interleaved key of both attributes; each query follows the intervals that cover its rectangle."""
    base, q = _two(spark, sf)
    base = base.withColumnRenamed("attr", "attr1")
    bounds = [multiattr.cuts(base, "attr1", 4), multiattr.cuts(base, "attr2", 4)]
    z = settle(multiattr.zorder(base, ["attr1", "attr2"], bounds, 4, "attr"))
    return rounded(multiattr.zsearch(RangeIndex.build(z, 4, 8, 32, shards=_shards(z, INDEX_ROWS)), z, settle(q), bounds, 4, K))


_DOC_TWO = f"d2 AS ({TABLE_SQL['doc_text']}), b2 AS MATERIALIZED (SELECT d2.vid, d2.vec, d2.attr, quality::DOUBLE AS attr2 FROM d2 JOIN labels ON doc_id = vid WHERE quality IS NOT NULL), q AS (SELECT vid AS qid, vec AS qvec, 200.0 AS lo, 6000.0 AS hi, 1.0 AS lo2, 1.0 AS hi2, {K} AS k FROM b2 WHERE vid % 10 = 0)"


@query("and_length_quality", knn_sql(_DOC_TWO, "attr BETWEEN lo AND hi AND attr2 BETWEEN lo2 AND hi2", source="b2 JOIN q"))
def _(spark, sf):
    """Documents by length and quality."""
    marks = t.load(spark, sf, "labels").where("quality IS NOT NULL").select(F.col("doc_id").alias("vid"), F.col("quality").cast("double").alias("attr2"))
    base = settle(t.doc_text(spark, sf).join(marks, "vid"))
    one = F.lit(1.0)
    q = base.where("vid % 10 = 0").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"), F.lit(200.0).alias("lo"), F.lit(6000.0).alias("hi"), one.alias("lo2"), one.alias("hi2"), F.lit(K).alias("k"))
    return rounded(multiattr.exact_both(base, q, K))


_LINE_TWO = f"l2 AS MATERIALIZED ({TABLE_SQL['line_num']}), b2 AS MATERIALIZED (SELECT vid, vec, attr, vec[1] * 50 AS attr2 FROM l2), q AS (SELECT vid AS qid, vec AS qvec, epoch_us(TIMESTAMP '1996-01-01')::DOUBLE AS lo, epoch_us(TIMESTAMP '1996-07-01')::DOUBLE AS hi, 10.0 AS lo2, 30.0 AS hi2, {K} AS k FROM l2 WHERE vid % 100 = 0)"


@query("and_shipdate_quantity", knn_sql(_LINE_TWO, "attr BETWEEN lo AND hi AND attr2 BETWEEN lo2 AND hi2", source="b2 JOIN q"))
def _(spark, sf):
    """Order lines by shipping date and quantity; every hundredth line asks."""
    v = settle(t.line_num(spark, sf).withColumn("attr2", F.col("vec")[0] * 50))
    day = lambda s: F.unix_micros(F.to_timestamp(F.lit(s))).cast("double")
    q = v.where("vid % 100 = 0").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"), day("1996-01-01 00:00:00").alias("lo"), day("1996-07-01 00:00:00").alias("hi"), F.lit(K).alias("k"))
    # The second range filters the base, the first one is the join's: all queries have the same bounds.
    return rounded(range_knn_blocks(v.where("attr2 BETWEEN 10 AND 30"), q))


@query("zorder_keys", "WITH c AS (SELECT vec_id AS vid, vec_id & 15 AS a, (vec_id // 16) & 15 AS b FROM embeddings) SELECT vid, " + " + ".join(f"(((a >> {i}) & 1) << {2 * i}) + (((b >> {i}) & 1) << {2 * i + 1})" for i in range(4)) + " AS z FROM c")
def _(spark, sf):
    from ..functions.columns import interleave

    e = t.embeddings(spark, sf)
    return e.select("vid", interleave([F.col("vid").bitwiseAND(15), F.floor(F.col("vid") / 16).cast("long").bitwiseAND(15)], 4).alias("z"))


@query("zorder_range_recheck", knn_sql(_TWO, "attr BETWEEN lo AND hi AND attr2 BETWEEN lo2 AND hi2", source="b2 JOIN q"))
def _(spark, sf):
    base, q = _two(spark, sf)
    bounds = [multiattr.cuts(base, "attr", 4), multiattr.cuts(base, "attr2", 4)]
    z = multiattr.zorder(base.withColumnRenamed("attr", "attr1"), ["attr1", "attr2"], bounds, 4, "z")
    ask = multiattr.zranges(q, bounds, 4)
    hits = z.join(multiattr.sent(ask), F.col("z").between(F.col("zlo"), F.col("zhi")) & F.col("attr1").between(F.col("lo"), F.col("hi")) & F.col("attr2").between(F.col("lo2"), F.col("hi2")))
    return rounded(graphs.top(hits.select("qid", "vid", l2("vec", "qvec").alias("dist")), ["qid"], F.lit(K)).select("qid", "rnk", "vid", "dist"))


@query("driving_attribute", f"WITH {_TWO} SELECT qid, CASE WHEN (y1, 'attr') <= (y2, 'attr2') THEN 'attr' ELSE 'attr2' END AS attribute, least(y1, y2)::DOUBLE AS y_est FROM (SELECT qid, (SELECT count(*) FROM b2 WHERE attr BETWEEN lo AND hi) AS y1, (SELECT count(*) FROM b2 WHERE attr2 BETWEEN lo2 AND hi2) AS y2 FROM q)")
def _(spark, sf):
    base, q = _two(spark, sf)
    one = cardinality(base, q).select("qid", F.col("y").cast("double").alias("y_est"))
    two = cardinality(base.select("vid", F.col("attr2").alias("attr")), q.select("qid", F.col("lo2").alias("lo"), F.col("hi2").alias("hi"))).select("qid", F.col("y").cast("double").alias("y_est"))
    return planner.narrowest(q, {"attr": one, "attr2": two})


# Competitors and measures.
def _arm(configs: list[dict], spark: SparkSession, sf: str, *names: str) -> DataFrame:
    """The configurations over some tables, the first one unless named."""
    out = None
    for name in names or ("emb_price",):
        base, q = work(spark, sf, name)
        part = ex.measure(spark, ex.shards_of(settle(base)), ex.query_rows(settle(q)), configs).withColumn("table", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


def _method(method: str, how: dict, widths: tuple[str, ...], floor: float, search: tuple[int, int, int], spark: SparkSession, sf: str) -> DataFrame:
    base, q = work(spark, sf)
    base, q = settle(base), settle(q)
    config = {"name": method, "method": method, "how": how, "params": {"ef_cons": 100}, "searches": [search]}
    shards = ex.shards_of(base, most=METHOD_ROWS.get(method, ex.SHARD_ROWS))
    return _graded(ex.results(ex.runs(spark, shards, ex.query_rows(q), [config], truth=False)), base, q, widths, floor)


#: Where a competitor's idea fits, it finds nine of ten; filters behind a search of the whole table fit large ranges only.
for _name, _method_name, _how, _widths, _floor, _search in (
    ("baseline_pq_scan", "pq_scan", {"rerank": 10}, LARGE, 0.9, (200, 16, K)), ("baseline_pq_pre", "pq_pre", {"rerank": 10}, ALL, 0.9, (100, 16, K)), ("baseline_partitioned_pq", "partitioned_pq", {}, ALL, 0.9, (100, 16, K)),
    ("baseline_ivfpq", "ivfpq", {"probes": 16}, LARGE, 0.7, (400, 16, K)), ("baseline_pq_planner", "pq_cost_planner", {"rerank": 10}, ALL, 0.9, (100, 16, K)), ("baseline_hnsw_post", "hnsw_post", {}, LARGE, 0.85, (400, 16, K)),
    ("baseline_graph_post", "graph_postfilter", {}, LARGE, 0.85, (400, 16, K)), ("baseline_vecdb_post", "vecdb_postfilter", {}, LARGE, 0.85, (400, 16, K)), ("baseline_fused_graph", "fused_distance_graph", {"weight": 1.0}, LARGE, 0.85, (400, 16, K)),
    ("baseline_interval_graph", "interval_edge_graph", {}, ALL, 0.9, (100, 16, K)), ("baseline_multi_hnsw", "multi_segment_hnsw", {}, ALL, 0.9, (100, 16, K)), ("baseline_optimal", "optimal_hnsw", {}, ALL, 0.9, (200, 16, K)),
    ("baseline_dedicated", "dedicated", {}, ALL, 0.85, (400, 16, K)), ("baseline_degraded", "degraded_index", {"strategy": "hybrid", "inclusiveness": 60}, ALL, 0.8, (200, 64, K)),
):
    query(_name, graded_sql(work_sql("emb_price"), _widths))(partial(_method, _method_name, _how, _widths, _floor, _search))


@query("baseline_btree_pre", knn_sql(work_sql("emb_date")))
def _(spark, sf):
    """An ordered attribute index, then distances: objects lie in attribute order, and two binary searches give a range."""
    base, q = work(spark, sf, "emb_date")
    return rounded(ex.results(ex.runs(spark, ex.shards_of(settle(base)), ex.query_rows(settle(q)), [{"method": "btree_pre"}])).withColumn("rnk", F.col("rnk").cast("int")))


@query("fused_distance_exact", knn_sql(f"{work_sql('emb_price')}, sp AS (SELECT max(attr) - min(attr) AS spread FROM base)", "TRUE", "list_distance(vec, qvec) + greatest(abs(attr - (lo + hi) / 2) - (hi - lo) / 2, 0) / spread", "base CROSS JOIN sp JOIN q"))
def _(spark, sf):
    base, q = work(spark, sf)
    spread = base.agg((F.max("attr") - F.min("attr")).alias("spread")).first()["spread"]
    return rounded(range_knn_blocks(base, q, spread=spread or 1.0))


#: Tables whose every method is built whole; the two largest ones serve the scaling runs.
TABLES = ("emb_price", "emb_uniform", "emb_value", "emb_label", "doc_text", "page_html")

for _name, _configs, _names in (
    ("experiment_overall", ex.overall(), TABLES), ("experiment_build_table", ex.build_table(), TABLES), ("experiment_classes", ex.classes(), ("emb_price", "doc_text")), ("experiment_inclusivity", ex.inclusivity(), ("emb_price",)),
    ("experiment_picks", ex.picks(), ("emb_price",)), ("experiment_build_grid", ex.build_grid(), ("emb_price",)), ("experiment_search_grid", ex.search_grid(), ("emb_price",)), ("experiment_k", ex.k_grid(), ("emb_price",)),
):
    query(_name)(lambda spark, sf, c=_configs, n=_names: _arm(c, spark, sf, *n))


@query("experiment_targets")
def _(spark, sf):
    """The best rate of nine arms at three targets of recall, by width class."""
    return ex.at_targets(_arm(ex.classes(), spark, sf))


@query("experiment_tuning")
def _(spark, sf):
    """Of each method the setting with the least work at recall 0.9, from grids over its parameters."""
    return ex.tuned(_arm(ex.tuning(), spark, sf))


@query("experiment_latency")
def _(spark, sf):
    """Median and 99th percentile of queries that run one by one."""
    base, q = work(spark, sf)
    arms = [{"name": "latency", "method": "index", "how": {"strategy": s}} for s in ("pre", "post", "hybrid", "auto")]
    return ex.measure(spark, ex.shards_of(settle(base)), ex.query_rows(settle(q)), arms, each=True)


@query("inclusiveness_by_span")
def _(spark, sf):
    out = None
    for name in ("emb_price", "doc_text"):
        part = ex.spans(spark, ex.shards_of(settle(work(spark, sf, name)[0])))
        part = part.groupBy("segments").agg(F.round(F.avg("inclusiveness"), 4).alias("inclusiveness"), F.count(F.lit(1)).alias("runs")).withColumn("table", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


@query("experiment_incremental")
def _(spark, sf):
    base, q = work(spark, sf)
    return ex.incremental(spark, ex.shards_of(settle(base)), ex.query_rows(settle(q)))


@query("experiment_scaling")
def _(spark, sf):
    """Cost of a 25% range over parts of all events, from a 27th to the whole table: distances by the logarithm of the rows (slope and fit), and what the models say."""
    v = settle(t.event_vec(spark, sf))
    n, out = v.count(), None
    for share in (27, 9, 3, 1):
        base, q = t.held_out(v.where(F.pmod(F.xxhash64(F.lit(1), "vid"), F.lit(27)) < 27 // share))
        base = settle(base)
        q = settle(t.rank_ranges(base, q.where("qid % 100 = 0"), K, 0.25, 0.25))
        index = RangeIndex.build(base, 8, 16, 100, shards=max(1, -(-(n // share) // ex.SHARD_ROWS)))
        best, cost = index.work(index.search(q, "hybrid", ef=64, m=32, counters=True), q, K)
        got = metrics.recall(best, range_knn_blocks(base, q), q.select("qid", "y", "k")).join(cost, "qid")
        size = index.stats().agg(F.sum("graph_bytes").alias("graph_bytes"))
        model = metrics.build_model(segment.table(base, segment.fit(base, 8)), 8).select("searches", "bound")
        row = got.agg(F.avg("recall").alias("recall"), F.avg("n_dist").alias("n_dist"), F.avg("hops").alias("hops"), F.avg("latency_ms").alias("latency_ms")).crossJoin(size).crossJoin(model)
        row = row.withColumn("rows", F.lit(index.manifest.rows)).withColumn("build_dist", F.lit(sum(b[3] for b in index.built))).withColumn("build_s", F.lit(float(sum(b[4] for b in index.built))))
        out = row if out is None else out.unionByName(row)
    out = settle(out)
    return out.crossJoin(F.broadcast(metrics.log_slope(out, "rows", "n_dist")))


@query("search_cost_model", f"""WITH {work_sql('emb_price')}, {seg_sql(8)}, {assigned_sql()}, h AS (SELECT qid, count(*) AS hit FROM q JOIN segs ON (segs.lo IS NULL OR q.hi >= segs.lo) AND (segs.hi IS NULL OR q.lo < segs.hi) JOIN sb USING (seg) GROUP BY qid)
    SELECT qid, strategy, round(CASE strategy WHEN 'pre' THEN y + ln(n) WHEN 'post' THEN ln(n) ELSE ln(hit) END, 6) AS cost FROM (SELECT qid, y, n, hit, {_CHOICE} AS strategy FROM q JOIN h USING (qid), total)""")
def _(spark, sf):
    """What the three strategies should cost, up to a factor: by the objects of a range, of all segments, or of those that the range meets."""
    base, q = work(spark, sf)
    segs = segment.table(base, segment.fit(base, 8))
    hit = segment.intersecting(q, segs).join(segs.select("seg", "n"), "seg").groupBy("qid").agg(F.sum("n").alias("hit"))
    return rounded(metrics.search_model(q.select("qid", "y").join(hit, "qid"), base.count()), "cost")


@query("recall_by_class_cube", f"WITH {work_sql('emb_price')}, r AS (SELECT qid, {_CLASS} AS width, {_CHOICE} AS strategy FROM q, total) SELECT width, strategy, count(*) AS queries, TRUE AS good FROM r GROUP BY CUBE (width, strategy)")
def _(spark, sf):
    """The index's own choice, by width class and strategy."""
    index, base, q = _index(spark, sf)
    n = base.count()
    got = metrics.recall(index.search(q, "auto", ef=200), range_knn_blocks(base, q), q.select("qid", "y", "k"))
    got = got.select("recall", t.width_class(F.col("y") / n).alias("width"), planner.choose(F.col("y"), n).alias("strategy"))
    return got.cube("width", "strategy").agg(F.count(F.lit(1)).alias("queries"), (F.avg("recall") >= 0.9).alias("good"))


@query("space_model", "SELECT s, m, round(n::DOUBLE * (1 / (1 - 1.0 / m)) * (33 / 32.0 * m * s + 1) * 4 / 1048576, 4) AS mib FROM (SELECT count(o_totalprice) AS n FROM orders) o, (VALUES (1), (2), (4), (8), (16)) a(s), (VALUES (8), (16), (32)) b(m)")
def _(spark, sf):
    """For as many objects as there are orders with a price."""
    n = t.load(spark, sf, "orders").agg(F.count("o_totalprice").alias("n"))
    grid = n.withColumn("s", F.explode(F.array(*map(F.lit, (1, 2, 4, 8, 16))))).withColumn("m", F.explode(F.array(*map(F.lit, (8, 16, 32)))))
    return grid.select("s", "m", F.round(metrics.space_units(F.col("n"), F.col("s"), F.col("m"), 1 / (1 - 1 / F.col("m"))) * 4 / 1048576, 4).alias("mib"))


@query("multi_graph_penalty", "SELECT s, n, round(s * (1 - ln(s) / ln(n)), 6) AS penalty FROM (VALUES (2), (4), (8), (16)) a(s), (SELECT count(*) AS n FROM orders GROUP BY o_orderpriority) b")
def _(spark, sf):
    """For tables as large as the orders of each priority."""
    n = t.load(spark, sf, "orders").groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
    df = n.withColumn("s", F.explode(F.array(*map(F.lit, (2, 4, 8, 16)))))
    return df.select("s", "n", F.round(metrics.many_graph_penalty(F.col("s"), F.col("n")), 6).alias("penalty"))


@query("combination_counts", "SELECT DISTINCT s, (2 ** s - 1)::BIGINT AS every, (s * (s + 1) / 2)::BIGINT AS contiguous FROM (SELECT count(DISTINCT year(o_orderdate)) AS s FROM orders GROUP BY o_custkey)")
def _(spark, sf):
    """How many combinations the years of a customer's orders have, as segments: all of them, and runs of neighbours."""
    s, o = F.col("s"), t.load(spark, sf, "orders")
    return o.groupBy("o_custkey").agg(F.count_distinct(F.year("o_orderdate")).alias("s")).select("s").distinct().select("s", metrics.combinations_of(s).cast("long").alias("every"), metrics.combinations_of(s, True).cast("long").alias("contiguous"))


@query("pareto_curve")
def _(spark, sf):
    """Settings that no other beats in recall and rate, for each method, with the best rate at recall 0.9."""
    base, q = work(spark, sf)
    arms = [{"name": "pareto", "method": m, "searches": [(ef, 16, K) for ef in (20, 50, 100, 200)]} for m in ("index", "hnsw_post", "interval_edge_graph")]
    sweep = settle(ex.measure(spark, ex.shards_of(settle(base)), ex.query_rows(settle(q)), arms).where("width = 'all'").select("method", "ef", "recall", "qps", "n_dist"))
    return metrics.frontier(sweep, ["method"]).join(metrics.best_at(sweep, 0.9, ["method"]), "method")


# Streams.
_RANKED_ALL = f"""ranks AS MATERIALIZED (SELECT attr, row_number() OVER (ORDER BY attr, vid) - 1 AS rank FROM v), q1 AS (SELECT vid AS qid, 0.001 + 0.999 * {u_sql('vid', 'range:w')} AS w FROM v WHERE vid % 100 = 0),
    q2 AS (SELECT qid, greatest(1, floor(w * n))::BIGINT AS y, n FROM q1, total), q3 AS (SELECT qid, y, floor({u_sql('qid', 'range:s')} * (n - y + 1))::BIGINT AS s FROM q2),
    q AS MATERIALIZED (SELECT qid, a.attr AS lo, b.attr AS hi, {K} AS k FROM q3 JOIN ranks a ON a.rank = s JOIN ranks b ON b.rank = s + y - 1)"""


def _event_stream(spark: SparkSession, sf: str) -> DataFrame:
    files = t.load(spark, sf, "events")
    folder = f"{shared_folder(spark)}/events-{uuid.uuid4().hex}"
    files.write.parquet(folder)
    return spark.readStream.schema(files.schema).option("maxFilesPerTrigger", 4).parquet(folder)


@query("stream_window_counts", "SELECT CAST(date_trunc('day', ts) AS DATE) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def _(spark, sf):
    from ..streaming.ingest import memory_result

    s = _event_stream(spark, sf).withWatermark("ts", "100 days").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    out = memory_result(s, "rv_window_counts", "complete")
    return out.select(F.col("window.start").cast("date").alias("day"), "event_type", "n")


@query("stream_sessions", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOURS THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, sid, count(*) AS n FROM s GROUP BY ALL) GROUP BY ALL")
def _(spark, sf):
    from ..streaming.ingest import memory_result

    s = _event_stream(spark, sf).withWatermark("ts", "100 days").groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return memory_result(s, "rv_sessions", "complete").groupBy("user_id", "n").agg(F.count(F.lit(1)).alias("sessions"))


@query("stream_dedup", "SELECT event_id FROM events")
def _(spark, sf):
    from ..streaming.ingest import folder_result

    s = _event_stream(spark, sf)
    twice = s.unionByName(s).withWatermark("ts", "100 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")
    return folder_result(twice, f"{shared_folder(spark)}/dedup-{uuid.uuid4().hex}")


_LATE = f"SELECT event_id, ts FROM events WHERE {u_sql('event_id', 'late')} < 0.05"


@query("stream_late_rows", f"""WITH late AS ({_LATE}), mark AS (SELECT max(ts) - INTERVAL 3 DAYS AS w FROM events), seen AS (SELECT date_trunc('day', ts) AS day FROM events UNION ALL SELECT date_trunc('day', ts) FROM late, mark WHERE date_trunc('day', ts) + INTERVAL 1 DAY > w)
    SELECT CAST(day AS DATE) AS day, count(*) AS n FROM seen GROUP BY day""")
def _(spark, sf):
    """Some events come again after all others: those behind the watermark are dropped, the others count twice."""
    from ..streaming.ingest import late_counts

    e = t.load(spark, sf, "events").select("event_id", "ts")
    root = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    for part in (e, e.where(uniform("event_id", "late") < 0.05)):
        part.write.mode("append").parquet(f"{root}/in")
        late_counts(spark.readStream.schema(e.schema).parquet(f"{root}/in"), "3 days", "1 day", f"{root}/out", f"{root}/checkpoint").awaitTermination()
    out = spark.read.parquet(f"{root}/out")
    return out.groupBy("start").agg(F.max_by("n", "batch").alias("n")).select(F.col("start").cast("date").alias("day"), "n")


@query("stream_drift_monitor")
def _(spark, sf):
    from ..streaming.ingest import drift_monitor, memory_result

    v = t.load(spark, sf, "events").select(F.col("event_id").alias("vid"), F.col("value").alias("attr"))
    bounds = segment.fit(v, 8)
    ref = [r["n"] for r in segment.table(v, bounds).orderBy("seg").collect()]
    s = _event_stream(spark, sf).select(F.col("value").alias("attr"))
    return memory_result(drift_monitor(s, ref, bounds, 0.2), "rv_drift", "update")


@query("stream_ingest_final", f"""WITH v AS MATERIALIZED ({TABLE_SQL['event_vec']}), total AS (SELECT count(*) AS n FROM v), {_RANKED_ALL}
    SELECT qid, least(k, (SELECT count(*) FROM v WHERE attr BETWEEN lo AND hi)) AS found, least(k, (SELECT count(*) FROM v WHERE attr BETWEEN lo AND hi)) AS right, n AS rows FROM q, total""")
def _(spark, sf):
    """Half of the events are there, half arrive as a stream; the index afterwards holds all of them and answers as an exact search: ``right`` of those found."""
    from ..streaming.ingest import IndexWriter, ingest

    v = settle(t.event_vec(spark, sf))
    # Ids follow time: every other event at the start, so that the first boundaries deal the later ones over all shards.
    first, rest = v.where("vid % 2 = 0"), v.where("vid % 2 <> 0")
    root = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    rest.repartition(3).write.parquet(f"{root}/in")
    writer = IndexWriter(f"{root}/index")
    writer.start(RangeIndex.build(first, 4, 8, 50, shards=_shards(v)))
    stream = spark.readStream.schema(v.schema).option("maxFilesPerTrigger", 2).parquet(f"{root}/in")
    ingest(stream, writer, f"{root}/cp").awaitTermination()
    index = writer.current(spark)
    q = settle(t.rank_ranges(v, v.where("vid % 100 = 0").select(F.col("vid").alias("qid"), F.col("vec").alias("qvec")), K))
    found, truth = index.search(q, "pre"), range_knn_blocks(v, q)
    right = found.join(truth.select("qid", "rnk", "vid"), ["qid", "rnk", "vid"]).groupBy("qid").agg(F.count(F.lit(1)).alias("right"))
    counts = found.groupBy("qid").agg(F.count(F.lit(1)).alias("found")).join(q.select("qid", "y"), "qid").join(right, "qid", "left")
    return counts.select("qid", "found", F.coalesce("right", F.lit(0)).alias("right")).crossJoin(index.vectors().agg(F.count(F.lit(1)).alias("rows")))


@query("join_asof", "SELECT q.o_orderkey AS okey, b.price FROM (SELECT o_orderkey, o_totalprice AS v FROM orders WHERE o_orderkey % 10 = 0) q ASOF LEFT JOIN (SELECT o_totalprice AS v, o_totalprice AS price FROM orders WHERE o_orderkey % 10 <> 0) b ON q.v >= b.v")
def _(spark, sf):
    from ..operators.asof import asof

    o = t.load(spark, sf, "orders")
    left = o.where("o_orderkey % 10 = 0").select(F.col("o_orderkey").alias("okey"), F.col("o_totalprice").alias("v"))
    right = o.where("o_orderkey % 10 <> 0").select("o_orderkey", F.col("o_totalprice").alias("v"), F.col("o_totalprice").alias("price"))
    return asof(left, right, "v", "price", "o_orderkey").select("okey", "price")


# Sources, sinks and user functions.
def _roundtrip(fmt: str, spark: SparkSession, sf: str) -> DataFrame:
    df = t.load(spark, sf, "orders").select("o_orderkey", "o_totalprice", "o_orderpriority")
    path = f"{shared_folder(spark)}/{fmt}-{uuid.uuid4().hex}"
    df.write.format(fmt).option("header", "true").save(path)
    return spark.read.schema(df.schema).format(fmt).option("header", "true").load(path)


for _fmt in ("csv", "json", "orc", "parquet"):
    query(f"src_{_fmt}_roundtrip", "SELECT o_orderkey, o_totalprice, o_orderpriority FROM orders")(partial(_roundtrip, _fmt))


@query("src_parquet_pruned", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 300000")
def _(spark, sf):
    return t.load(spark, sf, "orders").where("o_totalprice > 300000").select("o_orderkey", "o_totalprice")


_NORM_SQL = "SELECT vec_id AS vid, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS n FROM embeddings"


@query("udf_pandas", _NORM_SQL)
def _(spark, sf):
    import numpy as np

    @F.pandas_udf("double")
    def length(v: pd.Series) -> pd.Series:
        return pd.Series(np.sqrt((np.stack(v.to_numpy()) ** 2).sum(axis=1)) if len(v) else [])

    return t.embeddings(spark, sf).select("vid", F.round(length("vec"), 6).alias("n"))


@query("udf_arrow", _NORM_SQL)
def _(spark, sf):
    import numpy as np
    import pyarrow as pa

    def run(batches):
        for b in batches:
            x = np.array(b.column("vec").to_pylist(), np.float64).reshape(b.num_rows, -1)
            yield pa.RecordBatch.from_arrays([b.column("vid"), pa.array(np.round(np.sqrt((x**2).sum(axis=1)), 6))], names=["vid", "n"])

    return t.embeddings(spark, sf).select("vid", "vec").mapInArrow(run, "vid long, n double")


@query("udf_grouped_topk", knn_sql(work_sql("emb_price")))
def _(spark, sf):
    base, q = work(spark, sf)
    near = base.join(multiattr.sent(q), F.col("attr").between(F.col("lo"), F.col("hi"))).select("qid", "vid", "k", l2("vec", "qvec").alias("dist"))

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        out = pdf.sort_values(["dist", "vid"]).head(int(pdf.k.iloc[0])).reset_index(drop=True)
        return pd.DataFrame({"qid": out.qid, "rnk": (out.index + 1).astype("int32"), "vid": out.vid, "dist": out.dist})

    return rounded(near.groupBy("qid").applyInPandas(best, "qid long, rnk int, vid long, dist double"))
