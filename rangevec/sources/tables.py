"""Attributed vector tables (vid, vec, attr) and query workloads made from the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..functions.columns import uniform
from .durable import ranked

DIM = 64


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table, with timestamps that carry no zone read as UTC."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*[F.col(c).cast("timestamp").alias(c) if kind == "timestamp_ntz" else F.col(c) for c, kind in df.dtypes])


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), F.col("embedding").cast("array<double>").alias("vec"), "label")


def emb_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors with the price of the order of the same key."""
    o = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vid"), F.col("o_totalprice").alias("attr"))
    return embeddings(spark, sf_dir).join(o, "vid").select("vid", "vec", "attr")


def emb_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A random attribute from 0 to 10,000."""
    return embeddings(spark, sf_dir).select("vid", "vec", (uniform("vid", "attr") * 10000).alias("attr"))


def emb_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vid"), F.unix_micros("o_orderdate").cast("double").alias("attr"))
    return embeddings(spark, sf_dir).join(o, "vid").select("vid", "vec", "attr")


def emb_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Skewed attribute with ties."""
    e = load(spark, sf_dir, "events").select(F.col("event_id").alias("vid"), F.col("value").alias("attr"))
    return embeddings(spark, sf_dir).join(e, "vid").select("vid", "vec", "attr")


def emb_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A category as a number."""
    return embeddings(spark, sf_dir).select("vid", "vec", F.col("label").cast("double").alias("attr"))


def emb_retail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An attribute that follows the id and is missing for ids without a part."""
    p = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"), F.col("p_retailprice").alias("attr"))
    return embeddings(spark, sf_dir).join(p, "vid", "left").select("vid", "vec", "attr")


def hashed_words(text: Column, dim: int = DIM) -> Column:
    """Counts of lower-cased words ``[a-z0-9]+`` hashed to ``dim`` places, as a unit vector; zeros without a word."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-z0-9]+"), lambda w: w != "")
    places = F.transform(words, lambda w: F.conv(F.substring(F.md5(w), 1, 8), 16, 10).cast("long") % dim)
    counts = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.size(F.filter(places, lambda p: p == i)).cast("double"))
    return _unit(counts)


def _unit(v: Column) -> Column:
    n = F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x))
    return F.transform(v, lambda x: F.when(n > 0, x / n).otherwise(F.lit(0.0)))


def text_vectors(df: DataFrame, id_col: str, text: Column, attr: Column, dim: int = DIM) -> DataFrame:
    """Word vectors by aggregation: one row per (document, place) is combined before the shuffle, so a long text costs no long array scans."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-z0-9]+"), lambda w: w != "")
    rows = df.select(F.col(id_col).alias("vid"), attr.cast("double").alias("attr"), F.explode_outer(words).alias("w"))
    place = F.when(F.col("w").isNotNull(), F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long") % dim)
    sums = [F.sum(F.when(place == i, 1.0).otherwise(0.0)).alias(f"c{i}") for i in range(dim)]
    return rows.groupBy("vid", "attr").agg(*sums).select("vid", _unit(F.array(*[F.col(f"c{i}") for i in range(dim)])).alias("vec"), "attr")


def doc_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_vectors(load(spark, sf_dir, "documents"), "doc_id", F.col("text"), F.col("n_chars"))


def page_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_vectors(load(spark, sf_dir, "pages"), "page_id", F.regexp_replace("html", "<[^>]*>", " "), F.length("html"))


def line_num(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scaled numbers and one-hot flags of order lines by shipping date; the id is the line's rank over all its columns."""
    df = load(spark, sf_dir, "lineitem")
    df = ranked(df, df.columns, "vid")
    hot = [(F.col(c) == v).cast("double") for c, vs in (("l_returnflag", "ANR"), ("l_linestatus", "FO")) for v in vs]
    vec = F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 105000, F.col("l_discount") / 0.1, F.col("l_tax") / 0.08, *hot)
    return df.select("vid", vec.alias("vec"), F.unix_micros("l_shipdate").cast("double").alias("attr"))


def event_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event features by event time."""
    df = load(spark, sf_dir, "events")
    hour = F.hour("ts") * (2 * 3.141592653589793 / 24)
    hot = [(F.col("event_type") == t).cast("double") for t in EVENT_TYPES]
    vec = F.array(F.log(1 + F.col("value")), F.sin(hour), F.cos(hour), F.col("user_id") / 150, *hot, F.get_json_object("props", "$.k").cast("double") / 100)
    return df.select(F.col("event_id").alias("vid"), vec.alias("vec"), F.unix_micros("ts").cast("double").alias("attr"))


#: The kinds of events of the given table.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")

TABLES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "emb_price": emb_price, "emb_uniform": emb_uniform, "emb_date": emb_date, "emb_value": emb_value, "emb_label": emb_label,
    "emb_retail": emb_retail, "doc_text": doc_text, "line_num": line_num, "event_vec": event_vec, "page_html": page_html,
}


def held_out(df: DataFrame, every: int = 10) -> tuple[DataFrame, DataFrame]:
    """Base rows and query vectors (qid, qvec): every tenth id is a query and not in the base."""
    return df.where(F.col("vid") % every != 0), df.where(F.col("vid") % every == 0).select(F.col("vid").alias("qid"), F.col("vec").alias("qvec"))


def rank_ranges(base: DataFrame, queries: DataFrame, k: int = 10, low: float = 0.001, high: float = 1.0, salt: str = "range") -> DataFrame:
    """Adds lo, hi, k, w and y: a range over y objects, a share w between ``low`` and ``high`` of all in attribute order, at a random place.

    Bounds are attributes of base objects; with ties the range may hold more than y. Objects without an attribute aren't counted.
    """
    have = ranked(base.where("attr is not null").select("attr", "vid"), ["attr", "vid"], "rank")
    n = have.count()
    w = F.lit(low) + F.lit(high - low) * uniform("qid", salt + ":w")
    q = queries.withColumn("w", w).withColumn("y", F.greatest(F.lit(1), F.floor(F.col("w") * n)).cast("long"))
    q = q.withColumn("_lo", F.floor(uniform("qid", salt + ":s") * (n - F.col("y") + 1)).cast("long"))
    at = have.select("rank", "attr")
    q = q.join(at.select(F.col("rank").alias("_lo"), F.col("attr").alias("lo")), "_lo").withColumn("_hi", F.col("_lo") + F.col("y") - 1)
    return q.join(at.select(F.col("rank").alias("_hi"), F.col("attr").alias("hi")), "_hi").select("qid", "qvec", "lo", "hi", F.lit(k).alias("k"), "w", "y")


def width_class(share: Column) -> Column:
    return F.when(share <= 0.01, "small").when(share < 0.5, "medium").otherwise("large")
