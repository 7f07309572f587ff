"""Exact deduplication: 128-bit content hashes, with a byte comparison inside each hash group."""

from __future__ import annotations

import hashlib
import string

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from .shared import join_hot, null_safe, settle, slices, unclear


def _digests(id_col: str, text_col: str, with_text: bool, bits: int):
    schema = pa.schema([(id_col, pa.int64()), ("h", pa.binary()), ("sha", pa.binary())] + [("body", pa.string())] * with_text)

    def run(batches):
        for b in slices(batches, text_col):
            low = pc.ascii_lower(pc.fill_null(b.column(text_col), "")).cast(pa.string())
            raw = low.cast(pa.binary()).to_pylist()
            h = [hashlib.blake2b(x, digest_size=bits // 8).digest() for x in raw]
            sha = [hashlib.sha256(x).digest() for x in raw]
            yield pa.RecordBatch.from_arrays([b.column(id_col).cast(pa.int64()), pa.array(h, pa.binary()), pa.array(sha, pa.binary())] + [low] * with_text, schema=schema)

    return run, f"{id_col} long, h binary, sha binary" + ", body string" * with_text


def duplicate_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", bits: int = 128) -> DataFrame:
    """One row per document: id, ``keep_id``, ``group_size``, ``kept``, ``text_sha256``.

    Texts are equal when identical after lower-casing A-Z; null counts as empty, so null and empty texts form one group. ``keep`` says
    whether the smallest or largest id stays; a missing one does only where no row of the group has an id. Rows that repeat an id count as
    rows of their own and all carry that id. Other columns are ignored; an empty table gives an empty result.

    Hash groups are split by their bytes: the aggregation key holds the normalised text itself, combined before the shuffle, so a group of
    any size is one row for each map task and a hash collision (``bits`` can be lowered to test it) joins nothing.
    """
    if keep not in ("min", "max"):
        raise ValueError("keep is 'min' or 'max'")
    rows = docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).alias(text_col))
    whole, schema = _digests(id_col, text_col, True, bits)
    best = F.min if keep == "min" else F.max
    groups = settle(rows.mapInArrow(whole, schema).groupBy("h", "sha", "body").agg(best(id_col).alias("keep_id"), F.count(F.lit(1)).alias("group_size")).drop("body"))
    narrow, schema = _digests(id_col, text_col, False, bits)
    members = settle(rows.mapInArrow(narrow, schema))
    out = join_hot(members, groups, ["h", "sha"], "group_size")
    return out.select(id_col, "keep_id", "group_size", F.col(id_col).eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256"))


def drop_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """The documents that stay, with all their columns: one of each group of equal texts.

    Where ids are missing or on several rows, a row is known by its id and the hash of its normalised text; of rows that share both one stays.
    """
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col(id_col).cast("long").alias("_id"))
    kept = duplicate_groups(docs, id_col, text_col, keep).where("kept").select(F.col(id_col).alias("_id"), F.col("text_sha256").alias("_sha"))
    if not unclear(docs, id_col):
        return rows.join(kept.select("_id"), "_id", "left_semi").select("row.*")
    low = F.translate(F.coalesce(F.col(f"row.{text_col}"), F.lit("")), string.ascii_uppercase, string.ascii_lowercase)
    out = rows.withColumn("_sha", F.sha2(low, 256)).alias("a").join(kept.alias("b"), null_safe("a", "b", ["_id", "_sha"]), "left_semi")
    return out.dropDuplicates(["_id", "_sha"]).select("row.*")
