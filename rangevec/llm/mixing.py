"""Mixing sources to target weights by highest-quotient apportionment of equal token blocks. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from .shared import null_safe, settle, unclear

WORD = r"[^\x20\x09-\x0D]+"
#: Bounds tried at once in a round of apportionment, and rounds: together they resolve 2^60 places.
GRID, MOST_ROUNDS = 32, 12


def targets(sources: DataFrame, cycle: tuple[float, ...] = (5, 2, 1), most: float = 3.0) -> DataFrame:
    """``target`` for each row of (source, source_size): shares of the sum of all sizes by weight, none above ``most`` times its size.

    Sources by code point, null last, get the weights of ``cycle`` in turn. Handing the excess on by weight until none is above ends at one
    level: a source gets the lesser of its cap and level * weight. The level follows from the sources ordered by cap / weight.
    The rows are one for each source, a list that a mixing recipe spells out.
    """
    order = Window.orderBy(F.col("source").isNull(), F.hex("source"))
    rows = sources.withColumn("n", F.row_number().over(order) - 1)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in cycle]), (F.col("n") % len(cycle) + 1).cast("int"))
    rows = rows.withColumn("weight", weight).withColumn("cap", most * F.col("source_size"))
    before = Window.orderBy(F.col("cap") / F.col("weight"), "n").rowsBetween(Window.unboundedPreceding, -1)
    after = Window.orderBy(F.col("cap") / F.col("weight"), "n").rowsBetween(Window.currentRow, Window.unboundedFollowing)
    every = Window.orderBy(F.lit(0)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = rows.withColumn("_level", (F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after))
    # The first source in this order whose cap isn't reached sets the level.
    level = F.min(F.when(F.col("cap") >= F.col("_level") * F.col("weight"), F.struct((F.col("cap") / F.col("weight")).alias("r"), F.col("n").alias("n"), F.col("_level").alias("v")))).over(every)
    rows = rows.withColumn("_first", level)
    return rows.select("source", "source_size", "weight", F.least("cap", F.coalesce(F.col("_first.v") * F.col("weight"), F.col("cap"))).alias("target"))


def apportion(rows: DataFrame, within: list[str], key: str, claim: str, seats: str, cap: str) -> DataFrame:
    """Adds ``got``: ``seats`` places of each group ``within`` given to its rows by the highest quotients claim / (2 j + 1), none above ``cap``.

    A row has claim * t + 1/2 places, rounded down, whose quotients are above a bound that t stands for. Each round counts a group's places at GRID
    values of t at once, combined before the shuffle, and keeps the interval in which the asked number lies, until no row changes by more than
    two places in it. Only rows that change there are ranked, by quotient and then key: the outcome is that of giving one place at a time.
    """
    placed = lambda t: F.least(F.floor(F.col(claim) * t + 0.5), F.col(cap)).cast("long")
    asked = rows.where(F.col(claim) > 0)
    groups = asked.groupBy(*within).agg(F.count(F.lit(1)).alias("_n"), F.sum(claim).alias("_c"), F.max(claim).alias("_top"), F.max(seats).alias("_s"), F.sum(cap).alias("_room"), F.max((F.col(cap) + 0.5) / F.col(claim)).alias("_most"))
    # Rounding misses by half a place for each row at most; where caps bind, the upper end is what fills every row.
    lo, hi = F.greatest(F.lit(0.0), (F.col("_s") - F.col("_n") / 2 - 1) / F.col("_c")), (F.col("_s") + F.col("_n") / 2 + 1) / F.col("_c")
    groups = settle(groups.withColumn("_s", F.least("_s", "_room")).select(*within, "_top", "_most", "_s", lo.alias("_lo"), hi.alias("_hi"), F.lit(False).alias("_sure")))
    for _ in range(MOST_ROUNDS):
        if groups.where("NOT _sure OR (_hi - _lo) * _top > 1").isEmpty():
            break
        met = asked.alias("a").join(groups.alias("b"), null_safe("a", "b", within)).select(*[f"b.{c}" for c in within], claim, cap, "_top", "_most", "_s", "_lo", "_hi")
        point = lambda i: F.col("_lo") + (F.col("_hi") - F.col("_lo")) * i / GRID
        sums = met.groupBy(*within, "_top", "_most", "_s", "_lo", "_hi").agg(F.array(*[F.sum(placed(point(i))) for i in range(1, GRID + 1)]).alias("_at"))
        few, many = F.size(F.filter("_at", lambda n: n <= F.col("_s"))), F.size(F.filter("_at", lambda n: n < F.col("_s"))) + 1
        groups = settle(sums.select(*within, "_top", "_most", "_s", point(few).alias("_lo"), F.when(many > GRID, F.col("_most")).otherwise(point(many)).alias("_hi"), (many <= GRID).alias("_sure")))
    met = asked.alias("a").join(groups.alias("b"), null_safe("a", "b", within)).select("a.*", placed(F.col("_lo")).alias("_least"), F.greatest(placed(F.col("_lo")), placed(F.col("_hi"))).alias("_full"), "_s")
    met = settle(met)
    gaps = met.groupBy(*within).agg((F.max("_s") - F.sum("_least")).alias("_gap")).where("_gap > 0")
    open_ = met.where("_full > _least").alias("a").join(gaps.alias("b"), null_safe("a", "b", within)).select("a.*", "_gap")
    each = open_.select(*within, key, "_gap", F.explode(F.transform(F.sequence("_least", F.col("_full") - 1), lambda j: F.col(claim) / (2 * j + 1))).alias("_q"))
    ranked = each.withColumn("_r", F.row_number().over(Window.partitionBy(*within).orderBy(F.col("_q").desc(), key))).where("_r <= _gap")
    more = ranked.groupBy(*within, key).agg(F.count(F.lit(1)).alias("_more"))
    keys = [*within, key]
    out = rows.alias("a").join(met.select(*keys, "_least").alias("b"), null_safe("a", "b", keys), "left").select("a.*", "_least")
    out = out.alias("a").join(more.alias("b"), null_safe("a", "b", keys), "left")
    return out.select(*[f"a.{c}" for c in rows.columns], (F.coalesce("a._least", F.lit(0)) + F.coalesce("b._more", F.lit(0))).cast("long").alias("got"))


def _rank(seed: int, id_col: str) -> Column:
    return F.xxhash64(F.lit(seed), F.col(id_col))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", cycle: tuple[float, ...] = (5, 2, 1), most: float = 3.0, block_words: int = 1, shard_docs: int = 512, seed: int = 7) -> DataFrame:
    """One row per document: id, ``size``, ``source_size``, ``target`` (both of its source) and ``taken``, the words the mix takes of it.

    The sum of all sizes is cut into equal blocks of ``block_words`` words, one at every size of the corpus unless asked otherwise, so that no source
    is too small for a block; the blocks go to sources by
    highest quotients of their targets, and each source's blocks to its shards, hash ranges of about ``shard_docs`` documents, by their
    words. A shard hands out its documents in a seeded order, whole rounds first; the last document of the last round may give a part.
    None gives more than ``most`` times its size. Null text has size 0, a null source is one source. A row that repeats an id is a document
    of its own; equal ids order by size. Reruns agree. Other columns are ignored; an empty table gives an empty result.
    """
    return _mix(docs, id_col, text_col, source_col, cycle, most, block_words, shard_docs, seed).drop("_source")


def _mix(docs: DataFrame, id_col: str, text_col: str, source_col: str, cycle: tuple[float, ...] = (5, 2, 1), most: float = 3.0, block_words: int = 1, shard_docs: int = 512, seed: int = 7) -> DataFrame:
    """``mix`` with each row's source as ``_source``."""
    rows = settle(docs.select(F.col(id_col).cast("long").alias(id_col), F.col(source_col).cast("string").alias("source"), F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long").alias("size")))
    sources = rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("docs"))
    total = rows.agg(F.sum("size")).first()[0] or 0
    block = block_words
    aims = targets(sources.select("source", "source_size"), cycle, most).withColumn("one", F.lit(1)).withColumn("seats", F.lit(total // block)).withColumn("cap", F.ceil(most * F.col("source_size") / block))
    aims = apportion(settle(aims), ["one"], "source", "target", "seats", "cap").select("source", "source_size", "target", F.col("got").alias("seats"))
    counts = sources.select("source", F.greatest(F.lit(1), F.ceil(F.col("docs") / shard_docs)).alias("shards"))
    aims = settle(aims.join(counts, aims.source.eqNullSafe(counts.source)).drop(counts.source))
    # Sources beyond a few thousand would shuffle: Spark broadcasts this side only below its own size limit.
    placed = rows.alias("r").join(aims.alias("s"), F.col("r.source").eqNullSafe(F.col("s.source"))).select(f"r.{id_col}", "r.source", "size", "source_size", "target", "seats", F.pmod(_rank(seed + 1, id_col), F.col("shards")).alias("shard"))
    shards = settle(placed.groupBy("source", "shard", "seats").agg(F.sum("size").alias("words")).withColumn("cap", F.ceil(most * F.col("words") / block)))
    quotas = apportion(shards, ["source"], "shard", "words", "seats", "cap").select("source", "shard", "words", F.least(F.col("got") * block, (most * F.col("words")).cast("long")).alias("quota"))
    dealt = placed.alias("p").join(quotas.alias("q"), F.col("p.source").eqNullSafe(F.col("q.source")) & (F.col("p.shard") == F.col("q.shard"))).select("p.*", "words", "quota")
    run = Window.partitionBy("source", "shard").orderBy(_rank(seed, id_col), id_col, "size").rowsBetween(Window.unboundedPreceding, -1)
    dealt = dealt.withColumn("_at", F.coalesce(F.sum("size").over(run), F.lit(0)))
    rounds = F.when(F.col("words") > 0, F.floor(F.col("quota") / F.col("words"))).otherwise(F.lit(0))
    dealt = dealt.withColumn("_rounds", rounds)
    rest = F.least(F.greatest(F.col("quota") - F.col("_rounds") * F.col("words") - F.col("_at"), F.lit(0)), F.col("size"))
    return dealt.select(F.col("source").alias("_source"), id_col, "size", "source_size", F.col("target").cast("double").alias("target"), (F.col("_rounds") * F.col("size") + rest).cast("long").alias("taken"))


def mixed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **how) -> DataFrame:
    """The documents of the mix with all their columns: each as often as ``taken`` asks, a part counting as one copy.

    Where ids are missing or on several rows, rows that share id, source and size get the copies of those that ``mix`` deals them in the order of their texts' hashes.
    """
    every = _mix(docs, id_col, text_col, source_col, **how)
    copies = F.ceil(F.col("taken") / F.col("size")).cast("int").alias("_copies")
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col(id_col).cast("long").alias("_id"))
    if not unclear(docs, id_col):
        out = rows.join(every.where("taken > 0").select(F.col(id_col).alias("_id"), copies), "_id")
    else:
        keys, text = ["_id", "_source", "_size"], F.col(f"row.{text_col}")
        size = F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")
        rows = rows.select("row", "_id", F.col(f"row.{source_col}").cast("string").alias("_source"), size.alias("_size"), F.sha2(F.coalesce(text, F.lit("")), 256).alias("_sha"))
        rows = rows.withColumn("_n", F.row_number().over(Window.partitionBy(*keys).orderBy("_sha")))
        taken = every.select(F.col(id_col).alias("_id"), "_source", F.col("size").alias("_size"), copies)
        taken = taken.withColumn("_n", F.row_number().over(Window.partitionBy(*keys).orderBy(F.col("_copies").desc()))).where("_copies > 0")
        out = rows.alias("a").join(taken.alias("b"), null_safe("a", "b", [*keys, "_n"])).select("row", "_copies")
    return out.select(F.explode(F.array_repeat("row", F.col("_copies"))).alias("row")).select("row.*")
