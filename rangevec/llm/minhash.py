"""Near-duplicate documents: universal hash minima, banding, signature check, confirmation on full shingle sets, components."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .components import components
from .shared import HOT_LEAST, HOT_PARTS, Words, hashes, join_hot, null_safe, release, settle, slices, tidy, unclear

#: 28 bands of 4 minima miss a pair of similarity 0.8 with probability 4e-7.
BANDS, ROWS = 28, 4
#: A pair of similarity 0.8 falls below this share of equal minima (six standard deviations) with probability under 1e-8.
SLACK = 0.23
SALTS = 64
CHUNK = 1 << 14
TILE_OTHERS, TILE_ALL = 256, 1024


def _odd(n: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).integers(1, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_sets(texts: pa.Array, k: int) -> list[tuple[np.ndarray, bytes]]:
    """For each text the sorted distinct hashes of its k-word shingles, and 128 bits that stand for its word sequence."""
    w = Words(texts)
    own = hashes(w.vocab)[w.codes] if w.vocab else np.zeros(0, np.uint64)
    mult, out = _odd(k, 5), []
    whole = np.zeros(max(0, len(own) - k + 1), np.uint64)
    for j in range(k):
        whole += own[j : j + len(whole)] * mult[j]
    whole ^= whole >> np.uint64(31)
    whole *= np.uint64(0x9E3779B97F4A7C15)
    whole ^= whole >> np.uint64(29)
    for lo, hi in zip(w.offsets[:-1], w.offsets[1:], strict=True):
        key = hashlib.blake2b(own[lo:hi].tobytes(), digest_size=16).digest()
        if hi == lo:
            s = whole[:0]
        elif hi - lo < k:
            s = np.frombuffer(key, np.uint64)[:1]
        else:
            s = np.sort(whole[lo : hi - k + 1])
            s = s[np.concatenate([[True], s[1:] != s[:-1]])]
        out.append((s, key))
    return out


def signature(s: np.ndarray, mult: np.ndarray, add: np.ndarray) -> np.ndarray:
    """The upper halves of the minima of ``mult * s + add`` modulo 2^64."""
    best = np.full(len(mult), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(s), CHUNK):
        t = np.multiply.outer(mult, s[at : at + CHUNK])
        t += add[:, None]
        np.minimum(best, t.min(axis=1), out=best)
    return (best >> np.uint64(32)).astype("<u4")


def _sign(k: int, n: int):
    schema = pa.schema([("doc_id", pa.int64()), ("h", pa.binary()), ("n_shingles", pa.int64()), ("sig", pa.binary())])

    def run(batches):
        mult, add = _odd(n, 1), _odd(n, 2)
        for b in slices(batches, "text"):
            sets = shingle_sets(b.column("text"), k)
            sigs = [signature(s, mult, add).tobytes() if len(s) else None for s, _ in sets]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([key for _, key in sets], pa.binary()), pa.array([len(s) for s, _ in sets], pa.int64()), pa.array(sigs, pa.binary())], schema=schema)

    return run


def _agree(least: float):
    """Pairs whose signatures agree in a share of ``least`` of their places at least."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), "<u4").reshape(b.num_rows, -1) for c in ("sig_a", "sig_b"))
                yield b.select(["a", "b"]).filter(pa.array((x == y).mean(axis=1) >= least))

    return run


def _confirm(k: int, percent: int):
    def run(batches):
        for b in slices(batches, "text_a", 1 << 20):
            keep = []
            known: dict[int, np.ndarray] = {}
            sets = [s for s, _ in shingle_sets(b.column("text_a"), k)]
            fresh = {x: i for i, x in enumerate(b.column("b").to_pylist())}
            for x, (s, _) in zip(fresh, shingle_sets(b.column("text_b").take(pa.array(list(fresh.values()))), k), strict=True):
                known[x] = s
            for s, other in zip(sets, b.column("b").to_pylist(), strict=True):
                t = known[other]
                both = np.concatenate([s, t])
                both.sort()
                common = int((both[1:] == both[:-1]).sum())
                keep.append(100 * common >= percent * (len(s) + len(t) - common))
            yield b.select(["a", "b"]).filter(pa.array(keep))

    return run


def _salted(pairs: DataFrame, rows: DataFrame, key: str, other: str) -> DataFrame:
    """Join rows, one per key, to pairs, where one key may be in any share of the pairs: such keys' rows go out in SALTS copies.

    Only the ids of keys in more than 1/HOT_PARTS of the pairs are broadcast, HOT_PARTS at most.
    """
    counts = pairs.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    limit = max((counts.agg(F.sum("n")).first()[0] or 0) // HOT_PARTS, HOT_LEAST)
    hot = F.broadcast(counts.where(F.col("n") > limit).select(key, F.lit(True).alias("hot")))
    left = pairs.join(hot, key, "left").withColumn("salt", F.when(F.col("hot"), F.pmod(F.xxhash64(other), F.lit(SALTS)).cast("int")).otherwise(F.lit(0))).drop("hot")
    right = rows.join(hot, key, "left").withColumn("salt", F.explode(F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0))))).drop("hot")
    return left.join(right, [key, "salt"]).drop("salt")


def _verify(pairs: DataFrame, reps: DataFrame, texts: DataFrame, k: int, percent: int, least: float) -> DataFrame:
    """The pairs (a, b) that signatures don't exclude and full sets confirm."""
    signed = _salted(pairs, reps.select(F.col("doc_id").alias("b"), F.col("sig").alias("sig_b")), "b", "a").join(reps.select(F.col("doc_id").alias("a"), F.col("sig").alias("sig_a")), "a")
    pairs = settle(signed.mapInArrow(_agree(least), "a long, b long"))
    full = _salted(pairs, texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b", "a")
    full = full.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a")
    return settle(full.select("a", "b", "text_a", "text_b").mapInArrow(_confirm(k, percent), "a long, b long"))


def _tile_links(k: int, percent: int, least: float):
    """Links between a tile's others and all of its members that join different components; each pair is tested on full sets unless its ends are already joined."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(table: pa.Table) -> pa.Table:
        other = table.column("other").to_numpy()
        ids = table.column("doc_id").to_numpy()
        _, root = np.unique(table.column("component").to_numpy(), return_inverse=True)
        sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), "<u4").reshape(table.num_rows, -1)
        rest, asked = np.flatnonzero(~other), []
        for i in np.flatnonzero(other):
            share = (sig[rest] == sig[i]).mean(axis=1)
            near = (share >= least) & (root[rest] != root[i])
            asked.append(np.stack([np.full(near.sum(), i), rest[near], -share[near]]))
        asked = np.concatenate([*asked, np.zeros((3, 0))], axis=1)
        parent = list(range(int(root.max()) + 1))

        def find(x: int) -> int:
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        sets: dict[int, np.ndarray] = {}
        used = np.unique(asked[:2]).astype(np.int64)
        text = table.column("text").combine_chunks()
        for at in range(0, len(used), 64):
            sets.update(zip(used[at : at + 64].tolist(), (s for s, _ in shingle_sets(text.take(pa.array(used[at : at + 64])), k)), strict=True))
        found = []
        # The likeliest first: most ends are joined before their other pairs come up.
        for i, j in asked[:2, np.argsort(asked[2], kind="stable")].T.astype(np.int64).tolist():
            u, v = find(int(root[i])), find(int(root[j]))
            if u == v:
                continue
            x, y = sets[i], sets[j]
            if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
                continue
            place = np.minimum(np.searchsorted(x, y), len(x) - 1)
            common = int((x[place] == y).sum())
            if 100 * common >= percent * (len(x) + len(y) - common):
                parent[u] = v
                found.append((int(ids[i]), int(ids[j])))
        release()
        return pa.Table.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], schema=schema)

    return run


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """One row per document: id, ``n_shingles``, ``component_id`` and ``kept``.

    Words are ``[^\\x20\\x09-\\x0D]+`` after lower-casing A-Z, a document's set its distinct ``shingle``-word shingles; with fewer words the
    whole sequence is one, without any the set is empty and linked with nothing. Two documents are linked when
    100 * intersection >= percent * union. ``component_id`` is the smallest id reachable by links, ``kept`` whether it is the own one.

    Documents with one word sequence are one representative. Every bucket of a band compares its members with its smallest one, which
    is a row per member and not per pair, and confirmed links give components. Buckets that then still hold several components are joined,
    where they share members, to clusters. In a cluster, members outside its largest component meet all members of fitting set sizes in tiles of
    bounded size, which test pairs on full sets and hand on only links that join components. So each pair that shares a bucket is
    either in one component or has been tested. Where ids are missing or on several rows, each id and text is a document of its own, in
    the order of ids (missing ones last) and hashes of the texts. Other columns are ignored; an empty table gives an empty result.
    """
    if not unclear(docs, id_col):
        return _linked(docs, id_col, text_col, shingle, percent, bands, rows)
    return _by_row(docs, id_col, text_col, shingle, percent, bands, rows).drop("_sha")


def _by_row(docs: DataFrame, id_col: str, text_col: str = "text", shingle: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """``near_duplicates`` over keys that stand for id and text, with the hash of the text as ``_sha``."""
    texts = docs.select(F.col(id_col).cast("long").alias("_id"), F.sha2(F.coalesce(F.col(text_col), F.lit("")), 256).alias("_sha"), F.col(text_col).alias("text"))
    # Numbers that grow over a sorted frame keep its order.
    keys = settle(texts.select("_id", "_sha").distinct().orderBy(F.col("_id").asc_nulls_last(), "_sha").withColumn("_key", F.monotonically_increasing_id()))
    keyed = texts.alias("a").join(keys.alias("b"), null_safe("a", "b", ["_id", "_sha"])).select("_key", "text")
    found = _linked(keyed, "_key", "text", shingle, percent, bands, rows).join(keys, "_key")
    heads = keys.select(F.col("_key").alias("component_id"), F.col("_id").alias("_head"))
    return found.join(heads, "component_id").select(F.col("_id").alias(id_col), "n_shingles", F.col("_head").alias("component_id"), "kept", "_sha")


def _linked(docs: DataFrame, id_col: str, text_col: str, shingle: int, percent: int, bands: int, rows: int) -> DataFrame:
    """``near_duplicates`` where equal ids have equal texts and none is missing."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    signed = settle(texts.mapInArrow(_sign(shingle, bands * rows), "doc_id long, h binary, n_shingles long, sig binary"))
    full = signed.where("n_shingles > 0")
    groups = settle(full.groupBy("h").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n")))
    reps = settle(full.alias("s").join(groups.alias("g"), (F.col("s.h") == F.col("g.h")) & (F.col("s.doc_id") == F.col("g.rep"))).select("s.doc_id", "s.n_shingles", "s.sig").dropDuplicates(["doc_id"]))
    repeated = not groups.groupBy("rep").count().where("count > 1").isEmpty()
    cut = [F.xxhash64(F.lit(i), F.substring("sig", i * rows * 4 + 1, rows * 4)) for i in range(bands)]
    # A bucket's number covers its band; if two numbers coincide, their members are compared in vain.
    spread = reps.select("doc_id", F.explode(F.array(*cut)).alias("bucket"))
    shared = settle(spread.groupBy("bucket").agg(F.min("doc_id").alias("hub"), F.count(F.lit(1)).alias("n")).where("n > 1"))
    members = settle(join_hot(spread, shared, ["bucket"], "n").drop("n"))
    tidy(docs.sparkSession)
    least = percent / 100 - SLACK if percent > 100 * SLACK else 0.0
    pairs = settle(members.where("doc_id != hub").select(F.col("doc_id").alias("a"), F.col("hub").alias("b")).distinct())
    ids = pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b").alias("doc_id"))).distinct()
    texts = texts.join(ids, "doc_id", "left_semi")
    texts = settle(texts.dropDuplicates(["doc_id"]) if repeated else texts)
    links = _verify(pairs, reps, texts, shingle, percent, least)
    found = settle(components(links))
    tidy(docs.sparkSession)

    # Buckets that still hold several components.
    named = found.withColumnRenamed("node", "doc_id")
    placed = members.join(named, "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    mixed = settle(placed.groupBy("bucket").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count(F.lit(1)).alias("n")).where("lo != hi").select("bucket", "n"))
    if not mixed.isEmpty():
        rest = join_hot(members, mixed, ["bucket"], "n").select("doc_id", "hub").distinct()
        rest = settle(rest.join(named, "doc_id", "left").select("doc_id", "hub", F.coalesce("component", "doc_id").alias("component")))
        clusters = components(rest.select(F.col("doc_id").alias("a"), F.col("hub").alias("b"))).withColumnsRenamed({"node": "doc_id", "component": "cluster"})
        rest = settle(rest.select("doc_id", "component").distinct().join(clusters, "doc_id"))
        largest = rest.groupBy("cluster", "component").agg(F.count(F.lit(1)).alias("c")).groupBy("cluster").agg(F.max_by("component", F.struct("c", "component")).alias("main"), F.sum("c").alias("n"))
        rest = join_hot(rest, settle(largest), ["cluster"], "n").join(reps.select("doc_id", "n_shingles"), "doc_id")
        # Linked sets differ in size by one step of this scale at most.
        step = F.floor(F.log("n_shingles") / F.log(F.lit(100 / percent)) + 1e-9).cast("int") if percent < 100 else F.col("n_shingles")
        rest = settle(rest.select("cluster", "doc_id", "component", (F.col("component") != F.col("main")).alias("apart"), step.alias("step")))
        as_all = rest.select("cluster", "step", "doc_id", "component", F.lit(False).alias("other"))
        as_other = rest.where("apart").select("cluster", F.explode(F.array(F.col("step") - 1, F.col("step"), F.col("step") + 1)).alias("step"), "doc_id", "component", F.lit(True).alias("other"))
        both = as_all.unionByName(as_other)
        sizes = both.groupBy("cluster", "step").agg(F.sum(F.col("other").cast("long")).alias("others"), F.sum((~F.col("other")).cast("long")).alias("alls"), F.count(F.lit(1)).alias("n")).where("others > 0 AND alls > 0")
        tidy(docs.sparkSession)
        tiled = join_hot(settle(both), settle(sizes), ["cluster", "step"], "n")
        ni, nj = F.ceil(F.col("others") / TILE_OTHERS), F.ceil(F.col("alls") / TILE_ALL)
        upto = lambda n: F.sequence(F.lit(0).cast("long"), n - 1)
        tiled = tiled.withColumn("i", F.when(F.col("other"), F.array(F.pmod(F.xxhash64("doc_id"), ni))).otherwise(upto(ni))).withColumn("j", F.when(F.col("other"), upto(nj)).otherwise(F.array(F.pmod(F.xxhash64("doc_id"), nj))))
        tiled = tiled.select("cluster", "step", "doc_id", "component", "other", F.explode("i").alias("i"), "j").select("cluster", "step", "doc_id", "component", "other", "i", F.explode("j").alias("j"))
        late = settle(tiled.join(reps.select("doc_id", "sig"), "doc_id").join(texts, "doc_id").groupBy("cluster", "step", "i", "j").applyInArrow(_tile_links(shingle, percent, least), "a long, b long"))
        if not late.isEmpty():
            found = settle(components(late.unionByName(found.select(F.col("node").alias("a"), F.col("component").alias("b")))))

    whole = settle(groups.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("h", "n", F.coalesce("component", "rep").alias("component_id")))
    out = join_hot(full.select("doc_id", "h", "n_shingles"), whole, ["h"], "n").select("doc_id", "n_shingles", "component_id")
    out = out.unionByName(signed.where("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id")))
    return out.select(F.col("doc_id").alias(id_col), "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """One document of each component, with all columns; of rows that repeat id and text all or none stay."""
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col(id_col).cast("long").alias("_id"))
    if not unclear(docs, id_col):
        kept = near_duplicates(docs, id_col, text_col, **how).where("kept").select(F.col(id_col).alias("_id")).distinct()
        return rows.join(kept, "_id", "left_semi").select("row.*")
    kept = _by_row(docs, id_col, text_col, **how).where("kept").select(F.col(id_col).alias("_id"), "_sha")
    rows = rows.withColumn("_sha", F.sha2(F.coalesce(F.col(f"row.{text_col}"), F.lit("")), 256))
    return rows.alias("a").join(kept.alias("b"), null_safe("a", "b", ["_id", "_sha"]), "left_semi").select("row.*")
