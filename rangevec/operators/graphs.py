"""Proximity graphs as plans: nearest-neighbour graphs, their chunked form, inclusion checks, pruning, chains and the bulk build."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.columns import l2, level
from ..sources.durable import settle
from .exact import range_knn_blocks, top


def _pairs(src: DataFrame, dst: DataFrame) -> DataFrame:
    """Distances between different objects. Every object meets every other: the exact graph is for segments of bounded size and for tests; the index kernel is the way beyond."""
    a = src.select(F.col("vid").alias("src"), F.col("vec").alias("a"), *[F.col(c).alias(f"src_{c}") for c in src.columns if c == "seg"])
    b = dst.select(F.col("vid").alias("dst"), F.col("vec").alias("b"), *[c for c in dst.columns if c == "seg"])
    return a.join(b, F.col("src") != F.col("dst")).withColumn("dist", l2("a", "b")).drop("a", "b")


def knn_graph(base: DataFrame, k: int) -> DataFrame:
    """(src, dst, dist, rnk): edges from each object to its k nearest others, by distance and id."""
    return top(_pairs(base.select("vid", "vec"), base.select("vid", "vec")), ["src"], F.lit(k), ["dist", "dst"])


def chunked(base: DataFrame, k: int) -> DataFrame:
    """(src, chunk, dst, dist, rnk): edges from each object to its k nearest others in every segment."""
    rows = base.select("vid", "vec", "seg")
    return top(_pairs(rows, rows), ["src", "seg"], F.lit(k), ["dist", "dst"]).select("src", F.col("seg").alias("chunk"), "dst", "dist", "rnk")


def subsets(segs: list[int], contiguous: bool = False) -> list[tuple[int, ...]]:
    """Non-empty combinations: 2^s - 1, or s (s + 1) / 2 contiguous ones."""
    if contiguous:
        return [tuple(segs[i:j]) for i in range(len(segs)) for j in range(i + 1, len(segs) + 1)]
    return [c for r in range(1, len(segs) + 1) for c in combinations(segs, r)]


def exhaustive(base: DataFrame, k: int, segs: list[int], contiguous: bool = False) -> DataFrame:
    """Distinct edges of the graphs of all combinations, built one by one: the cost that the chunked graph avoids."""
    out = None
    for combo in subsets(segs, contiguous):
        g = knn_graph(base.where(F.col("seg").isin(*combo)), k).select("src", "dst", "dist")
        out = g if out is None else out.unionByName(g)
    return out.distinct()


def rebuild(edges: DataFrame, segs: tuple[int, ...], k: int, nodes: DataFrame) -> DataFrame:
    """The graph of a combination from chunks alone: of each of its nodes, the k nearest over the chosen chunks."""
    inside = edges.where(F.col("chunk").isin(*segs)).join(nodes.where(F.col("seg").isin(*segs)).select(F.col("vid").alias("src")), "src", "left_semi")
    return top(inside.select("src", "dst", "dist"), ["src"], F.lit(k), ["dist", "dst"])


def missing(sub: DataFrame, full: DataFrame) -> DataFrame:
    """Edges of ``sub`` that ``full`` lacks."""
    return sub.select("src", "dst").join(full.select("src", "dst"), ["src", "dst"], "left_anti")


def inclusiveness(sub: DataFrame, full: DataFrame) -> DataFrame:
    """(common, total, inclusiveness in percent)."""
    have = full.select("src", "dst", F.lit(1).alias("hit")).distinct()
    joined = sub.select("src", "dst").join(have, ["src", "dst"], "left")
    n, total = F.sum(F.coalesce("hit", F.lit(0))), F.count(F.lit(1))
    return joined.agg(n.alias("common"), total.alias("total"), (100.0 * n / total).alias("inclusiveness"))


def prune(cands: Column, m: int, fill: bool = False) -> Column:
    """Of candidates struct(dist, id, vec), nearest first, those not nearer to a kept one than to the node itself, up to m.

    ``fill`` adds the nearest of the others until there are m.
    """
    ordered = F.array_sort(cands)
    empty = F.filter(ordered, lambda c: F.lit(False))

    def step(kept: Column, r: Column) -> Column:
        clear = F.forall(kept, lambda e: l2(e["vec"], r["vec"]) >= r["dist"])
        return F.when((F.size(kept) < m) & clear, F.concat(kept, F.array(r))).otherwise(kept)

    kept = F.aggregate(ordered, empty, step)
    if not fill:
        return kept

    def filled(kept: Column) -> Column:
        ids = F.transform(kept, lambda c: c["id"])
        rest = F.filter(ordered, lambda c: ~F.array_contains(ids, c["id"]))
        return F.array_sort(F.slice(F.concat(kept, rest), 1, m))

    # As a variable of a lambda, the kept ones are found once and not again for each candidate.
    return F.element_at(F.transform(F.array(kept), filled), 1)


def pruned_edges(edges: DataFrame, base: DataFrame, m: int, by: list[str], fill: bool = False) -> DataFrame:
    """Prune each group's edges (src, dst, dist); groups hold a node's candidates, a bounded number."""
    vec = base.select(F.col("vid").alias("dst"), "vec")
    groups = edges.join(vec, "dst").groupBy(*by).agg(F.collect_list(F.struct("dist", F.col("dst").alias("id"), "vec")).alias("c"))
    return groups.select(*by, F.posexplode(prune(F.col("c"), m, fill)).alias("pos", "e")).select(*by, F.col("e.id").alias("dst"), F.col("e.dist").alias("dist"), (F.col("pos") + 1).alias("rnk"))


def layers(base: DataFrame, m: int, rule: str = "decay") -> DataFrame:
    """One row per (layer, vid): each node is on all layers up to its own."""
    rows = base.withColumn("level", level("vid", m, rule))
    return rows.withColumn("layer", F.explode(F.sequence(F.lit(0), F.col("level"))))


def entries(base: DataFrame, m: int, rule: str = "decay") -> DataFrame:
    """(seg, top_layer, entry): in each segment the first inserted of the nodes that reach its top layer; ids give the order."""
    rows = base.withColumn("level", level("vid", m, rule))
    return rows.groupBy("seg").agg(F.max("level").alias("top_layer"), F.max_by("vid", F.struct("level", -F.col("vid"))).alias("entry"))


def chain(base: DataFrame, m: int, rule: str = "decay") -> DataFrame:
    """(layer, seg, vid, attr, next): the successor of each node in attribute order on each of its layers.

    Within a segment a window finds it; the last node of a segment continues with the first of the next one that has any, which takes one
    row per segment and layer. So no layer is sorted in one task.
    """
    rows = layers(base.where("attr is not null"), m, rule).select("layer", "seg", "vid", "attr")
    own = Window.partitionBy("layer", "seg").orderBy("attr", "vid")
    inside = rows.withColumn("next", F.lead("vid").over(own))
    first = rows.groupBy("layer", "seg").agg(F.min(F.struct("attr", "vid")).getField("vid").alias("head"))
    after = first.withColumn("after", F.lead("head").over(Window.partitionBy("layer").orderBy("seg"))).select("layer", "seg", "after")
    return inside.join(F.broadcast(after), ["layer", "seg"]).select("layer", "seg", "vid", "attr", F.coalesce("next", "after").alias("next"))


def bulk_backbone(base: DataFrame, m: int, ef_cons: int, rule: str = "decay") -> DataFrame:
    """(layer, src, chunk, dst, dist, rnk): for each node, layer and segment the ef_cons nearest others pruned to m; the order-free form of the build."""
    rows = settle(layers(base, m, rule).select("layer", "vid", F.col("vec").cast("array<double>").alias("vec"), "seg"))
    most = rows.agg(F.max("seg").alias("seg"), F.max("layer").alias("layer")).first()
    if most["seg"] is None:
        return pruned_edges(rows.select("layer", F.col("vid").alias("src"), F.col("seg").alias("chunk"), F.col("vid").alias("dst"), F.lit(0.0).alias("dist")), base, m, ["layer", "src", "chunk"])
    # Layer and segment are one number, the attribute in which a node asks for one value; an object of that value may be the node itself.
    wide = most["seg"] + 1
    codes = wide * (most["layer"] + 1)
    chunks = rows.select("layer", "vid", "vec", F.explode(F.sequence(F.lit(0), F.lit(most["seg"]))).alias("chunk"))
    code = (F.col("layer") * wide + F.col("chunk")).cast("long")
    ask = chunks.select((F.col("vid") * codes + code).alias("qid"), F.col("vec").alias("qvec"), code.cast("double").alias("lo"), code.cast("double").alias("hi"), F.lit(ef_cons + 1).alias("k"))
    have = rows.select("vid", "vec", (F.col("layer") * wide + F.col("seg")).cast("double").alias("attr"))
    near = range_knn_blocks(have.sortWithinPartitions("attr"), ask).select(F.expr(f"(qid - pmod(qid, {codes})) div {codes}").cast("long").alias("src"), F.pmod("qid", F.lit(codes)).alias("_code"), F.col("vid").alias("dst"), "dist")
    near = near.where("src <> dst").select(F.floor(F.col("_code") / wide).cast("int").alias("layer"), "src", F.pmod("_code", F.lit(wide)).cast("int").alias("chunk"), "dst", "dist")
    near = top(near, ["layer", "src", "chunk"], F.lit(ef_cons), ["dist", "dst"]).drop("rnk")
    return pruned_edges(near, base, m, ["layer", "src", "chunk"])


def closed(edges: DataFrame, base: DataFrame, m: int) -> DataFrame:
    """Add each edge's reverse, in the chunk of its new end's segment, and prune every chunk to m again."""
    seg = base.select(F.col("vid").alias("src"), F.col("seg").alias("chunk"))
    back = edges.select("layer", F.col("dst").alias("src2"), F.col("src").alias("dst2"), "dist").join(seg.withColumnRenamed("src", "dst2"), "dst2")
    both = edges.select("layer", "src", "chunk", "dst", "dist").unionByName(back.select("layer", F.col("src2").alias("src"), "chunk", F.col("dst2").alias("dst"), "dist")).dropDuplicates(["layer", "src", "chunk", "dst"])
    return pruned_edges(both, base, m, ["layer", "src", "chunk"])


def global_mask(edges: DataFrame, base: DataFrame, m: int) -> DataFrame:
    """(layer, src, dst, dist, rnk): of each node's edges over all chunks the m that pruning keeps, the graph of the whole table."""
    return pruned_edges(edges.select("layer", "src", "dst", "dist"), base, m, ["layer", "src"])


def expand(edges: DataFrame, queries: DataFrame, node: str, m: int, pick: str) -> DataFrame:
    """(qid, dst, dist, fanout): neighbours that one expansion of ``node`` looks at.

    ``queries`` holds (qid, node, segs): segments of the range. ``chunk`` takes the first ceil(m / segments) of each chunk, ``distance`` the m
    nearest over all of them.
    """
    hit = queries.withColumn("share", F.ceil(m / F.size("segs"))).join(edges.withColumnRenamed("src", node), node).where(F.array_contains("segs", F.col("chunk")))
    if pick == "chunk":
        return hit.where(F.col("rnk") <= F.col("share")).select("qid", "dst", "dist")
    return top(hit.select("qid", "dst", "dist"), ["qid"], F.lit(m), ["dist", "dst"]).select("qid", "dst", "dist")
