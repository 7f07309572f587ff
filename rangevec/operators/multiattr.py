"""Two and more attributes: exact conjunctions and disjunctions, and one attribute made of several by interleaving ranks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.columns import METRICS, in_range, interleave
from .exact import batch_blocks, top


def sent(queries: DataFrame) -> DataFrame:
    """Queries, broadcast if their size allows; else Spark chooses how to meet them."""
    return F.broadcast(queries) if batch_blocks(queries) == 1 else queries


def exact_both(base: DataFrame, queries: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """Nearest objects with attr in [lo, hi] and attr2 in [lo2, hi2]."""
    pairs = base.join(sent(queries), in_range("attr", "lo", "hi") & in_range("attr2", "lo2", "hi2"))
    return top(pairs.select("qid", "vid", METRICS[metric](F.col("vec"), F.col("qvec")).alias("dist")), ["qid"], F.lit(k)).select("qid", "rnk", "vid", "dist")


def exact_either(base: DataFrame, queries: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """Nearest objects with one of the two."""
    pairs = base.join(sent(queries), in_range("attr", "lo", "hi") | in_range("attr2", "lo2", "hi2"))
    return top(pairs.select("qid", "vid", METRICS[metric](F.col("vec"), F.col("qvec")).alias("dist")), ["qid"], F.lit(k)).select("qid", "rnk", "vid", "dist")


def cuts(base: DataFrame, attr: str, bits: int, method: str = "exact") -> list[float]:
    """At most 2^bits - 1 boundaries of about equal counts."""
    from .segment import fit

    return fit(base.select("vid", F.col(attr).alias("attr")), 1 << bits, method)


def cell(attr: str, bounds: list[float]):
    from .segment import segment_of

    return segment_of(F.col(attr), bounds)


def zorder(base: DataFrame, attrs: list[str], bounds: list[list[float]], bits: int, name: str = "attr") -> DataFrame:
    """Adds the interleaved cells of several attributes as one attribute."""
    return base.withColumn(name, interleave([cell(a, b) for a, b in zip(attrs, bounds, strict=True)], bits).cast("double"))


def zranges(queries: DataFrame, bounds: list[list[float]], bits: int) -> DataFrame:
    """Adds zlo and zhi: the interleaved keys of a rectangle's lower and upper corner enclose those of all its cells, and others; results need the rectangle's test."""
    return zorder(zorder(queries, ["lo", "lo2"], bounds, bits, "zlo"), ["hi", "hi2"], bounds, bits, "zhi")


def zcover(lo: tuple[int, ...], hi: tuple[int, ...], bits: int, most: int = 16) -> list[tuple[int, int]]:
    """At most ``most`` intervals of keys that cover a rectangle of cells, none of which lies wholly outside it.

    Blocks of the curve are split while they are partly outside and the number allows; the fewer, the more cells outside are covered.
    """
    n = len(lo)
    todo, done = [(0, bits)], []
    while todo:
        todo.sort(key=lambda t: -t[1])
        z, b = todo.pop(0)
        corner = [sum(((z >> (i * n + j)) & 1) << i for i in range(bits)) for j in range(n)]
        size = 1 << b
        if any(c + size - 1 < x or c > y for c, x, y in zip(corner, lo, hi, strict=True)):
            continue
        inside = all(x <= c and c + size - 1 <= y for c, x, y in zip(corner, lo, hi, strict=True))
        if inside or b == 0 or len(todo) + len(done) + (1 << n) > most:
            done.append((z, z + (1 << (n * b)) - 1))
        else:
            todo += [(z + (i << (n * (b - 1))), b - 1) for i in range(1 << n)]
    out: list[tuple[int, int]] = []
    for a, b in sorted(done):
        if out and out[-1][1] + 1 == a:
            out[-1] = (out[-1][0], b)
        else:
            out.append((a, b))
    return out


def covers(queries: DataFrame, bounds: list[list[float]], bits: int, most: int = 16) -> DataFrame:
    """Queries with zlo and zhi, a row for each of at most ``most`` intervals of keys that together cover the query's rectangle of cells."""
    low, high = [cell(c, b) for c, b in zip(("lo", "lo2"), bounds, strict=True)], [cell(c, b) for c, b in zip(("hi", "hi2"), bounds, strict=True)]

    @F.udf("array<struct<zlo:double,zhi:double>>")
    def cut(a: list[int], b: list[int]) -> list[tuple[float, float]]:
        return [(float(x), float(y)) for x, y in zcover(tuple(a), tuple(b), bits, most)]

    return queries.withColumn("_z", F.explode(cut(F.array(*low), F.array(*high)))).select(*queries.columns, "_z.zlo", "_z.zhi")


def zsearch(index, base: DataFrame, queries: DataFrame, bounds: list[list[float]], bits: int, k: int, most: int = 16) -> DataFrame:
    """A conjunction by one index over the interleaved key of two attributes: (qid, rnk, vid, dist), exact.

    ``index`` holds the key as its attribute, ``base`` (vid, attr1, attr2). Each interval that covers a query's rectangle is followed along the chain, and what it gives
    has to pass the rectangle's own test, since a cover also holds cells outside.
    """
    parts = covers(queries, bounds, bits, most).withColumn("part", F.row_number().over(Window.partitionBy("qid").orderBy("zlo")))
    # The rectangle is tested in the index, so an interval gives k objects and not all that it holds.
    ask = parts.select((F.col("qid") * most + F.col("part") - 1).alias("qid"), "qvec", F.col("zlo").alias("lo"), F.col("zhi").alias("hi"), *[F.col(a).alias(b) for a, b in (("lo", "lo2"), ("hi", "hi2"), ("lo2", "lo3"), ("hi2", "hi3"))])
    found = index.search(ask, "pre", k=k, also=base.select("vid", F.col("attr1").alias("attr2"), F.col("attr2").alias("attr3")))
    near = found.select(F.floor(F.col("qid") / most).alias("qid"), "vid", "dist").distinct()
    return top(near, ["qid"], F.lit(k)).select("qid", "rnk", "vid", "dist")
