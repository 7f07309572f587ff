"""Built from Spark's own functions, so they stay in the JVM and the optimizer sees them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, SparkSession, functions as F

ColumnOrName = Column | str


def _doubles(c: ColumnOrName) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("array<double>")


def _sum(c: Column) -> Column:
    return F.aggregate(c, F.lit(0.0), lambda a, x: a + x)


def l2sq(a: ColumnOrName, b: ColumnOrName) -> Column:
    """Squared Euclidean distance in double precision; null if the lengths differ."""
    return _sum(F.zip_with(_doubles(a), _doubles(b), lambda x, y: (x - y) * (x - y)))


def l2(a: ColumnOrName, b: ColumnOrName) -> Column:
    return F.sqrt(l2sq(a, b))


def inner_product(a: ColumnOrName, b: ColumnOrName) -> Column:
    return _sum(F.zip_with(_doubles(a), _doubles(b), lambda x, y: x * y))


def norm(a: ColumnOrName) -> Column:
    return F.sqrt(_sum(F.transform(_doubles(a), lambda x: x * x)))


def cosine_distance(a: ColumnOrName, b: ColumnOrName) -> Column:
    """One minus the cosine; null for a zero vector."""
    return 1 - inner_product(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0))


def add(a: ColumnOrName, b: ColumnOrName) -> Column:
    return F.zip_with(_doubles(a), _doubles(b), lambda x, y: x + y)


def scale(a: ColumnOrName, by: ColumnOrName | float) -> Column:
    k = F.lit(by) if isinstance(by, (int, float)) else by
    return F.transform(_doubles(a), lambda x: x * k)


METRICS = {"l2": l2, "cosine": cosine_distance, "ip": lambda a, b: -inner_product(a, b)}


def register_sql(spark: SparkSession) -> None:
    """Temporary SQL functions of the same meaning; Spark inlines their bodies."""
    two, one = "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "a ARRAY<DOUBLE>"
    total = "aggregate({}, 0D, (s, x) -> s + x)"
    for name, args, body in (
        ("rv_l2sq", two, total.format("zip_with(a, b, (x, y) -> (x - y) * (x - y))")),
        ("rv_l2", two, "sqrt(" + total.format("zip_with(a, b, (x, y) -> (x - y) * (x - y))") + ")"),
        ("rv_ip", two, total.format("zip_with(a, b, (x, y) -> x * y)")),
        ("rv_norm", one, "sqrt(" + total.format("transform(a, x -> x * x)") + ")"),
        ("rv_cos", two, total.format("zip_with(a, b, (x, y) -> x * y)") + " / nullif(sqrt(" + total.format("transform(a, x -> x * x)") + ") * sqrt(" + total.format("transform(b, x -> x * x)") + "), 0D)"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")


def in_range(attr: ColumnOrName, lo: ColumnOrName, hi: ColumnOrName) -> Column:
    """Closed range; a null bound is open on that side, a null or NaN attribute is in no range."""
    a, low, high = (F.col(c) if isinstance(c, str) else c for c in (attr, lo, hi))
    return a.isNotNull() & ~F.isnan(a.cast("double")) & F.coalesce(a >= low, F.lit(True)) & F.coalesce(a <= high, F.lit(True))


def uniform(key: ColumnOrName, salt: str) -> Column:
    """A number in (0, 1) that depends on the key and the salt alone: 32 bits of an MD5 digest."""
    k = F.col(key) if isinstance(key, str) else key
    head = F.conv(F.substring(F.md5(F.concat(k.cast("string"), F.lit(f":{salt}"))), 1, 8), 16, 10)
    return (head.cast("double") + 0.5) / F.lit(4294967296.0)


def level(key: ColumnOrName, m: int, rule: str = "decay", salt: str = "level") -> Column:
    """The top layer of a node: exponentially fewer nodes in higher layers.

    ``decay``: floor(-ln(u) / ln(m)), layers shrink by m. ``inside``: the scale stands inside the logarithm, floor(-ln(u / ln(m))), not below 0.
    """
    u = uniform(key, salt)
    scale_ = F.lit(1.0) / F.log(F.lit(float(m)))
    raw = -F.log(u) * scale_ if rule == "decay" else -F.log(u * scale_)
    return F.greatest(F.floor(raw), F.lit(0)).cast("int")


def interleave(columns: list[Column], bits: int) -> Column:
    """Z-order key of non-negative integers below 2^bits: bit b of column j goes to place b * n + j."""
    n = len(columns)
    if n * bits > 62:
        raise ValueError("the key needs more than 62 bits")
    parts = [F.shiftleft(F.shiftright(c.cast("long"), b).bitwiseAND(F.lit(1).cast("long")), b * n + j) for b in range(bits) for j, c in enumerate(columns)]
    return reduce(lambda x, y: x.bitwiseOR(y), parts)
