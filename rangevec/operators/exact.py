"""Exact answers: nearest neighbours within an attribute range, and range cardinalities."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.columns import METRICS, in_range

#: A query batch whose vectors take up to so many bytes is broadcast; a larger one is joined by segment, or taken in blocks.
MOST_BYTES = 32 << 20


def batch_blocks(queries: DataFrame) -> int:
    """In how many blocks a query batch (qvec) may be broadcast, by its rows and the length of its vectors."""
    seen = queries.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("qvec")).alias("d")).first()
    return max(1, -(-seen["n"] * (8 * (seen["d"] or 0) + 64) // MOST_BYTES))


def top(df: DataFrame, by: list[str], k: Column, order: list[str] = ("dist", "vid")) -> DataFrame:
    """The first k rows of each group with their rank; Spark limits each group before the shuffle."""
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("rnk", F.row_number().over(w)).where(F.col("rnk") <= k)


def range_knn(base: DataFrame, queries: DataFrame, k: int | None = None, metric: str = "l2", segments: DataFrame | None = None) -> DataFrame:
    """(qid, rnk, vid, dist): for each query the k objects of its closed range nearest to it, by distance and then id; all objects if fewer.

    A null bound is open, an object without attribute is in no range, an empty range gives no row. Query batches of a checked size are broadcast, and the
    range is tested before any distance. With ``segments``, or beyond that size, both sides are joined on the segments that a range meets.
    """
    q = queries if k is None else queries.withColumn("k", F.lit(k))
    q = q.select("qid", "qvec", "lo", "hi", "k")
    dist = METRICS[metric](F.col("vec"), F.col("qvec")).alias("dist")
    if segments is None and (parts := batch_blocks(q)) > 1:
        from .segment import fit, table

        segments = table(base, fit(base, max(64, parts)))
    if segments is None:
        bounds = q.agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.max(F.col("lo").isNull() | F.col("hi").isNull()).alias("open")).first()
        if bounds["lo"] is not None and bounds["hi"] is not None and not bounds["open"]:
            # The batch's envelope reaches the scan; the join tests each range.
            base = base.where(F.col("attr").between(bounds["lo"], bounds["hi"]))
        pairs = base.join(F.broadcast(q), in_range("attr", "lo", "hi"))
        return top(pairs.select("qid", "vid", dist, "k"), ["qid"], F.col("k")).select("qid", "rnk", "vid", "dist")
    from .segment import assign, intersecting

    hit = intersecting(q, segments).select("qid", "seg").join(q, "qid")
    pairs = assign(base, segments).join(hit, "seg").where(in_range("attr", "lo", "hi"))
    # Winners of each segment first, so that no query gathers more than k rows of each.
    part = top(pairs.select("qid", "seg", "vid", dist, "k"), ["qid", "seg"], F.col("k")).drop("rnk")
    return top(part, ["qid"], F.col("k")).select("qid", "rnk", "vid", "dist")


def knn(base: DataFrame, queries: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """The same without a range."""
    return range_knn(base, queries.select("qid", "qvec").withColumns({"lo": F.lit(None).cast("double"), "hi": F.lit(None).cast("double")}), k, metric)


def range_knn_blocks(base: DataFrame, queries: DataFrame, k: int | None = None, block: int = 2048, metric: str = "l2", spread: float | None = None) -> DataFrame:
    """``range_knn`` by matrix products: the queries go to the tasks as one matrix of a checked size, or several; each task hands on its k best for each query.

    Products only choose candidates: a margin covers their rounding, and kept distances are taken from differences. ``metric`` is l2, cosine or ip; a zero vector's
    cosine is NaN and comes last. With ``spread`` no object is filtered: its distance grows by the gap between its attribute and the range, over ``spread``.
    """
    q = queries if k is None else queries.withColumn("k", F.lit(k))
    parts = batch_blocks(q)
    if parts > 1:
        # The stated queries against all rows, in blocks of about half the bound.
        each = [_block_knn(base, q.where(F.pmod(F.xxhash64("qid"), F.lit(2 * parts)) == i), block, metric, spread) for i in range(2 * parts)]
        return reduce(DataFrame.unionByName, each)
    return _block_knn(base, q, block, metric, spread)


def _matrix(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(column), -1)


def _unit_rows(x: np.ndarray) -> np.ndarray:
    """Rows over their lengths; NaN for a zero vector."""
    with np.errstate(invalid="ignore", divide="ignore"):
        return x / np.sqrt((x**2).sum(axis=1))[:, None]


def _leaves(x: np.ndarray, most: int) -> list[np.ndarray]:
    """Rows in runs of at most ``most`` that lie close together: halves of the widest dimension. All runs but the last are full."""
    todo, out = [np.arange(len(x))], []
    while todo:
        at = todo.pop()
        if len(at) <= most:
            out.append(at)
            continue
        half, wide = max(most, len(at) // (2 * most) * most), int(np.ptp(x[at], axis=0).argmax())
        at = at[np.argpartition(x[at, wide], half)]
        todo += [at[half:], at[:half]]
    return out


class _Best:
    """The k best objects of each query so far, over blocks of objects (``see``): distances and ids, nearest first, padded by infinity."""

    #: Entries of a tile of queries by objects, and components of the pairs whose differences are taken at once.
    TILE, PAIRS = 1 << 18, 1 << 20
    #: Objects of a leaf, queries that go through the leaves side by side, objects that are held for it, and the most dimensions in which boxes part much.
    LEAF, SIDE, HELD, DIMS = 256, 256, 1 << 17, 16

    def __init__(self, x: np.ndarray, lo: np.ndarray, hi: np.ndarray, ks: np.ndarray, metric: str, spread: float | None):
        self.x, self.lo, self.hi, self.ks, self.metric, self.spread = x, lo, hi, ks, metric, spread
        self.k = int(ks.max())
        self.dist, self.vid = np.full((len(x), self.k), np.inf), np.zeros((len(x), self.k), np.int64)
        self.count = np.zeros(len(x), np.int64)
        self.norm = np.sqrt((x**2).sum(axis=1))
        self.unit = _unit_rows(x) if metric == "cosine" else None
        # The square of a difference as one product.
        self.wide = np.hstack([-2 * x, (self.norm**2)[:, None], np.ones((len(x), 1))])
        # Queries lie by their lower bounds first, so they lie close together only where many share one.
        self.boxed = metric == "l2" and spread is None and x.shape[1] <= self.DIMS and self.SIDE * len(np.unique(lo)) <= len(lo) and bool(np.isfinite(x).all())

    def _gap(self, attr: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        return np.maximum(np.abs(attr - (lo + hi) / 2) - (hi - lo) / 2, 0) / self.spread

    def _rough(self, at: slice, vec: np.ndarray, attr: np.ndarray, norm: np.ndarray) -> np.ndarray:
        """What orders a tile's objects up to rounding: a distance or its square; infinity out of range."""
        if self.metric == "l2":
            r = self.wide[at] @ np.hstack([vec, np.ones((len(vec), 1)), (norm**2)[:, None]]).T
        elif self.metric == "ip":
            r = -(self.x[at] @ vec.T)
        else:
            r = 1 - self.unit[at] @ _unit_rows(vec).T
            # Without a cosine an object comes last, but before those out of range.
            r[np.isnan(r)] = np.finfo(np.float64).max
        lo, hi = self.lo[at], self.hi[at]
        if self.spread is not None:
            return np.sqrt(np.maximum(r, 0, out=r), out=r) + self._gap(attr[None, :], lo[:, None], hi[:, None])
        if len(attr) and (attr.min() < lo.max() or attr.max() > hi.min()):
            r[(attr[None, :] < lo[:, None]) | (attr[None, :] > hi[:, None])] = np.inf
        return r

    def _exact(self, rows: np.ndarray, vec: np.ndarray, attr: np.ndarray, cols: np.ndarray) -> np.ndarray:
        out, step = np.empty(len(rows)), max(1, self.PAIRS // max(1, vec.shape[1]))
        for i in range(0, len(rows), step):
            r, c = rows[i : i + step], cols[i : i + step]
            if self.metric == "l2":
                d = np.sqrt(((vec[c] - self.x[r]) ** 2).sum(axis=1))
            else:
                d = (vec[c] * self.x[r]).sum(axis=1)
                if self.metric == "cosine":
                    with np.errstate(invalid="ignore"):
                        d = 1 - d / (np.sqrt((vec[c] ** 2).sum(axis=1)) * self.norm[r])
                else:
                    d = -d
            out[i : i + step] = d if self.spread is None else d + self._gap(attr[c], self.lo[r], self.hi[r])
        return out

    def see(self, vec: np.ndarray, attr: np.ndarray, vid: np.ndarray) -> None:
        norm = np.sqrt((vec**2).sum(axis=1))
        step, first, end = max(1, self.TILE // max(1, len(vid))), 0, len(self.x)
        if self.spread is None and len(attr):
            # Queries lie by their lower bounds; those before and behind these meet no object of the block.
            met = np.flatnonzero((self.lo <= attr.max()) & (self.hi >= attr.min()))
            first, end = (int(met[0]), int(met[-1]) + 1) if len(met) else (0, 0)
        for start in range(first, end, step):
            self._tile(slice(start, min(end, start + step)), vec, attr, vid, norm)

    def near(self, vec: np.ndarray, attr: np.ndarray, vid: np.ndarray) -> None:
        """``see`` for many objects of few dimensions: queries that lie close together go through boxes of objects, the nearest first, as long as one may hold a nearer object."""
        if not np.isfinite(vec).all():
            for i in range(0, len(vid), 2048):
                self.see(vec[i : i + 2048], attr[i : i + 2048], vid[i : i + 2048])
            return
        norm = np.sqrt((vec**2).sum(axis=1))
        leaves = [(vec[i], attr[i], vid[i], norm[i]) for i in _leaves(vec, self.LEAF)]
        low, high = np.array([v[0].min(axis=0) for v in leaves]), np.array([v[0].max(axis=0) for v in leaves])
        first, last = np.array([v[1].min() for v in leaves]), np.array([v[1].max() for v in leaves])
        gap = lambda a, b, c, d: (np.maximum(np.maximum(c - b, a - d), 0) ** 2).sum(axis=-1)
        for start in range(0, len(self.x), self.SIDE):
            at = slice(start, min(len(self.x), start + self.SIDE))
            x, slack = self.x[at], 1e-9 + 1e-12 * (1 + self.norm[at].max() + norm.max()) ** 2
            far = gap(x.min(axis=0), x.max(axis=0), low, high)
            far[(last < self.lo[at].min()) | (first > self.hi[at].max())] = np.inf
            for j in np.argsort(far):
                edge = self.dist[at, self.k - 1] ** 2 * (1 + 1e-9) + slack
                if far[j] == np.inf or far[j] > edge.max():
                    break
                if (gap(x, x, low[j], high[j]) <= edge).any():
                    self._tile(at, *leaves[j])

    def _tile(self, at: slice, vec: np.ndarray, attr: np.ndarray, vid: np.ndarray, norm: np.ndarray) -> None:
        rough, k, n = self._rough(at, vec, attr, norm), self.k, at.stop - at.start
        size = 1 + self.norm[at] + norm.max()
        margin = 1e-6 * size if self.spread is not None else 1e-9 + 1e-12 * size**2
        last = self.dist[at, k - 1]
        full = self.count[at] >= k
        edge = np.full(n, np.inf)
        known = last[full]
        edge[full] = np.where(np.isnan(known), np.inf, known**2 if self.metric == "l2" and self.spread is None else known)
        if rough.shape[1] > k and not full.all():
            edge[~full] = np.partition(rough[~full], k - 1, axis=1)[:, k - 1]
        near = rough <= (edge + margin + 1e-9 * np.abs(np.where(np.isfinite(edge), edge, 0)))[:, None]
        rows, cols = np.divmod(np.flatnonzero(near), near.shape[1])
        inside = rough[rows, cols] < np.inf
        rows, cols = rows[inside], cols[inside]
        if not len(rows):
            return
        touched = np.unique(rows)
        i, kept = np.nonzero(np.arange(k)[None, :] < self.count[at][touched][:, None])
        own = touched[i]
        d = np.concatenate([self.dist[at][own, kept], self._exact(rows + at.start, vec, attr, cols)])
        v = np.concatenate([self.vid[at][own, kept], vid[cols]])
        r = np.concatenate([own, rows])
        order = np.lexsort([v, d, r])
        d, v, r = d[order], v[order], r[order]
        place = np.arange(len(r)) - np.searchsorted(r, r, "left")
        ok = place < k
        self.dist[at][r[ok], place[ok]], self.vid[at][r[ok], place[ok]] = d[ok], v[ok]
        self.count[at] = np.maximum(self.count[at], np.minimum(np.bincount(r, minlength=n), k))

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, id, distance), of each query as many as it asks for."""
        r, c = np.nonzero(np.arange(self.k)[None, :] < np.minimum(self.count, self.ks)[:, None])
        return r, self.vid[r, c], self.dist[r, c]


def _block_knn(base: DataFrame, q: DataFrame, block: int, metric: str = "l2", spread: float | None = None) -> DataFrame:
    """``range_knn_blocks`` for queries that go to the tasks as one matrix."""
    spark, rows = base.sparkSession, q.select("qid", "qvec", "lo", "hi", "k").toArrow()
    if not rows.num_rows:
        return spark.createDataFrame([], "qid long, rnk int, vid long, dist double")
    qid = rows.column("qid").to_numpy()
    x = _matrix(rows.column("qvec").combine_chunks())
    lo = np.array([-np.inf if v is None else v for v in rows.column("lo").to_pylist()], np.float64)
    hi = np.array([np.inf if v is None else v for v in rows.column("hi").to_pylist()], np.float64)
    ks, order = rows.column("k").to_numpy(), np.arange(len(lo))
    if metric == "l2" and x.shape[1] <= _Best.DIMS and np.isfinite(x).all():
        order = np.concatenate(_leaves(x, _Best.SIDE))
    order = order[np.argsort(lo[order], kind="stable")]
    qid, x, lo, hi, ks = (c[order] for c in (qid, x, lo, hi, ks))
    sent = spark.sparkContext.broadcast((qid, x, lo, hi, ks))
    schema = pa.schema([("qid", pa.int64()), ("vid", pa.int64()), ("dist", pa.float64()), ("k", pa.int32())])

    def run(batches):
        qid, x, lo, hi, ks = sent.value
        best, held = _Best(x, lo, hi, ks, metric, spread), []
        for whole in batches:
            for at in range(0, whole.num_rows, block):
                b = whole.slice(at, block)
                part = _matrix(b.column("vec")), b.column("attr").to_numpy(), b.column("vid").to_numpy()
                if not best.boxed:
                    best.see(*part)
                    continue
                held.append(part)
                if sum(len(p[2]) for p in held) >= best.HELD:
                    best.near(*map(np.concatenate, zip(*held, strict=True)))
                    held = []
        if held:
            best.near(*map(np.concatenate, zip(*held, strict=True)))
        r, vid, dist = best.rows()
        for i in range(0, len(r), 1 << 16):
            at = slice(i, i + (1 << 16))
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (qid[r[at]], vid[at], dist[at], ks[r[at]].astype(np.int32))], schema=schema)

    near = base.where("attr is not null and not isnan(attr)").select("vid", F.col("vec").cast("array<double>").alias("vec"), F.col("attr").cast("double").alias("attr"))
    if spread is None and np.isfinite(lo.min()) | np.isfinite(hi.max()):
        # The batch's envelope reaches the scan.
        near = near.where(F.col("attr").between(float(lo.min()), float(hi.max())))
    # A task keeps k rows of each query, so there are no more tasks than cores keep busy.
    parts = near.coalesce(2 * spark.sparkContext.defaultParallelism).mapInArrow(run, "qid long, vid long, dist double, k int")
    return top(parts, ["qid"], F.col("k")).select("qid", "rnk", "vid", "dist")


def cardinality(base: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, y): the number of objects in each range, zero included. Objects are ranked once, and each bound looks up the ranks at the nearest value below it."""
    from ..sources.durable import ranked, settle
    from .asof import asof

    rows = base.where(F.col("attr").isNotNull() & ~F.isnan(F.col("attr").cast("double"))).select(F.col("attr").cast("double").alias("v"), "vid")
    have = ranked(rows, ["v", "vid"], "rank").groupBy("v").agg(F.min("rank").alias("before"), (F.max("rank") + 1).alias("upto"))
    have = settle(have.select("v", F.col("upto").alias("key"), F.struct("v", "before", "upto").alias("at")))
    n = have.agg(F.max("key")).first()[0] or 0
    ends = queries.select("qid", F.explode(F.array(F.struct(F.lit("lo").alias("end"), F.col("lo").cast("double").alias("v")), F.struct(F.lit("hi").alias("end"), F.col("hi").cast("double").alias("v")))).alias("e")).select("qid", "e.end", "e.v")
    met = asof(ends.where("v IS NOT NULL"), have, "v", "at", "key")
    below = F.when(F.col("at.v") == F.col("v"), F.col("at.before")).otherwise(F.col("at.upto"))
    count = F.coalesce(F.when(F.col("end") == "lo", -below).otherwise(F.col("at.upto")), F.lit(0))
    sums = met.groupBy("qid").agg(F.sum(count).alias("y"))
    # An open upper bound holds everything.
    y = F.coalesce("y", F.lit(0)) + F.when(F.col("hi").isNull(), F.lit(n)).otherwise(F.lit(0))
    return queries.select("qid", "hi").join(sums, "qid", "left").select("qid", F.greatest(y, F.lit(0)).cast("long").alias("y"))
