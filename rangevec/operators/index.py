"""The stored index: shards by attribute range, each a layered chunk graph in flat arrays, searched by filtering before, after or during the vector search."""

from __future__ import annotations

import functools
import json
import time
import uuid
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.columns import level
from ..sources.durable import copy_file, open_arrays, settle, shared_folder, store_arrays
from . import segment
from .exact import top
from .kernel import BRIDGE, DIST, EDGES, HOPS, VISITED, Graph, Params, estimated

PARTS = "shard int, path string, rows long, n_dist long, build_s double"
RESULT = "qid long, k int, vid long, dist double, strategy string, n_dist long, n_visited long, n_bridge long, hops long, n_edges long, latency_ms double"
COUNTS = ("n_dist", "n_visited", "n_bridge", "hops", "n_edges", "latency_ms")
#: Queries that one task searches side by side in a shard.
QUERY_BLOCK = 64


@dataclass
class Manifest:
    """``outer`` cuts the attribute into shards, ``inner[s]`` shard s into segments; both are fixed when the index is built. ``parts`` names each shard's file: (shard, path, rows)."""

    s: int
    params: dict
    outer: list[float]
    inner: list[list[float]]
    dim: int
    level_rule: str
    rows: int
    tau: tuple[float, float] = (0.01, 0.5)
    parts: list[tuple[int, str, int]] = field(default_factory=list)


@functools.lru_cache(maxsize=64)
def _arrays(path: str) -> dict[str, np.ndarray]:
    return open_arrays(path)


def _vectors(column: pa.ChunkedArray, dim: int) -> np.ndarray:
    flat = column.combine_chunks().flatten()
    return np.asarray(flat.to_numpy(zero_copy_only=False), np.float64).reshape(len(column), dim)


class RangeIndex:
    """One index for all three strategies.

    Shards are attribute ranges, so a query opens only those that its range meets; within a shard, S segments share one graph. A shard is one file of arrays in the
    shared folder, which tasks map into memory: a search moves its queries to the shards and no node to the queries. One task builds a shard, so
    ``shards`` must keep rows * (8 d + 13 S M) bytes within a worker's memory.
    """

    def __init__(self, spark: SparkSession, manifest: Manifest):
        self.spark, self.manifest, self.params = spark, manifest, Params(**manifest.params)
        #: What the last build or append took: (shard, path, rows, n_dist, build_s).
        self.built: list[tuple] = []

    # Construction.
    @staticmethod
    def _checked(base: DataFrame) -> tuple[DataFrame, int]:
        rows = base.where(F.col("attr").isNotNull() & ~F.isnan(F.col("attr").cast("double"))).select("vid", F.col("vec").cast("array<double>").alias("vec"), F.col("attr").cast("double").alias("attr"))
        seen = rows.agg(F.min(F.size("vec")).alias("a"), F.max(F.size("vec")).alias("b"), F.max(F.exists("vec", lambda x: x.isNull() | F.isnan(x))).alias("bad"), F.count("vid").alias("n")).first()
        twice = not rows.groupBy("vid").count().where("count > 1").isEmpty()
        if seen["n"] and (seen["a"] != seen["b"] or seen["bad"] or twice):
            raise ValueError("vectors must have one length and no missing component, and ids must be unique")
        return rows, seen["a"] or 0

    @classmethod
    def build(cls, base: DataFrame, s: int = 8, m: int = 16, ef_cons: int = 500, shards: int = 1, level_rule: str = "decay", order: str = "vid", segment_method: str = "exact", folder: str | None = None, **more) -> RangeIndex:
        """Cut the attribute into shards and segments, and insert each shard's objects in the order of ``order``. Objects without an attribute stay out."""
        if s < 1 or m < 2 or shards < 1:
            raise ValueError("s and shards must be 1 at least, m 2")
        rows, dim = cls._checked(base)
        outer, inner = segment.fit_nested(rows, shards, s, segment_method)
        manifest = Manifest(s, asdict(Params(m=m, ef_cons=ef_cons, **more)), outer, inner, dim, level_rule, 0)
        return cls._inserted(rows, manifest, order, folder)

    @classmethod
    def _inserted(cls, rows: DataFrame, manifest: Manifest, order: str = "vid", folder: str | None = None) -> RangeIndex:
        """Insert rows into the shards that they belong to; those files are written anew, the others stay."""
        spark = rows.sparkSession
        folder = folder or f"{shared_folder(spark)}/index-{uuid.uuid4().hex}"
        outer, inner, s, params, dim = np.array(manifest.outer), [np.array(b) for b in manifest.inner], manifest.s, Params(**manifest.params), manifest.dim
        old = {shard: path for shard, path, _ in manifest.parts}

        @F.pandas_udf("shard int, seg int")
        def place(attr: pd.Series) -> pd.DataFrame:
            a = attr.to_numpy(np.float64)
            shard = np.searchsorted(outer, a, "right").astype(np.int32)
            seg = np.zeros(len(a), np.int32)
            for i in np.unique(shard):
                seg[shard == i] = np.searchsorted(inner[i], a[shard == i], "right")
            return pd.DataFrame({"shard": shard, "seg": seg})

        rows = rows.withColumn("at", F.col(order).cast("double")).withColumn("level", level("vid", manifest.params["m"], manifest.level_rule)).withColumn("place", place("attr"))

        def grow(table: pa.Table) -> pa.Table:
            began = time.perf_counter()
            shard = table.column("shard")[0].as_py()
            attr, vid, seg, lev, at = (table.column(c).to_numpy() for c in ("attr", "vid", "seg", "level", "at"))
            x, to = _vectors(table.column("vec"), dim), np.lexsort((vid, at))
            more = (x[to], attr[to], vid[to], seg[to], lev[to])
            g = Graph.of_arrays(open_arrays(old[shard]), s, params).grown(*more) if shard in old else Graph(*more, s, params)
            for v in range(g.size, len(g.vid)):
                g.insert(v)
            path = store_arrays(folder, f"shard-{shard}", g.arrays())
            return pa.Table.from_pylist([{"shard": shard, "path": path, "rows": g.size, "n_dist": g.dist, "build_s": time.perf_counter() - began}], pa.schema([("shard", pa.int32()), ("path", pa.string()), ("rows", pa.int64()), ("n_dist", pa.int64()), ("build_s", pa.float64())]))

        # A partition for each shard: by bytes, Spark would give several of them to one task.
        rows = rows.select("place.shard", "place.seg", "vid", "vec", "attr", "level", "at").repartitionById(len(outer) + 1, F.col("shard"))
        made = rows.groupBy("shard").applyInArrow(grow, PARTS).collect()
        parts = {shard: (shard, path, n) for shard, path, n in manifest.parts} | {r["shard"]: (r["shard"], r["path"], r["rows"]) for r in made}
        out = cls(spark, replace(manifest, parts=[parts[k] for k in sorted(parts)], rows=sum(p[2] for p in parts.values())))
        out.built = sorted(map(tuple, made))
        return out

    def append(self, new: DataFrame, order: str = "vid", folder: str | None = None) -> RangeIndex:
        """The index with more objects; boundaries stay, and only shards that get objects are opened again. Appending in order equals building at once."""
        rows, dim = self._checked(new)
        if dim not in (0, self.manifest.dim) and self.manifest.rows:
            raise ValueError("vectors of another length")
        return self._inserted(rows, replace(self.manifest, dim=self.manifest.dim or dim), order, folder)

    # Storage.
    def commit(self, path: str) -> None:
        """Write the manifest alone; shard files are immutable and stay where they are."""
        self.spark.createDataFrame([(json.dumps(asdict(self.manifest)),)], "value string").coalesce(1).write.text(f"{path}/manifest")

    def save(self, path: str | None = None) -> str:
        """Copy the shard files into a folder, and write the manifest beside them."""
        path = path or f"{shared_folder(self.spark)}/index-{uuid.uuid4().hex}"

        def copy(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                yield pdf.assign(path=[copy_file(p, f"{path}/shards") for p in pdf.path])

        moved = {r["shard"]: r["path"] for r in self._listed().mapInPandas(copy, "shard int, path string, rows long").collect()}
        RangeIndex(self.spark, replace(self.manifest, parts=[(s, moved[s], n) for s, _, n in self.manifest.parts])).commit(path)
        return path

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> RangeIndex:
        m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        return cls(spark, Manifest(**{**m, "tau": tuple(m["tau"]), "parts": [tuple(p) for p in m["parts"]]}))

    def _listed(self) -> DataFrame:
        """(shard, path, rows), a task for each shard."""
        n = max(1, len(self.manifest.parts))
        return self.spark.createDataFrame(self.manifest.parts, "shard int, path string, rows long").repartition(n, "shard")

    # Views.
    def _view(self, schema: str, make: Callable[[int, Graph], pd.DataFrame]) -> DataFrame:
        s, params = self.manifest.s, self.params

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                for shard, path in zip(pdf["shard"], pdf["path"], strict=True):
                    yield make(int(shard), Graph.of_arrays(_arrays(path), s, params))

        return self._listed().mapInPandas(run, schema)

    def segments(self) -> DataFrame:
        """(shard, seg, lo, hi): attribute intervals, closed below and open above."""
        rows, ends = [], [None, *self.manifest.outer, None]
        for i, inner in enumerate(self.manifest.inner):
            cuts = [ends[i], *inner, ends[i + 1]]
            rows += [(i, j, a, b) for j, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))]
        return self.spark.createDataFrame(rows, "shard int, seg int, lo double, hi double")

    def edges(self) -> DataFrame:
        """(shard, layer, src, chunk, dst, dist, rnk, masked)."""

        def make(shard: int, g: Graph) -> pd.DataFrame:
            out = []
            for i, one in enumerate(g.layers):
                r, j, c = np.nonzero(one.ids >= 0)
                out.append(pd.DataFrame({"shard": shard, "layer": i, "src": g.vid[one.node[r]], "chunk": j, "dst": g.vid[one.ids[r, j, c]], "dist": one.dist[r, j, c], "rnk": c + 1, "masked": one.mask[r, j, c]}))
            return pd.concat(out)

        return self._view("shard int, layer int, src long, chunk int, dst long, dist double, rnk int, masked boolean", make)

    def chain(self) -> DataFrame:
        """(shard, layer, vid, attr, next)."""

        def make(shard: int, g: Graph) -> pd.DataFrame:
            out = []
            for i, one in enumerate(g.layers):
                out.append(pd.DataFrame({"shard": shard, "layer": i, "vid": g.vid[one.node], "attr": g.attr[one.node], "next": pd.array(np.where(one.next >= 0, g.vid[one.next], 0), "Int64")}))
                out[-1].loc[one.next < 0, "next"] = pd.NA
            return pd.concat(out)

        return self._view("shard int, layer int, vid long, attr double, next long", make)

    def entries(self) -> DataFrame:
        """(shard, seg, top_layer, entry)."""

        def make(shard: int, g: Graph) -> pd.DataFrame:
            j = np.flatnonzero(g.entry >= 0)
            return pd.DataFrame({"shard": shard, "seg": j, "top_layer": g.level[g.entry[j]], "entry": g.vid[g.entry[j]]})

        return self._view("shard int, seg int, top_layer int, entry long", make)

    def vectors(self) -> DataFrame:
        """(vid, vec, attr, seg, shard)."""
        return self._view("vid long, vec array<double>, attr double, seg int, shard int", lambda shard, g: pd.DataFrame({"vid": g.vid, "vec": list(g.x), "attr": g.attr, "seg": g.seg, "shard": shard}))

    def stats(self) -> DataFrame:
        """Per layer: nodes, edges, masked edges, logical bytes of the graph with 32-bit edges, bit masks and successors, and those of 32-bit vectors."""

        def make(shard: int, g: Graph) -> pd.DataFrame:
            return pd.DataFrame([(i, len(one.node), int((one.ids >= 0).sum()), int(one.mask.sum()), 4 * g.x.shape[1] * len(g.vid) if i == 0 else 0) for i, one in enumerate(g.layers)], columns=["layer", "nodes", "edges", "masked", "vector_bytes"])

        parts = self._view("layer int, nodes long, edges long, masked long, vector_bytes long", make)
        sums = parts.groupBy("layer").agg(*[F.sum(c).alias(c) for c in ("nodes", "edges", "masked", "vector_bytes")])
        return sums.withColumn("graph_bytes", F.col("edges") * (4 + 1 / 8) + F.col("nodes") * 4)

    def locate(self, queries: DataFrame) -> DataFrame:
        """(qid, first, steps): the first object at or above each query's ``lo``, found by descending the chain of its shard, or of the next one, since no shard is empty."""
        shard = segment.segment_of(F.col("lo"), self.manifest.outer)
        asked = queries.select("qid", F.col("lo").cast("double").alias("lo")).select("qid", "lo", F.explode(F.sequence(shard, F.least(shard + 1, F.lit(len(self.manifest.outer))))).alias("shard"))
        s, params, paths = self.manifest.s, self.params, {shard: path for shard, path, _ in self.manifest.parts}

        def run(table: pa.Table) -> pa.Table:
            key, qid, lo = table.column("shard")[0].as_py(), table.column("qid"), table.column("lo").to_numpy()
            first, steps = [None] * len(lo), [0] * len(lo)
            if key in paths:
                g = Graph.of_arrays(_arrays(paths[key]), s, params)
                for i, x in enumerate(lo):
                    first[i], steps[i] = g.first_from(x)
            return pa.table({"qid": qid, "shard": pa.array([key] * len(lo), pa.int32()), "first": pa.array(first, pa.int64()), "steps": pa.array(steps, pa.int64())})

        found = asked.groupBy("shard").applyInArrow(run, "qid long, shard int, first long, steps long")
        return found.groupBy("qid").agg(F.min_by("first", F.when(F.col("first").isNotNull(), F.col("shard"))).alias("first"), F.sum("steps").alias("steps"))

    # Search.
    def _attached(self, also: DataFrame) -> dict[int, str]:
        """A second attribute, and a third, in the order of each shard's nodes, as files beside them; objects without one hold NaN."""
        folder, paths = f"{shared_folder(self.spark)}/also-{uuid.uuid4().hex}", {shard: path for shard, path, _ in self.manifest.parts}
        ids = self._view("shard int, vid long", lambda shard, g: pd.DataFrame({"shard": shard, "vid": g.vid}))
        names = [c for c in ("attr2", "attr3") if c in also.columns]
        rows = ids.join(also.select("vid", *[F.col(c).cast("double").alias(c) for c in names]), "vid")

        def write(table: pa.Table) -> pa.Table:
            shard = table.column("shard")[0].as_py()
            vid = _arrays(paths[shard])["vid"]
            order = np.argsort(vid, kind="stable")
            out = {c: np.full(len(vid), np.nan) for c in names}
            for c in names:
                out[c][order[np.searchsorted(vid[order], table.column("vid").to_numpy())]] = table.column(c).to_numpy(zero_copy_only=False)
            return pa.table({"shard": pa.array([shard], pa.int32()), "path": [store_arrays(folder, f"also-{shard}", out)]})

        return {r["shard"]: r["path"] for r in rows.groupBy("shard").applyInArrow(write, "shard int, path string").collect()}

    def search(self, queries: DataFrame, strategy: str = "auto", k: int | None = None, ef: int = 100, m: int = 16, pick: str = "chunk", stop: str = "full", scope: str = "hit", grow: bool = False, counters: bool = False, also: DataFrame | None = None, block: int = QUERY_BLOCK) -> DataFrame:
        """(qid, rnk, vid, dist), with ``counters`` what each query's search of each shard found and took.

        ``strategy``: pre, post, hybrid, or auto: each query goes, shard by shard, by the share of the shard that its range covers, estimated from the shard's
        histogram. With one shard that is the rule for the whole table. ``also`` is (vid, attr2), a second attribute whose closed range [lo2, hi2]
        the queries then hold too; it is tested where results are accepted, as is attr3 with lo3 and hi3 if it is there. Queries are dealt to the shards that their ranges meet, in blocks of about
        ``block``; there may be any number of them.
        """
        q = queries if k is None else queries.withColumn("k", F.lit(k))
        third = also is not None and "attr3" in also.columns
        second = [(F.col(c) if c[2] == "2" and also is not None or third else F.lit(None)).cast("double").alias(c) for c in ("lo2", "hi2", "lo3", "hi3")]
        q = q.select("qid", F.col("qvec").cast("array<double>").alias("qvec"), *second, F.col("lo").cast("double").alias("lo"), F.col("hi").cast("double").alias("hi"), F.col("k").cast("int").alias("k"))
        worst = q.agg(F.min("k").alias("k"), F.max("k").alias("most"), F.min(F.size("qvec")).alias("least"), F.max(F.size("qvec")).alias("d"), F.max((F.col("lo") > F.col("hi")).cast("int")).alias("bad"), F.count(F.lit(1)).alias("n")).first()
        if worst["n"] and (worst["k"] < 1 or worst["bad"] or {worst["d"], worst["least"]} != {self.manifest.dim} or m < 1 or ef < worst["most"] and strategy != "pre"):
            raise ValueError("k and m must be 1 at least, ef at least k, lo at most hi, and vectors as long as the index's")
        if strategy not in ("auto", "pre", "post", "hybrid"):
            raise ValueError(f"no strategy {strategy}")
        if len(self.manifest.outer):
            # One row for each shard.
            shards = self.segments().groupBy("shard").agg(F.min(F.struct(F.col("lo").isNotNull(), "lo")).getField("lo").alias("lo"), F.max(F.struct(F.col("hi").isNull(), "hi")).getField("hi").alias("hi"))
            ask = segment.intersecting(q, shards.withColumnRenamed("shard", "seg")).withColumnRenamed("seg", "shard").join(q, "qid")
        else:
            ask = q.withColumn("shard", F.lit(0))
        s, params, inner, (ta, tb), dim = self.manifest.s, self.params, self.manifest.inner, self.manifest.tau, self.manifest.dim
        paths, seconds = {shard: path for shard, path, _ in self.manifest.parts}, self._attached(also) if also is not None else {}
        both, blocks = also is not None, max(1, -(-worst["n"] // max(1, block)))

        def run(table: pa.Table) -> pa.Table:
            shard = table.column("shard")[0].as_py()
            out: dict[str, list] = {c.split()[0]: [] for c in RESULT.split(", ")}
            if shard in paths:
                g, cuts = Graph.of_arrays(_arrays(paths[shard]), s, params), np.array(inner[shard])
                x, ids, ks = _vectors(table.column("qvec"), dim), table.column("qid").to_numpy(), table.column("k").to_numpy()
                bound = lambda c, open_: np.nan_to_num(table.column(c).to_numpy(zero_copy_only=False).astype(np.float64), nan=open_, posinf=np.inf, neginf=-np.inf)
                lo, hi, tests = bound("lo", -np.inf), bound("hi", np.inf), []
                for i in ("2", "3")[: 1 + third] if both else ():
                    tests.append((open_arrays(seconds[shard])[f"attr{i}"] if shard in seconds else np.full(g.size, np.nan), bound(f"lo{i}", -np.inf), bound(f"hi{i}", np.inf)))
                first, last = np.searchsorted(cuts, lo, "right"), np.searchsorted(cuts, hi, "right")
                hit = (np.arange(s) >= first[:, None]) & (np.arange(s) <= last[:, None])
                share = estimated(_arrays(paths[shard])["histogram"], lo, hi) / max(1, g.size)
                how = np.where(share <= ta, "pre", np.where(share >= tb, "post", "hybrid")) if strategy == "auto" else np.full(len(ids), strategy)
                for name in np.unique(how):
                    at = np.flatnonzero(how == name)
                    k, tested = int(ks[at].max()), (lambda rows, nodes, at=at: np.logical_and.reduce([(a[nodes] >= l[at[rows]]) & (a[nodes] <= h[at[rows]]) for a, l, h in tests])) if both else None
                    began = time.perf_counter()
                    if name == "pre":
                        found = g.pre_many(x[at], lo[at], hi[at], k, tested)
                    elif name == "post":
                        found = g.post_many(x[at], lo[at], hi[at], k, ef, grow, tested)
                    else:
                        found = g.hybrid_many(x[at], lo[at], hi[at], k, ef, hit[at], m, pick, stop, scope, tested)
                    took = (time.perf_counter() - began) * 1000 / len(at)
                    for i, got, c in zip(at, found, g.spent, strict=True):
                        # A row for each result, or one without a result.
                        for d, v in got[: ks[i]] or [(None, None)]:
                            for key, value in zip(out, (ids[i], ks[i], None if v is None else g.vid[v], d, str(name), c[DIST], c[VISITED], c[BRIDGE], c[HOPS], c[EDGES], took), strict=True):
                                out[key].append(value)
            types = [pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.string(), *[pa.int64()] * 5, pa.float64()]
            return pa.table({c: pa.array(v, t) for (c, v), t in zip(out.items(), types, strict=True)})

        dealt = ask.withColumn("_block", F.pmod(F.xxhash64("qid"), F.lit(blocks)))
        # By bytes, Spark would give few tasks all searches.
        tasks = min(max(1, len(paths)) * blocks, 4 * self.spark.sparkContext.defaultParallelism)
        found = dealt.select("shard", "_block", "qid", "qvec", "lo", "hi", "lo2", "hi2", "lo3", "hi3", "k").repartition(tasks, "shard", "_block").groupBy("shard", "_block").applyInArrow(run, RESULT)
        if counters:
            return settle(found)
        return top(found.where("vid is not null"), ["qid"], F.col("k")).select("qid", "rnk", "vid", "dist")

    def work(self, found: DataFrame, queries: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
        """Results and costs of a search with counters: (qid, rnk, vid, dist) and (qid, strategy, and the sums over shards of COUNTS)."""
        best = top(found.where("vid is not null"), ["qid"], F.lit(k)).select("qid", "rnk", "vid", "dist")
        each = found.dropDuplicates(["qid", "strategy", *COUNTS])
        cost = each.groupBy("qid").agg(F.concat_ws("+", F.array_sort(F.collect_set("strategy"))).alias("strategy"), *[F.sum(c).alias(c) for c in COUNTS])
        return best, cost

    def search_both(self, queries: DataFrame, other: DataFrame, **how) -> DataFrame:
        """A conjunction: ``other`` is (vid, attr2), queries also hold lo2 and hi2. The second range is tested where results are accepted."""
        return self.search(queries, also=other, **how)

    @staticmethod
    def search_either(first: RangeIndex, second: RangeIndex, queries: DataFrame, k: int, **how) -> DataFrame:
        """A disjunction: both indexes are searched and the results merged; an object found by both counts once."""
        a = first.search(queries, k=k, **how)
        b = second.search(queries.drop("lo", "hi").withColumnsRenamed({"lo2": "lo", "hi2": "hi"}), k=k, **how)
        both = a.unionByName(b).groupBy("qid", "vid").agg(F.min("dist").alias("dist"))
        return top(both, ["qid"], F.lit(k)).select("qid", "rnk", "vid", "dist")
