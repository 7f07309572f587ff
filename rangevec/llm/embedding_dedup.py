"""Near-duplicate vectors by an exact metric range join over pivot cells."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .components import components
from .shared import join_hot, null_safe, settle, unclear

#: Pivots go to the executors as a matrix of so many bytes at most; up to that their number follows the vectors, so that cells stay small.
PIVOT_BYTES = 32 << 20
#: Numbers of a slice of vectors times pivots.
SLICE = 1 << 22
LEAST_BLOCK, MOST_BLOCK = 256, 4096
SLAB = 512


def _vectors(batch: pa.RecordBatch) -> list[np.ndarray]:
    return [np.frombuffer(v, "<f8") for v in batch.column("vec").to_pylist()]


def _read():
    schema = pa.schema([("id", pa.int64()), ("key", pa.binary()), ("vec", pa.binary()), ("dim", pa.int32())])

    def run(batches):
        for b in batches:
            key, vec, dim = [], [], []
            for v in b.column("v").to_pylist():
                x = np.array(v, np.float64) if v and None not in v else None
                with np.errstate(over="ignore"):
                    fit = x is not None and np.isfinite(x).all() and (x != 0).any()
                raw = (x + 0.0).astype("<f8").tobytes() if fit else None
                key.append(hashlib.blake2b(raw, digest_size=16).digest() if fit else None)
                vec.append(raw)
                dim.append(len(x) if fit else 0)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(key, pa.binary()), pa.array(vec, pa.binary()), pa.array(dim, pa.int32())], schema=schema)

    return run


def _units(vectors: list[np.ndarray], dim: int) -> np.ndarray:
    """Unit vectors, with zeros behind shorter ones."""
    out = np.zeros((len(vectors), dim))
    for i, v in enumerate(vectors):
        v = v / np.abs(v).max()
        out[i, : len(v)] = v / np.sqrt(v @ v)
    return out


def _near_cells(x: np.ndarray, pivots: np.ndarray, reach: float) -> tuple[np.ndarray, np.ndarray]:
    """Home cells, and for each vector the cells in which a vector within ``reach`` of it may be at home.

    If y is at home in q and x in p, then y lies on q's side of the plane between p and q, so by the triangle inequality x
    is at most |x - y| away from that plane.
    """
    dots = x @ pivots.T
    home = dots.argmax(axis=1)
    slack = dots[np.arange(len(x)), home][:, None] - dots
    apart = np.sqrt(np.maximum(2 - 2 * pivots[home] @ pivots.T, 0))
    return home, slack <= apart * reach + 1e-9


def _homes(pivots: np.ndarray):
    def run(batches):
        step = max(1, SLICE // len(pivots))
        for whole in batches:
            for at in range(0, whole.num_rows, step):
                home = (_units(_vectors(whole.slice(at, step)), pivots.shape[1]) @ pivots.T).argmax(axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(home.astype(np.int32))], names=["cell"])

    return run


def _deal(pivots: np.ndarray, first: np.ndarray, parts: np.ndarray, reach: float):
    """A row for each tile, a pair of blocks, that a vector takes part in. Cell c has the blocks first[c] .. first[c] + parts[c] - 1."""
    schema = pa.schema([("tile", pa.int64()), ("side", pa.int32()), ("rep", pa.int64()), ("n", pa.int64()), ("dim", pa.int32()), ("vec", pa.binary())])

    def run(batches):
        for whole in batches:
            step = min(256, max(1, SLICE // len(pivots)))
            for at in range(0, whole.num_rows, step):
                b = whole.slice(at, step)
                home, near = _near_cells(_units(_vectors(b), pivots.shape[1]), pivots, reach)
                near[np.arange(len(home)), home] = True
                rep = b.column("rep").to_numpy()
                own = first[home] + (rep.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)).astype(np.int64) % parts[home]
                row, cell = np.nonzero(near)
                n = parts[cell]
                row, cell = np.repeat(row, n), np.repeat(cell, n)
                other = first[cell] + np.arange(len(cell)) - np.repeat(np.cumsum(n) - n, n)
                lo, hi = np.minimum(own[row], other), np.maximum(own[row], other)
                take = pa.array(row)
                yield pa.RecordBatch.from_arrays([pa.array(lo << 31 | hi), pa.array((own[row] != lo).astype(np.int32)), *(b.column(c).take(take) for c in ("rep", "n", "dim", "vec"))], schema=schema)

    return run


def forest(i: np.ndarray, j: np.ndarray, n: int) -> np.ndarray:
    """The smallest node that each of n nodes reaches over the links (i, j)."""
    label = np.arange(n)
    while len(i):
        low = np.minimum(label[i], label[j])
        np.minimum.at(label, i, low)
        np.minimum.at(label, j, low)
        label = label[label]
        open_ = label[i] != label[j]
        i, j = i[open_], j[open_]
    while (label != label[label]).any():
        label = label[label]
    return label


def _tile(threshold: float):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("links", pa.int64())])

    def run(table: pa.Table) -> pa.Table:
        side, rep, n, dim = (table.column(c).to_numpy() for c in ("side", "rep", "n", "dim"))
        vectors = [np.frombuffer(v, "<f8") for v in table.column("vec").to_pylist()]
        order = np.lexsort([rep, side])
        side, rep, n, dim = side[order], rep[order], n[order], dim[order]
        x = _units([vectors[i] for i in order], int(dim.max()))
        left = np.flatnonzero(side == 0)
        right = np.flatnonzero(side == 1)
        alone = table.column("tile")[0].as_py()
        alone = (alone >> 31) == (alone & ((1 << 31) - 1))
        if alone:
            right = left
        links, out = np.zeros(len(x), np.int64), []
        for at in range(0, len(left), SLAB):
            own = left[at : at + SLAB]
            hit = (x[own] @ x[right].T >= threshold) & (dim[own][:, None] == dim[right])
            if alone:
                hit &= own[:, None] != right
            if not hit.any():
                continue
            links[own] += hit @ n[right]
            if not alone:
                links[right] += n[own] @ hit
            i, j = np.nonzero(hit)
            label = forest(own[i], right[j], len(x))
            moved = np.flatnonzero(label != np.arange(len(x)))
            out.append(np.stack([rep[moved], rep[label[moved]]]))
        some = np.flatnonzero(links)
        pairs = np.concatenate([*out, np.zeros((2, 0), np.int64)], axis=1)
        a = pa.concat_arrays([pa.array(pairs[0]), pa.array(rep[some])])
        b = pa.concat_arrays([pa.array(pairs[1]), pa.nulls(len(some), pa.int64())])
        return pa.Table.from_arrays([a, b, pa.concat_arrays([pa.nulls(pairs.shape[1], pa.int64()), pa.array(links[some])])], schema=schema)

    return run


def near_vectors(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", threshold: float = 0.9, pivot_bytes: int = PIVOT_BYTES) -> DataFrame:
    """One row per vector: id, ``n_links`` (other vectors of cosine >= threshold), ``component_id`` (smallest id reachable) and ``kept``.

    Cosines are taken in double precision between vectors of one length. Vectors that are null, empty, zero or hold null or non-finite
    components link with nothing. Equal vectors are one representative that counts for all of them. Each vector's home is its nearest
    pivot; it is copied to the cells that the triangle inequality doesn't exclude, and cells are split into blocks, so a tile
    compares two blocks of bounded size and hands on counts and a spanning forest, never its pairs. Rows that repeat an id, or have none, are vectors of
    their own; of a component without any id the first vector stays. Other columns are ignored; an empty table gives an empty result.

    The join is exact. Where vectors fill their space evenly no exact method excludes much: then most pairs of blocks are compared.
    """
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v"))
    read = settle(rows.mapInArrow(_read(), "id long, key binary, vec binary, dim int"))
    if not unclear(read, "id"):
        return _linked(read, threshold, pivot_bytes).select(F.col("id").alias(id_col), "n_links", "component_id", (F.col("id") == F.col("component_id")).alias("kept"))
    # Numbers that grow over a sorted frame keep its order: each id and vector has one of its own.
    nodes = settle(read.select("id", "key").distinct().orderBy(F.col("id").asc_nulls_last(), "key").withColumn("node", F.monotonically_increasing_id()))
    keyed = read.alias("a").join(nodes.alias("b"), null_safe("a", "b", ["id", "key"])).select(F.col("node").alias("id"), "a.key", "vec", "dim")
    found = _linked(settle(keyed), threshold, pivot_bytes).withColumnsRenamed({"id": "node", "component_id": "head"})
    heads = nodes.select(F.col("node").alias("head"), F.col("id").alias("component_id"))
    found = found.join(nodes.select("node", "id"), "node").join(heads, "head")
    kept = F.when(F.col("id").isNull(), F.col("node") == F.col("head")).otherwise(F.coalesce(F.col("id") == F.col("component_id"), F.lit(False)))
    return found.select(F.col("id").alias(id_col), "n_links", "component_id", kept.alias("kept"))


def _linked(read: DataFrame, threshold: float, pivot_bytes: int) -> DataFrame:
    """(id, n_links, component_id) where equal ids have equal vectors and none is missing."""
    members = read.select("id", "key")
    groups = read.where("key is not null").groupBy("key").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("n"), F.min_by(F.struct("vec", "dim"), "id").alias("v"))
    groups = settle(groups.select("key", "rep", "n", "v.vec", "v.dim"))
    total = groups.count()
    none = members.where("key IS NULL").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    if total:
        block = min(max(total // 16, LEAST_BLOCK), MOST_BLOCK)
        dim = groups.agg(F.max("dim")).first()[0]
        chosen = groups.orderBy(F.xxhash64("key")).limit(max(1, min(pivot_bytes // (8 * dim), -(-total // block)))).select("vec").toArrow()
        pivots = _units([np.frombuffer(v, "<f8") for v in chosen.column("vec").to_pylist()], dim)
        counts = np.ones(len(pivots), np.int64)
        for r in groups.select("vec").mapInArrow(_homes(pivots), "cell int").groupBy("cell").count().collect():
            counts[r["cell"]] = r["count"]
        parts = -(-counts // block)
        dealt = groups.select("rep", "n", "dim", "vec").mapInArrow(_deal(pivots, np.cumsum(parts) - parts, parts, float(np.sqrt(max(0.0, 2 - 2 * threshold)))), "tile long, side int, rep long, n long, dim int, vec binary")
        found = settle(dealt.groupBy("tile").applyInArrow(_tile(threshold), "a long, b long, links long"))
        links = found.where("b is null").groupBy(F.col("a").alias("rep")).agg(F.sum("links").alias("links"))
        named = components(found.where("b is not null").select("a", "b")).withColumnRenamed("node", "rep")
        named = groups.select("key", "rep", "n").join(links, "rep", "left").join(named, "rep", "left")
        named = settle(named.select("key", "n", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id")))
        none = join_hot(members, named, ["key"], "n").select("id", "n_links", "component_id").unionByName(none)
    return none.select("id", "n_links", "component_id")
