"""Interpolated modified Kneser-Ney model of order two or three: counted in Spark, kept as sorted arrays that workers map into memory."""

from __future__ import annotations

import atexit
import functools
import os
import shutil
import tempfile
import uuid
from dataclasses import dataclass
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame, functions as F

from .shared import Words, by_row, hashes, shared_folder, slices, tidy

END = np.uint64(0)
FLUSH = 3_000_000
LEAST_PARTS = 32
PART_BYTES, PART_TOKENS = 64 << 20, 1 << 21
#: Of so many bigrams one has the place noted at which its trigrams begin.
STRIDE = 8
LOW32 = np.uint64((1 << 32) - 1)
BLOB = pa.schema([("part", pa.int32()), ("keys", pa.binary()), ("counts", pa.binary())])


def _put(folder: str, name: str, array: np.ndarray) -> None:
    """Write under another name and rename: a task that runs twice leaves one whole file."""
    own = f"{name}.{uuid.uuid4().hex}"
    if urlparse(folder).scheme in ("", "file"):
        path = urlparse(folder).path
        os.makedirs(path, exist_ok=True)
        with open(f"{path}/{own}", "wb") as f:
            np.save(f, array)
        os.replace(f"{path}/{own}", f"{path}/{name}.npy")
        return
    fs, path = pafs.FileSystem.from_uri(folder)
    fs.create_dir(path)
    with fs.open_output_stream(f"{path}/{own}") as f:
        np.save(f, array)
    fs.move(f"{path}/{own}", f"{path}/{name}.npy")


@functools.cache
def _copies() -> str:
    folder = tempfile.mkdtemp()
    atexit.register(shutil.rmtree, folder, True)
    return folder


@functools.lru_cache(maxsize=4096)
def _get(folder: str, name: str) -> np.ndarray:
    """The array, mapped from the shared folder; from a store without paths a worker's own copy is mapped."""
    path = f"{urlparse(folder).path}/{name}.npy"
    if urlparse(folder).scheme not in ("", "file"):
        fs, source = pafs.FileSystem.from_uri(f"{folder}/{name}.npy")
        path = f"{_copies()}/{uuid.uuid4().hex}"
        with fs.open_input_stream(source) as f, open(path, "wb") as g:
            shutil.copyfileobj(f, g)
    return np.load(path, mmap_mode="r")


def _put_counts(folder: str, name: str, counts: np.ndarray) -> None:
    """A byte for each count. 255 stands for what is no less: such counts follow in a list, by place."""
    much = np.flatnonzero(counts >= 255)
    _put(folder, f"much-{name}", np.stack([much, counts[much]]).astype("<i8"))
    _put(folder, name, np.minimum(counts, 255).astype(np.uint8))


def _get_counts(folder: str, name: str, at: np.ndarray) -> np.ndarray:
    out = _get(folder, name)[at].astype(np.int64)
    if (out == 255).any():
        much = _get(folder, f"much-{name}")
        out[out == 255] = much[1][np.searchsorted(much[0], at[out == 255])]
    return out


def _word_hashes(words: list[str]) -> np.ndarray:
    h = hashes(words)
    return np.where(h < 2, h + np.uint64(2), h)


def _merge(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    k, c = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(k, kind="stable")
    k, c = k[order], c[order]
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]])) if len(k) else np.zeros(0, np.int64)
    return k[first], (np.add.reduceat(c, first) if len(k) else c)


def _counted(batches, key_of, emit):
    """Keys of text batches, summed up within the task until there are FLUSH of them."""
    keys, counts, held = [], [], 0
    for b in slices(batches, "text"):
        k, c = key_of(b)
        keys.append(k)
        counts.append(c)
        held += len(k)
        if held > FLUSH:
            k, c = _merge(keys, counts)
            keys, counts, held = [k], [c], len(k)
            if held > FLUSH // 2:
                yield from emit(k, c)
                keys, counts, held = [], [], 0
    if held:
        yield from emit(*_merge(keys, counts))


@dataclass
class Vocabulary:
    """Word numbers: places in the sorted word hashes, which lie in parts by their upper bits."""

    folder: str
    bits: int
    first: np.ndarray
    mass: np.ndarray

    @property
    def size(self) -> int:
        return int(self.first[-1])

    @property
    def tokens(self) -> int:
        return int(self.mass[-1])

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Number (-1: unknown), count and the tokens of all words before it, for each hash."""
        number, count, before = np.full(len(h), -1, np.int64), np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
        order = np.argsort(h)
        part = (h[order] >> np.uint64(64 - self.bits)).astype(np.int64)
        ends = np.searchsorted(part, np.arange(1 << self.bits), "right")
        lo = 0
        for p, hi in enumerate(ends):
            if hi > lo and self.first[p + 1] > self.first[p]:
                words, sums = _get(self.folder, f"words-{p}"), _get(self.folder, f"sums-{p}")
                at = order[lo:hi]
                i = np.searchsorted(words, h[at])
                ok = words[np.minimum(i, len(words) - 1)] == h[at]
                at, i = at[ok], i[ok]
                number[at], count[at], before[at] = self.first[p] + i, sums[i + 1] - sums[i], self.mass[p] + sums[i]
            lo = hi
        return number, count, before


def _discounts(n: list[int]) -> np.ndarray:
    """Amounts taken off counts 0, 1, 2 and more, from the numbers of items with count 1 to 4."""
    n1, n2, n3, n4 = (float(x) for x in n)
    if min(n1, n2, n3, n4) <= 0:
        return np.array([0.0, 0.5, 0.75, 0.9])
    y = n1 / (n1 + 2 * n2)
    return np.array([0.0, *(min(max(k - (k + 1) * y * b / a, 0.0), float(k)) for k, a, b in ((1, n1, n2), (2, n2, n3), (3, n3, n4)))])


@dataclass
class Pairs:
    """Sorted bigram keys in parts. A bigram's place is its number among all; ``first`` holds the place at which each part begins, and the end."""

    folder: str
    bounds: np.ndarray
    first: np.ndarray

    def find(self, keys: np.ndarray, *tallies: str) -> list[np.ndarray]:
        """Place (-1: unknown) and the named counts of sorted keys."""
        out = [np.full(len(keys), -1, np.int64), *(np.zeros(len(keys), np.int64) for _ in tallies)]
        ends = np.searchsorted(keys, np.append(self.bounds[1:], np.uint64(2**64 - 1)), "left")
        lo = int(np.searchsorted(keys, self.bounds[0])) if len(self.bounds) else len(keys)
        for p, hi in enumerate(ends[: len(self.bounds)]):
            if hi > lo:
                have = _get(self.folder, f"pairs-{p}")
                i = np.minimum(np.searchsorted(have, keys[lo:hi]), len(have) - 1)
                ok = have[i] == keys[lo:hi]
                out[0][lo:hi] = np.where(ok, self.first[p] + i, -1)
                for tally, to in zip(tallies, out[1:], strict=True):
                    to[lo:hi] = np.where(ok, _get_counts(self.folder, f"{tally}-{p}", i), 0)
                lo = hi
        return out


@dataclass
class Triples:
    """Trigrams in the order of their keys: a bigram's place above ``bits`` bits of the word behind it. The trigrams of a part of the bigrams lie in the sub-parts from ``start`` on, by word.

    Only the words are stored, four bytes each: where those of a bigram lie follows from the numbers of words behind the bigrams before it, and every STRIDE-th place.
    """

    pairs: Pairs
    start: np.ndarray
    bits: int

    def sub_part(self, keys: np.ndarray) -> np.ndarray:
        p = np.searchsorted(self.pairs.first, (keys >> np.uint64(self.bits)).astype(np.int64), "right") - 1
        word = (keys & np.uint64((1 << self.bits) - 1)) * np.uint64(0x9E3779B97F4A7C15)
        return self.start[p] + ((word >> np.uint64(40)) % np.diff(self.start)[p].astype(np.uint64)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Counts of sorted keys."""
        out = np.zeros(len(keys), np.int64)
        s = self.sub_part(keys)
        order = np.argsort(s, kind="stable")
        cuts = np.flatnonzero(np.diff(s[order], prepend=-1))
        for lo, hi in zip(cuts, np.append(cuts[1:], len(s)) if len(s) else cuts, strict=True):
            at = order[lo:hi]
            own = int(s[at[0]])
            have = np.asarray(_get(self.pairs.folder, f"triples-{own}"))
            word = (keys[at] & np.uint64((1 << self.bits) - 1)).astype(have.dtype)
            i, end = self._spans(own, (keys[at] >> np.uint64(self.bits)).astype(np.int64))
            # The first word of the span that is no less, by halves.
            top, left = end.copy(), np.flatnonzero(i < end)
            while len(left):
                mid = (i[left] + top[left]) >> 1
                less = have[mid] < word[left]
                i[left[less]], top[left[~less]] = mid[less] + 1, mid[~less]
                left = left[i[left] < top[left]]
            inside = np.flatnonzero(i < end)
            inside = inside[have[i[inside]] == word[inside]]
            out[at[inside]] = _get_counts(self.pairs.folder, f"triple_times-{own}", i[inside])
        return out

    def _spans(self, s: int, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the words behind bigrams, in order of place, begin and end in a sub-part."""
        p = int(np.searchsorted(self.start, s, "right")) - 1
        local, times = _runs(place - self.pairs.first[p])
        block, inside = np.divmod(local, STRIDE)
        last = 3 * int(self.pairs.first[p + 1] - self.pairs.first[p]) - 1
        behind = _get_counts(self.pairs.folder, f"behind-{s}", np.minimum(3 * STRIDE * block[:, None] + np.arange(3 * STRIDE), last)).reshape(-1, STRIDE, 3).sum(axis=2)
        first = _get(self.pairs.folder, f"starts-{s}")[block] + (behind * (np.arange(STRIDE) < inside[:, None])).sum(axis=1)
        return np.repeat(first, times), np.repeat(first + behind[np.arange(len(local)), inside], times)

    def kinds(self, place: np.ndarray) -> np.ndarray:
        """For bigrams in order of place (-1: unknown) the numbers of words that follow them once, twice and more often."""
        out = np.zeros((len(place), 3), np.int64)
        ends = np.searchsorted(place, self.pairs.first[1:], "left")
        lo = int(np.searchsorted(place, 0))
        for p, hi in enumerate(ends):
            if hi > lo:
                for s in range(self.start[p], self.start[p + 1]):
                    out[lo:hi] += _get_counts(self.pairs.folder, f"behind-{s}", 3 * (place[lo:hi] - self.pairs.first[p])[:, None] + np.arange(3))
                lo = hi
        return out


@dataclass
class Model:
    """``cut`` and ``cut3`` are what bigram and trigram counts lose; without ``triples`` the order is two. ``tally`` names the bigram counts: of places, or of words before."""

    vocabulary: Vocabulary
    docs: int
    pairs: Pairs
    triples: Triples | None
    tally: str
    split: dict[int, tuple[int, int, int, int]]
    cut3: np.ndarray
    cut: np.ndarray
    low_cut: np.ndarray
    low_total: int
    low_kinds: np.ndarray

    def low(self, number: np.ndarray) -> np.ndarray:
        """Probabilities by the number of different words that a word follows; of unknown words too."""
        v = self.vocabulary
        if not self.low_total:
            return np.full(len(number), 1 / (v.size + 1))
        n = np.zeros(len(number), np.int64)
        order = np.argsort(number)
        ends = np.searchsorted(number[order], v.first[1:], "left")
        lo = int(np.searchsorted(number[order], 0))
        for p, hi in enumerate(ends):
            if hi > lo:
                n[order[lo:hi]] = _get_counts(v.folder, f"after-{p}", number[order[lo:hi]] - v.first[p])
                lo = hi
        spare = float(self.low_cut[1:] @ self.low_kinds) / self.low_total
        return np.maximum(n - self.low_cut[np.minimum(n, 3)], 0) / self.low_total + spare / (v.size + 1)

    def kinds(self, context: np.ndarray) -> np.ndarray:
        """For each context the numbers of words with a count of one, two and more behind it, and the sum of the counts."""
        out = np.zeros((len(context), 4), np.int64)
        order = np.argsort(context)
        sorted_ = context[order]
        part = np.searchsorted(self.pairs.bounds, (sorted_.astype(np.uint64) << np.uint64(32)) | LOW32, "right") - 1
        for p in np.unique(part[(part >= 0) & (sorted_ >= 0)]):
            at = order[(part == p) & (sorted_ >= 0)]
            have = _get(self.vocabulary.folder, f"contexts-{p}")
            i = np.minimum(np.searchsorted(have["u"], context[at]), len(have) - 1)
            ok = have["u"][i] == context[at]
            for j, c in enumerate(KINDS):
                out[at, j] = np.where(ok, have[c][i], 0)
        for u, n in self.split.items():
            out[context == u] = n
        return out


KINDS = ("n1", "n2", "n3", "total")
CONTEXT = np.dtype([("u", "<u4"), *((c, "<u4") for c in KINDS[:3]), ("total", "<i8")])


def _store_contexts(folder: str, p: int, u: np.ndarray, c: np.ndarray) -> None:
    """The contexts of a part's bigrams; beside them numbers of bigrams with count 1 to 4, the first context and the last, as other parts may share them."""
    at = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]]))
    ctx = np.zeros(len(at), CONTEXT)
    ctx["u"] = u[at]
    for name, value in (("n1", c == 1), ("n2", c == 2), ("n3", c > 2), ("total", c)):
        ctx[name] = np.add.reduceat(value.astype(np.int64), at)
    _put(folder, f"contexts-{p}", ctx)
    _put(folder, f"level-{p}", np.array([*((c == i).sum() for i in range(1, 5)), *ctx[0].item(), *ctx[-1].item()], np.int64))


def _planes(numbers: np.ndarray) -> bytes:
    """All first bytes, all second ones and so on, compressed behind their length."""
    raw = np.ascontiguousarray(numbers.view(np.uint8).reshape(len(numbers), -1).T).tobytes()
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _numbers(planes: bytes, dtype: str) -> np.ndarray:
    raw = pa.decompress(planes[8:], int.from_bytes(planes[:8], "little"), codec="zstd", asbytes=True) if planes else b""
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(np.dtype(dtype).itemsize, -1).T).view(dtype).ravel()


def _runs(sorted_: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different values, and how often each is there."""
    first = np.flatnonzero(np.concatenate([[True], sorted_[1:] != sorted_[:-1]])) if len(sorted_) else np.zeros(0, np.int64)
    return sorted_[first], np.diff(np.append(first, len(sorted_)))


def _tokens(texts: pa.Array, v: Vocabulary | None):
    """Codes of all tokens, an end behind each text, and of the token before each; offsets; hashes by code. The last code is the end, one more the begin."""
    w = Words(texts)
    end = len(w.vocab)
    n = len(w.offsets) - 1
    codes = np.full(len(w.codes) + n, end, np.int64)
    offs = w.offsets + np.arange(n + 1)
    inside = np.ones(len(codes), bool)
    inside[offs[1:] - 1] = False
    codes[inside] = w.codes
    before = np.empty_like(codes)
    before[1:] = codes[:-1]
    before[offs[:-1]] = end + 1
    return codes, before, offs, np.append(_word_hashes(w.vocab), END)


def _contexts(v: Vocabulary, h: np.ndarray, docs: int):
    """Number, count and tokens before, by code, with the begin as the last word of all."""
    number, count, mass = v.find(h)
    return np.append(number, v.size), np.append(count, docs), np.append(mass, v.tokens)


def fit(docs: DataFrame, learn: Column, text_col: str = "text", order: int = 3) -> Model:
    """Count all documents where ``learn`` holds, for a model of order 2 or 3.

    Word counts come first and fix the word numbers. A bigram's key is its two numbers. Keys are dealt to parts of about equal
    tokens: under independence a pair's place among all tokens follows from the word counts, which also splits frequent contexts.
    A trigram's key is the place of its first two words among all bigrams, and its last word; it lies with that bigram's part, in as many
    sub-parts as the part's tokens ask for. Of order three, a bigram counts the different words before it; behind the begin of
    a text, where none is, its occurrences. The first token of a text is scored behind the begin alone. Where no gram of a level has
    one of the counts 1 to 4, that level's counts lose 0.5, 0.75 and 0.9. More than 2^32 words, or place and word of more
    than 64 bits, raise an error.
    """
    if order not in (2, 3):
        raise ValueError("the order is 2 or 3")
    spark = docs.sparkSession
    folder = f"{shared_folder(spark).rstrip('/')}/lm-{uuid.uuid4().hex}"
    rows = docs.where(learn).select(F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    size = int(str(rows._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    bits = max(LEAST_PARTS.bit_length() - 1, min(16, (size // PART_BYTES).bit_length()))

    def blobs(part: np.ndarray, k: np.ndarray, c: np.ndarray):
        """One row for each part; keys are sorted, and parts follow them."""
        at = np.flatnonzero(np.diff(part, prepend=-1))
        for lo, hi in zip(at, np.append(at[1:], len(k)) if len(k) else at, strict=True):
            yield pa.RecordBatch.from_arrays([pa.array([int(part[lo])], pa.int32()), pa.array([_planes(np.diff(k[lo:hi], prepend=np.uint64(0)))], pa.binary()), pa.array([_planes(c[lo:hi].astype("<u4"))], pa.binary())], schema=BLOB)

    def words(batches):
        def key_of(b):
            codes, _, _, h = _tokens(b.column("text"), None)
            return h, np.bincount(codes, minlength=len(h)).astype(np.int64)

        yield from _counted(batches, key_of, lambda k, c: blobs((k >> np.uint64(64 - bits)).astype(np.int64), k, c))

    def read(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        return _merge([np.cumsum(_numbers(x, "<u8"), dtype=np.uint64) for x in table.column("keys").to_pylist()], [_numbers(x, "<u4").astype(np.int64) for x in table.column("counts").to_pylist()])

    def store_words(table: pa.Table) -> pa.Table:
        p = table.column("part")[0].as_py()
        k, c = read(table)
        k, c = k[c > 0], c[c > 0]
        _put(folder, f"words-{p}", k)
        _put(folder, f"sums-{p}", np.concatenate([[0], np.cumsum(c)]).astype("<i8"))
        return pa.table({"part": pa.array([p], pa.int32()), "n": pa.array([len(k)], pa.int64()), "tokens": pa.array([int(c.sum())], pa.int64())})

    blob = "part int, keys binary, counts binary"
    got = rows.mapInArrow(words, blob).groupBy("part").applyInArrow(store_words, "part int, n long, tokens long").collect()
    n, mass = np.zeros((1 << bits) + 1, np.int64), np.zeros((1 << bits) + 1, np.int64)
    for r in got:
        n[r["part"] + 1], mass[r["part"] + 1] = r["n"], r["tokens"]
    v = Vocabulary(folder, bits, np.cumsum(n), np.cumsum(mass))
    if v.size >= 1 << 32:
        raise ValueError("more than 2^32 words")
    begun = int(_get(folder, "sums-0")[1]) if v.size and v.first[1] and _get(folder, "words-0")[0] == END else 0
    parts = max(LEAST_PARTS, -(-(v.tokens + begun) // PART_TOKENS))

    def pairs(batches):
        def key_of(b):
            codes, before, _, h = _tokens(b.column("text"), v)
            number, _, _ = _contexts(v, h, begun)
            return _runs(np.sort((number[before].astype(np.uint64) << np.uint64(32)) | number[codes].astype(np.uint64)))

        def emit(k, c):
            yield from blobs(_part_of(v, begun, parts, k), k, c)

        yield from _counted(batches, key_of, emit)

    def store_pairs(table: pa.Table) -> pa.Table:
        p = table.column("part")[0].as_py()
        k, c = read(table)
        u = (k >> np.uint64(32)).astype(np.int64)
        if order == 2:
            _store_contexts(folder, p, u, c)
        _put(folder, f"pairs-{p}", k)
        _put_counts(folder, f"times-{p}", c)
        _put(folder, f"stats-{p}", np.array([int(u[0]), int(k[0] & LOW32), len(k), int(c.sum())], np.int64))
        w, times = np.unique((k & LOW32).astype(np.int64), return_counts=True)
        part = np.searchsorted(v.first, w, "right") - 1
        own = list(blobs(part, w.astype(np.uint64), times))
        return pa.Table.from_batches(own, schema=BLOB)

    def store_after(table: pa.Table) -> pa.Table:
        p = table.column("part")[0].as_py()
        k, c = read(table)
        after = np.zeros(v.first[p + 1] - v.first[p], "<u4")
        after[k.astype(np.int64) - v.first[p]] = c
        _put_counts(folder, f"after-{p}", after)
        return pa.table({"part": pa.array([p], pa.int32()), "total": pa.array([int(c.sum())], pa.int64()), **{f"n{i}": pa.array([int((c == i).sum())], pa.int64()) for i in range(1, 5)}, "n": pa.array([len(c)], pa.int64())})

    low = rows.mapInArrow(pairs, blob).groupBy("part").applyInArrow(store_pairs, blob).groupBy("part").applyInArrow(store_after, "part int, total long, n1 long, n2 long, n3 long, n4 long, n long").collect()
    known = _known_parts(folder, parts) if v.tokens else []
    stats = [_get(folder, f"stats-{p}") for p in known]
    if len(known) < parts and known:
        _rename(folder, known, ("pairs", "times", "much-times", "stats", *(("contexts", "level") if order == 2 else ())))
    bounds = np.array([(int(s[0]) << 32) | int(s[1]) for s in stats], np.uint64)
    bigrams = Pairs(folder, bounds, np.concatenate([[0], np.cumsum([s[2] for s in stats])]).astype(np.int64))
    low_n = [sum(r[f"n{i}"] for r in low) for i in range(1, 5)]
    low_kinds = np.array([low_n[0], low_n[1], sum(r["n"] for r in low) - low_n[0] - low_n[1]])
    triples, cut3 = None, _discounts([0, 0, 0, 0])
    tidy(spark, rounds=2)
    if order == 3 and stats:
        triples, cut3 = _fit_triples(rows, v, begun, bigrams, np.array([s[3] for s in stats]), blobs, read)
    levels = [_get(folder, f"level-{p}") for p in range(len(stats))]
    ends: dict[int, np.ndarray] = {}
    seen: dict[int, int] = {}
    for level in levels:
        for u, *n in {tuple(level[4:9].tolist()), tuple(level[9:].tolist())}:
            ends[u] = ends.get(u, 0) + np.array(n)
            seen[u] = seen.get(u, 0) + 1
    split = {u: tuple(map(int, ends[u])) for u, times in seen.items() if times > 1}
    cut = _discounts([int(sum(level[i] for level in levels)) for i in range(4)])
    return Model(v, begun, bigrams, triples, "adjusted" if triples else "times", split, cut3, cut, _discounts(low_n), sum(r["total"] for r in low), low_kinds)


def _fit_triples(rows: DataFrame, v: Vocabulary, begun: int, pairs: Pairs, tokens: np.ndarray, blobs, read) -> tuple[Triples, np.ndarray]:
    """Count trigrams, and for each bigram the different words before it."""
    spark, folder = rows.sparkSession, v.folder
    bits = v.size.bit_length()
    if int(pairs.first[-1]).bit_length() + bits > 64:
        raise ValueError("place and word of a trigram have more than 64 bits")
    triples = Triples(pairs, np.concatenate([[0], np.cumsum(np.maximum(1, -(-tokens // (2 * PART_TOKENS))))]).astype(np.int64), bits)
    word = np.uint64((1 << bits) - 1)

    def count(batches):
        def key_of(b):
            codes, before, offs, h = _tokens(b.column("text"), v)
            number, _, _ = _contexts(v, h, begun)
            distinct, inv = np.unique((number[before].astype(np.uint64) << np.uint64(32)) | number[codes].astype(np.uint64), return_inverse=True)
            inner = np.ones(len(codes), bool)
            inner[offs[:-1]] = False
            at = np.flatnonzero(inner)
            place = pairs.find(distinct)[0].astype(np.uint64)
            return _runs(np.sort((place[inv[at - 1]] << np.uint64(bits)) | number[codes[at]].astype(np.uint64)))

        def emit(k, c):
            s = triples.sub_part(k)
            order = np.argsort(s, kind="stable")
            yield from blobs(s[order], k[order], c[order])

        yield from _counted(batches, key_of, emit)

    def store(table: pa.Table) -> pa.Table:
        s = table.column("part")[0].as_py()
        p = int(np.searchsorted(triples.start, s, "right")) - 1
        k, c = read(table)
        _put(folder, f"triples-{s}", (k & word).astype("<u4"))
        _put_counts(folder, f"triple_times-{s}", c)
        own = _get(folder, f"pairs-{p}")
        local = (k >> np.uint64(bits)).astype(np.int64) - pairs.first[p]
        _put(folder, f"starts-{s}", np.searchsorted(local, np.arange(0, len(own), STRIDE)).astype("<u4"))
        _put_counts(folder, f"behind-{s}", np.bincount(local * 3 + np.minimum(c, 3) - 1, minlength=3 * len(own)))
        _put(folder, f"triple_stats-{s}", np.array([(c == i).sum() for i in range(1, 5)], np.int64))
        back, before = _runs(np.sort((own[local] & LOW32) << np.uint64(32) | (k & word)))
        return pa.Table.from_batches(list(blobs(np.searchsorted(pairs.bounds, back, "right") - 1, back, before)), schema=BLOB)

    def adjust(table: pa.Table) -> pa.Table:
        p = table.column("part")[0].as_py()
        own = _get(folder, f"pairs-{p}")
        u = (own >> np.uint64(32)).astype(np.int64)
        k, c = read(table)
        adjusted = np.where(u == v.size, _get_counts(folder, f"times-{p}", np.arange(len(own))), 0)
        adjusted[np.searchsorted(own, k)] = c
        _put_counts(folder, f"adjusted-{p}", adjusted)
        _store_contexts(folder, p, u, adjusted)
        return pa.table({"part": pa.array([p], pa.int32())})

    def every(n: int) -> DataFrame:
        """A row without keys for each part, so that none lacks its files."""
        return spark.range(n).selectExpr("CAST(id AS int) AS part", "CAST('' AS binary) AS keys", "CAST('' AS binary) AS counts")

    blob = "part int, keys binary, counts binary"
    subs = int(triples.start[-1])
    back = rows.mapInArrow(count, blob).unionByName(every(subs)).groupBy("part").applyInArrow(store, blob)
    back.unionByName(every(len(pairs.bounds))).groupBy("part").applyInArrow(adjust, "part int").collect()
    del back
    tidy(spark, rounds=2)
    return triples, _discounts(np.sum([_get(folder, f"triple_stats-{s}") for s in range(subs)], axis=0).tolist())


def _part_of(v: Vocabulary, begun: int, parts: int, k: np.ndarray) -> np.ndarray:
    """The part of each key: rises with the key."""
    u, w = (k >> np.uint64(32)).astype(np.int64), (k & LOW32).astype(np.int64)
    mass, count = _mass(v, np.concatenate([u, w]), begun)
    total = v.tokens + begun
    place = mass[: len(u)] + count[: len(u)] * (mass[len(u) :] / max(1, v.tokens))
    return np.minimum((place * parts / max(1, total)).astype(np.int64), parts - 1)


def _mass(v: Vocabulary, number: np.ndarray, begun: int) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of all words before, and count, by word number."""
    distinct, inv = np.unique(number, return_inverse=True)
    mass, count = np.full(len(distinct), v.tokens, np.int64), np.full(len(distinct), begun, np.int64)
    lo = 0
    for p, hi in enumerate(np.searchsorted(distinct, v.first[1:], "left")):
        if hi > lo:
            sums, i = _get(v.folder, f"sums-{p}"), distinct[lo:hi] - v.first[p]
            mass[lo:hi], count[lo:hi] = v.mass[p] + sums[i], sums[i + 1] - sums[i]
            lo = hi
    return mass[inv], count[inv]


def _known_parts(folder: str, parts: int) -> list[int]:
    if urlparse(folder).scheme in ("", "file"):
        return [p for p in range(parts) if os.path.exists(f"{urlparse(folder).path}/stats-{p}.npy")]
    fs, path = pafs.FileSystem.from_uri(folder)
    return [p for p, i in enumerate(fs.get_file_info([f"{path}/stats-{p}.npy" for p in range(parts)])) if i.type != pafs.FileType.NotFound]


def _rename(folder: str, known: list[int], names: tuple[str, ...]) -> None:
    """Close the gaps that empty parts leave."""
    fs, path = pafs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("file:") else f"file://{folder}")
    for new, old in enumerate(known):
        for name in names if new != old else ():
            fs.move(f"{path}/{name}-{old}.npy", f"{path}/{name}-{new}.npy")
    _get.cache_clear()


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, ``n_tokens``, ``n_known``, ``train_tokens``, ``base_score``, ``score`` and ``perplexity``.

    Words are ``[^\\x20\\x09-\\x0D]+`` after lower-casing A-Z, an end behind them counts as a token, null counts as an empty text. ``base_score`` is
    the log10 probability under add-one smoothed word counts, ``score`` that of the model. Rows that repeat an id are scored
    one by one. Other columns are ignored; an empty table gives an empty result.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = ["n_tokens", "n_known", "train_tokens", "base_score", "score", "perplexity"]
    schema = pa.schema([("_id", pa.int64()), *[(n, pa.int64()) for n in names[:3]], *[(n, pa.float64()) for n in names[3:]]])

    def run(batches):
        m = shared.value
        v = m.vocabulary
        for b in slices(batches, "text"):
            codes, before, offs, h = _tokens(b.column("text"), v)
            number, count, _ = _contexts(v, h, m.docs)
            base = np.log10((count + 1.0) / (v.tokens + v.size + 1.0))
            low, kinds = m.low(number[:-1]), m.kinds(number)
            u, w = number[before], number[codes]
            both = (u >= 0) & (w >= 0)
            key = np.where(both, (u.astype(np.uint64) << np.uint64(32)) | w.astype(np.uint64), np.uint64(2**64 - 1))
            distinct, inv = np.unique(key, return_inverse=True)
            place, c, *raw = m.pairs.find(distinct, m.tally, *(["times"] if m.triples else []))
            c = c[inv]
            spare, times = (kinds[:, :3] @ m.cut[1:])[before], kinds[:, 3][before]
            p = np.where(times > 0, (np.maximum(c - m.cut[np.minimum(c, 3)], 0) + spare * low[codes]) / np.maximum(times, 1), low[codes])
            if m.triples:
                inner = np.ones(len(codes), bool)
                inner[offs[:-1]] = False
                at = np.flatnonzero(inner)
                behind = np.zeros((len(distinct), 3), np.int64)
                known = place >= 0
                behind[known] = m.triples.kinds(place[known])
                at = at[behind.any(axis=1)[inv[at - 1]]]
                pair, w = inv[at - 1], w[at]
                key = (place[pair].astype(np.uint64) << np.uint64(m.triples.bits)) | np.maximum(w, 0).astype(np.uint64)
                distinct, same = np.unique(key, return_inverse=True)
                c = np.where(w >= 0, m.triples.find(distinct)[same], 0)
                p[at] = (np.maximum(c - m.cut3[np.minimum(c, 3)], 0) + (behind @ m.cut3[1:])[pair] * p[at]) / raw[0][pair]
            n = np.diff(offs)
            total = by_row(np.log10(p), offs)
            yield pa.RecordBatch.from_arrays([b.column("_id"), pa.array(n), pa.array(by_row((count[codes] > 0).astype(np.int64), offs)), pa.array(np.full(len(n), v.tokens)), pa.array(by_row(base[codes], offs)), pa.array(total), pa.array(10 ** np.minimum(-total / n, 300))], schema=schema)

    rows = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "_id long, n_tokens long, n_known long, train_tokens long, base_score double, score double, perplexity double").withColumnRenamed("_id", id_col)
