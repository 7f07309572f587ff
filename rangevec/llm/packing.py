"""Packing token sequences into windows by multiway differencing."""

from __future__ import annotations

import functools
import heapq
import json
import threading
import unicodedata
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from .shared import by_row, release, settle, slices

CACHE_WORDS, REST_SECONDS = 700_000, 2.0
MARKS = frozenset(".,;:!?|")
#: What the names of special tokens begin with.
SPECIAL = "<|"
TEXT_BYTES = 12 << 20
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


class WordTokenizer:
    """Ids of whole texts, made from the ids of their distinct words: this kind of vocabulary never looks across white space."""

    #: How the vocabulary cuts words before merging; the last id of each cut, and no other, ends a word.
    CUT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

    @classmethod
    def reads(cls, kind: dict) -> bool:
        """Whether a tokenizer file is of this kind: white space goes, letters become small, words are cut as above and their last ids marked."""
        model, norm, cut = kind.get("model") or {}, kind.get("normalizer") or {}, kind.get("pre_tokenizer") or {}
        steps, cuts = [n.get("type") for n in norm.get("normalizers", [])], cut.get("pretokenizers", [])
        return (
            model.get("type") == "BPE" and model.get("end_of_word_suffix") == "</w>" and not model.get("dropout") and steps == ["NFC", "Replace", "Lowercase"]
            and len(cuts) == 2 and cuts[0].get("type") == "Split" and cuts[0].get("pattern") == {"Regex": cls.CUT} and cuts[0].get("behavior") == "Removed" and bool(cuts[0].get("invert"))
            and cuts[1].get("type") == "ByteLevel" and not cuts[1].get("add_prefix_space") and not cuts[1].get("use_regex")
        )

    def __init__(self, path: str):
        import regex
        from tokenizers import Tokenizer

        self.inner, self.cut = Tokenizer.from_file(path), regex.compile(self.CUT)
        vocab = self.inner.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for w, i in vocab.items() if w.endswith("</w>")]] = True
        self.lock, self.idle = threading.Lock(), None
        self._forget()

    def wake(self) -> None:
        if self.idle:
            self.idle.cancel()

    def rest(self) -> None:
        """Known words help the next task of this worker, if it comes soon; otherwise their memory is given back."""

        def forget() -> None:
            with self.lock:
                self._forget()
                release()

        self.idle = threading.Timer(REST_SECONDS, forget)
        self.idle.daemon = True
        self.idle.start()

    def _forget(self) -> None:
        self.at: dict[str, int] = {}
        self.flat, self.sizes = np.zeros(0, np.uint32), np.zeros(0, np.int64)

    def _cuts(self, words: list[str]) -> list[int]:
        return [1 if w.isalpha() else len(self.cut.findall(unicodedata.normalize("NFC", w).lower())) for w in words]

    def _ids(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, and how many each has. Words go in together and come apart at the ids that end words; where the cuts don't add up, one by one."""
        if len(words) == 1:
            ids = np.array(self.inner.encode(words[0], add_special_tokens=False).ids, np.uint32)
            return ids, np.array([len(ids)])
        ids = np.array(self.inner.encode_batch_fast([" ".join(words)], add_special_tokens=False)[0].ids, np.uint32)
        cuts = np.cumsum(self._cuts(words))
        stops = np.flatnonzero(self.ends[ids]) + 1
        if len(stops) == cuts[-1] and cuts[0] and (not len(ids) or stops[-1] == len(ids)):
            return ids, np.diff(np.concatenate([[0], stops])[cuts], prepend=0)
        each = [self._ids([w]) for w in words]
        return np.concatenate([x for x, _ in each]), np.concatenate([n for _, n in each])

    def _add(self, words: list[str], flat: list[np.ndarray], sizes: list[np.ndarray]) -> None:
        self.at.update(zip(words, range(len(self.at), len(self.at) + len(words)), strict=True))
        self.flat = np.concatenate([self.flat, *flat])
        self.sizes = np.concatenate([self.sizes, *sizes])

    def _joined(self, places: np.ndarray) -> pa.Array:
        """The ids of words by place."""
        lists = pa.LargeListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(self.sizes)])), pa.array(self.flat))
        return lists.take(pa.array(places)).flatten()

    def _places(self, words: list[str]) -> np.ndarray:
        if len(self.at) + len(words) > CACHE_WORDS:
            self._forget()
        at = self.at
        new = [w for w in words if w not in at]
        # A mark behind letters is a cut of its own, so both are looked up apart.
        marked = [w for w in new if w[-1:] in MARKS and w[:-1].isalpha()]
        stems, apart = [w[:-1] for w in marked], set(marked)
        need = [s for s in dict.fromkeys([*(w for w in new if w not in apart), *stems, *MARKS]) if s not in at]
        parts = [self._ids(need[i : i + 2000]) for i in range(0, len(need), 2000)]
        self._add(need, [x for x, _ in parts], [n for _, n in parts])
        if marked:
            pair = np.array([(at[s], at[w[-1]]) for s, w in zip(stems, marked, strict=True)])
            self._add(marked, [self._joined(pair.ravel()).to_numpy()], [self.sizes[pair].sum(axis=1)])
        return np.fromiter(map(at.__getitem__, words), np.int64, len(words))

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, and where each text's ids begin, with their end."""
        with self.lock:
            return self._encode(texts)

    def _encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        texts = pc.fill_null(texts, "")
        if pc.any(pc.match_substring(texts, SPECIAL)).as_py():
            # Special tokens are found in texts as they are, before letters become small.
            found = [np.array(e.ids, np.uint32) for e in self.inner.encode_batch_fast(texts.to_pylist(), add_special_tokens=False)]
            return np.concatenate(found), np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int64)
        # The vocabulary is one of small letters; A-Z first, so that fewer words differ.
        lists = pc.ascii_split_whitespace(pc.ascii_lower(texts))
        ends = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)
        coded = lists.flatten().dictionary_encode()
        place = self._places(coded.dictionary.to_pylist())[coded.indices.to_numpy(zero_copy_only=False)]
        starts = np.concatenate([[0], np.cumsum(by_row(self.sizes[place], ends))]).astype(np.int64)
        return self._joined(place).to_numpy(), starts


class WholeTokenizer:
    """Ids of whole texts by any vocabulary."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.inner = Tokenizer.from_file(path)

    def wake(self) -> None: ...

    def rest(self) -> None: ...

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        found = [np.array(e.ids, np.uint32) for e in self.inner.encode_batch_fast(pc.fill_null(texts, "").to_pylist(), add_special_tokens=False)]
        return np.concatenate([*found, np.zeros(0, np.uint32)]), np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int64)


@functools.cache
def _tokenizer(path: str) -> WordTokenizer | WholeTokenizer:
    with open(path, encoding="utf-8") as f:
        return WordTokenizer(path) if WordTokenizer.reads(json.load(f)) else WholeTokenizer(path)


def _pieces(path: str, end_id: int, window: int):
    def run(batches):
        tokenizer = _tokenizer(path)
        tokenizer.wake()
        for b in slices(batches, "text", TEXT_BYTES):
            ids, offs = tokenizer.encode(b.column("text"))
            out = []
            for row, (lo, hi) in enumerate(zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)):
                own = np.append(ids[lo:hi], np.uint32(end_id)).astype("<u4")
                out += [(row, s, len(own[s : s + window]), zlib.crc32(own[s : s + window].tobytes()), len(own)) for s in range(0, len(own), window)]
            row, *rest = (pa.array(c, pa.int64()) for c in zip(*out, strict=True))
            yield pa.RecordBatch.from_arrays([b.column("doc_id").take(row), *rest], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])
        tokenizer.rest()

    return run


def differencing(sizes: list[int], k: int) -> list[list[int]]:
    """Multiway differencing: ``k`` groups of indices with near-equal sums.

    Each item starts as a partition with one filled part. The two partitions with the widest spread are merged, largest part against
    smallest, until one is left. Parts that are empty aren't stored.
    """
    parts: list[list[tuple]] = [[(s, (i, None))] for i, s in enumerate(sizes)]
    spread = lambda p: p[0][0] - (p[-1][0] if len(p) == k else 0)
    heap = [(-spread(p), i) for i, p in enumerate(parts)]
    heapq.heapify(heap)
    while len(heap) > 1:
        _, i = heapq.heappop(heap)
        _, j = heapq.heappop(heap)
        a, b = parts[i], parts[j]
        if len(a) < len(b):
            a, b = b, a
        free = k - len(a)
        new = b[: max(0, min(free, len(b)))] if free else []
        rest = b[len(new) :]
        # The empty parts of the larger partition take the largest of the other; what remains meets its smallest parts.
        merged = a[: len(a) - len(rest)] + new
        for (x, left), (y, right) in zip(reversed(a[len(a) - len(rest) :]) if rest else [], rest, strict=True):
            merged.append((x + y, (left, right)))
        merged.sort(key=lambda p: -p[0])
        parts[i], parts[j] = merged, []
        heapq.heappush(heap, (-spread(merged), i))
    out = []
    for _, tree in parts[heap[0][1]] if heap else []:
        stack, items = [tree], []
        while stack:
            node = stack.pop()
            if node is None:
                continue
            left, right = node
            if isinstance(left, int):
                items.append(left)
            else:
                stack.append(left)
            stack.append(right)
        out.append(sorted(items))
    return out


def pack_group(sizes: list[int], window: int) -> list[list[int]]:
    """As few windows as differencing fills without one above capacity.

    No two pieces above half a window share one, which bounds the count from below. It rises by what the windows above capacity hold too much,
    in windows, and by one at least, until none is above.
    """
    k = max(1, -(-sum(sizes) // window), sum(2 * s > window for s in sizes))
    while True:
        found = differencing(sizes, k)
        over = sum(max(0, sum(sizes[i] for i in g) - window) for g in found)
        if not over:
            return found
        k += max(1, over // window)


def pack(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", window: int = 4096, end_id: int = 2, group_pieces: int = 1024) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A document's ids, with ``end_id`` behind them, are cut into full windows and a rest. Pieces meet in hash groups of about
    ``group_pieces``; in a group full pieces are windows of their own and rests are packed by differencing. A null or empty text is one
    piece that holds ``end_id``; whole texts are read, however long. A row that repeats an id is a document of its own, and one without an id
    too. Sequence ids are unique, not gapless. Other columns are ignored; an empty table gives an empty result. Vocabularies that never look across
    white space are read word by word, others text by text.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    pieces = settle(rows.mapInArrow(_pieces(tokenizer_path, end_id, window), PIECES))
    groups = max(1, -(-pieces.count() // group_pieces))

    def place(table: pa.Table) -> pa.Table:
        table = table.sort_by([(c, "ascending") for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")])
        length = table.column("length").to_numpy()
        full, rest = np.flatnonzero(length == window), np.flatnonzero(length < window)
        seqs = [[i] for i in full] + ([[int(rest[i]) for i in g] for g in pack_group(length[rest].tolist(), window)] if len(rest) else [])
        seq, off = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
        for n, items in enumerate(seqs):
            at = 0
            for i in items:
                seq[i], off[i] = n, at
                at += length[i]
        first = table.column("g")[0].as_py() * (1 << 24)
        return table.drop_columns("g").append_column("sequence_id", pa.array(first + seq)).append_column("offset", pa.array(off))

    dealt = pieces.withColumn("g", F.pmod(F.xxhash64(F.lit(11), "doc_id", "start"), F.lit(groups)))
    return dealt.groupBy("g").applyInArrow(place, PIECES + ", sequence_id long, offset long")
