"""Language identification by averaged hashed subword embeddings, with calibrated rejection."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from .shared import Words, by_row, slices
from .subword import Grams, Model, bag, letters, softmax, train

MOST_CLASSES = 1024
UNKNOWN = "und"


@dataclass
class Identifier:
    """``least`` is the probability below which an answer is rejected."""

    names: list[str]
    model: Model | None
    temperature: float = 1.0
    least: float = 0.0

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        w = Words(texts)
        known = by_row(letters(w.vocab)[w.codes] if w.vocab else np.zeros(0, bool), w.offsets, np.logical_or)
        if self.model is None:
            return [UNKNOWN] * len(known), np.zeros(len(known))
        sums, n = self.model.sums(w.vocab)
        total = by_row(n[w.codes].astype(np.float64), w.offsets)
        z = by_row(sums[w.codes].astype(np.float64), w.offsets) / np.maximum(total, 1)[:, None] + self.model.bias
        p = softmax(z / self.temperature)
        best = p.argmax(axis=1)
        return [self.names[i] if ok else UNKNOWN for i, ok in zip(best, known, strict=True)], np.where(known, p.max(axis=1), 0.0)


def sample(labelled: DataFrame, label: str, text: str, id_col: str, per_class: int, seed: int) -> list[tuple]:
    """(label, text) of about ``per_class`` rows of each label, chosen by a hash of the id."""
    counts = labelled.groupBy(label).count().limit(MOST_CLASSES + 1).collect()
    if len(counts) > MOST_CLASSES:
        raise ValueError(f"more than {MOST_CLASSES} labels")
    if not counts:
        return []
    rate = F.create_map(*[x for r in counts for x in (F.lit(r[label]), F.lit(min(1.0, per_class / r["count"])))])
    rows = labelled.where(F.pmod(F.xxhash64(F.lit(seed), id_col), F.lit(1_000_000)) < rate[F.col(label)] * 1_000_000).select(label, text, id_col).toArrow()
    return sorted(zip(rows.column(label).to_pylist(), rows.column(text).to_pylist(), rows.column(id_col).to_pylist(), strict=True), key=lambda r: (str(r[0]), r[2]))


def fit(docs: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_class: int = 400, most_chars: int = 20_000, rejected: float = 0.0005, seed: int = 3) -> Identifier:
    """Learn from the rows where ``learn`` holds and the language isn't null.

    The sample is bounded by ``per_class`` rows of each language, about, of at most ``most_chars`` characters each. A fifth of it is held
    back: it sets the temperature, and the threshold that would reject a share ``rejected`` of its right answers. Short runs of
    words count as examples of their own.
    """
    rows = docs.where(learn & F.col(lang_col).isNotNull() & (F.length(text_col) <= most_chars)).select(F.col(lang_col).alias("y"), F.col(text_col).alias("x"), F.col(id_col).cast("long").alias("i"))
    got = sample(rows, "y", "x", "i", per_class, seed)
    names = sorted({r[0] for r in got})
    if not names:
        return Identifier([], None)
    grams, rng = Grams((1, 2, 3, 4)), np.random.default_rng(seed)
    bags, labels, held = [], [], []
    for k, (y, x, _) in enumerate(got):
        if k % 5 == 4:
            held.append((names.index(y), x))
            continue
        w = Words(pa.array([x]))
        ids, offs = grams.of(w.vocab)
        parts = [ids[offs[c] : offs[c + 1]] for c in range(len(w.vocab))]
        runs = [(0, len(w.codes))] + [(a := int(rng.integers(0, max(1, len(w.codes)))), a + int(rng.integers(1, 12))) for _ in range(3)]
        for a, b in runs:
            if len(own := w.codes[a:b]):
                bags.append(bag(np.concatenate([parts[c] for c in own])))
                labels.append(names.index(y))
    out = Identifier(names, train(grams, bags, np.array(labels), len(names), epochs=6, seed=seed))
    if held:
        y, texts = np.array([h[0] for h in held]), pa.array([h[1] for h in held])

        def at(t: float) -> np.ndarray:
            out.temperature = t
            w, p = out.predict(texts)
            return np.where(np.array([names.index(x) if x in names else -1 for x in w]) == y, p, (1 - p) / max(1, len(names) - 1))

        loss = {t: -np.log(np.maximum(at(t), 1e-12)).mean() for t in (0.25, 0.5, 1.0, 2.0, 4.0)}
        out.temperature = min(loss, key=loss.get)
        found, p = out.predict(texts)
        right = np.array([f == names[k] for f, k in zip(found, y, strict=True)])
        out.least = min(0.5, float(np.quantile(p[right], rejected))) if right.any() else 0.0
    return out


def identify(docs: DataFrame, model: Identifier, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, ``lang_pred``, ``score``, the probability of that answer, and ``rejected``.

    Whole texts are read. ``und`` with score 0 if the text is null or has no letter, or nothing was learned; ``rejected`` says that, or that
    the score is below the calibrated threshold. Rows that repeat an id are answered one by one. Other columns are ignored; an empty
    table gives an empty result.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = pa.schema([("_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64()), ("rejected", pa.bool_())])

    def run(batches):
        m = shared.value
        for b in slices(batches, "text"):
            names, p = m.predict(b.column("text"))
            yield pa.RecordBatch.from_arrays([b.column("_id"), pa.array(names, pa.string()), pa.array(p), pa.array([n == UNKNOWN or x < m.least for n, x in zip(names, p, strict=True)])], schema=schema)

    rows = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "_id long, lang_pred string, score double, rejected boolean").withColumnRenamed("_id", id_col)


def keep_identified(docs: DataFrame, model: Identifier, text_col: str = "text") -> DataFrame:
    """The documents that aren't rejected, with all their columns, in one pass."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for b in slices(batches, text_col):
            names, p = m.predict(b.column(text_col))
            yield b.filter(pa.array([n != UNKNOWN and x >= m.least for n, x in zip(names, p, strict=True)]))

    return docs.mapInArrow(run, docs.schema)
