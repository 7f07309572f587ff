"""Toxicity scores: subword bags averaged over short runs of words under a linear softmax; a document is as toxic as its worst run."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from .langid import sample
from .shared import Words, by_row, slices
from .subword import Grams, Model, bag, train

RUN = 2


def _clean(words: list[str]) -> list[str]:
    return ["".join(c for c in w if c.isalnum()).lower() for w in words]


@dataclass
class Scorer:
    """``slope`` and ``shift`` turn the worst run's margin into a probability."""

    model: Model | None
    slope: float = 1.0
    shift: float = 0.0

    def margins(self, texts: pa.Array) -> np.ndarray:
        """The largest margin of any run of RUN words in each text; NaN without a word."""
        w = Words(texts)
        sums, n = self.model.sums(_clean(w.vocab))
        d = (sums[:, 1] - sums[:, 0]).astype(np.float64)
        z, m = d[w.codes], n[w.codes].astype(np.float64)
        best = z / np.maximum(m, 1)
        if len(z) > 1:
            inside = np.ones(len(z) - 1, bool)
            inside[w.offsets[1:-1][(w.offsets[1:-1] > 0) & (w.offsets[1:-1] < len(z))] - 1] = False
            pair = (z[1:] + z[:-1]) / np.maximum(m[1:] + m[:-1], 1)
            best[:-1] = np.where(inside, np.maximum(best[:-1], pair), best[:-1])
        out = by_row(best, w.offsets, np.maximum)
        return np.where(np.diff(w.offsets) > 0, out + self.model.bias[1] - self.model.bias[0], np.nan)

    def score(self, texts: pa.Array) -> np.ndarray:
        if self.model is None:
            return np.full(len(texts), 1 / (1 + np.exp(-self.shift)))
        z = self.margins(texts)
        return np.where(np.isnan(z), 1 / (1 + np.exp(30)), 1 / (1 + np.exp(-np.clip(self.slope * z + self.shift, -30, 30))))


def fit(docs: DataFrame, labels: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", per_class: int = 2000, most_chars: int = 20_000, rounds: int = 3, seed: int = 5) -> Scorer:
    """Learn from labelled rows where ``learn`` holds.

    The sample is bounded by ``per_class`` labels of each kind, about, and texts of at most ``most_chars`` characters. A label speaks of
    a whole document. First, words far commoner in toxic documents than in clean ones stand for the toxic ones; then, in turns, the model is
    fitted to each toxic document's telling and worst runs and to clean documents' worst and other runs. A fifth is held back to fit the probability.
    """
    marked = labels.where(learn & F.col(label_col).isin(0, 1)).select(F.col(label_col).cast("int").alias("y"), F.lit("").alias("x"), F.col(id_col).cast("long").alias("i"))
    chosen = sample(marked, "y", "x", "i", per_class, seed)
    if not chosen:
        return Scorer(None)
    spark = docs.sparkSession
    ids = spark.createDataFrame([(int(i), int(y)) for y, _, i in chosen], "i long, y int")
    texts = docs.where(F.length(text_col) <= most_chars).select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("x")).join(F.broadcast(ids), "i").toArrow()
    rows = sorted(zip(texts.column("i").to_pylist(), texts.column("y").to_pylist(), texts.column("x").to_pylist(), strict=True))
    y = np.array([r[1] for r in rows], np.int64)
    if len(set(y.tolist())) < 2:
        return Scorer(None, shift=float(np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))))
    held = np.arange(len(rows)) % 5 == 4
    w = Words(pa.array([r[2] for r in rows]))
    vocab = _clean(w.vocab)
    forms, code = np.unique(np.array(vocab, object).astype(str), return_inverse=True)
    codes = code[w.codes]
    grams = Grams((2, 3, 4, 5), 17)
    gram_ids, offs = grams.of(forms.tolist())
    part = lambda c: gram_ids[offs[c] : offs[c + 1]]
    docs_of = [codes[a:b] for a, b in zip(w.offsets[:-1], w.offsets[1:], strict=True)]
    # Share of toxic and clean documents that hold each word.
    seen = np.zeros((2, len(forms)))
    for k, own in enumerate(docs_of):
        if not held[k]:
            seen[y[k], np.unique(own)] += 1
    size = np.array([(~held & (y == c)).sum() for c in (0, 1)])
    lift = np.log((seen[1] + 0.1) / (size[1] + 1)) - np.log((seen[0] + 0.1) / (size[0] + 1))
    # A word of few documents says little.
    lift *= np.minimum(1, (seen[1] + seen[0]) / 5)
    rng = np.random.default_rng(seed)
    margin, out = lift, Scorer(None)
    for turn in range(rounds):
        bags, marks = [], []
        for k, own in enumerate(docs_of):
            if held[k] or not len(own):
                continue
            order = np.argsort(-margin[own], kind="stable")
            if y[k]:
                # Every word whose own share speaks for toxicity, and the one the model finds worst.
                telling = [at for at in np.argsort(-lift[own], kind="stable")[:8] if lift[own[at]] >= max(1.0, 0.5 * lift[own].max())]
                for at in dict.fromkeys([*map(int, telling), *map(int, order[:1])] if turn or not telling else map(int, telling)):
                    a = max(0, int(at) - int(rng.integers(0, 2)))
                    bags += [bag(part(own[at])), bag(np.concatenate([part(c) for c in own[a : a + RUN]]))]
                    marks += [1, 1]
            else:
                for at in [*order[: 4 if turn else 2], *rng.integers(0, len(own), 10)]:
                    bags.append(bag(part(own[at])))
                    marks.append(0)
                for at in rng.integers(0, len(own), 4):
                    bags.append(bag(np.concatenate([part(c) for c in own[at : at + RUN]])))
                    marks.append(0)
        model = train(grams, bags, np.array(marks), 2, dim=8, epochs=4, seed=seed + turn)
        out = Scorer(model)
        sums = by_row(model.table[gram_ids], offs)
        margin = (sums[:, 1] - sums[:, 0]) / np.maximum(np.diff(offs), 1) + model.bias[1] - model.bias[0]
    z = out.margins(pa.array([r[2] for r in rows]))
    use = held & ~np.isnan(z)
    if use.any() and len(set(y[use].tolist())) == 2:
        # Probabilities at the share of toxic documents among the labels, not in the sample.
        a, b = 1.0, 0.0
        total = labels.where(learn).groupBy(label_col).count().collect()
        n = {int(r[0]): r["count"] for r in total if r[0] in (0, 1)}
        weight = np.where(y[use] == 1, n.get(1, 1) / max(1, (y == 1).sum()), n.get(0, 1) / max(1, (y == 0).sum()))
        weight = weight / weight.sum()
        mid, wide = z[use].mean(), z[use].std() + 1e-9
        zs = (z[use] - mid) / wide
        x, ridge = np.stack([zs, np.ones(len(zs))], axis=1), 1e-6
        beta = np.array([a, b])
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
            h = (x * (p * (1 - p) * weight + 1e-9)[:, None]).T @ x + ridge * np.eye(2)
            beta = beta - np.clip(np.linalg.solve(h, x.T @ ((p - y[use]) * weight) + ridge * beta), -2, 2)
        a, b = beta
        out.slope, out.shift = a / wide, b - a * mid / wide
    return out


def score(docs: DataFrame, model: Scorer, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, ``score`` (0 to 1) and ``predicted`` (1 from 0.5).

    Whole texts are read. Null, empty and wordless texts score next to nothing. Rows that repeat an id are scored one by one. Other
    columns are ignored; an empty table gives an empty result.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = pa.schema([("_id", pa.int64()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(batches):
        for b in slices(batches, "text"):
            p = shared.value.score(b.column("text"))
            yield pa.RecordBatch.from_arrays([b.column("_id"), pa.array(p), pa.array((p >= 0.5).astype(np.int32))], schema=schema)

    rows = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "_id long, score double, predicted int").withColumnRenamed("_id", id_col)
