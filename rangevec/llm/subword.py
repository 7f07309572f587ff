"""Averaged hashed subword embeddings under a linear softmax, trained by stochastic gradient descent in numpy."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .shared import by_row


def letters(words: list[str]) -> np.ndarray:
    """Whether each word has a letter."""
    return np.fromiter((w.isalpha() or any(map(str.isalpha, w)) for w in words), bool, len(words))


@dataclass
class Grams:
    """Bucket numbers of the character n-grams of words that are set in angle brackets."""

    sizes: tuple[int, ...] = (2, 3, 4)
    bits: int = 16

    def of(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All buckets, and where each word's begin, with their end."""
        if not words:
            return np.zeros(0, np.int64), np.zeros(1, np.int64)
        codes = np.frombuffer(("<" + "><".join(words) + ">").encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
        lens = np.fromiter(map(len, words), np.int64, len(words)) + 2
        left = np.repeat(np.cumsum(lens), lens) - np.arange(len(codes))
        ids = np.zeros((len(codes), len(self.sizes)), np.int64)
        ok = np.zeros(ids.shape, bool)
        for j, n in enumerate(self.sizes):
            m = len(codes) - n + 1
            if m <= 0:
                continue
            h = np.full(m, n, np.uint64)
            for i in range(n):
                h = (h ^ codes[i : i + m]) * np.uint64(0x100000001B3)
                h ^= h >> np.uint64(29)
            h *= np.uint64(0x9E3779B97F4A7C15)
            ids[:m, j] = (h >> np.uint64(64 - self.bits)).astype(np.int64)
            ok[:m, j] = left[:m] >= n
        per = by_row(ok.sum(axis=1), np.concatenate([[0], np.cumsum(lens)]))
        return ids[ok], np.concatenate([[0], np.cumsum(per)])


@dataclass
class Model:
    """``table`` holds, for each bucket, what it adds to each class; a text's logits are the mean over its buckets, plus ``bias``."""

    grams: Grams
    table: np.ndarray
    bias: np.ndarray

    def sums(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """For each word the sum over its buckets, and their number."""
        ids, offs = self.grams.of(words)
        return by_row(self.table[ids], offs), np.diff(offs)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def train(grams: Grams, bags: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, classes: int, dim: int = 16, epochs: int = 8, rate: float = 0.4, batch: int = 64, seed: int = 0, scale: float = 8.0) -> Model:
    """Embeddings and softmax weights fitted together. A bag is its buckets and their counts; ``scale`` sets how far one mean embedding can move a logit."""
    rng = np.random.default_rng(seed)
    emb = rng.normal(0, 1 / dim, (1 << grams.bits, dim)).astype(np.float32)
    out, bias = rng.normal(0, 1 / dim, (dim, classes)).astype(np.float32), np.zeros(classes, np.float32)
    emb_g, out_g, bias_g = np.full(1 << grams.bits, 1e-8, np.float32), np.full(out.shape, 1e-8, np.float32), np.full(classes, 1e-8, np.float32)
    bags = [(i, (c / c.sum()).astype(np.float32) * scale) for i, c in bags]
    for _ in range(epochs):
        order = rng.permutation(len(bags))
        for at in range(0, len(order), batch):
            take = [k for k in order[at : at + batch] if len(bags[k][0])]
            if not take:
                continue
            ids, wts = np.concatenate([bags[k][0] for k in take]), np.concatenate([bags[k][1] for k in take])
            lens = np.array([len(bags[k][0]) for k in take])
            starts = np.cumsum(lens) - lens
            mean = np.add.reduceat(emb[ids] * wts[:, None], starts)
            g = softmax(mean @ out + bias)
            g[np.arange(len(take)), labels[take]] -= 1
            g /= len(take)
            d_out, d_mean = mean.T @ g, g @ out.T
            rows, inv = np.unique(ids, return_inverse=True)
            order2 = np.argsort(inv, kind="stable")
            first = np.searchsorted(inv[order2], np.arange(len(rows)))
            d_emb = np.add.reduceat((np.repeat(d_mean, lens, axis=0) * wts[:, None])[order2], first)
            emb_g[rows] += (d_emb**2).mean(axis=1)
            emb[rows] -= rate * d_emb / np.sqrt(emb_g[rows])[:, None]
            out_g += d_out**2
            out -= rate * d_out / np.sqrt(out_g)
            bias_g += g.sum(axis=0) ** 2
            bias -= rate * g.sum(axis=0) / np.sqrt(bias_g)
    return Model(grams, (emb @ out * scale).astype(np.float32), bias)


def bag(model_ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    ids, n = np.unique(model_ids, return_counts=True)
    return ids, n.astype(np.float32)
