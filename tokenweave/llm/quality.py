"""Document quality by supervised subword embeddings.

Each word is the sum of learned vectors for itself and its character n-grams, each pair of neighbouring words has a
vector of its own, all by hashing; a document is the mean of these vectors and a softmax layer reads it. All
is trained by stochastic gradient descent in numpy.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MIX_A, char_grams, labelled_sample, mix, sum_runs

BITS, PAIR_BITS, DIM = 16, 15, 16
GRAMS = (3, 4, 5)


def subwords(tokens: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the tokens' character n-grams and of the tokens themselves, and where each token's begin."""
    grams, starts = char_grams(tokens, GRAMS, BITS)
    whole = np.fromiter((token_hash(t) & ((1 << BITS) - 1) for t in tokens), np.int64, len(tokens))
    return np.insert(grams, starts[:-1], whole), starts + np.arange(len(starts))


def pair_buckets(hashes: np.ndarray) -> np.ndarray:
    """Buckets of neighbouring words; a word that follows itself is one kind of pair, whatever the word."""
    found = (mix(hashes[:-1] * MIX_A + hashes[1:]) & np.uint64((1 << PAIR_BITS) - 1)).astype(np.int64)
    return np.where(hashes[:-1] == hashes[1:], 0, found)


def token_hash(token: str) -> int:
    return xxhash.xxh3_64_intdigest(token.encode("utf-8", "surrogatepass"))


@dataclass
class QualityModel:
    words: np.ndarray
    pairs: np.ndarray
    output: np.ndarray
    bias: np.ndarray
    cached: int = 100_000
    index: dict = field(init=False, repr=False)

    def __post_init__(self):
        self._anew()

    def __reduce__(self):
        return QualityModel, (self.words, self.pairs, self.output, self.bias, self.cached)

    def _anew(self):
        self.index = {}
        self.sums = np.zeros((1024, self.words.shape[1]), np.float32)
        self.sizes, self.hashes = np.zeros(1024, np.int64), np.zeros(1024, np.uint64)

    def _learn(self, tokens: list[str]) -> None:
        at, starts = subwords(tokens)
        k, need = len(self.index), len(self.index) + len(tokens)
        if need > len(self.sizes):
            size = max(need, 2 * len(self.sizes))
            self.sums, self.sizes, self.hashes = (np.concatenate([x, np.zeros((size - len(x), *x.shape[1:]), x.dtype)]) for x in (self.sums, self.sizes, self.hashes))
        self.sums[k:need], self.sizes[k:need] = sum_runs(self.words[at], starts), np.diff(starts)
        self.hashes[k:need] = np.fromiter(map(token_hash, tokens), np.uint64, len(tokens))
        self.index.update(zip(tokens, range(k, need)))

    def scores(self, texts: list[str | None]) -> list[float]:
        """Probability of label 1 for each text."""
        if len(self.index) >= self.cached:
            self._anew()
        out, index = [], self.index
        for a in range(0, len(texts), 128):
            docs = [t.split() if t else [] for t in texts[a : a + 128]]
            if new := list(set().union(*docs).difference(index)):
                self._learn(new)
            found = [list(map(index.__getitem__, d)) for d in docs]
            for f in found:
                hidden = np.zeros(self.words.shape[1])
                if f:
                    at = np.array(f)
                    between = pair_buckets(self.hashes[at])
                    total = self.sums[at].sum(0, dtype=np.float64) + self.pairs[between].sum(0, dtype=np.float64)
                    hidden = total / (int(self.sizes[at].sum()) + len(between))
                x = hidden @ self.output + self.bias
                out.append(float(1 / (1 + np.exp(np.clip(x[0] - x[1], -500, 500)))))
        return out


def train(rows: list[tuple], epochs: int = 5, rate: float = 0.5, seed: int = 5) -> QualityModel:
    """Fit on ``(id, text, label)`` rows with labels 0 and 1."""
    rng = np.random.default_rng(seed)
    size = 1 << BITS
    table = ((rng.random((size + (1 << PAIR_BITS), DIM)) - 0.5) / DIM).astype(np.float32)
    output, bias = np.zeros((DIM, 2), np.float32), np.zeros(2, np.float32)
    docs, cache = [], {}
    for _, text, label in rows:
        tokens = text.split()
        if new := sorted(set(tokens).difference(cache)):
            at, starts = subwords(new)
            cache.update((t, (at[a:b].astype(np.int32), token_hash(t))) for t, a, b in zip(new, starts[:-1], starts[1:]))
        parts = [cache[t][0] for t in tokens]
        if parts:
            parts.append((size + pair_buckets(np.array([cache[t][1] for t in tokens], np.uint64))).astype(np.int32))
            at, count = np.unique(np.concatenate(parts), return_counts=True)
            docs.append((at, (count / count.sum()).astype(np.float32), int(label)))
    if docs:
        share = np.clip(np.mean([d[2] for d in docs]), 0.01, 0.99)
        bias[:] = np.log([1 - share, share])
    steps, done = max(1, epochs * len(docs)), 0
    for _ in range(epochs):
        for k in rng.permutation(len(docs)):
            at, part, label = docs[k]
            now = rate * (1 - done / steps)
            done += 1
            vectors = table[at]
            hidden = part @ vectors
            x = hidden @ output + bias
            p = np.exp(x - x.max())
            p /= p.sum()
            p[label] -= 1
            back = output @ p
            output -= now * np.outer(hidden, p)
            bias -= 0.1 * now * p
            table[at] = vectors - now * 20 * part[:, None] * back
    return QualityModel(table[:size], table[size:], output.astype(np.float64), bias.astype(np.float64))


def fit(docs: DataFrame, labels: DataFrame, max_docs: int = 3000, **settings) -> QualityModel:
    """Fit on a hash sample of at most about ``max_docs`` labelled documents (``labels``: ``doc_id, label``)."""
    return train(labelled_sample(docs, labels, max_docs), **settings)


def scored(docs: DataFrame, model: QualityModel, text_col: str = "text") -> Column:
    """A column with the score, 0 to 1, of each whole text; null and empty texts get what the bias gives.

    Repeated rows get equal scores, a long text is read whole, and no column but the text is looked at."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # 2 ** BITS + 2 ** PAIR_BITS vectors: 6 MB

    @F.pandas_udf(T.DoubleType())
    def score(texts):
        return pd.Series(shared.value.scores(texts.tolist()), dtype=float)

    return score(F.coalesce(F.col(text_col), F.lit("")))
