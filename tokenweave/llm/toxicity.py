"""Toxicity by a counterfactually regularised classifier.

A sparse logistic model over the words of a text (whole words, their beginnings, character 4-grams; each counts
once a document), trained by proximal stochastic gradient descent with an L1 penalty. Each labelled text gets copies in
which a group's name that it holds is swapped for another group's or for a neutral noun, one for each name; a text
without any is copied twice with a name inserted, another one each time. The squared change of the score between a text
and its copy is penalised, so that naming a group is no evidence by itself. It is the change of the logit, which an insult
beside the name doesn't saturate; features that a text and its copy share cancel out in it.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Kept, labelled_sample

#: Common group names and neutral nouns, by language. A parameter wherever they are used.
IDENTITY_TERMS = (
    "woman", "women", "man", "men", "girl", "boy", "muslim", "muslims", "christian", "christians", "jewish", "jew", "jews", "hindu", "buddhist", "atheist",
    "black", "white", "asian", "african", "latino", "immigrant", "immigrants", "refugee", "refugees", "gay", "lesbian", "transgender", "straight", "disabled", "blind", "deaf", "old", "young", "american", "mexican", "chinese", "german", "french",
    "frau", "frauen", "mann", "männer", "muslime", "christen", "juden", "schwarze", "ausländer", "flüchtlinge", "femme", "femmes", "homme", "hommes", "musulmans", "chrétiens", "juifs", "noirs", "immigrés", "réfugiés",
    "mujer", "mujeres", "hombre", "hombres", "musulmanes", "cristianos", "judíos", "negros", "inmigrantes", "refugiados",
)
NEUTRAL_TERMS = ("people", "person", "persons", "neighbours", "leute", "menschen", "gens", "personnes", "gente", "personas")
#: Strengths of the L1 penalty, for each labelled text, among which a fifth of the texts chooses.
STRENGTHS = (0.002, 0.005, 0.01, 0.02)
BITS = 20


def core(token: str) -> str:
    """A lower-case token without the marks around it."""
    a, b = 0, len(token)
    while a < b and not token[a].isalnum():
        a += 1
    while b > a and not token[b - 1].isalnum():
        b -= 1
    return token[a:b]


def features(token: str) -> set[str]:
    """Features of a lower-case token: the word, its beginnings of 3 to 6 letters, its 4-grams."""
    word = core(token)
    if not word:
        return set()
    return {"w" + word, *["p" + word[:k] for k in range(3, 7) if len(word) > k], *["g" + word[k : k + 4] for k in range(len(word) - 3)]}


def bucket(feature: str) -> int:
    """Where training keeps a feature's weight."""
    return xxhash.xxh3_64_intdigest(feature.encode("utf-8", "surrogatepass")) & ((1 << BITS) - 1)


def token_set(text: str | None) -> set[str]:
    return set(text.lower().split()) if text else set()


@dataclass
class ToxicityModel:
    bias: float
    weights: dict[str, float]
    cached: int = 100_000
    active: Kept = field(init=False, repr=False)

    def __post_init__(self):
        self.active = Kept(lambda token: tuple(sorted(features(token) & self.weights.keys())), self.cached)

    def __reduce__(self):
        return ToxicityModel, (self.bias, self.weights, self.cached)

    def scores(self, texts: list[str | None]) -> list[float]:
        """Probability of label 1 for each text."""
        out, weights = [], self.weights
        for a in range(0, len(texts), 128):
            docs = list(map(token_set, texts[a : a + 128]))
            known = {t: active for t in set().union(*docs) if (active := self.active[t])}
            marked = set(known)
            for doc in docs:
                found = {f for t in doc & marked for f in known[t]}
                x = self.bias + math.fsum(weights[f] for f in found)
                out.append(1 / (1 + math.exp(-max(-500.0, min(500.0, x)))))
        return out


def counterfactuals(text: str, identity: frozenset[str], others: tuple[str, ...], rng: np.random.Generator) -> list[tuple[set[str], set[str]]]:
    """Pairs of token sets between which a score should not change: the text and, for each name in it, its copy with that
    name swapped throughout; without a name, two copies with different names inserted."""
    tokens = token_set(text)
    named: dict[str, set[str]] = {}
    for t in sorted(tokens):
        if (word := core(t)) in identity:
            named.setdefault(word, set()).add(t)
    if not named:
        a, b = rng.choice(len(others), 2, replace=False)
        return [(tokens | {others[a]}, tokens | {others[b]})]
    out = []
    for word, held in named.items():
        other = others[int(rng.integers(len(others)))]
        out.append((tokens, (tokens - held) | {t.replace(word, other) for t in held}))
    return [(x, y) for x, y in out if x != y]


def logistic(x: float) -> float:
    return 1 / (1 + math.exp(-max(-500.0, min(500.0, x))))


def descend(docs: list[np.ndarray], labels: np.ndarray, pairs: list[list[tuple]], l1: float, epochs: int, rate: float, counterfactual: float, positive: float, seed: int) -> tuple[float, np.ndarray]:
    """Bias and weights by bucket."""
    size, rng = 1 << BITS, np.random.default_rng(seed)
    share = (labels.sum() + 0.5) / (len(labels) + 1)
    z, n, bias, bias_n = np.zeros(size), np.zeros(size), math.log(share / (1 - share)), 1.0

    def weight(at):
        v = z[at]
        return np.where(np.abs(v) <= l1, 0.0, -(v - np.sign(v) * l1) * rate / (1.0 + np.sqrt(n[at])))

    def step(at, g):
        before = n[at]
        after = before + g * g
        z[at] += g - (np.sqrt(after) - np.sqrt(before)) / rate * weight(at)
        n[at] = after

    for _ in range(epochs):
        for k in rng.permutation(len(docs)):
            at = docs[k]
            p = logistic(bias + float(weight(at).sum()))
            g = (p - labels[k]) * (positive if labels[k] else 1.0)
            if abs(g) > 1e-3:
                step(at, g)
                bias_n += g * g
                bias -= 1.0 * g / math.sqrt(bias_n)
            for gone, come in pairs[k] if counterfactual else ():
                change = float(weight(gone).sum() - weight(come).sum())
                if abs(change) > 1e-3:
                    step(gone, 2 * counterfactual * change)
                    step(come, -2 * counterfactual * change)
    return bias, weight(np.arange(size))


def train(rows: list[tuple], identity: tuple[str, ...] = IDENTITY_TERMS, neutral: tuple[str, ...] = NEUTRAL_TERMS, epochs: int = 8, rate: float = 0.3, l1: float | None = None, counterfactual: float = 1.0, positive: float = 4.0, seed: int = 11) -> ToxicityModel:
    """Fit on ``(id, text, label)`` rows, where a text of label 1 weighs ``positive`` times one of label 0; without rows, or
    with one label only, the score is that label's share. ``l1`` is the penalty for each row; without one, that of
    ``STRENGTHS`` holds which, learned from four fifths of the rows, gives the others the best likelihood, both labels
    weighing the same."""
    labels = np.array([float(r[2]) for r in rows])
    share = (labels.sum() + 0.5) / (len(rows) + 1)
    if len(set(labels.tolist())) < 2:
        return ToxicityModel(math.log(share / (1 - share)), {})
    rng, cache = np.random.default_rng(seed), Kept(lambda token: np.array(list(map(bucket, features(token))), np.int32).tobytes(), 10**6)  # bytes: the smallest form of some numbers
    found = lambda tokens: np.unique(np.frombuffer(b"".join(cache[t] for t in tokens), np.int32))
    docs = [found(token_set(r[1])) for r in rows]
    names, others, pairs = frozenset(identity), (*identity, *neutral, *neutral), []
    for _, text, _ in rows:
        made = []
        for before, after in counterfactuals(text, names, others, rng):
            a, b = found(before), found(after)
            made.append((np.setdiff1d(a, b, True), np.setdiff1d(b, a, True)))
        pairs.append(made)
    settings = (rate, counterfactual, positive, seed)
    if l1 is None:
        order = np.random.default_rng(seed).permutation(len(rows))
        held, own = order[::5], np.setdiff1d(np.arange(len(rows)), order[::5])
        losses = []
        for strength in STRENGTHS:
            bias, w = descend([docs[k] for k in own], labels[own], [pairs[k] for k in own], strength * len(own), max(1, epochs * 3 // 8), *settings)
            x = np.array([bias + w[docs[k]].sum() for k in held])
            loss = np.logaddexp(0, np.where(labels[held] > 0, -x, x))
            losses.append(sum(loss[labels[held] == y].mean() for y in (0, 1) if (labels[held] == y).any()))
        l1 = STRENGTHS[int(np.argmin(losses))]
    bias, w = descend(docs, labels, pairs, l1 * len(rows), epochs, *settings)
    at = np.flatnonzero(np.abs(w) > 1e-4)
    kept = dict(zip(at.tolist(), w[at].tolist()))
    return ToxicityModel(bias, {f: kept[bucket(f)] for t in cache if not kept.keys().isdisjoint(np.frombuffer(cache[t], np.int32).tolist()) for f in features(t) if bucket(f) in kept})


def fit(docs: DataFrame, labels: DataFrame, max_docs: int = 8000, **settings) -> ToxicityModel:
    """Fit on a hash sample of at most about ``max_docs`` labelled documents (``labels``: ``doc_id, label``)."""
    return train(labelled_sample(docs, labels, max_docs), **settings)


def scored(docs: DataFrame, model: ToxicityModel, text_col: str = "text") -> Column:
    """A column with the score, 0 to 1, of each whole text; null and empty texts get the model's base score.

    Repeated rows get equal scores, a long text is read whole, and no column but the text is looked at."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # as many weights as features at most: 2 ** BITS

    @F.pandas_udf(T.DoubleType())
    def score(texts):
        return pd.Series(shared.value.scores(texts.tolist()), dtype=float)

    return score(F.coalesce(F.col(text_col), F.lit("")))
