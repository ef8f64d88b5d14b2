"""Language of words and documents by a linear-chain conditional random field.

A word's evidence is the sum of learned weights of its affixes, its character n-grams and, for words of a lexicon
gathered from the training texts, of the word itself; learned transitions tie neighbours together, so that the words
of code-switched text are labelled jointly by forward-backward. Training texts are cut into segments and mixed into
code-switched sequences, since whole documents would only teach that the language never changes.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import char_grams, sum_runs

BITS = 16


def letters(token: str) -> str:
    """The letters of a token, in lower case."""
    low = token.lower()
    return low if low.isalpha() else "".join(c for c in low if c.isalpha())


def word_features(words: list[str], lexicon: frozenset[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the n-grams of words of letters (those at an edge are the affixes of up to three letters), and of
    the words that the lexicon has; and where each word's begin."""
    grams, starts = char_grams(words, (2, 3, 4), BITS, "^$")
    known = np.array([k for k, w in enumerate(words) if w in lexicon], np.int64)
    whole = np.fromiter((xxhash.xxh3_64_intdigest(words[k].encode()) & ((1 << BITS) - 1) for k in known.tolist()), np.int64, len(known))
    extra = np.zeros(len(starts), np.int64)
    extra[known + 1] = 1
    return np.insert(grams, starts[known], whole), starts + np.cumsum(extra)


def forward_backward(evidence: np.ndarray, begins: np.ndarray, transition: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Posterior label probabilities of many sequences, one after the other; ``begins`` marks their first words.

    A begin forgets what was before, so that all sequences are one chain of small matrices. The chain is folded into
    rows that advance side by side: first each row's product, then the vectors that enter the rows, then all words.
    """
    n, size = evidence.shape
    if not n or not size:
        return np.zeros((n, size))
    emit = np.exp(evidence - evidence.max(1, keepdims=True))
    step, first = np.exp(transition - transition.max()), np.exp(start - start.max())
    step, first = step / step.sum(), first / first.sum() / size
    cols = max(1, int(np.sqrt(n / 2)))
    rows = -(-n // cols)
    emit = np.concatenate([emit, np.ones((rows * cols - n, size))]).reshape(rows, cols, size)
    begin = np.concatenate([begins, np.ones(rows * cols - n, bool)]).reshape(rows, cols)
    links = np.where(begin[:, :, None, None], first[None, None, None, :], step[None, None]) * emit[:, :, None, :]
    links /= links.sum((2, 3), keepdims=True)
    whole = np.broadcast_to(np.eye(size), (rows, size, size))
    for c in range(cols):
        whole = whole @ links[:, c]
        if c % 8 == 7:
            whole = whole / whole.sum((1, 2), keepdims=True)
    enter, leave = np.empty((rows, size)), np.empty((rows, size))
    v = np.full(size, 1 / size)
    for r in range(rows):
        enter[r] = v
        v = v @ whole[r]
        v = v / v.sum()
    v = np.full(size, 1 / size)
    for r in range(rows - 1, -1, -1):
        leave[r] = v
        v = whole[r] @ v
        v = v / v.sum()
    ahead, v = np.empty((rows, cols, size)), enter
    for c in range(cols):
        v = (v[:, None, :] @ links[:, c])[:, 0]
        v = v / v.sum(1, keepdims=True)
        ahead[:, c] = v
    v = leave
    for c in range(cols - 1, -1, -1):
        ahead[:, c] *= v
        v = (links[:, c] @ v[:, :, None])[:, :, 0]
        v = v / v.sum(1, keepdims=True)
    both = ahead.reshape(-1, size)[:n]
    return both / both.sum(1, keepdims=True)


@dataclass
class LanguageModel:
    labels: list[str]
    weights: np.ndarray
    transition: np.ndarray
    start: np.ndarray
    lexicon: frozenset
    cached: int = 400_000
    index: dict = field(init=False, repr=False)

    def __post_init__(self):
        self._anew()

    def __reduce__(self):
        return LanguageModel, (self.labels, self.weights, self.transition, self.start, self.lexicon, self.cached)

    def _anew(self):
        self.index, self.rows = {}, np.zeros((1024, len(self.labels)), np.float32)
        self.spelt = np.zeros(1024, bool)

    def _learn(self, tokens: list[str]) -> None:
        k, need = len(self.index), len(self.index) + len(tokens)
        if need > len(self.rows):
            size = max(need, 2 * len(self.rows))
            self.rows, self.spelt = (np.concatenate([x, np.zeros((size - len(x), *x.shape[1:]), x.dtype)]) for x in (self.rows, self.spelt))
        words = list(map(letters, tokens))
        at, starts = word_features(words, self.lexicon)
        spelt = np.fromiter(map(bool, words), bool, len(words))
        self.rows[k:need], self.spelt[k:need] = np.where(spelt[:, None], sum_runs(self.weights[at], starts), 0), spelt
        self.index.update(zip(tokens, range(k, need)))

    def posteriors(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of all words of all texts: label probabilities, whether they have letters, and the texts' sizes in words."""
        if len(self.index) >= self.cached:
            self._anew()
        index = self.index
        words = [t.split() if t else [] for t in texts]
        sizes = np.array([len(w) for w in words], np.int64)
        if new := list(set().union(*words).difference(index)):
            self._learn(new)
        at = np.fromiter(map(index.__getitem__, chain.from_iterable(words)), np.int64, int(sizes.sum()))
        begins = np.zeros(len(at), bool)
        begins[(np.cumsum(sizes) - sizes)[sizes > 0]] = True
        return forward_backward(self.rows[at].astype(np.float64), begins, self.transition, self.start), self.spelt[at], sizes

    def documents(self, texts: list[str | None]) -> list[tuple[str, float]]:
        """The label with the largest mean probability over a text's words with letters, and that mean."""
        found, spelt, sizes = self.posteriors(texts)
        found = np.where(spelt[:, None], found, 0)
        sums = np.concatenate([np.zeros((1, len(self.labels))), np.cumsum(found, 0)])
        counts = np.concatenate([[0], np.cumsum(spelt)])
        ends = np.cumsum(sizes)
        out = []
        for a, b in zip((ends - sizes).tolist(), ends.tolist()):
            if not (n := int(counts[b] - counts[a])) or not self.labels:
                out.append(("und", 0.0))
            else:
                mean = (sums[b] - sums[a]) / n
                k = int(mean.argmax())
                out.append((self.labels[k], float(min(1.0, max(0.0, mean[k])))))
        return out


def train(rows: list[tuple], sequences: int = 2500, length: int = 60, epochs: int = 3, rate: float = 0.2, lexicon_from: int = 3, seed: int = 3) -> LanguageModel:
    """Fit on ``(id, text, language)`` rows by minibatch gradient steps (Adagrad) on the labels' log-likelihood."""
    labels, rng = sorted({r[2] for r in rows}), np.random.default_rng(seed)
    texts: dict[str, list[list[str]]] = {x: [] for x in labels}
    counts: Counter = Counter()
    for _, text, label in rows:
        words = [w for w in map(letters, text.split()) if w]
        if words:
            texts[label].append(words)
            counts.update(set(words))
    labels = [x for x in labels if texts[x]]
    size, lexicon = len(labels), frozenset(w for w, n in counts.items() if n >= lexicon_from)
    model = LanguageModel(labels, np.zeros((1 << BITS, size), np.float32), np.zeros((size, size)), np.zeros(size), lexicon)
    if not size:
        return model
    cache, made = {}, []
    for _ in range(sequences):
        words, marks = [], []
        k = int(rng.integers(size))
        while len(words) < length:
            if rng.random() < 0.5:
                k = int(rng.integers(size))
            doc = texts[labels[k]][int(rng.integers(len(texts[labels[k]])))]
            n = int(rng.integers(3, 21))
            a = int(rng.integers(max(1, len(doc) - n + 1)))
            part = doc[a : a + n]
            words += part
            marks += [k] * len(part)
        if new := sorted(set(words[:length]).difference(cache)):
            at, starts = word_features(new, lexicon)
            cache.update((w, at[a:b]) for w, a, b in zip(new, starts[:-1], starts[1:]))
        made.append(([cache[w] for w in words[:length]], marks[:length]))
    squares, square_t, square_s = np.full((1 << BITS, size), 1e-2, np.float32), np.full((size, size), 1e-2), np.full(size, 1e-2)
    batch = 50
    for _ in range(epochs):
        order = rng.permutation(len(made))
        for a in range(0, len(order), batch):
            some = [made[k] for k in order[a : a + batch]]
            flat = np.concatenate([f for words, _ in some for f in words])
            owner = np.repeat(np.arange(len(some) * length), [len(f) for words, _ in some for f in words])
            evidence = np.stack([np.bincount(owner, model.weights[flat, k], len(some) * length) for k in range(size)], 1)
            gold = np.array([m for _, m in some])
            emit = np.exp(evidence - evidence.max(1, keepdims=True)).reshape(len(some), length, size)
            step, first = np.exp(model.transition), np.exp(model.start)
            ahead, back = np.empty_like(emit), np.empty_like(emit)
            v = first * emit[:, 0]
            ahead[:, 0] = v / v.sum(1, keepdims=True)
            for t in range(1, length):
                v = (ahead[:, t - 1] @ step) * emit[:, t]
                ahead[:, t] = v / v.sum(1, keepdims=True)
            back[:, -1] = 1
            for t in range(length - 2, -1, -1):
                v = (back[:, t + 1] * emit[:, t + 1]) @ step.T
                back[:, t] = v / v.sum(1, keepdims=True)
            single = ahead * back
            single /= single.sum(2, keepdims=True)
            pairs = ahead[:, :-1, :, None] * step[None, None] * (emit[:, 1:] * back[:, 1:])[:, :, None, :]
            pairs /= pairs.sum((2, 3), keepdims=True)
            truth = np.eye(size)[gold]
            error = (single - truth).reshape(-1, size) / len(some)
            at, place = np.unique(flat, return_inverse=True)
            grad = np.stack([np.bincount(place, error[owner, k], len(at)) for k in range(size)], 1) + 1e-5 * model.weights[at]
            squares[at] += grad**2
            model.weights[at] -= (rate * grad / np.sqrt(squares[at])).astype(np.float32)
            seen = np.zeros((size, size))
            np.add.at(seen, (gold[:, :-1].ravel(), gold[:, 1:].ravel()), 1)
            grad = (pairs.sum((0, 1)) - seen) / len(some) / 10
            square_t += grad**2
            model.transition -= rate * grad / np.sqrt(square_t)
            grad = (single[:, 0] - truth[:, 0]).sum(0) / len(some)
            square_s += grad**2
            model.start -= rate * grad / np.sqrt(square_s)
    return model


def fit(docs: DataFrame, labels: DataFrame, per_label: int = 300, **settings) -> LanguageModel:
    """Fit on a hash sample of about ``per_label`` documents of each language (``labels``: ``doc_id, label``)."""
    labels = labels.where("label IS NOT NULL AND doc_id IS NOT NULL")
    shares = {r.label: int(min(1.0, per_label / r.n) * 2**31) for r in labels.groupBy("label").agg(F.count("*").alias("n")).collect()}  # a row a language
    if not shares:
        return train([])
    share = F.create_map([F.lit(x) for pair in shares.items() for x in pair])
    chosen = labels.where(F.pmod(F.xxhash64("doc_id", F.lit(13)), F.lit(2**31)) < share[F.col("label")])
    chosen = chosen.groupBy(F.col("doc_id").alias("id")).agg(F.min("label").alias("label"))
    table = docs.select("doc_id", "text").where("text IS NOT NULL").join(F.broadcast(chosen), F.col("doc_id") == F.col("id")).select("doc_id", "text", "label").toArrow()
    return train(sorted(zip(*(table.column(k).to_pylist() for k in range(3)))), **settings)


def predict(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, lang_pred, score`` of each whole text; ``und`` and 0 where it is null or has no letters.

    Equal means go to the label that sorts first. Repeated rows come out as often as they come in.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # 2 ** BITS weights a language and a lexicon of the sample's words
    schema = T.StructType([T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def run(batches):
        for batch in batches:
            for a in range(0, len(batch), 512):
                part = batch.slice(a, 512)
                found = shared.value.documents(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64())], schema.names)

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(run, schema)


def label_words(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, words``: each white-space word with its likeliest language (null without letters) and that probability."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("words", T.ArrayType(T.StructType([T.StructField("word", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("p", T.DoubleType())])))])

    def run(batches):
        for batch in batches:
            texts = batch.column(1).to_pylist()
            found, spelt, sizes = shared.value.posteriors(texts)
            best, at, out = found.argmax(1) if len(found) else [], 0, []
            for text, n in zip(texts, sizes.tolist()):
                out.append([{"word": w, "lang": shared.value.labels[best[at + k]] if spelt[at + k] else None, "p": float(found[at + k].max()) if spelt[at + k] else None} for k, w in enumerate((text or "").split())])
                at += n
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.list_(pa.struct([("word", pa.string()), ("lang", pa.string()), ("p", pa.float64())])))], schema.names)

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(run, schema)
