"""Masked pseudo-likelihood: a bidirectional window network scores each word from both its sides.

The vocabulary is all words, by 64-bit hash, counted over all documents. The network tells the commonest ones apart and
hash buckets of the rest; inside its bucket each word has the smoothed share of its own count. These counts grow with the
input and stay a distributed table: scoring sends each chunk of documents the counts of its own words only.
A hidden layer sums position-wise embeddings of the neighbours; a two-level softmax (class, then word in class)
predicts the masked word. For training the texts' ids are dealt by a hash of the row to shards, whose number follows from
the number of words alone: how the input is split into files changes nothing. In each round every shard takes gradient
steps in numpy from the shared parameters, and the shards' parameters are averaged by their numbers of words.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Scratch, text_words
from .parts import ragged, slices

#: Vocabulary: words by rank, then hash buckets; classes of as many words.
TOP, BUCKETS, SIDE = 768, 256, 32
SIZE = TOP + BUCKETS
SPAN, DIM = 2, 16
SHIFTS = [k for k in range(-SPAN, SPAN + 1) if k]
#: Messages summed up by a task; ranges of parameters that are summed up apart; words of a shard; places of a step.
MERGED, RANGES, SHARD_WORDS, STEP = 64, 16, 1 << 21, 2048
PARTS = {"embed": (len(SHIFTS), SIZE + 1, DIM), "bias": (DIM,), "classes": (DIM, SIDE), "class_bias": (SIDE,), "words": (SIZE // SIDE, DIM, SIDE), "word_bias": (SIZE // SIDE, SIDE)}
#: Words scored at once; words of a chunk of documents whose counts are fetched together; bytes of text read at once.
BLOCK, CHUNK_WORDS, SLICE = 8192, 1 << 20, 1 << 20
#: Added to each word's count inside its bucket, and the whole count of a bucket's unseen words.
UNSEEN = 0.5
#: Slots of the table that finds the network's own words.
SLOTS = 1 << 16


def bucket_of(words: np.ndarray) -> np.ndarray:
    """The buckets of words by hash."""
    return (words >> np.uint64(40)).astype(np.int64) % BUCKETS


def count_words(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``word, n`` over all documents, words by hash, summed up inside each task first."""

    def run(batches):
        held, n = [], 0

        def flush():
            words, counts = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(words.view(np.int64)), pa.array(counts)], ["word", "n"])

        for batch in batches:
            for a, m in slices(batch.column(0), SLICE):
                held.append(text_words(batch.column(0).slice(a, m), lower=True)[0])
                n += len(held[-1])
                if n >= 1 << 22:
                    yield flush()
                    held, n = [], 0
        if n:
            yield flush()

    return docs.select(F.col(text_col).cast("string")).mapInArrow(run, "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))


@dataclass
class WindowNetwork:
    """The hashes of the network's own words by rank, the weights, the logarithms of the buckets' smoothed totals, and
    ``word, n`` of all words in buckets (on the driver)."""

    top: np.ndarray
    weights: dict[str, np.ndarray]
    totals: np.ndarray | None = None
    counts: DataFrame | None = None

    def __post_init__(self):
        if self.totals is None:
            self.totals = np.full(BUCKETS, np.log(UNSEEN))
        self.slots = np.full(SLOTS, -1, np.int16)
        self.crowded = []
        for k, word in enumerate(self.top.tolist()):
            if self.slots[word % SLOTS] < 0:
                self.slots[word % SLOTS] = k
            else:
                self.crowded.append((k, np.uint64(word)))

    def __reduce__(self):
        return WindowNetwork, (self.top, self.weights, self.totals)

    def ids_of(self, words: np.ndarray) -> np.ndarray:
        out = self.slots[(words & np.uint64(SLOTS - 1)).astype(np.int64)].astype(np.int64)
        if len(self.top):
            wrong = (out < 0) | (self.top[out] != words)
            out[wrong] = TOP + bucket_of(words[wrong])
        else:
            out = TOP + bucket_of(words)
        for k, word in self.crowded:
            out[words == word] = k
        return out

    def encode(self, texts: pa.Array | list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of all words, SPAN places of padding after each text (and before the first), the texts' sizes, and the words."""
        words, ends = text_words(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()), lower=True)
        return padded(self.ids_of(words), ends), np.diff(ends), words

    def hidden(self, ids: np.ndarray, at: np.ndarray) -> np.ndarray:
        x = np.repeat(self.weights["bias"][None], len(at), 0)
        for k, shift in enumerate(SHIFTS):
            x += self.weights["embed"][k, ids[at + shift]]
        return np.tanh(x)

    def log_probs(self, ids: np.ndarray, at: np.ndarray) -> np.ndarray:
        """The log-probability of the word at each place, given its neighbours."""
        w, hidden, target = self.weights, self.hidden(ids, at), ids[at]
        scores = hidden @ w["classes"] + w["class_bias"]
        kind, inner = target // SIDE, target % SIDE
        out = scores[np.arange(len(at)), kind] - np.log(np.exp(scores).sum(1))
        order, ends = by_class(kind)
        for c in range(SIZE // SIDE):
            rows = order[ends[c] : ends[c + 1]]
            if len(rows):
                scores = hidden[rows] @ w["words"][c] + w["word_bias"][c]
                out[rows] += scores[np.arange(len(rows)), inner[rows]] - np.log(np.exp(scores).sum(1))
        return out

    def step(self, ids: np.ndarray, at: np.ndarray, squares: dict[str, np.ndarray], rate: float) -> None:
        """One Adagrad step on the mean log-probability of the words at some places."""
        w, hidden, target, n = self.weights, self.hidden(ids, at), ids[at], len(at)
        kind, inner = target // SIDE, target % SIDE

        def move(name, grad, rows=...):
            squares[name][rows] += grad * grad
            w[name][rows] -= (rate * grad / np.sqrt(squares[name][rows])).astype(np.float32)

        p = np.exp(hidden @ w["classes"] + w["class_bias"])
        p /= p.sum(1, keepdims=True)
        p[np.arange(n), kind] -= 1
        p /= n
        back = p @ w["classes"].T
        moves = {"classes": hidden.T @ p, "class_bias": p.sum(0), "words": np.zeros_like(w["words"]), "word_bias": np.zeros_like(w["word_bias"])}
        order, ends = by_class(kind)
        for c in range(SIZE // SIDE):
            rows = order[ends[c] : ends[c + 1]]
            if len(rows):
                p = np.exp(hidden[rows] @ w["words"][c] + w["word_bias"][c])
                p /= p.sum(1, keepdims=True)
                p[np.arange(len(rows)), inner[rows]] -= 1
                p /= n
                back[rows] += p @ w["words"][c].T
                np.matmul(hidden[rows].T, p, out=moves["words"][c])
                moves["word_bias"][c] = p.sum(0)
        back *= 1 - hidden * hidden
        for name, grad in moves.items():
            move(name, grad)
        move("bias", back.sum(0))
        for k, shift in enumerate(SHIFTS):
            near = ids[at + shift].astype(np.int16)
            order = np.argsort(near, kind="stable")
            near = near[order]
            first = np.flatnonzero(np.diff(near, prepend=-1))
            move("embed", np.add.reduceat(back[order], first, 0), (k, near[first]))

    def flat(self) -> np.ndarray:
        return np.concatenate([self.weights[name].ravel() for name in PARTS]).astype(np.float32)

    @staticmethod
    def unflat(values: np.ndarray) -> dict[str, np.ndarray]:
        out, at = {}, 0
        for name, shape in PARTS.items():
            n = int(np.prod(shape))
            out[name] = values[at : at + n].reshape(shape).astype(np.float32)
            at += n
        return out


def padded(ids: np.ndarray, ends: np.ndarray) -> np.ndarray:
    out = np.full(len(ids) + SPAN * len(ends), SIZE)
    out[np.arange(len(ids)) + SPAN * np.repeat(np.arange(1, len(ends)), np.diff(ends))] = ids
    return out


def by_class(kind: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order by class, and where each class begins in it."""
    return np.argsort(kind.astype(np.uint8), kind="stable"), np.concatenate([[0], np.cumsum(np.bincount(kind, minlength=SIZE // SIDE))])


def begin(counts: DataFrame, seed: int = 17) -> WindowNetwork:
    """Vocabulary and starting weights; the output biases are the words' log shares. ``counts`` is read again in scoring."""
    top = counts.orderBy(F.desc("n"), "word").limit(TOP).collect()
    share = np.ones(SIZE)
    share[: len(top)] += [r.n for r in top]
    spark = counts.sparkSession
    words = spark.createDataFrame([(r.word,) for r in top], "word long")
    rest = counts.join(F.broadcast(words), "word", "left_anti").select("word", "n")
    totals = np.full(BUCKETS, UNSEEN)
    for r in rest.groupBy(F.expr(f"shiftrightunsigned(word, 40) % {BUCKETS}").cast("int").alias("bucket")).agg(F.sum("n").alias("n"), F.count("*").alias("words")).collect():
        share[TOP + r.bucket] += r.n
        totals[r.bucket] += r.n + UNSEEN * r.words
    rng = np.random.default_rng(seed)
    weights = {name: rng.normal(0, 0.1, shape).astype(np.float32) for name, shape in PARTS.items()}
    weights["bias"][:] = 0
    by_class = share.reshape(-1, SIDE)
    weights["class_bias"] = np.log(by_class.sum(1) / share.sum()).astype(np.float32)
    weights["word_bias"] = np.log(by_class / by_class.sum(1, keepdims=True)).astype(np.float32)
    return WindowNetwork(np.array([r.word for r in top], np.int64).view(np.uint64), weights, np.log(totals), rest)


def shards(docs: DataFrame, network: WindowNetwork, words: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``shard, piece, sizes, ids``: the ids of all texts, dealt by a hash of id and text to shards of about SHARD_WORDS
    words, in the order of that hash; a piece holds a shard or, of larger ones, SHARD_WORDS words or a text more."""
    shared = docs.sparkSession.sparkContext.broadcast(network)
    number = max(1, -(-words // SHARD_WORDS))
    rows = docs.select(F.xxhash64(F.col(id_col).cast("string"), F.col(text_col)).alias("place"), F.col(text_col).cast("string").alias("text"))

    def run(batches):
        for batch in batches:
            for a, m in slices(batch.column(1), SLICE):
                part = batch.slice(a, m)
                found, ends = text_words(part.column(1), lower=True)
                ids = shared.value.ids_of(found).astype("<u2")
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([ids[x:y].tobytes() for x, y in zip(ends[:-1].tolist(), ends[1:].tolist())], pa.binary())], ["place", "ids"])

    def pack(table: pa.Table) -> pa.Table:
        shard = table.column("shard")[0].as_py()
        rows = sorted(zip(table.column("place").to_pylist(), table.column("ids").to_pylist()))
        ends = np.cumsum([len(x) // 2 for _, x in rows])
        out = []
        for k, part in enumerate(np.split(np.arange(len(rows)), np.flatnonzero(np.diff(ends // SHARD_WORDS)) + 1)):
            ids = [rows[r][1] for r in part]
            out.append((shard, k, np.array([len(x) // 2 for x in ids], "<i8").tobytes(), b"".join(ids)))
        return pa.table([pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int32(), pa.binary(), pa.binary()))], ["shard", "piece", "sizes", "ids"])

    dealt = rows.mapInArrow(run, "place long, ids binary").where("length(ids) > 0").withColumn("shard", F.pmod(F.col("place"), F.lit(number)))
    return dealt.groupBy("shard").applyInArrow(pack, "shard long, piece int, sizes binary, ids binary")


def train_round(pieces: DataFrame, network: WindowNetwork, number: int, shards: int, every: int = 1, rate: float = 0.1) -> WindowNetwork:
    """One round over all pieces: each trains on each ``every``-th word of each text (another one each round, so that
    ``every`` rounds take all), then all weights are averaged by trees of sums, one for each range of parameters, in the
    order of the shards."""
    shared = pieces.sparkSession.sparkContext.broadcast(network)
    cuts = np.linspace(0, sum(int(np.prod(s)) for s in PARTS.values()), RANGES + 1).astype(int).tolist()

    def run(batches):
        for batch in batches:
            for shard, piece, sizes, ids in zip(*(batch.column(k).to_pylist() for k in range(4))):
                own = WindowNetwork(shared.value.top, {k: v.copy() for k, v in shared.value.weights.items()})
                squares = {k: np.full(v.shape, 1e-3, np.float32) for k, v in own.weights.items()}
                sizes, ids = np.frombuffer(sizes, "<i8"), np.frombuffer(ids, "<u2").astype(np.int64)
                places = padded(ids, np.concatenate([[0], np.cumsum(sizes)]))
                at = np.flatnonzero(places < SIZE)
                at = at[ragged(np.zeros(len(sizes), np.int64), sizes) % every == number % every]
                for b in range(0, len(at), STEP):
                    own.step(places, at[b : b + STEP], squares, rate)
                total, words = own.flat().astype(np.float64) * len(ids), float(len(ids))
                names = [[shard] * RANGES, list(range(RANGES)), [piece] * RANGES, [words] * RANGES, [total[a:b].tobytes() for a, b in zip(cuts, cuts[1:])]]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(names, kinds)], columns)

    def add(table: pa.Table) -> pa.Table:
        rows = sorted(zip(*(table.column(c).to_pylist() for c in ("node", "piece", "words", "total"))))
        total = sum(np.frombuffer(r[3], np.float64) for r in rows)
        one = [[rows[0][0] // MERGED], table.column("range")[:1].to_pylist(), [0], [sum(r[2] for r in rows)], [total.tobytes()]]
        return pa.table([pa.array(c, t) for c, t in zip(one, kinds)], columns)

    columns, kinds = ["node", "range", "piece", "words", "total"], [pa.int64(), pa.int32(), pa.int32(), pa.float64(), pa.binary()]
    schema = "node long, range int, piece int, words double, total binary"
    parts, left = pieces.mapInArrow(run, schema), shards
    while True:
        parts = parts.groupBy("range", F.expr(f"node div {MERGED}")).applyInArrow(add, schema)
        left = -(-left // MERGED)
        if left <= 1:
            break
    rows = sorted((r.range, r.words, r.total) for r in parts.collect())  # a fixed number of rows
    if not rows:
        return network
    weights = WindowNetwork.unflat(np.concatenate([np.frombuffer(total, np.float64) / words for _, words, total in rows]))
    return WindowNetwork(network.top, weights, network.totals, network.counts)


def fit(docs: DataFrame, rounds: int = 2, id_col: str = "doc_id", text_col: str = "text", scratch: Scratch | None = None, **settings) -> WindowNetwork:
    """Every word of every text is predicted once: each round takes another share of the places."""
    scratch = scratch or Scratch(docs.sparkSession)
    counts = scratch.save(count_words(docs, text_col), "word-counts")
    network, words = begin(counts), counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    pieces = scratch.save(shards(docs, network, words, id_col, text_col), "shards")
    for k in range(rounds):
        network = train_round(pieces, network, k, max(1, -(-words // SHARD_WORDS)), every=rounds, **settings)
    scratch.drop(pieces)
    return network


def score(docs: DataFrame, network: WindowNetwork, id_col: str = "doc_id", text_col: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """``doc_id, n_words, log_prob, mean_log_prob`` of each whole text.

    ``log_prob`` sums each word's log-probability given up to two words on either side; that of a word in a bucket is
    the bucket's and the word's share of the bucket by its count. All words that weren't counted share one small count
    in each bucket. Null and empty texts have no words, 0 and a null mean. Repeated rows come out as often as they come
    in, with equal scores. Texts are scored by the network first; the counts of a chunk's distinct words then
    meet its scores.
    """
    spark, scratch = docs.sparkSession, scratch or Scratch(docs.sparkSession)
    shared = spark.sparkContext.broadcast(network)
    kind = docs.schema[id_col].dataType
    chunked = T.StructType([T.StructField("chunk", T.LongType()), T.StructField("ids", T.ArrayType(kind)), *(T.StructField(c, T.BinaryType()) for c in ("sizes", "sums", "rare", "places")), T.StructField("keys", T.ArrayType(T.LongType()))])

    def run(batches):
        number, waiting, words = TaskContext.get().partitionId() << 32, [], 0

        def chunk():
            ids, sizes, sums, rare, keys = zip(*waiting)
            keys, places = np.unique(np.concatenate(keys), return_inverse=True)
            whole = pa.concat_arrays(ids)
            blobs = [pa.array([np.concatenate(x).tobytes()], pa.binary()) for x in (sizes, sums, rare, [places.astype(np.int32)])]
            lists = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x) for x in (whole, pa.array(keys.view(np.int64)))]
            return pa.RecordBatch.from_arrays([pa.array([number], pa.int64()), lists[0], *blobs, lists[1]], chunked.names)

        for batch in batches:
            for a, m in slices(batch.column(1), SLICE):
                part = batch.slice(a, m)
                ids, sizes, keys = shared.value.encode(part.column(1))
                at, found = np.flatnonzero(ids < SIZE), np.empty(int(sizes.sum()))
                for b in range(0, len(at), BLOCK):
                    found[b : b + BLOCK] = shared.value.log_probs(ids, at[b : b + BLOCK])
                rare = ids[at] >= TOP
                found[rare] -= shared.value.totals[ids[at][rare] - TOP]
                owner = np.repeat(np.arange(len(sizes)), sizes)
                waiting.append((part.column(0), sizes, np.bincount(owner, found, len(sizes)), np.bincount(owner[rare], minlength=len(sizes)), keys[rare]))
                words += len(at)
                if words >= CHUNK_WORDS:
                    yield chunk()
                    number, waiting, words = number + 1, [], 0
        if waiting:
            yield chunk()

    def meet(scored: pa.Table, counts: pa.Table) -> pa.Table:
        sizes, sums, rare, places = (np.frombuffer(scored.column(c)[0].as_py(), t) for c, t in (("sizes", np.int64), ("sums", np.float64), ("rare", np.int64), ("places", np.int32)))
        n = np.full(int(places.max(initial=-1)) + 1, UNSEEN)
        n[counts.column("place").to_numpy()] += counts.column("n").to_numpy()
        own = np.bincount(np.repeat(np.arange(len(rare)), rare), np.log(n)[places], len(rare))
        return pa.table([scored.column("ids").combine_chunks().flatten(), pa.array(sizes), pa.array(sums + own)], out.names)

    out = T.StructType([T.StructField("doc_id", kind), T.StructField("n_words", T.LongType()), T.StructField("log_prob", T.DoubleType())])
    scored = scratch.save(docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, chunked), "scored")
    found = scored.select("chunk", F.posexplode("keys").alias("place", "key")).withColumnRenamed("chunk", "of")
    if network.counts is None:
        found = found.where("false").select("of", "place", F.col("key").alias("n"))
    else:
        found = found.join(network.counts.withColumnRenamed("word", "key"), "key").select("of", "place", "n")
    rows = scored.drop("keys").groupBy("chunk").cogroup(found.groupBy("of")).applyInArrow(meet, out)
    return rows.withColumn("mean_log_prob", F.when(F.col("n_words") > 0, F.col("log_prob") / F.col("n_words")))
