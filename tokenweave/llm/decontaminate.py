"""Benchmark decontamination by spaced-seed hashing.

A seed is a fixed mask over a window of words: it hashes the words at its marked places and ignores the others,
so that a substituted word leaves the seeds alone that ignore its place. Seeds of documents meet seeds of benchmark
items; around each meeting the two texts are laid side by side, and the longest stretch in which most words agree
decides. The masks are so many that every stretch of 12 words or more with 80 % agreement holds a seed.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MIX_B, U64, gram_hashes, mix, word_hashes, words_of

#: Fixed masks: four of 8 in 12 words for few substitutions, three of 6 words that some place spares wherever at most a
#: fifth of 12 or more words is substituted (a test goes through all placements). The first one is the longest.
MASKS = ("111010010111", "110110101011", "111100110101", "101011011101", "1110111", "111001011", "100011111")
#: Benchmarks of up to this many words are broadcast (about 50 bytes a word), larger ones are joined.
BROADCAST_WORDS = 500_000
MARKS = b".,;:!?\"'()[]{}<>*&%$#|"


def plain_hashes(text: str | None) -> np.ndarray:
    """Hashes of a text's words in lower case (A-Z), without marks around them; a word of marks alone is kept whole."""
    return word_hashes([w.strip(MARKS) or w for w in words_of(text, lower=True)])


def seeds(hashes: np.ndarray, mask: str, number: int) -> np.ndarray:
    """A hash for each position at which the mask fits."""
    n = len(hashes) - len(mask) + 1
    if n <= 0:
        return np.empty(0, U64)
    value = np.full(n, number + 1, U64)
    for k, mark in enumerate(mask):
        if mark == "1":
            value = value * MIX_B + hashes[k : k + n]
    return mix(value)


def stretch(equal: np.ndarray, share: float) -> tuple[int, int]:
    """Begin and end of the longest stretch (the first of equal ones) of which at least a share is equal; 0, 0 without one."""
    part = Fraction(str(share))
    gain = np.concatenate([[0], np.cumsum(np.where(equal, part.denominator - part.numerator, -part.numerator))])
    rest = np.maximum.accumulate(gain[::-1])[::-1]  # the most that is still reached: never rises
    last = np.searchsorted(-rest, -gain, "right") - 1
    begin = int((last - np.arange(len(gain))).argmax())
    return (begin, int(last[begin])) if last[begin] > begin else (0, 0)


@dataclass
class Benchmark:
    """Items' word hashes and the sorted seeds of all of them."""

    ids: list[int]
    words: list[np.ndarray]
    masks: tuple[str, ...]

    def __post_init__(self):
        keys, items, places = [], [], []
        for k, words in enumerate(self.words):
            for m, mask in enumerate(self.masks_of(len(words))):
                found = seeds(words, mask, m) if len(words) >= len(self.masks[0]) else gram_hashes(words, len(words))
                keys.append(found)
                items.append(np.full(len(found), k))
                places.append(np.arange(len(found)))
        joined = np.concatenate(keys) if keys else np.empty(0, U64)
        order = np.argsort(joined, kind="stable")
        self.keys = joined[order]
        self.items, self.places = (np.concatenate(x)[order] if x else np.empty(0, np.int64) for x in (items, places))
        self.known = np.zeros(1 << 20, bool)
        self.known[(self.keys & U64((1 << 20) - 1)).astype(np.int64)] = True
        self.short = sorted({len(w) for w in self.words if len(w) < len(self.masks[0])})

    def masks_of(self, n: int) -> tuple[str, ...]:
        return self.masks if n >= len(self.masks[0]) else ("1" * n,)

    def met(self, words: np.ndarray) -> set[tuple[int, int]]:
        """Items and offsets (of the document against the item) at which some seed agrees."""
        out = set()
        found = [seeds(words, mask, m) for m, mask in enumerate(self.masks)] + [gram_hashes(words, n) for n in self.short]
        for values in found:
            at = np.flatnonzero(self.known[(values & U64((1 << 20) - 1)).astype(np.int64)])
            if len(at):
                low, high = np.searchsorted(self.keys, values[at], "left"), np.searchsorted(self.keys, values[at], "right")
                for p, a, b in zip(at[high > low].tolist(), low[high > low].tolist(), high[high > low].tolist()):
                    out.update(zip(self.items[a:b].tolist(), (p - self.places[a:b]).tolist()))
        return out


def verify(words: np.ndarray, item: np.ndarray, offset: int, share: float, least: int) -> tuple[int, int, int] | None:
    """Begin and end in the document, and equal words, of the longest stretch at an offset; None where it's too short."""
    a, b = max(0, offset), min(len(words), offset + len(item))
    equal = words[a:b] == item[a - offset : b - offset]
    least = min(least, len(item))
    if np.count_nonzero(equal) < Fraction(str(share)) * least:
        return None
    begin, end = stretch(equal, share)
    if end - begin < least:
        return None
    return a + begin, a + end, int(equal[begin:end].sum())


def read_benchmark(items: DataFrame, id_col: str, text_col: str, shortest: int, masks: tuple[str, ...]) -> Benchmark:
    table = items.select(F.col(id_col).cast("long"), F.col(text_col)).where(F.col(id_col).isNotNull()).toArrow()
    pairs = sorted((i, t) for i, t in zip(*(table.column(k).to_pylist() for k in (0, 1))) if t)
    words = [(i, plain_hashes(t)) for i, t in pairs]
    words = [(i, w) for i, w in words if len(w) >= shortest]
    return Benchmark([i for i, _ in words], [w for _, w in words], masks)


RESULT = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("contaminated", T.BooleanType()), T.StructField("items", T.ArrayType(T.LongType())), T.StructField("spans", T.ArrayType(T.StructType([T.StructField("item_id", T.LongType()), T.StructField("begin", T.IntegerType()), T.StructField("end", T.IntegerType()), T.StructField("equal", T.IntegerType())])))])
SPAN = pa.list_(pa.struct([("item_id", pa.int64()), ("begin", pa.int32()), ("end", pa.int32()), ("equal", pa.int32())]))


def word_count(items: DataFrame, text_col: str) -> int:
    return items.agg(F.coalesce(F.sum(F.size(F.split(F.coalesce(F.col(text_col), F.lit("")), r"[\x20\x09-\x0D]+"))), F.lit(0))).first()[0]


def spans_of(text: str | None, bench: Benchmark, share: float, least: int) -> set[tuple]:
    words = plain_hashes(text)
    return {(bench.ids[k], *s) for k, offset in bench.met(words) if (s := verify(words, bench.words[k], offset, share, least))} if len(words) else set()


def _row(spans: set) -> tuple:
    spans = sorted(spans)
    return bool(spans), sorted({s[0] for s in spans}), [dict(zip(("item_id", "begin", "end", "equal"), s)) for s in spans]


def find_contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", share: float = 0.8, least: int = 16, shortest: int = 8, masks: tuple[str, ...] = MASKS, broadcast_words: int = BROADCAST_WORDS) -> DataFrame:
    """``doc_id, contaminated, items, spans`` for each row of ``docs``.

    A document is contaminated by an item if a stretch of at least ``least`` words (or the whole item, if shorter)
    agrees with the item at one offset in a ``share`` of its words or more; the given masks find each such stretch for
    shares of 0.8 or more. Spans are word positions in the document of the longest such stretch at an offset. Items of fewer than ``shortest`` words are no evidence and left out; items
    shorter than a mask must occur whole. Null and empty texts are clean. Repeated rows come out as often as they
    come in; repeated items give one span each. The benchmark's size is measured first: small ones are broadcast,
    larger ones joined by seed.
    """
    size = word_count(items, item_text)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    if size > broadcast_words:
        return _joined(rows, items, item_id, item_text, share, least, shortest, masks)
    shared = docs.sparkSession.sparkContext.broadcast(read_benchmark(items, item_id, item_text, shortest, masks))

    def run(batches):
        bench = shared.value
        for batch in batches:
            for a in range(0, len(batch), 512):
                part = batch.slice(a, 512)
                out = []
                for text in part.column(1).to_pylist():
                    out.append(_row(spans_of(text, bench, share, least)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([r[0] for r in out]), pa.array([r[1] for r in out], pa.list_(pa.int64())), pa.array([r[2] for r in out], SPAN)], RESULT.names)

    return rows.mapInArrow(run, RESULT)


def drop_contaminated(docs: DataFrame, items: DataFrame, text_col: str = "text", item_id: str = "item_id", item_text: str = "text", share: float = 0.8, least: int = 16, shortest: int = 8, masks: tuple[str, ...] = MASKS, broadcast_words: int = BROADCAST_WORDS) -> DataFrame:
    """The rows of ``docs``, all columns, that no item contaminates (see ``find_contaminated``), repeated rows included.

    With a small benchmark rows are judged where they are, nothing is shuffled. With a larger one texts stand for their
    64-bit hashes, so that a clean text whose hash is that of a contaminated one would go too.
    """
    if word_count(items, item_text) <= broadcast_words:
        shared = docs.sparkSession.sparkContext.broadcast(read_benchmark(items, item_id, item_text, shortest, masks))

        @F.pandas_udf(T.BooleanType())
        def clean(texts):
            return texts.map(lambda t: not spans_of(t, shared.value, share, least)).astype(bool)

        return docs.where(clean(F.coalesce(F.col(text_col), F.lit(""))))
    key = next(n for k in range(len(docs.columns) + 1) if (n := f"row_key_{k}") not in docs.columns)
    keyed = docs.withColumn(key, F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))))
    found = find_contaminated(keyed.select(F.col(key).alias("doc_id"), F.col(text_col).alias("text")), items, item_id=item_id, item_text=item_text, share=share, least=least, shortest=shortest, masks=masks, broadcast_words=broadcast_words)
    bad = found.where("contaminated").select(F.col("doc_id").alias(key)).distinct()
    return keyed.join(bad, key, "left_anti").select(*docs.columns)


def _joined(rows: DataFrame, items: DataFrame, item_id: str, item_text: str, share: float, least: int, shortest: int, masks: tuple[str, ...]) -> DataFrame:
    """The same for benchmarks of any size: seeds of both sides are shuffled and joined, then texts meet in pairs."""
    width = len(masks[0])
    items = items.select(F.col(item_id).cast("long").alias("item_id"), F.col(item_text).alias("item_text")).where("item_id IS NOT NULL AND item_text IS NOT NULL").distinct()
    rows = rows.withColumn("row_key", F.xxhash64("doc_id", "text"))
    short = sorted(r[0] for r in items.select(F.udf(lambda t: len(words_of(t)), "int")("item_text").alias("n")).where(f"n >= {shortest} AND n < {width}").distinct().collect())

    def seeded(is_item: bool):
        def run(batches):
            for batch in batches:
                key, text = [], []
                for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                    words = plain_hashes(t)
                    if is_item and len(words) < width:
                        found = [gram_hashes(words, len(words))] if len(words) >= shortest else []
                    else:
                        found = [seeds(words, mask, m) for m, mask in enumerate(masks)] + ([] if is_item else [gram_hashes(words, n) for n in short])
                    for values in found:
                        key += [i] * len(values)
                        text.append(np.stack([values.view(np.int64), np.arange(len(values))], 1))
                both = np.concatenate(text) if text else np.empty((0, 2), np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(key, pa.int64()), pa.array(both[:, 0]), pa.array(both[:, 1].astype(np.int32))], ["key", "seed", "place"])

        return run

    schema = "key long, seed long, place int"
    left = rows.select("row_key", "text").mapInArrow(seeded(False), schema).select(F.col("key").alias("row_key"), "seed", F.col("place").alias("p"))
    right = items.select("item_id", "item_text").mapInArrow(seeded(True), schema).select(F.col("key").alias("item_id"), "seed", F.col("place").alias("q"))
    met = left.join(right, "seed").select("row_key", "item_id", (F.col("p") - F.col("q")).alias("offset")).distinct()
    pairs = met.groupBy("row_key", "item_id").agg(F.collect_list("offset").alias("offsets"))

    def check(batches):
        for batch in batches:
            keys, ids, offsets, texts, others = (batch.column(k).to_pylist() for k in range(5))
            out = []
            for at, t, o in zip(offsets, texts, others):
                words, item = plain_hashes(t), plain_hashes(o)
                out.append(sorted({s for x in at if (s := verify(words, item, x, share, least))}))
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array([[{"item_id": i, "begin": s[0], "end": s[1], "equal": s[2]} for s in f] for i, f in zip(ids, out)], SPAN)], ["row_key", "found"])

    texts = rows.select("row_key", "text").dropDuplicates(["row_key"])
    found = pairs.join(texts, "row_key").join(items, "item_id").select("row_key", "item_id", "offsets", "text", "item_text").mapInArrow(check, T.StructType([T.StructField("row_key", T.LongType()), T.StructField("found", RESULT["spans"].dataType)]))
    spans = found.where("size(found) > 0").groupBy("row_key").agg(F.array_sort(F.flatten(F.collect_list("found"))).alias("spans"))
    return rows.join(spans, "row_key", "left").select("doc_id", F.col("spans").isNotNull().alias("contaminated"), F.coalesce(F.array_sort(F.array_distinct(F.col("spans.item_id"))), F.array().cast("array<long>")).alias("items"), F.coalesce("spans", F.array().cast(RESULT["spans"].dataType)).alias("spans"))
