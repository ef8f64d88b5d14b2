"""Removal of word runs that have been seen before, with a log-structured fingerprint index.

Documents come in batches of ascending ids. Of each document's hashed word grams the index keeps those that are smallest
in some window (a winnowing: any window of ``width`` words holds one, chosen by the window's words alone). History is a
table of immutable runs, one a batch: blocks of sorted fingerprints, bucketed by their range, so that a batch's blocks
meet those of all runs in place, without moving or sorting history again. Where a fingerprint has a partner, in the
batch or in history, all windows around it are compared whole (by 128 bits made of the words' 64-bit hashes, which is
the error that is accepted), and each one but the first occurrence is a repeat. What a batch adds as its run are its
fingerprints without those whose windows all repeat earlier ones, so that a passage that a third of all documents share
is kept once. Runs are compacted into one when there are ``fanout`` of them.

Equal keys meet in a task before anything moves: a task sends one entry for each of its fingerprints and windows, however
often they occur. So a bucket gets at most one entry of a key from each task, and a hot key is no hot group.
"""

from __future__ import annotations

import json
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MIX_B, Scratch, gram_hashes, mix, remove, text_words, words_of
from .parts import ragged, slices

#: A block: what it is, its bucket, and as many entries in each binary column (a and b: 64-bit hashes; docs, ties: 64 bits; at: 32 bits; flag: a byte).
BLOCK = "kind byte, bucket int, a binary, b binary, docs binary, ties binary, at binary, flag binary"
KINDS = {"a": "<u8", "b": "<u8", "docs": "<i8", "ties": "<i8", "at": "<i4", "flag": "u1"}
ONCE, HIT, OLD_HIT, OPEN, FIRST, AGAIN, SIZE, MORE, MARK = range(9)
#: Entries that a task holds before it sends a block; bytes of text it hashes at once; bytes of text for a bucket.
HELD, SLICE, BUCKET_TEXT = 1 << 20, 1 << 20, 64 << 20


def block(kind: int, bucket: int | None = None, **columns: np.ndarray) -> dict:
    return {"kind": kind, "bucket": bucket, **{c: np.ascontiguousarray(v, KINDS[c]).tobytes() for c, v in columns.items()}}


def blocks(rows: list[dict]) -> pa.RecordBatch:
    kinds = {"kind": pa.int8(), "bucket": pa.int32(), **{c: pa.binary() for c in KINDS}}
    return pa.RecordBatch.from_arrays([pa.array([r.get(c) for r in rows], t) for c, t in kinds.items()], list(kinds))


def unblock(table, *names: str) -> list[np.ndarray]:
    """The named columns of all blocks of a table, one block after the other."""
    out = []
    for c in names:
        raw = [x for x in table.column(c).to_pylist() if x]
        out.append(np.frombuffer(b"".join(raw), KINDS[c]) if raw else np.empty(0, KINDS[c]))
    return out


def bucket_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Ranges of 64-bit keys."""
    return ((keys >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int32)


def by_bucket(kind: int, buckets: int, a: np.ndarray, **columns: np.ndarray) -> list[dict]:
    """Blocks of entries in the order of ``a``, one for each bucket that has any."""
    of = bucket_of(a, buckets)
    cuts = np.concatenate([[0], np.flatnonzero(np.diff(of)) + 1, [len(a)]]) if len(a) else [0]
    return [block(kind, int(of[x]), a=a[x:y], **{c: v[x:y] for c, v in columns.items()}) for x, y in zip(cuts[:-1], cuts[1:])]


def _rolling(x: np.ndarray, n: int, pick) -> np.ndarray:
    """``pick`` over each n consecutive values, by doubling."""
    done = 1
    while done * 2 <= n:
        x = pick(x[:-done], x[done:])
        done *= 2
    return pick(x[: len(x) - (n - done)], x[n - done :]) if done < n else x


def winnow(hashes: np.ndarray, ends: np.ndarray, gram: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions and values of the gram hashes that are smallest in some window of ``width`` words of one text."""
    span, n = width - gram + 1, len(hashes) - width + 1
    if n <= 0:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    values = gram_hashes(hashes, gram)
    smallest = _rolling(values, span, np.minimum)
    smallest[np.arange(n) + width > np.repeat(ends[1:], np.diff(ends))[:n]] = 0  # over the end of a text
    none = np.zeros(span - 1, np.uint64)
    at = np.flatnonzero(_rolling(np.concatenate([none, smallest, none]), span, np.maximum) == values)
    return at, values[at]


def around(low: np.ndarray, high: np.ndarray, n: int) -> np.ndarray:
    """True for each of n places from a ``low`` to its ``high``, both included."""
    fits = high >= low
    edge = np.bincount(low[fits], minlength=n + 1) - np.bincount(high[fits] + 1, minlength=n + 1)
    return np.cumsum(edge)[:n] > 0


def first_of(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A stable order by both keys, and True where a pair of keys differs from the one before."""
    order = np.argsort(a, kind="stable")
    x, y = a[order], b[order]
    same = x[1:] == x[:-1]
    if (y[1:][same] != y[:-1][same]).any():
        order = np.lexsort((b, a))
        x, y = a[order], b[order]
        same = x[1:] == x[:-1]
    return order, np.concatenate([[True], ~(same & (y[1:] == y[:-1]))]) if len(a) else np.empty(0, bool)


def entries(schema: T.StructType):
    """Rows ``doc, tie, kind, x, y, print`` from blocks: hits (position, fingerprint), repeats (first and last start of a
    run of windows) and sizes (words)."""

    def run(batches):
        for batch in batches:
            for k in range(len(batch)):
                one = batch.slice(k, 1)
                docs, ties, at, prints = unblock(one, "docs", "ties", "at", "a")
                kind, y = one.column("kind")[0].as_py(), at
                if kind == AGAIN and len(at):
                    starts = np.concatenate([[True], (docs[1:] != docs[:-1]) | (ties[1:] != ties[:-1]) | (at[1:] != at[:-1] + 1)])
                    y = at[np.append(np.flatnonzero(starts)[1:], len(at)) - 1]
                    docs, ties, at = docs[starts], ties[starts], at[starts]
                prints = prints.view(np.int64) if len(prints) else np.zeros(len(at), np.int64)
                for a in range(0, len(at), 100_000):
                    cut = slice(a, a + 100_000)
                    yield pa.RecordBatch.from_arrays([pa.array(docs[cut]), pa.array(ties[cut]), pa.array(np.full(len(at[cut]), kind, np.int8)), pa.array(at[cut]), pa.array(y[cut]), pa.array(prints[cut])], schema.names)

    return run


ENTRY = T.StructType([T.StructField("doc", T.LongType()), T.StructField("tie", T.LongType()), T.StructField("kind", T.ByteType()), T.StructField("x", T.IntegerType()), T.StructField("y", T.IntegerType()), T.StructField("print", T.LongType())])


def spread(df: DataFrame) -> DataFrame:
    return df.select("kind", "docs", "ties", "at", "a").mapInArrow(entries(ENTRY), ENTRY)


class FingerprintIndex:
    """History of the documents seen so far, kept under ``path``; ``ingest`` takes the next batch.

    ``width`` words make a window, ``gram`` words a fingerprint. The tables ``texts`` (bucketed by document), ``runs``
    (bucketed by fingerprint range) and ``more`` (further occurrences of a fingerprint in one task's share of a run)
    have a folder for each batch or run. ``save`` writes what is needed to ``load`` the index in another session.
    ``close`` forgets the tables' names; the files stay.
    """

    def __init__(self, spark: SparkSession, scratch: Scratch, path: str, width: int = 20, gram: int = 6, fanout: int = 3, buckets: int | None = None, places: int | None = None):
        self.spark, self.scratch, self.path, self.width, self.gram, self.fanout = spark, scratch, path, width, gram, fanout
        self.places = places or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.buckets = buckets or self.places
        self.batches, self.made, self.live = 0, 0, []
        self.name = f"fingerprints_{uuid.uuid4().hex}"

    # ---- tables

    def _append(self, df: DataFrame, table: str, part: int, places: int, *by: str) -> None:
        with self.scratch.cleaning():
            (df.repartition(places, *by).withColumn("part", F.lit(part)).write.mode("append").partitionBy("part").bucketBy(places, *by).option("compression", "zstd")
             .option("path", f"{self.path}/{table}").saveAsTable(f"{self.name}_{table}"))
        if (name := f"{self.name}_{table}") not in self.scratch.names:
            self.scratch.names.append(name)

    def _table(self, table: str, parts: list[int]) -> DataFrame:
        return self.spark.table(f"{self.name}_{table}").where(F.col("part").isin(parts)).drop("part")

    def save(self) -> None:
        """Write the index's description beside its tables; its runs and texts are on disk already."""
        about = {k: getattr(self, k) for k in ("width", "gram", "fanout", "buckets", "places", "batches", "made", "live")}
        self.spark.createDataFrame([(json.dumps(about),)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.path}/about")

    @classmethod
    def load(cls, spark: SparkSession, scratch: Scratch, path: str, extra: str = "") -> FingerprintIndex:
        """The index that was saved under a path. ``extra``: carried columns of its texts, as ``name type, ``."""
        about = json.loads(spark.read.text(f"{path}/about").first()[0])
        out = cls(spark, scratch, path, *(about[k] for k in ("width", "gram", "fanout", "buckets", "places")))
        out.batches, out.made, out.live = about["batches"], about["made"], about["live"]
        tables = {"texts": (f"doc long, tie long, text string, {extra}part int", "doc, tie", out.places)}
        if out.made:
            tables |= {"runs": (BLOCK + ", part int", "bucket", out.buckets), "more": ("a long, doc long, tie long, at int, part int", "doc", out.buckets)}
        for table, (columns, by, n) in tables.items():
            spark.sql(f"CREATE TABLE {out.name}_{table} ({columns}) USING parquet OPTIONS (path '{path}/{table}', compression 'zstd') PARTITIONED BY (part) CLUSTERED BY ({by}) INTO {n} BUCKETS")
            spark.sql(f"MSCK REPAIR TABLE {out.name}_{table}")
        return out

    def close(self) -> None:
        for table in ("texts", "runs", "more"):
            self.spark.sql(f"DROP TABLE IF EXISTS {self.name}_{table}")

    # ---- the steps of a batch

    def _fingerprints(self, docs: DataFrame) -> DataFrame:
        """For each task and bucket its distinct fingerprints, and all places of those that the task has met twice."""
        width, gram, buckets = self.width, self.gram, self.buckets

        def flush(held):
            prints, doc, tie, at = (np.concatenate(c) for c in zip(*held))
            order = np.argsort(prints, kind="stable")
            prints, doc, tie, at = prints[order], doc[order], tie[order], at[order]
            new = np.concatenate([[True], prints[1:] != prints[:-1]])
            twice = ~new | ~np.append(new[1:], True)
            rows = by_bucket(ONCE, buckets, prints[new], docs=doc[new], ties=tie[new], at=at[new])
            return blocks([*rows, *([block(HIT, a=prints[twice], docs=doc[twice], ties=tie[twice], at=at[twice])] if twice.any() else [])])

        def run(batches):
            held, n = [], 0
            for batch in batches:
                for a, m in slices(batch.column(2), SLICE):
                    part = batch.slice(a, m)
                    hashes, ends = text_words(part.column(2))
                    at, prints = winnow(hashes, ends, gram, width)
                    owner = np.searchsorted(ends, at, "right") - 1
                    held.append((prints, part.column(0).to_numpy()[owner], part.column(1).to_numpy()[owner], (at - ends[owner]).astype(np.int32)))
                    n += len(at)
                    if n >= HELD:
                        yield flush(held)
                        held, n = [], 0
            if n:
                yield flush(held)

        return docs.select("doc", "tie", "text").mapInArrow(run, BLOCK)

    def _matched(self, prints: DataFrame) -> DataFrame:
        """Blocks of the fingerprints that occur once, of hits in the batch and in history, and of history's open keys."""
        buckets = self.buckets

        def match(new, old: pa.Table | None = None) -> pa.Table:
            a, docs, ties, at = unblock(new, "a", "docs", "ties", "at")
            order = np.argsort(a, kind="stable")
            a, docs, ties, at = a[order], docs[order], ties[order], at[order]
            first = np.concatenate([[True], a[1:] != a[:-1]]) if len(a) else np.empty(0, bool)
            shared, rows = ~first | ~np.append(first[1:], True)[: len(a)], []
            if old is not None and len(old):
                past, past_docs, past_ties, past_at, flag = unblock(old, "a", "docs", "ties", "at", "flag")
                at_first = np.searchsorted(a, past)
                met = (at_first < len(a)) & (a[np.minimum(at_first, len(a) - 1)] == past) if len(a) else np.zeros(len(past), bool)
                if met.any():
                    shared |= np.isin(a, past[met])
                    rows.append(block(OLD_HIT, docs=past_docs[met], ties=past_ties[met], at=past_at[met]))
                    if (more := met & (flag > 0)).any():
                        rows.append(block(OPEN, a=np.unique(past[more])))
            if shared.any():
                rows.append(block(HIT, a=a[shared], docs=docs[shared], ties=ties[shared], at=at[shared]))
            if not shared.all():
                rows += by_bucket(ONCE, buckets, a[~shared], docs=docs[~shared], ties=ties[~shared], at=at[~shared], flag=np.zeros(int((~shared).sum())))
            return pa.Table.from_batches([blocks(rows)])

        once = prints.where(F.col("kind") == ONCE).groupBy("bucket")
        if not self.live:
            return once.applyInArrow(lambda new: match(new), BLOCK)
        return once.cogroup(self._table("runs", self.live).groupBy("bucket")).applyInArrow(lambda new, old: match(new, old), BLOCK)

    def _windows(self, docs: DataFrame) -> DataFrame:
        """Windows around hits: for each task and bucket the first of equal ones, and all others as repeats."""
        width, gram, buckets = self.width, self.gram, self.buckets

        def flush(held):
            names = [np.concatenate(c) for c in zip(*[h[:3] for h in held])]
            one, two, at = (np.concatenate(c) for c in zip(*[h[3:6] for h in held]))
            sizes = np.concatenate([h[6] for h in held])
            order = np.lexsort((names[1], names[0]))  # documents in their order, so that a stable sort finds the first
            rows = ragged((np.cumsum(sizes) - sizes)[order], sizes[order])
            doc, tie, new = (np.repeat(x[order], sizes[order]) for x in names)
            one, two, at = one[rows], two[rows], at[rows]
            order, first = first_of(one, two)
            again = order[~first & new[order]]
            again.sort()
            order = order[first]
            out = by_bucket(FIRST, buckets, one[order], b=two[order], docs=doc[order], ties=tie[order], at=at[order], flag=new[order])
            return blocks([*out, block(AGAIN, docs=doc[again], ties=tie[again], at=at[again])])

        def run(batches):
            held, n = [], 0
            for batch in batches:
                for a, m in slices(batch.column(3), SLICE):
                    part = batch.slice(a, m)
                    hashes, ends = text_words(part.column(3))
                    lists = part.column(4)
                    hits, bounds = lists.values.to_numpy(), lists.offsets.to_numpy()
                    owner = np.repeat(np.arange(len(part)), np.diff(bounds))
                    at = hits[bounds[0] : bounds[-1]] + ends[owner]
                    starts = np.flatnonzero(around(np.maximum(at + gram - width, ends[owner]), np.minimum(at, ends[owner + 1] - width), len(hashes)))
                    one, two = gram_hashes(hashes, width), gram_hashes(mix(hashes + MIX_B), width)
                    doc, tie, new = part.column(0).to_numpy(), part.column(1).to_numpy(), part.column(2).to_numpy(zero_copy_only=False)
                    of = np.searchsorted(ends, starts, "right") - 1
                    held.append((doc, tie, new, one[starts], two[starts], (starts - ends[of]).astype(np.int32), np.bincount(of, minlength=len(part))))
                    n += len(starts)
                    yield blocks([block(SIZE, docs=doc[new], ties=tie[new], at=np.diff(ends)[new])])
                    if n >= HELD:
                        yield flush(held)
                        held, n = [], 0
            if held:
                yield flush(held)

        return docs.select("doc", "tie", "new", "text", "hits").mapInArrow(run, BLOCK)

    def _again(self, windows: DataFrame) -> DataFrame:
        """All windows of the batch, among the tasks' first ones, that aren't the first of all."""

        def later(table: pa.Table) -> pa.Table:
            one, two, docs, ties, at, new = unblock(table, "a", "b", "docs", "ties", "at", "flag")
            order, first = first_of(one, two)
            group = np.cumsum(first) - 1
            rows = order[(np.bincount(group) > 1)[group]]
            group = group[(np.bincount(group) > 1)[group]]
            by_place = np.lexsort((at[rows], ties[rows], docs[rows], group))
            rows, group = rows[by_place], group[by_place]
            rows = rows[~np.concatenate([[True], group[1:] != group[:-1]])] if len(rows) else rows
            rows = rows[new[rows] > 0]
            rows = rows[np.lexsort((at[rows], ties[rows], docs[rows]))]
            return pa.Table.from_batches([blocks([block(AGAIN, docs=docs[rows], ties=ties[rows], at=at[rows])])])

        return windows.where(F.col("kind") == FIRST).groupBy("bucket").applyInArrow(later, BLOCK)

    def _judged(self, found: DataFrame) -> DataFrame:
        """Marks (``doc, tie, begins, ends`` of removed words) and the blocks of hits that still stand in a first window."""
        width, gram, buckets = self.width, self.gram, self.buckets
        kinds = {"kind": pa.int8(), "bucket": pa.int32(), "a": pa.binary(), "docs": pa.binary(), "ties": pa.binary(), "at": pa.binary(), "flag": pa.binary()}

        def flush(held):
            prints, doc, tie, at = (np.concatenate(c) for c in zip(*held))
            order = np.argsort(prints, kind="stable")
            prints, doc, tie, at = prints[order], doc[order], tie[order], at[order]
            first = np.concatenate([[True], prints[1:] != prints[:-1]])
            more = (np.diff(np.append(np.flatnonzero(first), len(prints))) > 1).astype(np.uint8)
            rows = by_bucket(ONCE, buckets, prints[first], docs=doc[first], ties=tie[first], at=at[first], flag=more)
            if not first.all():
                rows.append(block(MORE, a=prints[~first], docs=doc[~first], ties=tie[~first], at=at[~first]))
            marks = [pa.nulls(len(rows), t) for t in (pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int32()))]
            return pa.RecordBatch.from_arrays([*[pa.array([r.get(c) for r in rows], t) for c, t in kinds.items()], *marks], schema.names)

        def run(batches):
            held, n = [], 0
            for batch in batches:
                for a in range(0, len(batch), 4096):
                    part = batch.slice(a, 4096)
                    lists = part.column(2)
                    bounds, values = lists.offsets.to_numpy(), lists.values
                    kind, x, y, prints = (values.field(k).to_numpy()[bounds[0] : bounds[-1]] for k in range(4))
                    owner = np.repeat(np.arange(len(part)), np.diff(bounds))
                    sizes = np.zeros(len(part), np.int64)
                    sizes[owner[kind == SIZE]] = x[kind == SIZE]
                    ends = np.concatenate([[0], np.cumsum(sizes)])
                    total, again = int(ends[-1]), kind == AGAIN
                    base = ends[owner[again]]
                    repeats = around(x[again] + base, y[again] + base, total)
                    gone = around(x[again] + base, y[again] + base + width - 1, total)
                    cut = gone.astype(np.int8)
                    edges = np.diff(cut, prepend=0, append=0)
                    doc_edge = np.zeros(total + 1, bool)
                    doc_edge[ends] = True
                    begins = np.flatnonzero((edges[:-1] == 1) | (doc_edge[:-1] & gone))
                    stops = np.flatnonzero((edges[1:] == -1) | (doc_edge[1:] & gone)) + 1
                    of = np.searchsorted(ends, begins, "right") - 1
                    counts = np.bincount(of, minlength=len(part))
                    some = np.flatnonzero(counts)
                    at_lists = pa.array(np.concatenate([[0], np.cumsum(counts[some])]).astype(np.int32))
                    made = [pa.ListArray.from_arrays(at_lists, pa.array((v - ends[of]).astype(np.int32))) for v in (begins, stops)]
                    rows = pa.array(some)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), MARK, np.int8)), *[pa.nulls(len(some), t) for t in list(kinds.values())[1:]], part.column(0).take(rows), part.column(1).take(rows), *made], schema.names)
                    hit = kind == HIT
                    who, at = owner[hit], x[hit]
                    fresh = np.concatenate([[0], np.cumsum(~repeats)])
                    low, high = np.maximum(at + gram - width, 0) + ends[who], np.minimum(at, sizes[who] - width) + ends[who]
                    stands = fresh[high + 1] > fresh[low]
                    if stands.any():
                        held.append((prints[hit][stands].view(np.uint64), part.column(0).to_numpy()[who[stands]], part.column(1).to_numpy()[who[stands]], at[stands]))
                        n += int(stands.sum())
                    if n >= HELD:
                        yield flush(held)
                        held, n = [], 0
            if n:
                yield flush(held)

        schema = T.StructType([T.StructField("kind", T.ByteType()), T.StructField("bucket", T.IntegerType()), *(T.StructField(c, T.BinaryType()) for c in list(kinds)[2:]), T.StructField("doc", T.LongType()), T.StructField("tie", T.LongType()), T.StructField("begins", T.ArrayType(T.IntegerType())), T.StructField("ends", T.ArrayType(T.IntegerType()))])
        return found.mapInArrow(run, schema)

    def ingest(self, docs: DataFrame, last: bool = False) -> DataFrame:
        """Take the next batch (``doc, tie, text`` and carried columns; each doc and tie once, all after those of earlier
        batches) and return its marks: ``doc, tie, begins, ends`` of removed words, of documents that lose any.
        ``last``: no batch follows, so no run is written. Texts come back by ``texts``."""
        scratch, number, key = self.scratch, self.batches, ["doc", "tie"]
        self._append(docs, "texts", number, self.places, *key)
        self.batches += 1
        prints = scratch.save(self._fingerprints(self._table("texts", [number])), "fingerprints")
        matched = scratch.save(self._matched(prints), "matched")
        hits = spread(prints.where(F.col("kind") == HIT)).union(spread(matched.where(F.col("kind") == HIT)))
        asked = hits.select(*key, "x")
        if self.live:
            asked = asked.union(spread(matched.where(F.col("kind") == OLD_HIT)).select(*key, "x"))
            more = self._table("more", self.live)
            opened = matched.where(F.col("kind") == OPEN).select("a").mapInArrow(_keys, "a long")
            asked = asked.union(more.join(opened.distinct(), "a", "left_semi").select(*key, "at"))
        asked = asked.groupBy(*key).agg(F.collect_list("x").alias("hits"))
        texts = self.spark.table(f"{self.name}_texts").select(*key, "text", (F.col("part") == number).alias("new"))
        windows = scratch.save(self._windows(texts.join(asked.hint("shuffle_hash"), key)), "windows")
        again = spread(windows.where(F.col("kind").isin(AGAIN, SIZE))).union(spread(self._again(windows)))
        found = hits.union(again).groupBy(*key).agg(F.collect_list(F.struct("kind", "x", "y", "print")).alias("found"))
        judged = scratch.save(self._judged(found), "judged")
        if not last:
            once = matched.where(F.col("kind") == ONCE).select("kind", "bucket", "a", "b", "docs", "ties", "at", "flag")
            stays = judged.where(F.col("kind") == ONCE).select("kind", "bucket", "a", F.lit(None).cast("binary").alias("b"), "docs", "ties", "at", "flag")
            self._append(once.union(stays), "runs", self.made, self.buckets, "bucket")
            others = spread(judged.where(F.col("kind") == MORE).select("kind", "docs", "ties", "at", "a")).select(F.col("print").alias("a"), *key, F.col("x").alias("at"))
            self._append(others, "more", self.made, self.buckets, "doc")
            self.live.append(self.made)
            self.made += 1
            if len(self.live) >= self.fanout:
                self.compact()
        scratch.drop(prints, matched, windows)
        marks = scratch.save(judged.where(F.col("kind") == MARK).select(*key, "begins", "ends"), "marks")
        scratch.drop(judged)
        return marks

    def texts(self, batches: list[int]) -> DataFrame:
        return self._table("texts", batches)

    def compact(self) -> None:
        """Merge all runs into one: each bucket's blocks, sorted, become one block; the old runs' files go."""
        buckets, old = self.buckets, self.live

        def merged(table: pa.Table) -> pa.Table:
            a, docs, ties, at, flag = unblock(table, "a", "docs", "ties", "at", "flag")
            order = np.argsort(a, kind="stable")
            return pa.Table.from_batches([blocks(by_bucket(ONCE, buckets, a[order], docs=docs[order], ties=ties[order], at=at[order], flag=flag[order]))])

        self._append(self._table("runs", old).groupBy("bucket").applyInArrow(merged, BLOCK), "runs", self.made, buckets, "bucket")
        self._append(self._table("more", old), "more", self.made, buckets, "doc")
        self.live, self.made = [self.made], self.made + 1
        for number in old:
            for table in ("runs", "more"):
                remove(self.spark, f"{self.path}/{table}/part={number}")
        for table in ("runs", "more"):
            self.spark.catalog.refreshTable(f"{self.name}_{table}")


def _keys(batches):
    for batch in batches:
        yield pa.RecordBatch.from_arrays([pa.array(unblock(batch, "a")[0].view(np.int64))], ["a"])


def without_marked(docs: DataFrame, carry: list[str], unchanged: bool) -> DataFrame:
    """``<carried>, n_words, n_removed, kept`` of rows with ``text, begins, ends``."""
    extra = [docs.schema[c] for c in carry]
    schema = T.StructType([*extra, T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept", T.StringType())])

    def run(batches):
        for batch in batches:
            for a, m in slices(batch.column(0), SLICE):
                part = batch.slice(a, m)
                n_words, n_removed, kept = [], [], []
                for text, begins, ends in zip(*(part.column(k).to_pylist() for k in range(3))):
                    words = words_of(text)
                    n_words.append(len(words))
                    left, at = words, 0
                    if begins:
                        left = []
                        for b, e in zip(begins, ends):
                            left += words[at:b]
                            at = e
                        left += words[at:]
                    n_removed.append(len(words) - len(left))
                    kept.append(text if unchanged and not begins else b" ".join(left).decode("utf-8", "surrogatepass"))
                yield pa.RecordBatch.from_arrays([*[part.column(3 + k) for k in range(len(extra))], pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(kept, pa.string())], schema.names)

    return docs.select("text", "begins", "ends", *carry).mapInArrow(run, schema)


def dedup_substrings(docs: DataFrame, width: int = 20, gram: int = 6, batches: int = 4, fanout: int = 3, id_col: str = "doc_id", text_col: str = "text", carry: list[str] = (), unchanged: bool = False, scratch: Scratch | None = None) -> DataFrame:
    """``doc_id, <carried>, n_words, n_removed, kept``: each text without words that an earlier window holds already.

    Words are runs of bytes other than blanks and 0x09-0x0D, unchanged; a word goes if a window of ``width`` words
    over it also begins earlier (at a smaller id, or earlier in the same text). Windows are judged on the input.
    Kept words are joined by one blank (``unchanged``: a text that loses none stays as it is). Null and empty texts have
    no words and give an empty text; a null id comes before all others. Rows that repeat an id come in order of their
    texts' hashes; rows that repeat id and text are one document and get equal results. Columns other than the carried
    ones are left out. The documents are ingested in ``batches`` ranges of the id into an index of their own, whose
    tables stay in the scratch folder as long as the result, which reads them.
    """
    spark = docs.sparkSession
    scratch = scratch or Scratch(spark)
    about = docs.agg(F.coalesce(F.sum(F.octet_length(text_col)), F.lit(0)), F.percentile_approx(F.col(id_col).cast("long"), [k / batches for k in range(1, batches)] or [0.5], 10_000)).first()
    edges = sorted(set(about[1] or [])) if batches > 1 else []
    repeated = not docs.groupBy(F.col(id_col).cast("long")).count().where("count > 1").isEmpty()
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    tie = F.xxhash64(text) if repeated else F.lit(0).cast("long")
    own = [F.col(id_col).alias("doc_id"), *[F.col(c).alias(f"carried_{c}") for c in carry]]
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(-(2**63))).alias("doc"), tie.alias("tie"), text.alias("text"), *own)
    names = ["doc_id", *[f"carried_{c}" for c in carry]]
    index = FingerprintIndex(spark, scratch, scratch.path("index"), width, gram, fanout, max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-about[0] // BUCKET_TEXT)))
    bounds, marks = [None, *edges, None], None
    for k, (low, high) in enumerate(zip(bounds[:-1], bounds[1:])):
        part = rows if low is None else rows.where(F.col("doc") > low)
        part = part if high is None else part.where(F.col("doc") <= high)
        if repeated:  # equal keys are one document
            part = part.groupBy("doc", "tie").agg(F.first("text").alias("text"))
        found = index.ingest(part, last=k == len(bounds) - 2)
        marks = found if marks is None else marks.union(found)
    for table in ("runs", "more"):
        spark.sql(f"DROP TABLE IF EXISTS {index.name}_{table}")
        remove(spark, f"{index.path}/{table}")
    source = rows.join(marks, ["doc", "tie"], "left") if repeated else index.texts(list(range(index.batches))).join(marks.hint("shuffle_hash"), ["doc", "tie"], "left")
    out = without_marked(source, names, unchanged)
    return out.select("doc_id", *[F.col(f"carried_{c}").alias(c) for c in carry], "n_words", "n_removed", "kept")
