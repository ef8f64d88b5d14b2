"""Links of one list of long texts: the same pairs and scores as ``batch.self_link``, with shuffles a fraction as large.

Arrow tasks move packed blocks in place of rows. A phrase is known by 80 bits of a digest and its bucket's number; one
that stands in more than ``k`` texts of a slice leaves it as a mark without ids. Pairs meet the texts' character counts
in blocks of ids, so that no bag travels with a pair.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import OTHER
from ..functions.bags import ALPHABET

#: Bytes of text packed at once, words of a bucket, texts of a block at a block alone (blocks grow with the root of the
#: texts), pairs scored at once, characters outside ASCII that get a column of a block (the others are looked up).
SLICE, BUCKET, BLOCK, PAIRS, WIDE = 8 << 20, 3_000_000, 6400, 1 << 18, 128
POSTED, OVER, NAMELESS = 0, 1, 2
ODD, SPREAD = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
PLACES = np.full(256, len(ALPHABET), np.int64)
PLACES[np.frombuffer(ALPHABET.encode(), np.uint8)] = np.arange(len(ALPHABET))


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays as compressed bytes, first bytes first: small numbers leave long runs of zeros."""
    return pa.compress(b"".join(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.itemsize).T.tobytes() for x in arrays if len(x)), codec="zstd", asbytes=True)


def unpack(blob: bytes, *kinds: tuple[type, int]) -> list[np.ndarray]:
    sizes = [np.dtype(t).itemsize * n for t, n in kinds]
    data = np.frombuffer(pa.decompress(blob, sum(sizes), codec="zstd", asbytes=True), np.uint8) if sum(sizes) else np.zeros(0, np.uint8)
    parts = np.split(data, np.cumsum(sizes)[:-1])
    return [np.ascontiguousarray(p.reshape(np.dtype(t).itemsize, n).T).reshape(-1).view(t) for p, (t, n) in zip(parts, kinds)]


def _starts(sorted_keys: np.ndarray) -> np.ndarray:
    """Where the runs of equal keys begin, and the end."""
    return np.append(np.flatnonzero(np.append(True, sorted_keys[1:] != sorted_keys[:-1])), len(sorted_keys)) if len(sorted_keys) else np.zeros(1, np.int64)


def _block_of(ids: np.ndarray, blocks: int) -> np.ndarray:
    x = (ids.view(np.uint64) + ODD) * SPREAD
    return ((x ^ (x >> np.uint64(32))) * ODD >> np.uint64(33)).astype(np.int64) % blocks


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows in tables of about SLICE bytes of text."""
    held, n = [], 0
    for batch in batches:
        size = np.cumsum(pc.binary_length(batch.column("text")).to_numpy(zero_copy_only=False).astype(np.int64))
        begin = 0
        while begin < batch.num_rows:
            before = int(size[begin - 1]) if begin else 0
            end = max(begin + 1, int(np.searchsorted(size, before + SLICE - n, "right")))
            held.append(batch.slice(begin, end - begin))
            n += int(size[end - 1]) - before
            begin = end
            if n >= SLICE or begin < batch.num_rows:
                yield pa.Table.from_batches(held).combine_chunks()
                held, n = [], 0
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _column(table: pa.Table, name: str) -> pa.Array:
    column = table.column(name)
    return column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column


def _posted(table: pa.Table, k: int, buckets: int) -> Iterator[dict]:
    """Rows for the buckets of a slice: its texts' distinct phrases by text, those over the cut, and those of texts without an id."""
    lists, ids = pc.split_pattern(_column(table, "text").cast(pa.large_string()), " "), _column(table, "id")
    words = pc.list_flatten(lists).dictionary_encode()
    codes, size = words.indices.to_numpy(zero_copy_only=False).astype(np.int64), len(words.dictionary)
    row = np.repeat(np.arange(len(lists)), pc.list_value_length(lists).to_numpy(zero_copy_only=False))
    both = row[:-1] == row[1:]
    known, who = np.unique(ids.fill_null(0).to_numpy(zero_copy_only=False), return_inverse=True)
    nameless = len(known)
    who = np.where(ids.is_null().to_numpy(zero_copy_only=False), nameless, who)[row[:-1][both]]
    phrase, number = np.unique(codes[:-1][both] * size + codes[1:][both], return_inverse=True)
    key = np.unique(number * (nameless + 1) + who)
    number, who = np.divmod(key, nameless + 1)
    if not len(phrase):
        return
    digests = np.frombuffer(b"".join(blake2b(w.encode("utf-8", "surrogatepass"), digest_size=16).digest() for w in words.dictionary.to_pylist()), "<u8").reshape(-1, 2)
    first, second = np.divmod(phrase, size)
    high, low = (digests[first] * ODD + digests[second]).T
    bucket, low = (low & np.uint64(buckets - 1)).astype(np.int64), (low >> np.uint64(48)).astype(np.uint16)
    over = np.diff(_starts(number)) > k
    for kind, of, texts in ((OVER, np.flatnonzero(over), None), (NAMELESS, number[(who == nameless) & ~over[number]], None), (POSTED, number, who)):
        if texts is not None:
            keep = (who < nameless) & ~over[number]
            of, texts = number[keep], who[keep]
        order = np.argsort(bucket[of] if texts is None else bucket[of] * nameless + texts, kind="stable")
        of = of[order]
        at = _starts(bucket[of])
        for begin, end in zip(at[:-1], at[1:]):
            part, held, m = of[begin:end], b"", 0
            if texts is not None:
                mine = texts[order[begin:end]]
                runs = _starts(mine)
                m, held = len(runs) - 1, pack(np.diff(known[mine[runs[:-1]]], prepend=0), np.diff(runs).astype(np.uint32))
            yield {"bucket": int(bucket[part[0]]), "kind": kind, "m": m, "ids": held, "n": end - begin, "hashes": high[part].tobytes() + low[part].tobytes()}


def _paired(table: pa.Table, k: int, blocks: int) -> Iterator[dict]:
    """The distinct pairs of a bucket's phrases that stand in no more than k texts, a row for every two blocks of ids."""
    highs, lows, names, kinds = [], [], [], []
    for r in table.to_pylist():
        n = r["n"]
        highs.append(np.frombuffer(r["hashes"], np.uint64, n))
        lows.append(np.frombuffer(r["hashes"], np.uint16, n, 8 * n))
        ids, counts = unpack(r["ids"], (np.int64, r["m"]), (np.uint32, r["m"])) if r["kind"] == POSTED else (np.zeros(1, np.int64), np.array([n]))
        names.append(np.repeat(np.cumsum(ids) if r["kind"] == POSTED else ids, counts))
        kinds.append(np.full(n, r["kind"], np.int8))
    high, low, names, kinds = map(np.concatenate, (highs, lows, names, kinds))
    order = np.argsort(high)
    at = _starts(high[order])
    size = np.diff(at)
    order, group = order[np.repeat(size > 1, size)], np.repeat(np.arange(np.count_nonzero(size > 1)), size[size > 1])  # what stands alone makes no pair
    if not len(order):
        return
    names, kinds = names[order], kinds[order]
    _, number = np.unique(group << 16 | low[order].astype(np.int64), return_inverse=True)
    known, who = np.unique(names, return_inverse=True)
    m = len(known)
    key = np.unique(number * (m + 2) + np.where(kinds == POSTED, who, m - 1 + kinds.astype(np.int64)))
    number, who = np.divmod(key, m + 2)
    at = _starts(number)
    df = np.add.reduceat(np.where(who == m - 1 + OVER, k + 1, 1), at[:-1])
    keep = np.repeat(df <= k, np.diff(at)) & (who < m)
    number, who = number[keep], who[keep]
    at = _starts(number)
    size, found = np.diff(at), [np.zeros(0, np.int64)]
    for n in np.unique(size[size > 1]).tolist():
        i, j = np.triu_indices(n, 1)
        begins = at[:-1][size == n]
        step = max(1, 4 * PAIRS // len(i))
        for b in range(0, len(begins), step):
            held = who[begins[b : b + step, None] + np.arange(n)]
            found.append(np.unique(held[:, i] * m + held[:, j]))
    pairs = np.unique(np.concatenate(found))
    x, y = np.divmod(pairs, m)
    block = _block_of(known, blocks)
    lo, hi = np.minimum(block[x], block[y]), np.maximum(block[x], block[y])
    order = np.argsort(lo * blocks + hi, kind="stable")
    at = _starts((lo * blocks + hi)[order])
    for begin, end in zip(at[:-1], at[1:]):
        part = order[begin:end]
        ids, both = np.unique(np.concatenate([x[part], y[part]]), return_inverse=True)
        n = end - begin
        yield {"lo": int(lo[part[0]]), "hi": int(hi[part[0]]), "m": len(ids), "n": n, "pairs": pack(np.diff(known[ids], prepend=0), np.bincount(both[:n], minlength=len(ids)).astype(np.uint32), both[n:].astype(np.uint32))}


def _bags(table: pa.Table, blocks: int) -> Iterator[dict]:
    """Character counts of a slice's texts, a row for each block of ids: letters and digits of ASCII in columns, the others as triples."""
    texts, ids = _column(table, "text"), _column(table, "id").to_numpy(zero_copy_only=False)
    length = pc.binary_length(texts).to_numpy(zero_copy_only=False)
    data = np.frombuffer("".join(texts.to_pylist()).encode("utf-8", "surrogatepass"), np.uint8)
    wide = len(ALPHABET) + 1
    key = np.repeat(np.arange(len(texts)) * wide, length)
    key += PLACES[data]
    counts = np.bincount(key, minlength=len(texts) * wide).reshape(-1, wide)[:, :-1].astype(np.uint32)
    del key
    beyond = np.flatnonzero(length != pc.utf8_length(texts).to_numpy(zero_copy_only=False))
    strings = texts.take(pa.array(beyond))
    points = np.frombuffer("".join(strings.to_pylist()).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64)
    key = np.repeat(beyond, pc.utf8_length(strings).to_numpy(zero_copy_only=False)) << 21 | points
    key, times = np.unique(key[points > 127], return_counts=True)
    row, block = key >> 21, _block_of(ids, blocks)
    order = np.lexsort((ids, block))
    at = _starts(block[order])
    for begin, end in zip(at[:-1], at[1:]):
        part = order[begin:end]
        lows, highs = np.searchsorted(row, part), np.searchsorted(row, part, "right")
        more = np.repeat(highs - np.cumsum(highs - lows), highs - lows) + np.arange(int((highs - lows).sum()))
        yield {
            "block": int(block[part[0]]), "n": len(part), "m": len(more),
            "bags": pack(np.diff(ids[part], prepend=0), (highs - lows).astype(np.uint32), counts[part].T.reshape(-1), (key[more] & 0x1FFFFF).astype(np.uint32), times[more].astype(np.uint32)),
        }


def _scored(pairs: pa.Table, bags: pa.Table, tau: float | None) -> pa.Table:
    """``id_1, id_2, score`` of two blocks' pairs, each once. The rows of one id are one text."""
    wide, names, counts, rows, points, times, n = len(ALPHABET), [], [], [], [], [], 0
    for r in bags.to_pylist():
        ids, held, c, p, t = unpack(r["bags"], (np.int64, r["n"]), (np.uint32, r["n"]), (np.uint32, wide * r["n"]), (np.uint32, r["m"]), (np.uint32, r["m"]))
        names.append(np.cumsum(ids))
        counts.append(c.reshape(wide, -1))
        rows.append(np.repeat(np.arange(n, n + r["n"]), held))
        points.append(p.astype(np.int64))
        times.append(t)
        n += r["n"]
    known, at = np.unique(np.concatenate(names), return_inverse=True)
    columns = np.zeros((wide, len(known)), np.int32)
    np.add.at(columns, (slice(None), at), np.concatenate(counts, 1))
    key, same = np.unique(np.concatenate(points) * len(known) + at[np.concatenate(rows)], return_inverse=True)
    times = np.bincount(same, np.concatenate(times), len(key)).astype(np.int32)
    size = columns.sum(0, dtype=np.int64) + np.bincount(key % len(known), times, len(known)).astype(np.int64)
    starts = _starts(key // len(known))
    dense, rest = list(columns), np.ones(len(key), bool)
    for c in np.argsort(-np.diff(starts), kind="stable")[:WIDE].tolist():
        of = slice(starts[c], starts[c + 1])
        column = np.zeros(len(known), np.int32)
        column[key[of] % len(known)] = times[of]
        dense.append(column)
        rest[of] = False
    point, row = np.divmod(key[rest], len(known))
    times = times[rest]
    order = np.argsort(row, kind="stable")  # of each text
    own = np.searchsorted(row[order], np.arange(len(known) + 1))
    seen = []
    for r in pairs.to_pylist():
        ids, held, other = unpack(r["pairs"], (np.int64, r["m"]), (np.uint32, r["m"]), (np.uint32, r["n"]))
        place = np.searchsorted(known, np.cumsum(ids))
        seen.append(np.repeat(place, held) * len(known) + place[other])
    seen, out = np.unique(np.concatenate(seen)), []
    for begin in range(0, len(seen), PAIRS):
        x, y = np.divmod(seen[begin : begin + PAIRS], len(known))
        shared = np.zeros(len(x), np.int64)
        for column in dense:
            shared += np.minimum(column[x], column[y])
        held = own[x + 1] - own[x]
        if len(order) and held.any():
            mine = order[np.repeat(own[x + 1] - np.cumsum(held), held) + np.arange(int(held.sum()))]
            pair = np.repeat(np.arange(len(x)), held)
            want, have = point[mine] * len(known) + y[pair], point * len(known) + row
            there = np.minimum(np.searchsorted(have, want), len(have) - 1)
            shared += np.bincount(pair, np.where(have[there] == want, np.minimum(times[there], times[mine]), 0), len(x)).astype(np.int64)
        score = 2.0 * shared / (size[x] + size[y])
        over = np.ones(len(x), bool) if tau is None else score > tau
        out.append(pa.table({"id_1": known[x][over], "id_2": known[y][over], "score": score[over]}))
    return pa.concat_tables(out)


SCORED = pa.schema([("id_1", pa.int64()), ("id_2", pa.int64()), ("score", pa.float64())])
POSTING = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("m", pa.int32()), ("n", pa.int32()), ("ids", pa.binary()), ("hashes", pa.binary())])
PAIR = pa.schema([("lo", pa.int32()), ("hi", pa.int32()), ("m", pa.int32()), ("n", pa.int32()), ("pairs", pa.binary())])
BAG = pa.schema([("block", pa.int32()), ("n", pa.int32()), ("m", pa.int32()), ("bags", pa.binary())])


def _spark(schema: pa.Schema) -> str:
    return ", ".join(f"{f.name} {({pa.int32(): 'int', pa.int64(): 'long', pa.float64(): 'double', pa.binary(): 'binary'})[f.type]}" for f in schema)


def self_link_packed(addresses: DataFrame, k: int = 100, tau: float | None = None, alphabet: str = "unicode") -> DataFrame:
    """``id_1 < id_2, score`` of one list ``id, address``: pairs that share a two-word phrase in no more than ``k`` of its texts,
    scored by ``pooled`` over their characters. Rows of one id count as one text; rows without an id count for ``k`` as one more."""
    texts = addresses.select(F.col("id").cast("long").alias("id"), F.trim(F.regexp_replace(F.lower("address"), OTHER[alphabet] + "+", " ")).alias("text")).where("text <> ''")
    n, chars = addresses.agg(F.count("address"), F.coalesce(F.sum(F.length("address")), F.lit(0))).first()
    buckets = 1 << min(14, max(3, math.ceil(math.log2(chars / 7 / BUCKET + 1))))
    blocks = max(1, math.ceil(math.sqrt(n / BLOCK)))

    def posted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _slices(batches):
            yield from pa.Table.from_pylist(list(_posted(table, k, buckets)), POSTING).to_batches()

    def bagged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _slices(batches):
            yield from pa.Table.from_pylist(list(_bags(table, blocks)), BAG).to_batches()

    def paired(table: pa.Table) -> pa.Table:
        return pa.Table.from_pylist(list(_paired(table, k, blocks)), PAIR)

    def scored(pairs: pa.Table, bags: pa.Table) -> pa.Table:
        return _scored(pairs, bags, tau) if pairs.num_rows and bags.num_rows else SCORED.empty_table()

    groups = blocks * (blocks + 1) // 2
    dealt = lambda df, parts, *by: df.repartition(min(2000, 2 * parts), *by)  # noqa: E731  packed rows are few and costly: small partitions must not be merged
    postings = dealt(texts.mapInArrow(posted, _spark(POSTING)), buckets, "bucket")
    pairs = dealt(postings.groupBy("bucket").applyInArrow(paired, _spark(PAIR)), groups, "lo", "hi")
    met = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    bags = texts.where("id IS NOT NULL").mapInArrow(bagged, _spark(BAG)).withColumn("other", met)
    bags = dealt(bags.select(F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "n", "m", "bags"), groups, "lo", "hi")
    return pairs.groupBy("lo", "hi").cogroup(bags.groupBy("lo", "hi")).applyInArrow(scored, _spark(SCORED))
