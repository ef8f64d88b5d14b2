"""Byte-level BPE by merge ranks, encoding and decoding.

The vocabulary file's own merges drive the encoder: a priority queue of merge ranks over a doubly linked
list of symbols, which skips entries whose symbols have changed since; decoding concatenates vocabulary
strings and maps their characters back to bytes.
"""

from __future__ import annotations

import heapq
import json
import re
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Kept
from .parts import PartCoder, lists_of, slices

#: Pieces that a merge never crosses: fixed by the format of byte-level BPE files.
PIECES = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")
#: Pieces whose ids a worker keeps; bytes of text encoded, and ids decoded, at once.
CACHED, SLICE, DECODED = 50_000, 6 << 20, 1 << 20


def byte_letters() -> list[str]:
    """The letter that stands for each byte: itself if printable, else the next free one from U+0100."""
    shown = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in shown else chr(next(spare)) for b in range(256)]


class MergeCoder(PartCoder):
    """Encoder for one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        model = data["model"]
        self.ids = model["vocab"]
        self.special = {x["content"]: x["id"] for x in data["added_tokens"]}
        pairs = [x.split(" ") if isinstance(x, str) else x for x in model["merges"]]
        self.left, self.right, self.made = ([self.ids[w] for w in ws] for ws in ([a for a, _ in pairs], [b for _, b in pairs], [a + b for a, b in pairs]))
        #: For each left symbol the ranks of its merges by right symbol.
        self.rank: list[dict[int, int]] = [{} for _ in range(1 + max(self.ids.values()))]
        for k, (a, b) in enumerate(zip(self.left, self.right)):
            self.rank[a][b] = k
        self.first = [self.ids[c] for c in byte_letters()]
        self.cut_special = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.pieces = Kept(lambda piece: array("I", self.merge(piece)).tobytes(), CACHED)
        super().__init__(lambda texts: list(map(self._whole, texts)), lambda parts: lists_of(list(map(self._plain, parts.to_pylist()))), list(self.special))

    def merge(self, piece: str) -> list[int]:
        """Token ids of one piece. A queue entry is a merge rank and, in the low half, the position of its left symbol."""
        symbols = [self.first[b] for b in piece.encode("utf-8", "surrogatepass")]
        n, rank = len(symbols), self.rank
        shift = 12 if n < 4096 else 32  # entries of usual pieces are small integers
        low = (1 << shift) - 1
        queue, a = [], symbols[0]
        for k in range(1, n):
            b = symbols[k]
            if (r := rank[a].get(b)) is not None:
                queue.append(r << shift | k - 1)
            a = b
        if not queue:
            return symbols
        heapq.heapify(queue)
        pop, push, left, right, made = heapq.heappop, heapq.heappush, self.left, self.right, self.made
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        while queue:
            entry = pop(queue)
            r, k = entry >> shift, entry & low
            j = after[k]
            if j >= n or symbols[k] != left[r] or symbols[j] != right[r]:
                continue  # stale: one of the two has been merged since
            symbols[k] = new = made[r]
            symbols[j] = -1
            after[k] = m = after[j]
            ranks = rank[new]
            if m < n:
                before[m] = k
                if (r := ranks.get(symbols[m])) is not None:
                    push(queue, r << shift | k)
            if (i := before[k]) >= 0 and (r := rank[symbols[i]].get(new)) is not None:
                push(queue, r << shift | i)
        return [s for s in symbols if s >= 0]

    def _plain(self, text: str) -> bytes:
        """Ids of a text without special tokens, piece by piece."""
        return b"".join(map(self.pieces.__getitem__, PIECES.findall(text)))

    def _whole(self, text: str) -> bytes:
        if self.cut_special is None or not self.cut_special.search(text):
            return self._plain(text)
        return b"".join(self.special[p].to_bytes(4, "little") if p in self.special else self._plain(p) for p in self.cut_special.split(text))

    def ids_of(self, text: str | None) -> list[int]:
        return np.frombuffer(self._whole(text or ""), "<u4").tolist()


class Decoder:
    """The bytes of each id of a vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        bytes_of = {c: b for b, c in enumerate(byte_letters())}
        words, special = data["model"]["vocab"], {x["content"]: x["id"] for x in data["added_tokens"]}
        self.raw: list[bytes] = [b""] * (1 + max([*words.values(), *special.values()]))
        for word, k in words.items():
            self.raw[k] = bytes(bytes_of[c] for c in word)
        for word, k in special.items():
            self.raw[k] = word.encode()

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids; bytes that aren't UTF-8 become U+FFFD, and ids outside the vocabulary nothing."""
        ids = np.asarray(ids)
        known = ids[(ids >= 0) & (ids < len(self.raw))]
        return b"".join(map(self.raw.__getitem__, known.tolist())).decode("utf-8", "replace")


@lru_cache(maxsize=4)
def coder(path: str) -> MergeCoder:
    """One coder for each file and Python worker."""
    return MergeCoder(path)


@lru_cache(maxsize=4)
def decoder(path: str) -> Decoder:
    return Decoder(path)


def encode(df: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, ids``: the token ids of every text, as array<int>.

    Null and empty texts have no ids; repeated rows come out as often as they come in; other columns are left out.
    ``vocabulary`` is the path of a byte-level BPE file on the executors.
    """
    schema = T.StructType([df.schema[id_col], T.StructField("ids", T.ArrayType(T.IntegerType(), False))])

    def run(batches):
        make = coder(vocabulary)
        for batch in batches:
            for at, n in slices(batch.column(1), SLICE):
                part = batch.slice(at, n)
                yield pa.RecordBatch.from_arrays([part.column(0), make.encode(part.column(1))], [id_col, "ids"])

    return df.select(F.col(id_col), F.col(text_col)).mapInArrow(run, schema)


def decode(df: DataFrame, vocabulary: str, id_col: str = "doc_id", ids_col: str = "ids", keep_ids: bool = False) -> DataFrame:
    """``id, text`` (and ``ids`` on request): the text of every array of ids; null counts as no ids."""
    schema = T.StructType([df.schema[id_col], *([T.StructField("ids", T.ArrayType(T.IntegerType(), False))] * keep_ids), T.StructField("text", T.StringType())])

    def run(batches):
        make = decoder(vocabulary)
        for batch in batches:
            ends = np.cumsum(pc.fill_null(pc.list_value_length(batch.column(1)), 0).to_numpy())
            for rows in np.split(np.arange(len(batch)), np.flatnonzero(np.diff(ends // DECODED)) + 1):
                if len(rows):
                    part = batch.slice(rows[0], len(rows))
                    lists = part.column(1)
                    flat, starts, sizes = np.asarray(lists.values), lists.offsets.to_numpy(), lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
                    texts = [make.decode(flat[a : a + n]) for a, n in zip(starts[:-1], sizes)]
                    yield pa.RecordBatch.from_arrays([part.column(0), *([lists] * keep_ids), pa.array(texts, pa.string())], schema.names)

    return df.select(F.col(id_col), F.col(ids_col).cast("array<int>")).mapInArrow(run, schema)
