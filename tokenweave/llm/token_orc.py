"""Token ids in ORC: stripes with integer run-length encoding, row indexes and Bloom filters on the document id."""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .parts import PartCoder, slices

#: Parts that the library encodes as one text.
JOINED = 20_000
#: Bytes of a stripe, and rows between two entries of its row index.
STRIPE, STRIDE = 16 << 20, 1000


class LibraryCoder(PartCoder):
    """The tokenizers library over each distinct part of the texts.

    Parts go to it together, as the text that they make one after the other. Each begins with the only blank or line end
    in it, so that a token that begins with one begins a part. Parts of letters a-z alone are one piece each: they go to the
    same model through a cut at blanks, which is quicker than the pattern for all pieces.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer, pre_tokenizers

        self.library = Tokenizer.from_file(path)
        self.library.no_padding()
        self.library.no_truncation()
        self.by_blanks = Tokenizer(self.library.model)
        self.by_blanks.pre_tokenizer = pre_tokenizers.CharDelimiterSplit(" ")
        self.blank, line = (self.library.encode(x, add_special_tokens=False).tokens[0] for x in " \n")
        vocabulary = self.library.get_vocab()
        self.begins = np.zeros(max(vocabulary.values()) + 1, bool)
        self.begins[[k for word, k in vocabulary.items() if word[0] in (self.blank, line)]] = True
        super().__init__(self._whole, self._parts, [x.content for x in self.library.get_added_tokens_decoder().values()])

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [np.array(x.ids, "<u4").tobytes() for x in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def _parts(self, parts: pa.StringArray) -> pa.ListArray:
        plain = pc.match_substring_regex(parts, r"\A [A-Za-z]+\z")
        letters, rest = parts.filter(plain), parts.filter(pc.invert(plain))
        letters = pc.replace_substring(letters, " ", f" {self.blank}")
        found = pa.concat_arrays([self._joined(letters, self.by_blanks), self._joined(rest, self.library)])
        plain = plain.to_numpy(zero_copy_only=False)
        return found.take(pa.array(np.where(plain, np.cumsum(plain) - 1, len(letters) + np.cumsum(~plain) - 1)))

    def _joined(self, parts: pa.StringArray, library) -> pa.ListArray:
        sizes, flat = [np.zeros(1, np.int64)], [np.empty(0, np.int32)]
        for a in range(0, len(parts), JOINED):
            some = parts[a : a + JOINED]
            text = pc.binary_join(pa.ListArray.from_arrays([0, len(some)], some), "")[0].as_py()
            ids = np.array(library.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.int32)
            starts = np.flatnonzero(self.begins[ids])
            if len(starts) != len(some):
                raise ValueError("this vocabulary's pieces don't begin at blanks")
            sizes.append(np.diff(starts, append=len(ids)))
            flat.append(ids)
        return pa.ListArray.from_arrays(pa.array(np.cumsum(np.concatenate(sizes)).astype(np.int32)), pa.array(np.concatenate(flat)))


@lru_cache(maxsize=4)
def library_coder(path: str) -> LibraryCoder:
    return LibraryCoder(path)


def write_tokens(df: DataFrame, path: str, tokenizer: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", partitions: int | None = None, compression: str = "zstd") -> None:
    """Encode every text and write ``doc_id, file_no, file_start, n_ids, ids`` as ORC in ascending order of the id.

    Files follow each other in id order (null ids first); ``file_start`` counts the ids of a file before the
    document and ``file_no`` numbers the files, so that any stripe can be placed without reading another one.
    Null and empty texts hold the end id alone. Documents with equal ids stay side by side, in no set order.
    Texts move once, by ranges of the id (equal ids in one range); the range bounds are sampled from the ids' scan.
    """
    rows = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    ranged = (rows.repartitionByRange(partitions, "doc_id") if partitions else rows.repartitionByRange("doc_id")).sortWithinPartitions("doc_id", F.xxhash64("text"))
    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("file_no", T.IntegerType()), T.StructField("file_start", T.LongType()), T.StructField("n_ids", T.IntegerType()), T.StructField("ids", T.ArrayType(T.IntegerType(), False))])

    def run(batches):
        from pyspark import TaskContext

        make, number, before = library_coder(tokenizer), TaskContext.get().partitionId(), 0
        for batch in batches:
            for at, n in slices(batch.column(1)):
                part = batch.slice(at, n)
                ids = make.encode(part.column(1), end_id)
                ends = ids.offsets.to_numpy().astype(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.full(len(part), number, np.int32)), pa.array(before + ends[:-1]), pa.array(np.diff(ends).astype(np.int32)), ids], schema.names)
                before += int(ends[-1])

    (ranged.mapInArrow(run, schema).write.option("orc.stripe.size", STRIPE).option("orc.row.index.stride", STRIDE).option("orc.create.index", "true")
     .option("orc.bloom.filter.columns", "doc_id").option("orc.bloom.filter.fpp", "0.01").option("orc.compress", compression.upper()).option("compression", compression).orc(path))


TOKEN_SCHEMA = "doc_id long, file_no int, file_start long, n_ids int, ids array<int>"


def read_tokens(spark: SparkSession, path: str, doc_ids: list[int] | None = None) -> DataFrame:
    """The rows of ``write_tokens``; given ids are pushed down, where stripes and row groups without them are skipped."""
    table = spark.read.schema(TOKEN_SCHEMA).orc(path)
    return table if doc_ids is None else table.filter(F.col("doc_id").isin(doc_ids))


def token_digests(spark: SparkSession, path: str) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` read from the files.

    One row a file (its number of ids) goes to the driver for the files' first positions; that many rows is the
    number of files, not of documents.
    """
    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("file_no", T.IntegerType()), T.StructField("file_start", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("ids_crc32", T.LongType())])

    def run(batches):
        for batch in batches:
            lists = batch.column(3)
            flat, at = np.ascontiguousarray(np.asarray(lists.values), "<i4"), lists.offsets.to_numpy()
            raw = memoryview(flat).cast("B")
            sums = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(np.diff(at).astype(np.int64)), pa.array(sums, pa.int64())], schema.names)

    table = read_tokens(spark, path)
    totals = sorted((r[0], r[1]) for r in table.groupBy("file_no").agg(F.max(F.col("file_start") + F.col("n_ids"))).collect())
    starts, before = [], 0
    for number, n in totals:
        starts.append((number, before))
        before += n
    firsts = spark.createDataFrame(starts, "file_no int, first long")
    rows = table.drop("n_ids").mapInArrow(run, schema)
    return rows.join(F.broadcast(firsts), "file_no").select("doc_id", (F.col("first") + F.col("file_start")).alias("start"), "n_tokens", "ids_crc32")
