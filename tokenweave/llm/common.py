"""What the operators of this subpackage share: scratch tables, word splitting and 64-bit hashing."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

U64 = np.uint64
#: Odd 64-bit multipliers of the integer mixers.
MIX_A, MIX_B, MIX_C = U64(0x9E3779B97F4A7C15), U64(0xC2B2AE3D27D4EB4F), U64(0x165667B19E3779F9)
WORD_HASH = xxhash.xxh3_64_intdigest


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: the session's spark.checkpoint.dir.

    Where it is unset (tests on one machine) a temporary folder of this process takes its place.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    context = spark.sparkContext
    if not context.getCheckpointDir():
        own = tempfile.mkdtemp(prefix="tokenweave-")
        atexit.register(shutil.rmtree, own, ignore_errors=True)
        context.setCheckpointDir(f"file://{own}")
    return context.getCheckpointDir().rstrip("/")


def remove(spark: SparkSession, path: str) -> None:
    """Delete a path of any file system that Spark knows."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


#: Spark deletes the shuffle files of a finished query where this is set (a session setting).
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


class Scratch:
    """Tables of one run in the shared folder.

    ``save`` cuts a plan by writing it as Parquet and reading it back, so that a lost executor costs at
    most the tasks of the current stage. ``finish`` writes the result and deletes all other tables; the
    result's own table stays for its reader and is the caller's to remove.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.root, self.paths = spark, f"{shared_dir(spark)}/run-{uuid.uuid4().hex}", []
        self.made, self.names = 0, []

    def path(self, name: str) -> str:
        self.made += 1
        self.paths.append(f"{self.root}/{self.made:03d}-{name}")
        return self.paths[-1]

    @contextmanager
    def cleaning(self):
        """The shuffles of what is written inside are deleted: the written table stands for the plan, nobody reads them again."""
        conf = self.spark.conf
        before = conf.get(CLEANUP, "false")
        conf.set(CLEANUP, "true")
        try:
            yield
        finally:
            conf.set(CLEANUP, before)

    def save(self, df: DataFrame, name: str) -> DataFrame:
        path = self.path(name)
        with self.cleaning():
            df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out.scratch_path = path
        return out

    def drop(self, *tables: DataFrame | None) -> None:
        """Delete saved tables that no later plan reads."""
        for table in tables:
            if table is not None and (path := getattr(table, "scratch_path", None)) in self.paths:
                self.paths.remove(path)
                remove(self.spark, path)

    def finish(self, df: DataFrame) -> DataFrame:
        out = self.save(df, "result")
        for name in self.names:  # of the session's catalogue
            self.spark.sql(f"DROP TABLE IF EXISTS {name}")
        for path in self.paths[:-1]:
            remove(self.spark, path)
        self.paths, self.names = self.paths[-1:], []
        return out


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def crc32_mod(column: str, n: int):
    """crc32 of the decimal text of an integer column, modulo n; -1 for null, which so belongs to no fold."""
    return F.coalesce(F.crc32(F.col(column).cast("string").cast("binary")) % n, F.lit(-1))


def words_of(text: str | None, lower: bool = False) -> list[bytes]:
    """Maximal runs of bytes other than 0x20 and 0x09-0x0D; ``lower`` folds A-Z only."""
    if not text:
        return []
    raw = text.encode("utf-8", "surrogatepass")
    return (raw.lower() if lower else raw).split()


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(WORD_HASH, words), U64, len(words))


def mix(x: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit integers (a bijection)."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def gram_hashes(hashes: np.ndarray, n: int) -> np.ndarray:
    """A hash for each run of n consecutive words: a polynomial in an odd base, by doubling, then mixed."""
    if len(hashes) < n:
        return np.empty(0, U64)
    out, done = hashes, 1
    for bit in bin(n)[3:]:
        base = U64(pow(int(MIX_A), done, 1 << 64))
        out, done = out[: len(out) - done] * base + out[done:], 2 * done
        if bit == "1":
            out, done = out[: len(out) - 1] * MIX_A + hashes[done : done + len(out) - 1], done + 1
    return mix(out)


#: Masks of the low bytes of an integer.
_LOW_BYTES = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [(1 << 64) - 1], U64)
#: Words of more bytes than this are hashed one by one.
LONG_WORD = 256


def text_words(texts: pa.Array, lower: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all words of all texts, and where each text's words end (one entry more than texts, from 0).

    Words are runs of bytes other than 0x20 and 0x09-0x0D; ``lower`` folds A-Z. Null texts have none. Each word is read
    in steps of 8 bytes, all words at once.
    """
    texts = pc.fill_null(texts.cast(pa.string()), "")
    offsets = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
    offsets = offsets - offsets[0]
    data = np.zeros(len(raw) + 8, np.uint8)
    data[: len(raw)] = raw | (((raw - np.uint8(0x41)) < 26).view(np.uint8) << np.uint8(5)) if lower else raw
    inside = (raw != 0x20) & ((raw - np.uint8(9)) > 4)
    edge = np.zeros(len(raw) + 1, bool)
    edge[offsets] = True
    edge[1:-1] |= inside[1:] != inside[:-1]
    at = np.flatnonzero(edge)
    begins, sizes = at[:-1], np.diff(at)
    words = inside[begins] if len(begins) else np.empty(0, bool)
    begins, sizes = begins[words], sizes[words]
    ends = np.searchsorted(begins, offsets)
    eights = np.ndarray((len(raw) + 1,), "<u8", data, strides=(1,))
    out = mix(sizes.astype(U64) * MIX_C)
    long = sizes > LONG_WORD
    rows = np.flatnonzero(~long)
    done = 0
    while len(rows):
        left = sizes[rows] - done
        out[rows] = mix((out[rows] ^ (eights[begins[rows] + done] & _LOW_BYTES[np.minimum(left, 8)])) * MIX_B)
        rows, done = rows[left > 8], done + 8
    for k in np.flatnonzero(long).tolist():
        out[k] = WORD_HASH(data[begins[k] : begins[k] + sizes[k]].tobytes())
    return out, ends


def char_grams(words: list[str], sizes: tuple[int, ...], bits: int, edges: tuple[str, str] | str = "<>") -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all character n-grams of words between edge marks, and the words' positions in them (one more than words).

    A gram that holds an edge mark is an affix. All words are hashed at once over their code points.
    """
    marked = [edges[0] + w + edges[1] for w in words]
    points = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), "<u4").astype(U64)
    length = np.fromiter(map(len, marked), np.int64, len(marked))
    owner, last = np.repeat(np.arange(len(marked)), length), np.repeat(np.cumsum(length), length)
    buckets, owners = [], []
    for n in sizes:
        if len(points) >= n:
            value = np.full(len(points) - n + 1, n, U64)
            for k in range(n):
                value = value * MIX_A + points[k : len(points) - n + 1 + k]
            inside = np.arange(len(value)) + n <= last[: len(value)]
            buckets.append((mix(value[inside]) & U64((1 << bits) - 1)).astype(np.int64))
            owners.append(owner[: len(value)][inside])
    if not buckets:
        return np.empty(0, np.int64), np.zeros(len(words) + 1, np.int64)
    buckets, owners = np.concatenate(buckets), np.concatenate(owners)
    order = np.argsort(owners, kind="stable")
    return buckets[order], np.searchsorted(owners[order], np.arange(len(words) + 1))


def sum_runs(rows: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Sums of consecutive runs of rows; ``starts`` has the runs' first rows and, last, the number of rows."""
    out = np.zeros((len(starts) - 1, rows.shape[1]), rows.dtype)
    full = np.flatnonzero(starts[1:] > starts[:-1])
    if len(full):
        out[full] = np.add.reduceat(rows, starts[full], 0)
    return out


class Kept(dict):
    """What a function gives for each key asked for; it starts anew at ``limit`` keys, which changes only the time."""

    def __init__(self, make, limit: int):
        super().__init__()
        self.make, self.limit = make, limit

    def __missing__(self, key):
        if len(self) >= self.limit:
            self.clear()
        self[key] = found = self.make(key)
        return found


def labelled_sample(docs: DataFrame, labels: DataFrame, limit: int, seed: int = 7) -> list[tuple]:
    """``(id, text, label)`` of about ``limit`` labelled documents, chosen by a hash of the id alone, in id order.

    ``labels``: ``doc_id, label``, no nulls; of an id's labels the largest holds. The sample's size is the bound on
    what goes to the driver and on what is broadcast to find the sample's texts.
    """
    labels = labels.where("doc_id IS NOT NULL AND label IS NOT NULL").groupBy("doc_id").agg(F.max("label").alias("label"))
    n = labels.count()
    share = int(min(1.0, limit / max(n, 1)) * 2**31)
    chosen = labels.where(F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(2**31)) < share)
    rows = docs.select("doc_id", "text").where("text IS NOT NULL").join(F.broadcast(chosen.withColumnRenamed("doc_id", "id")), F.col("doc_id") == F.col("id")).select("doc_id", "text", "label")
    table = rows.toArrow()
    return sorted(zip(*(table.column(k).to_pylist() for k in range(3))), key=lambda r: (r[0], r[1]))
