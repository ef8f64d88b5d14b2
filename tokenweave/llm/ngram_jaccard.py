"""Exact n-gram Jaccard self-join by a grouped prefix join.

Documents become sets of hashed word shingles. Equal sets fall together first. Each distinct set is ordered by how
common its shingles are (rarest first, from counts over all documents) and keeps a prefix so long that two sets
over the threshold must share a prefix element. Sets with the same size and prefix form a group; the join runs on
groups, filters group pairs by size and by the overlap that their shared prefix still allows, then expands them to
members and verifies each pair on the whole sets.

A shingle that is in up to ``light`` prefixes proposes all its pairs. One that is in more (a large family of near
copies) is worked through in blocks inside Arrow tasks: a first pass proposes for each group its closest partner in
a block, which after verification joins most of the family; the second pass takes all pairs of blocks, but only
those pairs of groups that aren't in one component yet, and verifies them in their blocks. All pairs between
different components are verified, so the components are exact, while a family's inner pairs aren't all spelt out.
Groups of more than ``light`` sets are worked through in the same two passes over blocks of their members.

Sets are compared by 64-bit shingle hashes, and equal sets by 128 bits over these: that is the error that is accepted.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import MIX_C, Scratch, gram_hashes, mix, text_words
from .graph import components
from .parts import slices

#: Counters of the frequency sketch (a bound on what is broadcast: 8 bytes each), and counters in a message.
COUNTERS, CHUNK = 1 << 18, 1 << 12
#: Needed document ids up to this number are broadcast (8 bytes each), more are joined by a shuffle.
BROADCAST_IDS = 1_000_000
#: Bytes of text read at once; columns of a comparison of blocks.
SLICE, COLUMNS = 1 << 20, 4096


def shingle_sets(texts: pa.Array, width: int) -> list[np.ndarray]:
    """Each text's sorted distinct 64-bit shingle hashes; a shorter text is one shingle; without words the set is empty."""
    hashes, ends = text_words(texts, lower=True)
    grams, ends = gram_hashes(hashes, width), ends.tolist()
    out = []
    for a, b in zip(ends[:-1], ends[1:]):
        if b - a >= width:
            out.append(np.unique(grams[a : b - width + 1]))
        else:
            out.append(mix(gram_hashes(hashes[a:b], b - a) + MIX_C * np.uint64(b - a)) if b > a else hashes[:0])
    return out


def arrays(column) -> list[np.ndarray]:
    """The lists of an Arrow column as arrays, without a copy."""
    lists = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat, ends = np.asarray(lists.values), lists.offsets.to_numpy().tolist()
    return [flat[a:b] for a, b in zip(ends[:-1], ends[1:])]


def prefix_length(n: int, num: int, den: int) -> int:
    """How many of the first of n ordered elements must include a shared one at a similarity of num/den or more."""
    return n - -(-num * n // den) + 1


def shingle_counts(texts: DataFrame, width: int) -> np.ndarray:
    """A sketch of document frequencies over all documents: one counter for each value of a shingle's low bits.

    It only orders shingles, so that shared counters cost time, never results.
    """

    def count(batches):
        from pyspark import TaskContext

        counts = np.zeros(COUNTERS, np.int64)
        for batch in batches:
            for at, m in slices(batch.column(0), SLICE):
                sets = shingle_sets(batch.column(0).slice(at, m), width)
                counts += np.bincount((np.concatenate(sets) & np.uint64(COUNTERS - 1)).astype(np.int64), minlength=COUNTERS)
        small = counts.astype("<u4").reshape(-1, CHUNK)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(small), dtype=np.int32)), pa.array([TaskContext.get().partitionId() % 64] * len(small), pa.int32()), pa.array([x.astype("<i8").tobytes() for x in small], pa.binary())], ["chunk", "salt", "counts"])

    def add(table: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x, "<i8") for x in table.column("counts").to_pylist())
        return pa.table({"chunk": table.column("chunk")[:1], "salt": table.column("salt")[:1], "counts": pa.array([total.tobytes()], pa.binary())})

    schema = "chunk int, salt int, counts binary"
    parts = texts.mapInArrow(count, schema).groupBy("chunk", "salt").applyInArrow(add, schema).groupBy("chunk").applyInArrow(add, schema)
    total = np.zeros((COUNTERS // CHUNK, CHUNK), np.int64)
    for row in parts.collect():  # a fixed number of rows
        total[row.chunk] = np.frombuffer(row.counts, "<i8")
    return total.reshape(-1)


def _prefixes(docs: DataFrame, counts: np.ndarray, width: int, num: int, den: int) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(counts)
    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("n", T.LongType()), T.StructField("sig", T.BinaryType()), T.StructField("gid", T.BinaryType()), T.StructField("prefix", T.ArrayType(T.LongType()))])

    def run(batches):
        counts = shared.value
        for batch in batches:
            for at, m in slices(batch.column(1), SLICE):
                part = batch.slice(at, m)
                ns, sigs, gids, prefixes = [], [], [], []
                for s in shingle_sets(part.column(1), width):
                    order = np.lexsort((s, counts[(s & np.uint64(COUNTERS - 1)).astype(np.int64)]))[: prefix_length(len(s), num, den)] if len(s) else []
                    prefix = s[order] if len(s) else s
                    ns.append(len(s))
                    sigs.append(xxhash.xxh3_128_digest(s.tobytes()))
                    gids.append(xxhash.xxh3_128_digest(prefix.tobytes() + len(s).to_bytes(8, "little")))
                    prefixes.append(prefix.view(np.int64))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ns, pa.int64()), pa.array(sigs, pa.binary()), pa.array(gids, pa.binary()), pa.array(prefixes, pa.list_(pa.int64()))], schema.names)

    return docs.mapInArrow(run, schema)


def _sets(docs: DataFrame, width: int) -> DataFrame:
    def run(batches):
        for batch in batches:
            for at, m in slices(batch.column(0), SLICE):
                sets = shingle_sets(batch.column(0).slice(at, m), width)
                yield pa.RecordBatch.from_arrays([pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary()), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], ["sig", "elements"])

    return docs.mapInArrow(run, "sig binary, elements array<long>")


def _overlaps(rows: dict, others: dict | None, num: int, den: int) -> np.ndarray:
    """For each pair of groups how many prefix elements they share; -1 where sizes or the best possible overlap rule it out."""
    both = rows["prefix"] + (others["prefix"] if others else [])
    _, column, count = np.unique(np.concatenate(both), return_inverse=True, return_counts=True)
    owner = np.repeat(np.arange(len(both)), [len(x) for x in both])
    used = count > 1  # others can't be shared
    number = np.cumsum(used) - 1
    owner, column = owner[used[column]], number[column[used[column]]]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    m = len(rows["prefix"])
    shared = np.zeros((m, len(both) - m if others else m), np.int64)
    for a in range(0, int(used.sum()), COLUMNS):  # some columns at a time: the rows' marks are a bounded matrix
        low, high = np.searchsorted(column, [a, a + COLUMNS])
        marks = np.zeros((len(both), COLUMNS), np.float32)
        marks[owner[low:high], column[low:high] - a] = 1
        shared += (marks[:m] @ (marks[m:] if others else marks).T).astype(np.int64)
    other = others or rows
    n, m = np.array(rows["n"])[:, None], np.array(other["n"])[None, :]
    rest, rest2 = n - np.array([len(x) for x in rows["prefix"]])[:, None], m - np.array([len(x) for x in other["prefix"]])[None, :]
    possible = (den * np.minimum(n, m) >= num * np.maximum(n, m)) & ((den + num) * (shared + np.maximum(rest, rest2)) >= num * (n + m))
    return np.where(possible & (shared > 0), shared, -1)


def jaccard_components(docs: DataFrame, width: int = 3, num: int = 90, den: int = 100, id_col: str = "doc_id", text_col: str = "text", light: int = 64, block: int = 256, scratch: Scratch | None = None) -> DataFrame:
    """``doc_id, n_shingles, component_id`` for each row: the size of its shingle set and the smallest id it is linked to.

    Words are runs of bytes other than blanks and 0x09-0x0D, with A-Z in lower case; rows whose sets have
    ``den * intersection >= num * union`` are linked. Null, empty and blank texts have an empty set and are linked
    with nothing, each being its own component. Rows that repeat an id are judged one by one and share the smallest
    id of their links. A null id counts as larger than any other. Other columns are left out.
    """
    spark = docs.sparkSession
    scratch = scratch or Scratch(spark)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    counts = shingle_counts(rows.select("text"), width)
    table = scratch.save(_prefixes(rows, counts, width, num, den), "prefixes")

    distinct = table.where("n > 0").groupBy("sig").agg(F.min("doc_id").alias("first_id"), F.first("n").alias("n"), F.first("gid").alias("gid"))
    members = scratch.save(distinct, "members")
    groups = scratch.save(table.where("n > 0").dropDuplicates(["gid"]).select("gid", "n", "prefix"), "groups")
    postings = groups.select("gid", "n", F.size("prefix").alias("p"), F.explode("prefix").alias("token"))
    common = postings.groupBy("token").agg(F.count("*").alias("df")).where("df > 1")
    postings = scratch.save(postings.join(common, "token"), "postings")
    heavy = postings.where(F.col("df") > light)
    weight = heavy.groupBy("gid").agg(F.count("*").alias("h"), F.sort_array(F.collect_list("token")).alias("hot"))  # up to a prefix's length

    # light shingles: all their pairs, summed up by pair
    side = postings.where(F.col("df") <= light).join(weight.select("gid", "h"), "gid", "left").select("token", "gid", "n", (F.col("n") - F.col("p")).alias("rest"), F.coalesce("h", F.lit(0)).alias("h"))
    a, b = side.alias("a"), side.alias("b")
    near = f"a.gid < b.gid AND {den} * least(a.n, b.n) >= {num} * greatest(a.n, b.n)"
    shared = a.join(b, (F.col("a.token") == F.col("b.token")) & F.expr(near)).groupBy(F.col("a.gid").alias("ga"), F.col("b.gid").alias("gb")).agg(
        F.count("*").alias("c"), F.first("a.n").alias("na"), F.first("b.n").alias("nb"), F.first(F.greatest("a.rest", "b.rest")).alias("rest"), F.first(F.least("a.h", "b.h")).alias("h"))
    possible = shared.where(f"{den + num} * (c + h + rest) >= {num} * (na + nb)").select("ga", "gb")

    # heavy shingles, first pass: the closest earlier partner in a block
    full = heavy.select("token", "gid", "df").join(groups, "gid").join(weight, "gid").select("token", "gid", "df", "n", "prefix", "hot")
    pair = "ga binary, gb binary"

    def closest(t: pa.Table) -> pa.Table:
        d = {"n": t.column("n").to_pylist(), "prefix": arrays(t.column("prefix"))}
        gids, out = t.column("gid").to_pylist(), ([], [])
        if len(gids) > 1:
            best = np.tril(_overlaps(d, None, num, den) + 1, -1)
            for i, j in enumerate(best.argmax(1).tolist()):
                if best[i, j] > 0:
                    x, y = sorted((gids[i], gids[j]))
                    out[0].append(x)
                    out[1].append(y)
        return pa.table({"ga": pa.array(out[0], pa.binary()), "gb": pa.array(out[1], pa.binary())})

    blocked = full.withColumn("block", F.pmod(F.xxhash64("gid"), F.ceil(F.col("df") / light)))
    first = blocked.groupBy("token", "block").applyInArrow(closest, pair)

    # members of one group share the whole prefix: the group stands for a shingle that each of them holds
    crowd = members.groupBy("gid").agg(F.count("*").alias("m")).where("m > 1")
    crowds = members.join(crowd.where(F.col("m") > light), "gid").select("gid", "sig", "m")
    inner = members.join(crowd.where(F.col("m") <= light), "gid").select("gid", "sig")
    i, j = inner.alias("i"), inner.alias("j")
    within = i.join(j, (F.col("i.gid") == F.col("j.gid")) & (F.col("i.sig") < F.col("j.sig"))).select(F.col("i.sig").alias("a"), F.col("j.sig").alias("b"))

    def expand(group_pairs: DataFrame) -> DataFrame:
        left, right = members.select(F.col("gid").alias("ga"), F.col("sig").alias("a")), members.select(F.col("gid").alias("gb"), F.col("sig").alias("b"))
        return group_pairs.join(left, "ga").join(right, "gb").select("a", "b")

    candidates = scratch.save(expand(possible.union(first).distinct()).union(within), "candidates")

    # whole sets of the members that any pair may need
    needed = candidates.select(F.col("a").alias("sig")).union(candidates.select("b")).union(crowds.select("sig")).union(members.join(heavy.select("gid").distinct(), "gid", "left_semi").select("sig")).distinct()
    needed = scratch.save(members.join(needed, "sig", "left_semi").select("sig", "first_id"), "needed")
    ids = needed.select(F.col("first_id").alias("doc_id"))
    ids = F.broadcast(ids) if needed.count() <= BROADCAST_IDS else ids
    texts = rows.join(ids, rows.doc_id.eqNullSafe(ids.doc_id), "left_semi").select("text")
    sets = scratch.save(_sets(texts, width).dropDuplicates(["sig"]), "sets")

    def verify(pairs: DataFrame) -> DataFrame:
        left, right = sets.select(F.col("sig").alias("a"), F.col("elements").alias("x")), sets.select(F.col("sig").alias("b"), F.col("elements").alias("y"))
        both = pairs.join(left, "a").join(right, "b").select("a", "b", F.size("x").alias("nx"), F.size("y").alias("ny"), F.size(F.array_intersect("x", "y")).alias("c"))
        return both.where(f"{den} * c >= {num} * (nx + ny - c)").select("a", "b")

    def linked(sigs: list[bytes], held: list[np.ndarray], parts: list, pairs) -> pa.Table:
        """Links of some pairs of sets, verified whole; those that earlier links, or their parts, have joined are left out."""
        root: dict = {}

        def find(s):
            while root.setdefault(s, s) != s:
                root[s] = s = root[root[s]]
            return s

        out = ([], [])
        for x, y in pairs:
            if (r := find(parts[x])) != (q := find(parts[y])):
                one, two = held[x], held[y]
                c = len(np.intersect1d(one, two, assume_unique=True)) if den * min(len(one), len(two)) >= num * max(len(one), len(two)) else 0
                if den * c >= num * (len(one) + len(two) - c):
                    root[r] = q
                    out[0].append(sigs[x])
                    out[1].append(sigs[y])
        return pa.table({"a": pa.array(out[0], pa.binary()), "b": pa.array(out[1], pa.binary())})

    def of_one_block(t: pa.Table) -> pa.Table:
        sigs = t.column("sig").to_pylist()
        return linked(sigs, arrays(t.column("elements")), sigs, ((x, y) for x in range(len(sigs)) for y in range(x)))

    def of_two_blocks(t: pa.Table) -> pa.Table:
        lo, hi, mine = t.column("lo")[0].as_py(), t.column("hi")[0].as_py(), t.column("mine").to_pylist()
        left, right = ([k for k, m in enumerate(mine) if m == side] for side in (lo, hi))
        return linked(t.column("sig").to_pylist(), arrays(t.column("elements")), t.column("part").to_pylist(), ((x, y) for x in left for y in right))

    crowded = crowds.join(sets, "sig").select("gid", "sig", "elements", F.ceil(F.col("m") / block).alias("blocks")).withColumn("mine", F.pmod(F.xxhash64("sig"), F.col("blocks")))
    links = scratch.save(verify(candidates).union(crowded.groupBy("gid", "mine").applyInArrow(of_one_block, "a binary, b binary")), "links")
    known = scratch.save(components(scratch, links), "components")
    if not crowds.isEmpty():
        placed = crowded.join(known.withColumnRenamed("node", "sig"), "sig", "left").withColumn("part", F.coalesce("component", "sig"))
        open_groups = placed.groupBy("gid").agg(F.min("part").alias("x"), F.max("part").alias("y")).where("x != y").select("gid")
        dealt = placed.join(open_groups, "gid", "left_semi").withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))).where("mine != other")
        dealt = dealt.select("gid", "sig", "elements", "part", "mine", F.least("mine", "other").alias("lo"), F.greatest("mine", "other").alias("hi"))
        links = scratch.save(links.union(dealt.groupBy("gid", "lo", "hi").applyInArrow(of_two_blocks, "a binary, b binary")), "links")
        known = scratch.save(components(scratch, links), "components")

    # heavy shingles, second pass: pairs of blocks, for groups that aren't joined yet
    of_group = members.groupBy("gid").agg(F.count("*").alias("m"), F.min("sig").alias("sig")).join(known.withColumnRenamed("node", "sig"), "sig", "left")
    of_group = of_group.select("gid", F.when(F.col("m") == 1, F.coalesce("component", "sig")).otherwise(F.col("gid")).alias("part"))
    placed = heavy.select("token", "gid", "df").join(of_group, "gid")
    open_tokens = placed.groupBy("token").agg(F.min("part").alias("x"), F.max("part").alias("y")).where("x != y").select("token")
    placed = placed.join(open_tokens, "token").join(groups, "gid").join(weight.select("gid", "hot"), "gid")
    placed = placed.withColumn("blocks", F.ceil(F.col("df") / block)).withColumn("mine", F.pmod(F.xxhash64("gid"), F.col("blocks")))
    tiles = placed.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))).select("token", F.least("mine", "other").alias("lo"), F.greatest("mine", "other").alias("hi"), "mine", "gid", "n", "prefix", "hot", "part")

    def open_pairs(t: pa.Table) -> pa.Table:
        token, lo, hi = t.column("token")[0].as_py(), t.column("lo")[0].as_py(), t.column("hi")[0].as_py()
        d = {c: t.column(c).to_pylist() for c in ("mine", "gid", "n", "part")} | {c: arrays(t.column(c)) for c in ("prefix", "hot")}
        take = lambda keep: {c: [v for v, k in zip(d[c], d["mine"]) if k == keep] for c in d}
        left, right = take(lo), take(hi) if hi != lo else None
        gids, at, out = [], {}, ([], [])
        if left["gid"] and (right is None or right["gid"]) and len(set(d["part"])) > 1:
            overlaps, other = _overlaps(left, right, num, den), right or left
            codes = {p: k for k, p in enumerate(set(d["part"]))}
            apart = np.array([codes[p] for p in left["part"]])[:, None] != np.array([codes[p] for p in other["part"]])[None, :]
            found = (overlaps > 0) & apart
            hot, others = [set(h.tolist()) for h in left["hot"]], [set(h.tolist()) for h in other["hot"]]
            for x, y in np.argwhere(np.tril(found, -1) if right is None else found).tolist():
                if min(hot[x] & others[y]) == token:  # once for each pair: at its smallest heavy shingle
                    for g, side in ((left["gid"][x], out[0]), (other["gid"][y], out[1])):
                        if g not in at:
                            at[g] = len(gids)
                            gids.append(g)
                        side.append(at[g])
        n = bool(gids)
        return pa.table({"token": pa.array([token] * n, pa.int64()), "lo": pa.array([lo] * n, pa.int64()), "hi": pa.array([hi] * n, pa.int64()), "gids": pa.array([gids] * n, pa.list_(pa.binary())), "x": pa.array([out[0]] * n, pa.list_(pa.int32())), "y": pa.array([out[1]] * n, pa.list_(pa.int32()))})

    def verify_tile(tile: pa.Table, held: pa.Table) -> pa.Table:
        """Links of a pair of blocks, verified on whole sets; pairs that earlier links have joined are left out."""
        owned: dict[int, list[tuple[bytes, np.ndarray]]] = {}
        for k, sig, elements in zip(*(held.column(c).to_pylist() for c in ("at", "sig")), arrays(held.column("elements"))):
            owned.setdefault(k, []).append((sig, elements))
        sigs, sets, numbers = [], [], {}
        for k, some in owned.items():
            numbers[k] = range(len(sigs), len(sigs) + len(some))
            sigs += [x for x, _ in some]
            sets += [x for _, x in some]
        pairs = ((i, j) for x, y in zip(tile.column("x")[0].as_py(), tile.column("y")[0].as_py()) for i in numbers.get(x, ()) for j in numbers.get(y, ()))
        return linked(sigs, sets, sigs, pairs)

    if not open_tokens.isEmpty():
        key = ["token", "lo", "hi"]
        tiles = scratch.save(tiles.groupBy(*key).applyInArrow(open_pairs, "token long, lo long, hi long, gids array<binary>, x array<int>, y array<int>"), "tiles")
        held = tiles.select(*key, F.posexplode("gids").alias("at", "gid")).join(members.select("gid", "sig"), "gid").join(sets, "sig").select(*[F.col(c).alias(f"of_{c}") for c in key], "at", "sig", "elements")
        more = tiles.select(*key, "x", "y").groupBy(*key).cogroup(held.groupBy(*[f"of_{c}" for c in key])).applyInArrow(lambda l, r: verify_tile(l, r), "a binary, b binary")
        links = scratch.save(links.union(more), "links")
        known = components(scratch, links)

    named = members.join(known.withColumnRenamed("node", "sig"), "sig", "left").select("sig", "first_id", F.coalesce("component", "sig").alias("component"))
    smallest = named.groupBy("component").agg(F.min("first_id").alias("component_id"))
    by_set = scratch.save(named.join(smallest, "component").select("sig", "component_id"), "by-set")
    return table.join(by_set, "sig", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))
