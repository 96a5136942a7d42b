"""Exact n-gram Jaccard join by token-combination prefixes, as components of near copies.

Tokens are the distinct word n-grams of a document, as 63-bit hashes whose first bits fall with the
length of the n-gram: long ones are rare as a rule, and come first.  In one order for all - rare
tokens first, then those that ``frequent`` documents or more hold near their head, by hash within -
two documents that reach the threshold share a token in their prefixes.  So

* a document with enough rare tokens indexes its prefix of rare tokens, singly;
* any other indexes all its rare tokens singly, and goes on into an extended prefix of frequent
  ones, of which it indexes combinations of two neighbours.  The prefix is so long that two linked
  documents that share no rare token keep a neighbouring pair in common, whatever they differ in.

The index is linear in the text.  A candidate must pass by its sizes, by the places of a shared key,
and by short bitmaps of both sets, none of which drops a link, and is then verified on the whole sets.  A key that many
documents share is not expanded into all pairs: each is compared with the first and the last of
its key, the links are contracted into components, and only pairs of different components are
compared after that.  A pair left out is one whose documents are connected already, so components
are exact.  Copies with equal sets are collapsed first.

Defined results: documents without words link with nothing and are their own component; rows that
share an id are one node; a null id gets the component of its copies, or null; extra columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

import functools
import math
import re
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpcluster.llm import scratch
from dpcluster.llm.scratch import Scratch
from dpcluster.llm.tokens import forget, small_batches

FREQUENT = 8
ROUNDS = 1
BITMAP = 1024
#: (size of a set, bits): bitmaps that travel with keys are folded to so many bits up to that size.
SHORT = ((120, 256), (300, 512))
#: Ids of candidates are broadcast up to so many, and joined by shuffle beyond.
MAX_BROADCAST_IDS = 1_000_000
MAX_FREQUENT_TOKENS = 2_000_000
#: Texts are hashed in pieces of so many bytes, cut at white space.
PIECE = 1 << 20
_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * _M2
    h = (h ^ (h >> np.uint64(29))) * _M1
    return h ^ (h >> np.uint64(32))


def _byte_values() -> np.ndarray:
    """A random number for each byte: the same for both cases of a letter, 0 for white space."""
    values = _mixed(np.arange(1, 257, dtype=np.uint64) * _M1)
    values[65:91] = values[97:123]
    values[[9, 10, 11, 12, 13, 32]] = 0
    return values


_VALUES, _SPACE = _byte_values(), re.compile(rb"[\x20\x09-\x0D]")
_BASE = 0xA0761D6478BD642F
_POWERS: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    """Powers of an odd number modulo 2^64, from 0 on."""
    if len(_POWERS.get(base, ())) < n:
        steps = np.full(1 << (n - 1).bit_length(), base, np.uint64)
        steps[0] = 1
        _POWERS[base] = np.multiply.accumulate(steps)
    return _POWERS[base][:n]


def word_hashes(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and lengths of the words, whatever the case of ASCII letters: polynomials in the bytes, all at once."""
    hashes, lengths, at = [], [], 0
    while at < len(text):
        cut = _SPACE.search(text, at + PIECE) if at + PIECE < len(text) else None
        stop = cut.start() if cut else len(text)
        values = _VALUES[np.frombuffer(text, np.uint8, stop - at, at)]
        inside = np.zeros(len(values) + 2, bool)
        inside[1:-1] = values != 0
        edges = np.flatnonzero(inside[1:] != inside[:-1])
        starts = edges[::2]
        if len(starts):
            values *= _powers(_BASE, len(values))
            hashes.append(np.add.reduceat(values, starts) * _powers(pow(_BASE, -1, 1 << 64), len(values))[starts])
            lengths.append(edges[1::2] - starts)
        at = stop
    if not hashes:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return (hashes[0], lengths[0]) if len(hashes) == 1 else (np.concatenate(hashes), np.concatenate(lengths))


def shingle_hashes(text: bytes | None, n: int) -> np.ndarray:
    """Sorted distinct hashes (signed) of the word n-grams; of all words as one, if there are fewer."""
    h, widths = word_hashes(text or b"")
    if not len(h):
        return np.zeros(0, np.int64)
    h, size = _mixed(h), min(n, len(h))
    count = len(h) - size + 1
    out, lengths = np.full(count, np.uint64(size)), np.zeros(count, np.int64)
    for i in range(size):
        out = _mixed(out * _M1 + h[i : count + i])
        lengths += widths[i : count + i]
    rank = np.uint64(31) - np.minimum(lengths // size, 31).astype(np.uint64)
    out = ((out >> np.uint64(6)) | rank << np.uint64(58)).view(np.int64)
    out.sort()
    return out[np.concatenate([[True], out[1:] != out[:-1]])]


class Plan:
    """Lengths of prefixes for a threshold of percent / 100."""

    def __init__(self, n: int, percent: int):
        if not 75 <= percent <= 100:
            raise ValueError("the prefixes need a threshold of 0.75 to 1")
        self.n, self.percent = n, percent

    def overlap(self, size: int) -> int:
        """Least number of tokens that a set shares with one it links with."""
        return -(-self.percent * size // 100)

    def prefix(self, size: int) -> int:
        return size - self.overlap(size) + 1

    def extended(self, size: int) -> int:
        return self.prefix(size) + 1 + (100 - self.percent) * size // self.percent

    def close(self, x: Column, y: Column, sizes: Column) -> Column:
        """The bitmaps differ in no more bits than linked sets may differ in tokens."""
        apart = F.bit_count(x[0].bitwiseXOR(y[0]))
        for i in range(1, BITMAP // 64):
            apart = apart + F.bit_count(x[i].bitwiseXOR(y[i]))
        return (100 + self.percent) * apart <= (100 - self.percent) * sizes

    def close_short(self, x: Column, y: Column, sizes: Column) -> Column:
        """As ``close`` for shortened bitmaps; those of different lengths are compared at the shortest length."""
        count = lambda i, of: F.bit_count(of(x, i).bitwiseXOR(of(y, i)))
        part = lambda b, i: F.coalesce(F.get(b, F.lit(i)), F.lit(0))
        least = SHORT[0][1] // 64
        folded = lambda b, i: functools.reduce(Column.bitwiseXOR, [part(b, j) for j in range(i, BITMAP // 64, least)])
        same, other = (functools.reduce(Column.__add__, [count(i, of) for i in range(n)]) for n, of in ((BITMAP // 64, part), (least, folded)))
        apart = F.when(F.size(x) == F.size(y), same).otherwise(other)
        return (100 + self.percent) * apart <= (100 - self.percent) * sizes

    def head(self, size: int) -> int:
        """How far tokens are counted."""
        return min(size, self.prefix(size) + self.prefix(size) // 2 + 4)


def bitmap(h: np.ndarray) -> bytes:
    """One bit for each hash; two sets differ in as many tokens as in bits, or more."""
    bits = np.zeros(BITMAP, np.uint8)
    bits[(h.view(np.uint64) % np.uint64(BITMAP)).astype(np.int64)] = 1
    return np.packbits(bits).tobytes()


def short_bits(bits: Column, n: Column) -> Column:
    """The bitmap folded by exclusive or, by the size of the set: two folds differ in no more bits than the whole ones."""
    out = bits
    for size, width in reversed(SHORT):
        fold = [functools.reduce(Column.bitwiseXOR, [bits[j] for j in range(i, BITMAP // 64, width // 64)]) for i in range(width // 64)]
        out = F.when(n <= size, F.array(*fold)).otherwise(out)
    return out


def maps_of(maps: list[bytes]) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(maps) + 1, dtype=np.int32) * (BITMAP // 64)), pa.array(np.frombuffer(b"".join(maps), np.int64)))


def _summary(plan: Plan):
    def run(batches):
        forget()
        for batch in small_batches(batches):
            sizes, sigs, heads, maps = [], [], [], []
            for t in batch.column("text").cast(pa.binary()).to_pylist():
                h = shingle_hashes(t, plan.n)
                sizes.append(len(h))
                sigs.append(blake2b(h.tobytes(), digest_size=16).digest())
                heads.append(h[: plan.head(len(h))])
                maps.append(bitmap(h))
            ends = np.cumsum([0, *map(len, heads)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*heads, np.zeros(0, np.int64)])))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(sigs, pa.binary()), lists, maps_of(maps)], names=["doc_id", "n", "sig", "head", "bits"])

    return run


def prefix_keys(h: np.ndarray, common: np.ndarray, plan: Plan) -> tuple[np.ndarray, int]:
    """Index keys of a set: single rare tokens, so many, and hashed combinations of neighbouring frequent ones."""
    size, need = len(h), plan.prefix(len(h))
    at = np.searchsorted(common, h)
    often = common[np.minimum(at, len(common) - 1)] == h if len(common) else np.zeros(size, bool)
    rare = h[~often]
    if len(rare) >= need:
        return rare[:need], need
    more = h[often][: plan.extended(size)].view(np.uint64)
    pairs = _mixed(_mixed(more[:-1] * _M1) + more[1:] * _M2).view(np.int64)
    return np.concatenate([rare, pairs]), len(rare)


def _keys(plan: Plan, common):
    def run(batches):
        table = common.value
        forget()
        for batch in small_batches(batches):
            sizes, sigs, keys, singles = [], [], [], []
            for t in batch.column("text").cast(pa.binary()).to_pylist():
                h = shingle_hashes(t, plan.n)
                sizes.append(len(h))
                sigs.append(blake2b(h.tobytes(), digest_size=16).digest())
                got = prefix_keys(h, table, plan) if len(h) else (h, 0)
                keys.append(got[0])
                singles.append(got[1])
            ends = np.cumsum([0, *map(len, keys)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*keys, np.zeros(0, np.int64)])))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(sigs, pa.binary()), lists, pa.array(singles, pa.int32())], names=["doc_id", "n", "sig", "keys", "singles"])

    return run


def _sets(plan: Plan):
    def run(batches):
        forget()
        for batch in small_batches(batches):
            sets = [shingle_hashes(t, plan.n) for t in batch.column("text").cast(pa.binary()).to_pylist()]
            ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*sets, np.zeros(0, np.int64)])))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), lists], names=["doc_id", "tokens"])

    return run


def components(edges: DataFrame, tables: Scratch, name: str) -> DataFrame:
    """(node, component) for edges (a, b), by large-star and small-star contraction."""
    now = tables.write(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), f"{name}_0")
    before = None
    for i in range(1, 100):
        # large star: neighbours above a node move to the least of its neighbourhood
        both = now.select("u", "v").unionAll(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # small star: a node and its neighbours below it move to the least of those
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        now = tables.write(small, f"{name}_{i}")
        seen = tuple(now.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0))).first())
        tables.drop(f"{name}_{i - 1}")
        if seen == before:
            break
        before = seen
    else:
        raise RuntimeError("the contraction of links did not end")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component"))


def groups(docs: DataFrame, n: int = 3, percent: int = 90, frequent: int = FREQUENT) -> DataFrame:
    """Per document: doc_id, n_shingles, component_id."""
    spark, plan, tables = docs.sparkSession, Plan(n, percent), Scratch(docs.sparkSession, "jaccard")
    scratch.share_code(spark)
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = tables.write(source.mapInArrow(_summary(plan), "doc_id long, n long, sig binary, head array<long>, bits array<long>"), "found")
    classes = tables.write(found.where("n > 0").groupBy("n", "sig").agg(F.min("doc_id").alias("rep"), F.count("*").alias("members")), "classes")

    counted = found.where("n > 0").select(F.explode("head").alias("token")).groupBy("token").count()
    total = found.agg(F.coalesce(F.sum(F.size("head")), F.lit(0))).first()[0]
    # a broadcast of bounded size: at most total / least tokens are held by that many documents
    least = max(frequent, math.ceil(total / MAX_FREQUENT_TOKENS))
    often = counted.where(F.col("count") >= least).select("token").toArrow().column("token").to_numpy()
    common = spark.sparkContext.broadcast(np.sort(often.astype(np.int64)))
    found = tables.write(found.drop("head"), "sizes")  # the heads are no longer needed
    del counted
    tables.drop("found")
    tables.release()

    others = found.join(classes.where("members > 1"), ["n", "sig"]).where("doc_id <> rep").select("doc_id", "sig").distinct()
    index = source.mapInArrow(_keys(plan, common), "doc_id long, n long, sig binary, keys array<long>, singles int").where("n > 0 and doc_id is not null")
    index = index.join(others, ["doc_id", "sig"], "left_anti").select("doc_id", "n", "singles", F.posexplode("keys").alias("at", "key"))
    index = tables.write(index.select("key", "doc_id", F.col("n").cast("int").alias("n"), F.least("at", "singles").alias("at")), "index")
    several = index.groupBy("key").agg(F.count("*").cast("int").alias("c")).where("c > 1")
    held = tables.write(index.join(several, "key").withColumn("comp", F.col("doc_id")), "held_0")
    tables.drop("index")
    tables.release()

    def near(x, y):
        """Sizes allow the threshold, and so does what is left if nothing before a single key, or no single key, is shared."""
        a, b, i, j = (F.col(c) for c in (f"{x}.n", f"{y}.n", f"{x}.at", f"{y}.at"))
        return (100 * F.least(a, b) >= percent * F.greatest(a, b)) & ((100 + percent) * F.least(a - i, b - j) >= percent * (a + b))

    def pairs(df, x, y):
        return df.where(near(x, y) & (F.col(f"{x}.doc_id") != F.col(f"{y}.doc_id"))).select(F.least(f"{x}.doc_id", f"{y}.doc_id").alias("a"), F.greatest(f"{x}.doc_id", f"{y}.doc_id").alias("b")).distinct()

    links, row = [], F.struct("doc_id", "n", "at", "comp")
    for i in range(ROUNDS):
        # of each key that joins several components: its first, last and main document; each document meets those of its most common such key
        ends = held.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y"), F.min(row).alias("lo"), F.max(row).alias("hi"), F.min_by(row, F.xxhash64("doc_id", F.lit(i))).alias("main")).where("x < y").drop("x", "y")
        left = tables.write(held.join(ends, "key"), f"mixed_{i}")
        tables.drop(f"held_{i}")
        end = left.select("doc_id", row.alias("x"), "c", "key", "lo", "hi", "main")
        kinds = ("lo", "hi", "main") if i == 0 else ("main",)
        best = [F.max_by(F.struct("x", F.col(e).alias("y")), F.when(near("x", e) & (F.col("x.comp") != F.col(f"{e}.comp")), F.struct("c", "key"))).alias(e) for e in kinds]
        met = end.groupBy("doc_id").agg(*best).select(F.explode(F.array(*kinds)).alias("p")).where("p is not null").select("p.x", "p.y")
        links.append(_verified(source, found, tables, plan, pairs(met, "x", "y"), f"star_{i}"))
        joined = tables.write(components(functools.reduce(DataFrame.unionAll, links), tables, f"star_{i}_parts"), f"joined_{i}")
        held = left.drop("comp", "lo", "hi", "main").join(joined, F.col("doc_id") == F.col("node"), "left").select("key", "doc_id", "n", "at", "c", F.coalesce("component", "doc_id").alias("comp"))
        held = tables.write(held, f"held_{i + 1}")
        tables.drop(f"mixed_{i}")
        tables.release()
    mixed = held.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y"), F.min_by("comp", F.xxhash64("doc_id", "key")).alias("main")).where("x < y").select("key", "main")
    # bitmaps travel with what is left, so that the join itself drops what can't be a link
    bits = found.select(F.col("doc_id").alias("node"), short_bits(F.col("bits"), F.col("n")).alias("bits"))
    left = held.select("key", "doc_id", "n", "at", "comp").join(mixed, "key").join(bits, F.col("doc_id") == F.col("node")).drop("node")
    left = tables.write(left, "mixed")
    tables.drop(f"held_{ROUNDS}")
    tables.release()
    small, every = left.where("comp <> main").drop("main").alias("s"), tables.read("mixed", left.schema).drop("main").alias("e")
    close = plan.close_short(F.col("s.bits"), F.col("e.bits"), F.col("s.n") + F.col("e.n"))
    rest = small.join(every, (F.col("s.key") == F.col("e.key")) & (F.col("s.comp") != F.col("e.comp")) & near("s", "e") & close)
    links.append(_verified(source, found, tables, plan, pairs(rest, "s", "e"), "rest"))
    whole = components(functools.reduce(DataFrame.unionAll, links), tables, "all")
    reps = found.drop("bits").join(classes.select("n", "sig", "rep"), ["n", "sig"], "left")
    return reps.join(whole, F.col("rep") == F.col("node"), "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "rep", "doc_id").alias("component_id"))


def _few(ids: DataFrame) -> DataFrame:
    """For a join with texts, which stay where they are unless there are too many ids to send to all of them."""
    return F.broadcast(ids) if ids.count() <= MAX_BROADCAST_IDS else ids


def _verified(source: DataFrame, found: DataFrame, tables: Scratch, plan: Plan, pairs: DataFrame, name: str) -> DataFrame:
    """The pairs that reach the threshold: first by their bitmaps, then on their whole sets."""
    one, two = (found.select(F.col("doc_id").alias(i), F.col("n").alias(f"n{i}"), F.col("bits").alias(f"bits{i}")) for i in "ab")
    hopeful = pairs.join(one, "a").join(two, "b").where(plan.close(F.col("bitsa"), F.col("bitsb"), F.col("na") + F.col("nb"))).select("a", "b").distinct()
    hopeful = tables.write(hopeful, f"{name}_pairs")
    ids = tables.write(hopeful.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), f"{name}_ids")
    sets = tables.write(source.join(_few(ids), "doc_id", "left_semi").mapInArrow(_sets(plan), "doc_id long, tokens array<long>"), f"{name}_sets")
    one, two = sets.select(F.col("doc_id").alias("a"), F.col("tokens").alias("x")), sets.select(F.col("doc_id").alias("b"), F.col("tokens").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    linked = hopeful.join(one, "a").join(two, "b").where(100 * both >= plan.percent * (F.size("x") + F.size("y") - both)).select("a", "b")
    out = tables.write(linked, name)
    tables.drop(f"{name}_sets")
    return out


def keep_first(docs: DataFrame, n: int = 5, percent: int = 80, **options) -> DataFrame:
    """One document of each group: the one with the smallest id, and one row of it.

    Where ids are missing or shared by several rows, rows are told apart by id and text: of each group the
    row with the smallest id stays (missing ids last, then by a hash of the text); rows without words stay all."""
    tables = Scratch(docs.sparkSession, "keep-first")
    told_of = lambda df: tables.write(groups(df, n, percent, **options), "groups")
    unclear = docs.groupBy(F.col("doc_id").cast("long").alias("doc_id")).count().where("count > 1 or doc_id is null")
    if unclear.isEmpty():
        gone = told_of(docs).where("doc_id <> component_id").select(F.col("doc_id").alias("__doc"))
        tables.release()
        return docs.join(_few(gone), F.col("doc_id") == F.col("__doc"), "left_anti")
    keyed = docs.withColumn("__key", F.xxhash64(F.col("doc_id").cast("long"), "text"))
    told = told_of(keyed.select(F.col("__key").alias("doc_id"), "text")).where("n_shingles > 0")
    ids = keyed.select(F.col("__key").alias("doc_id"), F.struct(F.col("doc_id").isNull(), F.col("doc_id").cast("long"), "__key").alias("at"))
    first = told.distinct().join(ids.distinct(), "doc_id").groupBy("component_id").agg(F.min("at").alias("at")).select(F.col("at.__key").alias("doc_id")).withColumn("first", F.lit(True))
    marks = told.groupBy("doc_id").agg(F.count("*").alias("rows")).join(first, "doc_id", "left").select(F.col("doc_id").alias("__doc"), "rows", F.coalesce("first", F.lit(False)).alias("first"))
    marks = tables.write(marks, "marks")
    tables.release()
    kept = keyed.join(_few(marks.where("not first")), F.col("__key") == F.col("__doc"), "left_anti")
    several = _few(tables.read("marks", marks.schema).where("first and rows > 1"))
    once = kept.join(several, F.col("__key") == F.col("__doc"), "left_anti")
    again = kept.join(several, F.col("__key") == F.col("__doc"), "left_semi").dropDuplicates(["__key"])
    return once.unionAll(again).select(*docs.columns)
