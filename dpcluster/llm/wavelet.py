"""Token ids in wavelet matrices, one compressed file a shard.

A shard holds the ids of whole documents in ascending order of doc_id.  Each bit of the ids is a
plane; on every plane zeros go before ones, stably, for the next plane.  Planes are stored in
blocks, compressed on their own where that is smaller, beside a directory of ranks, so that one
token, the number of occurrences of an id, or its k-th place are found without decoding the rest.

Layout (little-endian): magic, version, numbers of tokens, documents and planes, bytes in a block;
document ids (64-bit, and how many of the first have none) and lengths (32-bit), deflated; zeros of
each plane; for each plane the ranks before its blocks, the ends of its blocks, a flag for deflated
ones; then all blocks.  Each shard is the only row of a Parquet file, which Spark can write to and read
from any store.

Texts are encoded once, before they are ordered, so that what is sorted are ids of 16 bits where the
vocabulary allows that.  Ranges are cut by document id and then by a checksum of the ids, so rows that
share an id, or have none, are dealt to several tasks.

Defined results: null or empty text is the end id alone; documents without an id come first; rows
with one id follow each other in the order of their ids' checksums and ids; an empty table gives no
rows; extra columns are ignored.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dpcluster.llm import scratch, tokens
from dpcluster.llm.scratch import Scratch

MAGIC = b"WVMX"
BLOCK = 8192
SHARD_TOKENS = 1 << 20
END_ID = 2
_HEAD = "<4sHQQIIQ"


def encode(ids: np.ndarray, doc_ids, lengths, block: int = BLOCK, without_id: int = 0) -> bytes:
    """The file of one shard; so many of its first documents have no id."""
    n, planes = len(ids), max(1, int(ids.max(initial=0)).bit_length())
    docs = zlib.compress(np.asarray(doc_ids, "<i8").tobytes() + np.asarray(lengths, "<u4").tobytes(), 1)
    zeros, meta, body, end = [], [], [], 0
    at = ids.astype(np.uint16 if planes <= 16 else np.uint32)
    for p in range(planes - 1, -1, -1):
        bit = (at & at.dtype.type(1 << p)).astype(bool)
        packed = np.packbits(bit)
        ones = np.add.reduceat(np.bitwise_count(packed).astype("<u8"), np.arange(0, len(packed), block)) if n else np.zeros(0, "<u8")
        ranks, ends, flags = np.cumsum(ones) - ones, [], []
        useful = True  # a plane whose first block does not shrink is stored as it is
        for i in range(0, len(packed), block):
            raw = packed[i : i + block].tobytes()
            small = zlib.compress(raw, 1) if useful else raw
            useful = useful and len(small) < 0.97 * len(raw)
            flags.append(len(small) < len(raw))
            body.append(small if flags[-1] else raw)
            end += len(body[-1])
            ends.append(end)
        meta.append((ranks.astype("<u8"), np.asarray(ends, "<u8"), np.asarray(flags, "u1")))
        keep = ~bit
        zeros.append(int(keep.sum()))
        at = np.concatenate([at.compress(keep), at.compress(bit)])  # several times faster than masks as indices
    head = struct.pack(_HEAD, MAGIC, 2, n, len(doc_ids), planes, block, without_id) + struct.pack("<I", len(docs)) + docs + np.asarray(zeros, "<u8").tobytes()
    return head + b"".join(x.tobytes() for m in meta for x in m) + b"".join(body)


class Shard:
    """Reads one file."""

    def __init__(self, data: bytes):
        magic, version, self.n, n_docs, self.planes, self.block, self.without_id = struct.unpack_from(_HEAD, data)
        if magic != MAGIC or version != 2:
            raise ValueError("not a shard of token ids")
        at = struct.calcsize(_HEAD)
        (size,) = struct.unpack_from("<I", data, at)
        docs = zlib.decompress(data[at + 4 : at + 4 + size])
        self.doc_ids, self.lengths = np.frombuffer(docs, "<i8", n_docs), np.frombuffer(docs, "<u4", n_docs, 8 * n_docs)
        at += 4 + size
        self.zeros = np.frombuffer(data, "<u8", self.planes, at)
        at += 8 * self.planes
        blocks = -(-((self.n + 7) // 8) // self.block)
        self.meta = []
        for _ in range(self.planes):
            self.meta.append((np.frombuffer(data, "<u8", blocks, at), np.frombuffer(data, "<u8", blocks, at + 8 * blocks), np.frombuffer(data, "u1", blocks, at + 16 * blocks)))
            at += 17 * blocks
        self.data, self.body, self.kept = data, at, {}

    def _block(self, plane: int, i: int) -> np.ndarray:
        if (plane, i) not in self.kept:
            _, ends, flags = self.meta[plane]
            start = int(ends[i - 1]) if i else (int(self.meta[plane - 1][1][-1]) if plane else 0)
            raw = self.data[self.body + start : self.body + int(ends[i])]
            self.kept[plane, i] = np.unpackbits(np.frombuffer(zlib.decompress(raw) if flags[i] else raw, "u1"))
        return self.kept[plane, i]

    def _bit(self, plane: int, at: int) -> int:
        i, j = divmod(at, 8 * self.block)
        return int(self._block(plane, i)[j])

    def _ones(self, plane: int, at: int) -> int:
        """Ones before a place."""
        i, j = divmod(at, 8 * self.block)
        if j == 0 and i == len(self.meta[plane][0]):
            return self.n - int(self.zeros[plane])
        return int(self.meta[plane][0][i]) + int(self._block(plane, i)[:j].sum())

    def access(self, at: int) -> int:
        value = 0
        for p in range(self.planes):
            bit, ones = self._bit(p, at), self._ones(p, at)
            value = value << 1 | bit
            at = int(self.zeros[p]) + ones if bit else at - ones
        return value

    def _range(self, token: int, lo: int, hi: int) -> tuple[int, int]:
        for p in range(self.planes):
            a, b = self._ones(p, lo), self._ones(p, hi)
            lo, hi = (int(self.zeros[p]) + a, int(self.zeros[p]) + b) if token >> (self.planes - 1 - p) & 1 else (lo - a, hi - b)
        return lo, hi

    def count(self, token: int, lo: int = 0, hi: int | None = None) -> int:
        """Occurrences of a token in [lo, hi)."""
        if token >> self.planes:
            return 0
        lo, hi = self._range(token, lo, self.n if hi is None else hi)
        return hi - lo

    rank = count

    def select(self, token: int, k: int) -> int:
        """The place of the k-th occurrence, from 0; -1 if there are fewer."""
        if token >> self.planes:
            return -1
        lo, hi = self._range(token, 0, self.n)
        if k < 0 or lo + k >= hi:
            return -1
        at = lo + k
        for p in range(self.planes - 1, -1, -1):
            bit = token >> (self.planes - 1 - p) & 1
            at = self._place(p, bit, at - (int(self.zeros[p]) if bit else 0))
        return at

    def _place(self, plane: int, bit: int, k: int) -> int:
        """The place of the k-th one or zero of a plane."""
        ranks, width = self.meta[plane][0].astype(np.int64), 8 * self.block
        before = ranks if bit else np.arange(len(ranks)) * width - ranks
        i = int(np.searchsorted(before, k, side="right")) - 1
        return i * width + int(np.flatnonzero(self._block(plane, i) == bit)[k - int(before[i])])

    def decode(self) -> np.ndarray:
        """All ids, from the last plane to the first."""
        at = np.zeros(self.n, np.uint16 if self.planes <= 16 else np.uint32)
        for p in range(self.planes - 1, -1, -1):
            blocks = [self._block(p, i) for i in range(len(self.meta[p][0]))]
            bit = (np.concatenate(blocks)[: self.n] if blocks else np.zeros(0, "u1")) == 1
            for key in [k for k in self.kept if k[0] == p]:
                del self.kept[key]
            up, z = np.empty_like(at), int(self.zeros[p])
            up[np.flatnonzero(~bit)], up[np.flatnonzero(bit)] = at[:z], at[z:] | at.dtype.type(1 << (self.planes - 1 - p))
            at = up
        return at.astype("<u4")


_SHARDS = pa.schema([("part", pa.int32()), ("shard", pa.int32()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("payload", pa.binary())])


_ENCODED = pa.schema([("doc_id", pa.int64()), ("width", pa.int32()), ("crc", pa.int64()), ("ids", pa.binary())])


def _encoder(path: str, end_id: int):
    """Ids of each text and the end id, in as few bytes as the vocabulary allows."""

    def run(batches):
        for batch, texts in tokens.text_rows(batches):
            codec = tokens.codec(path)
            kind = np.dtype("<u2" if max(codec.tokenizer.get_vocab_size(), end_id + 1) <= 1 << 16 else "<u4")
            got = codec.encode_flat(*tokens.flat(texts))
            bounds = got.ids_before
            data = memoryview(np.insert(got.ids.astype(kind), bounds[1:], end_id).tobytes())
            ends = (kind.itemsize * (bounds + np.arange(len(bounds)))).tolist()
            ids = [data[a:b] for a, b in zip(ends, ends[1:])]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([kind.itemsize] * len(ids), pa.int32()), pa.array(map(zlib.crc32, ids), pa.int64()), pa.array(ids, pa.binary())], schema=_ENCODED)

    return run


def _writer(shard_tokens: int):
    def run(batches):
        tokens.forget()
        part, number, held, doc_ids, size = TaskContext.get().partitionId(), 0, [], [], 0

        def close():
            nonlocal number, held, doc_ids, size
            without = doc_ids.count(None)  # they come first
            file = encode(np.concatenate(held), [0] * without + doc_ids[without:], [len(x) for x in held], without_id=without)
            row = pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip((part, number, len(held), size, file), _SHARDS)], schema=_SHARDS)
            number, held, doc_ids, size = number + 1, [], [], 0
            return row

        for batch in batches:
            for doc_id, width, ids in zip(batch.column("doc_id").to_pylist(), batch.column("width").to_pylist(), batch.column("ids")):
                x = np.frombuffer(ids.as_buffer(), f"<u{width}")
                if held and size + len(x) > shard_tokens:
                    yield close()
                held.append(x)
                doc_ids.append(doc_id)
                size += len(x)
            held = [x.copy() for x in held]  # else what is left of a batch holds all of it
        if held:
            yield close()

    return run


def write(docs: DataFrame, path: str, tokenizer_file: str, end_id: int = END_ID, shard_tokens: int = SHARD_TOKENS) -> None:
    """Writes shards in ascending order of doc_id, each a file of its own beside its place."""
    scratch.share_code(docs.sparkSession)
    tables = Scratch(docs.sparkSession, "wavelet-ids")
    source = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"])
    encoded = tables.write(source.mapInArrow(_encoder(tokenizer_file, end_id), "doc_id long, width int, crc long, ids binary"), "ids")
    ordered = encoded.repartitionByRange(F.asc_nulls_first("doc_id"), "crc").sortWithinPartitions(F.asc_nulls_first("doc_id"), "crc", "ids")
    shards = ordered.mapInArrow(_writer(shard_tokens), "part int, shard int, n_docs long, n_tokens long, payload binary")
    shards.write.option("compression", "none").option("maxRecordsPerFile", 1).parquet(path)
    tables.drop()


def _reader(batches):
    tokens.forget()
    out = pa.schema([("part", pa.int32()), ("shard", pa.int32()), ("place", pa.int64()), ("doc_id", pa.int64()), ("within", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])
    for batch in batches:
        for i in range(batch.num_rows):
            shard = Shard(batch.column("payload")[i].as_buffer().to_pybytes())
            ids, ends = memoryview(shard.decode().tobytes()), np.cumsum(shard.lengths.astype(np.int64))
            starts, n = ends - shard.lengths, len(ends)
            sums = [zlib.crc32(ids[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist())]
            doc_ids = pa.array(shard.doc_ids, pa.int64(), mask=np.arange(n) < shard.without_id)
            same = [pa.array(np.full(n, batch.column(c)[i].as_py()), t) for c, t in (("part", pa.int32()), ("shard", pa.int32()))]
            yield pa.RecordBatch.from_arrays([*same, pa.array(np.arange(n)), doc_ids, pa.array(starts), pa.array(shard.lengths.astype(np.int64)), pa.array(sums, pa.int64())], schema=out)


def read(spark: SparkSession, path: str) -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32."""
    files = spark.read.parquet(path)
    rows = files.select("part", "shard", "payload").mapInArrow(_reader, "part int, shard int, place long, doc_id long, within long, n_tokens long, ids_crc32 long")
    sizes = files.select("part", "shard", "n_tokens")
    # one number a partition of the writer crosses the driver; shards are summed within their partition
    total, before = 0, []
    for part, n in sorted((r[0], r[1]) for r in sizes.groupBy("part").agg(F.sum("n_tokens")).collect()):
        before.append((part, total))
        total += n
    parts = spark.createDataFrame(before, "part int, base long")
    ahead = Window.partitionBy("part").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    bases = sizes.withColumn("ahead", F.coalesce(F.sum("n_tokens").over(ahead), F.lit(0))).drop("n_tokens").join(parts, "part")
    return rows.join(bases, ["part", "shard"]).select("doc_id", (F.col("base") + F.col("ahead") + F.col("within")).alias("start"), "n_tokens", "ids_crc32")
