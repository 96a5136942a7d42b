"""Packing by power-of-two decomposition.

Each document (ids, then the end id) is cut into pieces whose lengths are the largest allowed power
of two, repeated, and then the binary digits of the rest, longest first.  Every piece is a sequence
of its own, so none crosses documents and none is padded; pieces of one length form a bucket.

Defined results: a null or empty text is the end id alone; repeated rows are packed each on their
own; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from dpcluster.llm import scratch, tokens

END_ID = 2
MAX_LENGTH = 4096

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, bucket int"
_ARROW = pa.schema([("doc_id", pa.int64()), *((c, pa.int64()) for c in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")), ("bucket", pa.int32())])


def piece_lengths(n: int, max_length: int = MAX_LENGTH) -> list[int]:
    """Powers of two that add up to n, none above max_length, falling."""
    out = [max_length] * (n // max_length)
    rest = n % max_length
    while rest:
        top = 1 << (rest.bit_length() - 1)
        out.append(top)
        rest -= top
    return out


def _packer(path: str, end_id: int, max_length: int, with_ids: bool):
    end = np.array([end_id], np.uint32)

    def run(batches):
        number = TaskContext.get().partitionId() << 33
        schema = _ARROW.append(pa.field("ids", pa.binary())) if with_ids else _ARROW
        for batch, texts in tokens.text_rows(batches):
            got = tokens.codec(path).encode_flat(*tokens.flat(texts))
            bounds, rows = got.ids_before, []
            data = memoryview(np.insert(got.ids, bounds[1:], end).tobytes())
            places = (bounds + np.arange(len(bounds))).tolist()
            for doc_id, a, b in zip(batch.column("doc_id").to_pylist(), places, places[1:]):
                start = 0
                for length in piece_lengths(b - a, max_length):
                    piece = data[4 * (a + start) : 4 * (a + start + length)]
                    rows.append((doc_id, start, length, zlib.crc32(piece), b - a, number, 0, length.bit_length() - 1, *((bytes(piece),) if with_ids else ())))
                    start += length
                    number += 1
            yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows), schema)], schema=schema)

    return run


def pack(docs: DataFrame, tokenizer_file: str, end_id: int = END_ID, max_length: int = MAX_LENGTH, with_ids: bool = False) -> DataFrame:
    """One row per piece; with_ids adds the ids themselves, little-endian 32-bit."""
    if max_length & (max_length - 1) or max_length < 1:
        raise ValueError("max_length must be a power of two")
    scratch.share_code(docs.sparkSession)
    source = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"])
    return source.mapInArrow(_packer(tokenizer_file, end_id, max_length, with_ids), SCHEMA + (", ids binary" if with_ids else ""))


def write_buckets(docs: DataFrame, path: str, tokenizer_file: str, **options) -> None:
    """Writes the sequences with their ids, one folder for each length."""
    pack(docs, tokenizer_file, with_ids=True, **options).write.partitionBy("bucket").parquet(path)
