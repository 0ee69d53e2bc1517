"""A global shuffle of distinct words: something is computed once for each distinct word and goes back to its texts.

Documents are read in chunks. A chunk is a dictionary of its distinct words and its documents' positions as dictionary
indexes, numbered so that the words of one hash bucket are a run of the dictionary. :func:`word_blocks` deals one block
a chunk and bucket; :func:`merge_blocks` meets all blocks of a bucket, handles each distinct word once and answers every
block in its own order; :func:`position_rows` packs the positions. Answers and positions meet by chunk. A word occurs once
a chunk, so a frequent word is no hot key, and rows are blocks of words, never single words or tokens.

Blocks and positions come from two reads of the same scan. A chunk's number contains a checksum of what was read, so reads
that differ (a source that is not stable) never meet, and the job stops instead of giving wrong results.
"""

from __future__ import annotations

import pickle
import zlib
from itertools import groupby

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CHUNK_CHARS, CHUNK_DOCS = 8_000_000, 1 << 17
#: Buckets for each shuffle partition of the session.
BUCKETS = 4
BLOCK = "bucket int, chunk long, data binary"


class Codes(dict):
    """Numbers keys in order of appearance."""

    def __missing__(self, key):
        self[key] = code = len(self)
        return code


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays as compressed byte planes; small numbers in wide types cost little."""
    return zstandard.compress(pickle.dumps([(a.dtype.str, np.ascontiguousarray(a.reshape(-1).view(np.uint8).reshape(len(a), a.dtype.itemsize).T).tobytes()) for a in arrays]), 3)


def unpack(data: bytes) -> list[np.ndarray]:
    out = []
    for kind, raw in pickle.loads(zstandard.decompress(data)):
        planes = np.frombuffer(raw, np.uint8).reshape(np.dtype(kind).itemsize, -1)
        out.append(np.ascontiguousarray(planes.T).reshape(-1).view(kind))
    return out


def source(docs: DataFrame) -> DataFrame:
    """What both reads take: id, text and the scan's own partition number (a task's number differs between reads)."""
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), F.spark_partition_id())


def n_buckets(docs: DataFrame) -> int:
    return BUCKETS * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def chunks(batches, keys, word_of, buckets: int):
    """(chunk, words as bytes in order of bucket, bounds of the buckets, ids, ends, codes)."""

    def done():
        every = np.concatenate(codes)
        h = xxhash.xxh3_64(repr((task, seq, ids)).encode())
        h.update(every.tobytes())
        words = [word_of(k) for k in table]
        bucket = np.fromiter(map(zlib.crc32, words), np.int64, len(words)) % buckets
        order = np.argsort(bucket, kind="stable")
        rank = np.empty(len(words), np.uint32)
        rank[order] = np.arange(len(words), dtype=np.uint32)
        return h.intdigest() >> 1, [words[k] for k in order.tolist()], np.searchsorted(bucket[order], np.arange(buckets + 1)), ids, np.array(ends, np.int64), rank[every]

    seq, task, chars, total = 0, 0, 0, 0
    table, ids, ends, codes = Codes(), [], [], []
    for b in batches:
        for doc, text, task in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist(), strict=True):
            text = text.as_py() or ""
            words = keys(text)
            own = np.fromiter(map(table.__getitem__, words), np.uint32, len(words))
            ids.append(doc)
            codes.append(own)
            total += len(own)
            ends.append(total)
            chars += len(text)
            if chars >= CHUNK_CHARS or len(ids) >= CHUNK_DOCS:
                yield done()
                seq += 1
                table, ids, ends, codes, chars, total = Codes(), [], [], [], 0, 0
    if ids:
        yield done()


def row_of(bucket: int, chunk: int, data: bytes):
    return pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([chunk], pa.int64()), pa.array([data], pa.binary())], ["bucket", "chunk", "data"])


def word_blocks(keys, word_of, buckets: int):
    """Task function: a block with the bucket's words for every chunk and bucket."""

    def run(batches):
        for chunk, words, bounds, _, _, _ in chunks(batches, keys, word_of, buckets):
            for k in range(buckets):
                part = words[bounds[k] : bounds[k + 1]]
                if part:
                    sizes = np.fromiter(map(len, part), np.int64, len(part))
                    yield row_of(k, chunk, pack(sizes, np.frombuffer(b"".join(part), np.uint8)))

    return run


def position_rows(keys, word_of, buckets: int, marks=None):
    """Task function: a row of bucket -1 a chunk: ids, ends, codes, the number of words, and ``marks(words)``, an array."""

    def run(batches):
        for chunk, words, _, ids, ends, codes in chunks(batches, keys, word_of, buckets):
            yield row_of(-1, chunk, pickle.dumps((ids, pack(ends, codes, *([marks(words)] if marks else [])), len(words))))

    return run


def merge_blocks(answer):
    """Task function on rows in order of (bucket, chunk): ``answer(bucket, words, [codes of each block])`` gives the bytes for
    every block."""

    def run(batches):
        for bucket, rows in groupby((r for b in batches for r in b.to_pylist()), key=lambda r: r["bucket"]):
            table, own, names = Codes(), [], []
            for r in rows:
                sizes, text = unpack(r["data"])
                text, ends = text.tobytes(), np.cumsum(sizes).tolist()
                own.append(np.array([table[text[a:b]] for a, b in zip([0, *ends], ends)], np.int64))
                names.append(r["chunk"])
            for chunk, data in zip(names, answer(bucket, list(table), own), strict=True):
                yield row_of(bucket, chunk, data)

    return run


def by_bucket(rows: DataFrame) -> DataFrame:
    return rows.repartition("bucket").sortWithinPartitions("bucket", "chunk")


def by_chunk(answers: DataFrame, positions: DataFrame) -> DataFrame:
    return answers.unionByName(positions).repartition("chunk").sortWithinPartitions("chunk", "bucket")


def assembled(batches):
    """Of rows in order of (chunk, bucket): (chunk, ids, ends, codes, n_words, marks if any, answers in order of bucket)."""
    for chunk, rows in groupby((r for b in batches for r in b.to_pylist()), key=lambda r: r["chunk"]):
        head = next(rows)
        if head["bucket"] != -1:
            raise RuntimeError("two reads of the documents differ; write them to a table first")
        ids, data, n_words = pickle.loads(head["data"])
        ends, codes, *marks = unpack(data)
        yield chunk, ids, ends, codes, n_words, *marks, [r["data"] for r in rows]
