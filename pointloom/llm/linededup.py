"""Line dedup by probing a sharded minimal perfect hash.

Lines are compared by 128-bit hashes of their keys. The texts are read twice and never rewritten in between:

1. One read gives, by chunk of documents, a row for each distinct line (hash, smallest and largest doc_id in the chunk) and
   one packed row with the places of the chunk's lines. A frequent line is one row a chunk, so it is no hot key.
2. The rows are dealt into shards by the first half of their hash; shards hold ``SHARD_ROWS`` rows on average, however
   many lines there are. A shard's task builds one minimal perfect hash (levels of bit arrays: a key that is alone at its
   position on a level is placed there, the others go on to the next level; the rank of its bit is its index) over
   its distinct lines, with arrays of fingerprints (the other half of the hash), smallest and largest doc_ids and counts.
   Every chunk's lines probe the arrays, and those that lose a line get the smallest doc_id as the answer.
3. Answers and places meet by chunk and give a mask for each document that loses lines.
4. The masks are joined to the second read of the documents, by id and hash of the text: broadcast while they take at most
   ``MASK_BYTES``, else by a shuffled join. Cutting the lines out is native.

Nothing but row counts and sizes reaches the driver.

Defined cases: null and empty texts are one empty line; a line's key may be empty or short, then it always stays; a
null doc_id counts as the largest id, and all null ids as one document; rows that share a doc_id are one document; an
empty table gives an empty result; :func:`dedup` keeps all columns and rewrites ``text`` (null stays null if nothing
was dropped) and ``n_chars`` where there is one.
"""

from __future__ import annotations

from itertools import groupby

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pointloom.llm.common import lean, materialize, own_prefix
from pointloom.llm.wordshuffle import pack, unpack

MIN_CHARS = 10
#: Lines or documents of a chunk, and rows of a shard on average.
CHUNK_LINES, CHUNK_DOCS = 1 << 20, 1 << 17
SHARD_ROWS = 1 << 18
#: Masks of at most this many bytes are broadcast.
MASK_BYTES = 32 << 20
NULL_ID = np.iinfo(np.int64).max
GAMMA = 2
#: The code of a line that is too short to be compared.
SHORT = 2**32 - 1


def line_key(line: bytes) -> bytes | None:
    """The normalised line if it is long enough to be compared; strip and lower of bytes are ASCII only."""
    key = line.strip().lower()
    if len(key) < MIN_CHARS or (len(key) < 4 * MIN_CHARS and not key.isascii() and len(key.decode()) < MIN_CHARS):
        return None
    return key


def _mix(keys: np.ndarray, level: int) -> np.ndarray:
    x = keys + np.uint64((0x9E3779B97F4A7C15 * (level + 1)) & (2**64 - 1))
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class PerfectHash:
    """Minimal perfect hash of distinct uint64 keys; keys it was not built on get any index or -1."""

    def __init__(self, levels: list[np.ndarray]):
        self.levels = levels
        self.ranks, total = [], 0
        for words in levels:
            counts = np.bitwise_count(words).astype(np.int64)
            self.ranks.append(total + np.cumsum(counts) - counts)
            total += int(counts.sum())
        self.n = total

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        levels = []
        while len(keys):
            size = max(64, (GAMMA * len(keys) + 63) // 64 * 64)
            at = (_mix(keys, len(levels)) % np.uint64(size)).astype(np.int64)
            alone = np.bincount(at, minlength=size) == 1
            levels.append(np.packbits(alone, bitorder="little").view(np.uint64))
            keys = keys[~alone[at]]
        return cls(levels)

    def index(self, keys: np.ndarray) -> np.ndarray:
        out, left = np.full(len(keys), -1, np.int64), np.arange(len(keys))
        for level, (words, ranks) in enumerate(zip(self.levels, self.ranks, strict=True)):
            at = _mix(keys[left], level) % np.uint64(len(words) * 64)
            word, bit = (at >> np.uint64(6)).astype(np.int64), at & np.uint64(63)
            hit = (words[word] >> bit) & np.uint64(1) == 1
            below = words[word[hit]] & ((np.uint64(1) << bit[hit]) - np.uint64(1))
            out[left[hit]] = ranks[word[hit]] + np.bitwise_count(below)
            left = left[~hit]
        return out


class Shard:
    """A perfect hash over the first halves of lines' hashes, with the arrays that it indexes."""

    def __init__(self, h1: np.ndarray, h2: np.ndarray, least: np.ndarray, most: np.ndarray, n: np.ndarray):
        keys, first = np.unique(h1, return_index=True)
        self.hash = PerfectHash.build(keys)
        self.fp = np.zeros(len(keys), np.uint64)
        self.fp[self.hash.index(keys)] = h2[first]
        at = self.hash.index(h1)
        main = self.fp[at] == h2
        # of lines that share the first half of their hash, the first is indexed and the others are listed
        self.twins: dict[tuple, list] = {}
        for a, b, lo, hi in zip(*(x[~main].tolist() for x in (h1, h2, least, most)), strict=True):
            old = self.twins.get((a, b), (lo, hi))
            self.twins[a, b] = (min(lo, old[0]), max(hi, old[1]))
        self.least, self.most = np.full(len(keys), NULL_ID), np.full(len(keys), np.iinfo(np.int64).min)
        np.minimum.at(self.least, at[main], least[main])
        np.maximum.at(self.most, at[main], most[main])
        self.counts = np.bincount(at[main], n[main], len(keys)).astype(np.int64)

    def probe(self, h1: np.ndarray, h2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether two or more documents hold each line, and the smallest doc_id that has it."""
        at = self.hash.index(h1)
        known = at >= 0
        known[known] = self.fp[at[known]] == h2[known]
        least, repeated = np.full(len(h1), NULL_ID), np.zeros(len(h1), bool)
        least[known] = self.least[at[known]]
        repeated[known] = least[known] < self.most[at[known]]
        for (a, b), (lo, hi) in self.twins.items():
            same = (h1 == np.uint64(a)) & (h2 == np.uint64(b))
            least[same], repeated[same] = lo, lo < hi
        return repeated, least


def _hashes(keys: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    both = np.frombuffer(b"".join(map(xxhash.xxh3_128_digest, keys)), "<u8").reshape(-1, 2)
    return np.ascontiguousarray(both[:, 0]), np.ascontiguousarray(both[:, 1])


def _ids(column) -> np.ndarray:
    return column.fill_null(int(NULL_ID)).to_numpy(zero_copy_only=False)


LINES = "chunk long, code int, h1 long, h2 long, least long, most long, n long, data binary"


def _chunk_rows(batches):
    """Rows of doc_id, text, hash of the text and scan partition -> the distinct lines of each chunk, and its lines' places."""
    held, lines, docs, seq, task = [], 0, 0, 0, 0

    def done():
        ids, hashes, sizes, h1, h2 = (np.concatenate(x) for x in zip(*held, strict=True))
        chunk = (task << 32) + seq
        long = np.flatnonzero((h1 != 0) | (h2 != 0))
        owner = np.repeat(ids, sizes)[long]
        order = np.lexsort((owner, h2[long], h1[long]))
        a, b, owner = h1[long][order], h2[long][order], owner[order]
        new = np.concatenate(([True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])))[: len(a)]
        at = np.flatnonzero(new)
        codes = np.full(len(h1), SHORT, np.uint32)
        codes[long[order]] = np.cumsum(new) - 1
        last = np.append(at[1:], len(a))[: len(at)] - 1
        # documents that hold a line: changes of the owner within its run
        n = np.add.reduceat(new | np.concatenate(([True], owner[1:] != owner[:-1]))[: len(owner)], at).astype(np.int64) if len(at) else at
        columns = [np.full(len(at), chunk), np.arange(len(at), dtype=np.int32), a[at].view(np.int64), b[at].view(np.int64), owner[at], owner[last], n]
        names = [f.split()[0] for f in LINES.split(", ")]
        yield pa.RecordBatch.from_arrays([*map(pa.array, columns), pa.nulls(len(at), pa.binary())], names)
        head = pack(ids, hashes, sizes.astype(np.uint32), codes)
        yield pa.RecordBatch.from_arrays([pa.array([chunk]), *(pa.nulls(1, t) for t in (pa.int32(), *[pa.int64()] * 5)), pa.array([head], pa.binary())], names)

    for b in batches:
        sizes, keys, places = [], [], []
        total = 0
        for text in b.column(1):
            own = (text.as_py() or "").encode().split(b"\n")
            sizes.append(len(own))
            for k, line in enumerate(own, total):
                if (key := line_key(line)) is not None:
                    keys.append(key)
                    places.append(k)
            total += len(own)
        h1, h2 = np.zeros(total, np.uint64), np.zeros(total, np.uint64)
        if keys:
            h1[places], h2[places] = _hashes(keys)
        if b.num_rows:
            held.append((_ids(b.column(0)), b.column(2).to_numpy(), np.array(sizes, np.int64), h1, h2))
            lines, docs, task = lines + total, docs + b.num_rows, b.column(3)[0].as_py()
        if lines >= CHUNK_LINES or docs >= CHUNK_DOCS:
            yield from done()
            held, lines, docs, seq = [], 0, 0, seq + 1
    if held:
        yield from done()


def _probe_shards(batches):
    """Rows in order of shard -> (chunk, code, least) of the lines that some document of the chunk loses."""

    def answers(parts):
        chunk, code, h1, h2, least, most, n = (np.concatenate(x) for x in zip(*parts, strict=True))
        h1, h2 = h1.view(np.uint64), h2.view(np.uint64)
        repeated, smallest = Shard(h1, h2, least, most, n).probe(h1, h2)
        lost = repeated & (most > smallest)
        return pa.RecordBatch.from_arrays([pa.array(chunk[lost]), pa.array(code[lost]), pa.array(smallest[lost])], ["chunk", "code", "least"])

    now, parts = None, []
    for b in batches:
        shard = b.column(0).to_numpy()
        cols = [c.to_numpy() for c in b.columns[1:]]
        cuts = [0, *(np.flatnonzero(np.diff(shard)) + 1).tolist(), len(shard)]
        for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
            if hi > lo:
                if shard[lo] != now and parts:
                    yield answers(parts)
                    parts = []
                now = shard[lo]
                parts.append([c[lo:hi] for c in cols])
    if parts:
        yield answers(parts)


def _mask_rows(batches):
    """Of rows in order of chunk, the places first: id, hash of the text and mask of every document that loses lines."""

    def masks(data, codes, least):
        ids, hashes, sizes, places = unpack(data)
        answer = np.full(int(codes.max(initial=0)) + 1, np.iinfo(np.int64).min)
        answer[codes] = least
        asked = places <= np.uint32(len(answer) - 1)
        doc = np.repeat(np.arange(len(ids)), sizes)
        drop = np.zeros(len(places), bool)
        got = answer[places[asked]]
        drop[asked] = (got != np.iinfo(np.int64).min) & (got != ids[doc[asked]])
        ends = np.cumsum(sizes, dtype=np.int64)
        for lo in range(0, len(ids), 4096):
            hi = min(lo + 4096, len(ids))
            first = int(ends[lo - 1]) if lo else 0
            part = drop[first : int(ends[hi - 1])]
            n = np.add.reduceat(part, ends[lo:hi] - sizes[lo:hi] - first)
            at = np.flatnonzero(n)
            if len(at):
                bounds = [(int(ends[lo + k]) - int(sizes[lo + k]) - first, int(ends[lo + k]) - first) for k in at.tolist()]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids[lo:hi][at]), pa.array(hashes[lo:hi][at]), pa.array([part[x:y].tolist() for x, y in bounds], pa.list_(pa.bool_()))], ["id", "hash", "mask"]
                )

    def rows():
        for b in batches:
            yield from zip(*(c.to_pylist() for c in b.columns), strict=True)

    for _, own in groupby(rows(), key=lambda r: r[0]):
        _, _, _, data = next(own)
        answers = np.array([(code, least) for _, code, least, _ in own], np.int64).reshape(-1, 2)
        if len(answers):
            yield from masks(data, answers[:, 0], answers[:, 1])


def line_masks(docs: DataFrame, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """id (null as the largest), hash of the text and mask (one flag a line, true where it goes) of the documents that lose lines."""
    text = F.col("text").cast("string")
    read = docs.select(F.col("doc_id").cast("long"), text, F.xxhash64(F.coalesce(text, F.lit(""))), F.spark_partition_id())
    rows = materialize(read.mapInArrow(lean(_chunk_rows), LINES))
    lines = rows.where("data is null")
    bits = max(0, int(np.ceil(np.log2(max(1, lines.count()) / shard_rows))))
    shard = F.shiftrightunsigned("h1", 64 - bits) if bits else F.lit(0).cast("long")
    width = max(1, min(1 << bits, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    dealt = lines.select(shard.alias("shard"), "chunk", "code", "h1", "h2", "least", "most", "n").repartition(width, "shard").sortWithinPartitions("shard")
    answers = dealt.mapInArrow(lean(_probe_shards), "chunk long, code int, least long").withColumn("data", F.lit(None).cast("binary"))
    places = rows.where("data is not null").select("chunk", F.lit(-1).alias("code"), F.lit(0).cast("long").alias("least"), "data")
    met = places.unionByName(answers).repartition("chunk").sortWithinPartitions("chunk", "code")
    # rows that share an id and a text share the mask
    return materialize(met.mapInArrow(lean(_mask_rows), "id long, hash long, mask array<boolean>").dropDuplicates(["id", "hash"]))


def _masked(docs: DataFrame, name: str, shard_rows: int, mask_bytes: int) -> DataFrame:
    """``docs`` with the mask of each row in column ``name``; null where nothing goes."""
    masks = line_masks(docs, shard_rows)
    size = masks.agg(F.sum(F.size("mask") + 32)).first()[0] or 0
    key_id, key_hash = name + "i", name + "h"
    masks = masks.toDF(key_id, key_hash, name)
    keyed = docs.withColumns({key_id: F.coalesce(F.col("doc_id").cast("long"), F.lit(int(NULL_ID))), key_hash: F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit("")))})
    return keyed.join(F.broadcast(masks) if size <= mask_bytes else masks, [key_id, key_hash], "left")


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text.cast("string"), F.lit("")), "\n", -1)


def _kept(text: Column, mask: Column) -> Column:
    stay = F.filter(_lines(text), lambda line, at: ~F.get(mask, at))
    return F.when(mask.isNull(), text.cast("string")).otherwise(F.array_join(stay, "\n"))


def line_report(docs: DataFrame, shard_rows: int = SHARD_ROWS, mask_bytes: int = MASK_BYTES) -> DataFrame:
    rows = _masked(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), "__m", shard_rows, mask_bytes)
    return rows.select(
        "doc_id",
        F.size(_lines(F.col("text"))).cast("long").alias("n_lines"),
        F.coalesce(F.size(F.filter("__m", lambda x: x)), F.lit(0)).cast("long").alias("n_dropped"),
        F.sha2(F.coalesce(_kept(F.col("text"), F.col("__m")), F.lit("")).cast("binary"), 256).alias("kept_sha256"),
    )


def dedup(docs: DataFrame, shard_rows: int = SHARD_ROWS, mask_bytes: int = MASK_BYTES) -> DataFrame:
    """``docs`` without the repeated lines; every row stays."""
    name = own_prefix(docs) + "m"
    rows = _masked(docs, name, shard_rows, mask_bytes)
    text = _kept(F.col("text"), F.col(name))

    def column(f):
        if f.name == "text":
            return text.cast(f.dataType).alias("text")
        if f.name == "n_chars":
            return F.when(F.col(name).isNull(), F.col("n_chars")).otherwise(F.length(text).cast(f.dataType)).alias("n_chars")
        return F.col(f"`{f.name}`")

    return rows.select(*map(column, docs.schema))


ORACLE = r"""
WITH l AS (
  SELECT doc_id, pos, line, lower_key AS key FROM (
    SELECT doc_id, pos, line, regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g') AS stripped,
           translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS lower_key
    FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
                 generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents))),
k AS (SELECT key, min(doc_id) AS least FROM l WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) >= 2)
SELECT l.doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (WHERE k.least IS NOT NULL AND k.least <> l.doc_id)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE k.least IS NULL OR k.least = l.doc_id), '')) AS kept_sha256
FROM l LEFT JOIN k ON l.key = k.key GROUP BY l.doc_id
"""
