"""One document of every group of near-duplicates: linked are exactly the pairs whose sets of five-word shingles have a
Jaccard similarity of 4/5 or more.

1. SimHash: fingerprints of the sets within ``BITS`` bits meet by the trie join; every link is checked on the sets.
   This only saves work: groups of copies are one class before the second pass, and are no longer compared in it.
2. Completion: two sets that are similar enough share one of the first ``n - ceil(4n/5) + 1`` shingles of any common
   order. Here it is by the number of sets that hold a shingle, counted over all documents, so a set that has enough shingles of
   its own meets no other. Hashes go to the shard that counts them, in packed blocks; the places of those that two or more
   sets hold come back by chunk of documents, and all others come first. Shingles that meet one class only are left out.

Both passes give groups of vertices with an anchor, and groups are dealt by it: those of much the same members come
together, and the sets are sent there once. A task compares what its groups bring together, pairs of one class never: every
link that it finds joins two classes, so it gives fewer links than it has vertices, and no pairs. What is too large for one
task is cut into buckets of vertices, a task for two buckets. Sets are made from the texts of those documents only that are
in a group, when they are needed. Shingles are compared by 64-bit hashes and meet by the first half of these; vertices are
named by the first row that holds their set.

Defined cases: null and empty texts form one group; fewer words than a shingle: the whole sequence is the only shingle; documents
with equal sets form one vertex; a null doc_id is the largest id; an empty table gives an empty result. Of every group one row
stays: that of the smallest doc_id, of the smallest hash of the text where ids repeat, and any one of rows that share both.
"""

from __future__ import annotations

from itertools import groupby

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.llm.common import KEY_ROWS, join_lookup, lean, materialize, one_of_each, own_prefix, text_key
from pointloom.llm.components import connected_components
from pointloom.llm.simhash import SEED, STEP, links
from pointloom.llm.wordshuffle import BLOCK, pack, row_of, unpack

SHINGLE, BITS = 5, 4
#: Similarity UP / DOWN, in whole numbers so that a pair just at the bound is linked.
UP, DOWN = 4, 5
#: Shingles and documents of a chunk (a document's number there has two bytes), and from where on counts are one.
CHUNK_SHINGLES, CHUNK_DOCS, MANY = 1 << 21, 1 << 16, 255
#: Vertices and bytes of their sets in a bucket, and documents in an Arrow batch that a task gives.
BUCKET, BUCKET_BYTES, DOCS = 512, 16 << 20, 500


def shingle_hashes(words: list[bytes]):
    """Arrays of the hashes of the words' shingles, in order; none without words."""
    digest, n = xxhash.xxh64_intdigest, max(1, len(words) - SHINGLE + 1)
    for at in range(0, n if words else 0, STEP):
        part = words[at : at + STEP + SHINGLE - 1] if n > 1 else words
        line = b" ".join(part)
        ends = np.cumsum(np.fromiter(map(len, part), np.int64, len(part)) + 1)
        k = min(SHINGLE, len(part))
        starts = np.concatenate(([0], ends[:-1]))[: len(part) - k + 1].tolist()
        yield np.array([digest(line[a:b], SEED) for a, b in zip(starts, (ends[k - 1 :] - 1).tolist(), strict=True)], np.uint64)


def majority(s: np.ndarray) -> int:
    """The bit-wise majority of a set's hashes, as a signed long; zero of none."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(s), STEP):
        ones += np.unpackbits(s[at : at + STEP].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits((ones * 2 > len(s)).astype(np.uint8), bitorder="little").view(np.int64)[0])


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted distinct hashes of the text's shingles."""
    parts = list(shingle_hashes((text or "").encode().lower().split()))
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Of two sorted sets that are not empty."""
    if len(a) > len(b):
        a, b = b, a
    if DOWN * len(a) < UP * len(b):
        return False
    both = int((b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a).sum())
    return DOWN * both >= UP * (len(a) + len(b) - both)


def _rows(docs: DataFrame) -> DataFrame:
    """row, doc_id, key (hash of the text), name of the set, fp, n of every document."""

    def run(batches):
        for b in batches:
            sets = (shingle_set(t.as_py()) for t in b.column(3))
            made = np.array([(xxhash.xxh64_intdigest(s.tobytes()), majority(s) & (2**64 - 1), len(s)) for s in sets], np.uint64).reshape(-1, 3).view(np.int64)
            yield pa.RecordBatch.from_arrays([*b.columns[:3], *(pa.array(np.ascontiguousarray(c)) for c in made.T)], ["row", "doc_id", "key", "name", "fp", "n"])

    read = docs.select(F.monotonically_increasing_id(), F.col("doc_id").cast("long"), text_key(docs), F.col("text").cast("string"))
    return materialize(read.mapInArrow(lean(run), "row long, doc_id long, key long, name long, fp long, n long"))


def _hash_blocks(bits: int):
    """Rows of scan partition and text -> by chunk, a block of (first half of the hash, document) for every shard, and a row of the
    sets' names and sizes with a negative shard. Equal sets of a chunk are one."""

    def done(chunk, held):
        names = np.array(list(held), np.uint64)
        sizes = np.array([len(s) for s in held.values()], np.int64)
        yield row_of(-1 - chunk % (1 << 30), chunk, pack(names, sizes))
        # sets are sorted, and so are the first halves of their hashes
        h = np.concatenate([(s >> np.uint64(32)).astype(np.uint32) for s in held.values()])
        order = np.argsort(h, kind="stable")
        h, doc = h[order], np.repeat(np.arange(len(sizes), dtype=np.uint16), sizes)[order]
        bounds = np.searchsorted(h, np.arange(1 << bits, dtype=np.uint64) << np.uint64(32 - bits))
        for k, (lo, hi) in enumerate(zip(bounds.tolist(), [*bounds[1:].tolist(), len(h)], strict=True)):
            if hi > lo:
                yield row_of(k, chunk, pack(np.diff(h[lo:hi], prepend=np.uint32(0)), doc[lo:hi]))

    def run(batches):
        held, total, seq, task = {}, 0, 0, 0
        for b in batches:
            for task, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                s = shingle_set(text.as_py())
                if len(s) and held.setdefault(xxhash.xxh64_intdigest(s.tobytes()), s) is s:
                    total += len(s)
                if total >= CHUNK_SHINGLES or len(held) >= CHUNK_DOCS:
                    yield from done((task << 24) + seq, held)
                    held, total, seq = {}, 0, seq + 1
        if held:
            yield from done((task << 24) + seq, held)

    return run


def _shared(batches):
    """Blocks in order of shard -> of every block, the documents, hashes and counts of what two or more sets hold."""
    for shard, rows in groupby((r for b in batches for r in b.to_pylist()), key=lambda r: r["bucket"]):
        if shard < 0:
            for r in rows:
                yield row_of(-1, r["chunk"], r["data"])
            continue
        chunks, hashes, docs = [], [], []
        for r in rows:
            h, doc = unpack(r["data"])
            chunks.append(r["chunk"])
            hashes.append(np.cumsum(h, dtype=np.uint32))
            docs.append(doc)
        _, of, n = np.unique(np.concatenate(hashes), return_inverse=True, return_counts=True)
        n = np.minimum(n, MANY)[of].astype(np.uint8)
        lo = 0
        for chunk, h, doc in zip(chunks, hashes, docs, strict=True):
            own = n[lo : lo + len(h)]
            lo += len(h)
            if (own > 1).any():
                yield row_of(shard, chunk, pack(doc[own > 1], h[own > 1], own[own > 1]))


def _entries(batches):
    """Rows in order of (chunk, shard), names and sizes first -> a row (s, name, n, left) for each leading shingle that is shared;
    left: the set's shingles from it on."""
    for _, rows in groupby((r for b in batches for r in b.to_pylist()), key=lambda r: r["chunk"]):
        names, sizes = unpack(next(rows)["data"])
        parts = [unpack(r["data"]) for r in rows]
        if not parts:
            continue
        doc, h, n = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.lexsort((h, n, doc))
        doc, h = doc[order].astype(np.int64), h[order]
        held = np.bincount(doc, minlength=len(sizes))
        # what no other set holds comes first
        place = np.arange(len(doc)) - np.repeat(np.cumsum(held) - held, held) + (sizes - held)[doc]
        lead = place < (sizes - -(-UP * sizes // DOWN) + 1)[doc]
        doc = doc[lead]
        yield pa.RecordBatch.from_arrays([pa.array(h[lead].astype(np.int64)), pa.array(names[doc].view(np.int64)), pa.array(sizes[doc]), pa.array(sizes[doc] - place[lead])], ["s", "name", "n", "left"])


class _Block:
    """The vertices that meet in a task, their sets and their classes, and the links found between these."""

    def __init__(self, sets: list[tuple[int, int, np.ndarray]], cross: bool):
        self.names, self.bucket = (np.array([x[k] for x in sets], np.int64) for k in (0, 1))
        self.sets, self.cross = [x[2] for x in sets], cross
        self.at = {v: k for k, v in enumerate(self.names.tolist())}
        self.n = np.array([len(x) for x in self.sets])
        self.counts = np.array([np.bincount((x >> np.uint64(56)).astype(np.int64), minlength=256) for x in self.sets], np.int32)
        self.label, self.by_class = np.arange(len(sets)), {}
        self.done = np.zeros((len(sets), len(sets)), bool)

    def group(self, rows) -> list[tuple[int, int]]:
        """Rows (vertex, left, class) of one shingle -> the links that join classes."""
        at = np.array([self.at[v] for v, _, _ in rows])
        left = np.array([x for _, x, _ in rows])
        for k, (_, _, c) in zip(at.tolist(), rows, strict=True):
            self._join(self.by_class.setdefault(c, k), k)
        found, n = [], self.n[at]
        for k in range(len(at) - 1):
            me, others = int(at[k]), at[k + 1 :]
            fits = (self.label[others] != self.label[me]) & ~self.done[me, others] & (DOWN * np.minimum(n[k + 1 :], n[k]) >= UP * np.maximum(n[k + 1 :], n[k]))
            fits &= (UP + DOWN) * np.minimum(left[k + 1 :], left[k]) >= UP * (n[k + 1 :] + n[k])
            if self.cross:
                fits &= self.bucket[others] != self.bucket[me]
            others = others[fits]
            self.done[me, others] = self.done[others, me] = True
            others = others[(UP + DOWN) * np.minimum(self.counts[others], self.counts[me]).sum(axis=1) >= UP * (self.n[others] + self.n[me])]
            for other in others.tolist():
                if self.label[other] != self.label[me] and similar(self.sets[me], self.sets[other]):
                    self._join(me, other)
                    found.append((int(self.names[me]), int(self.names[other])))
        return found

    def _join(self, a: int, b: int) -> None:
        x, y = sorted((int(self.label[a]), int(self.label[b])))
        if x != y:
            self.label[self.label == y] = x


def _within(batches):
    """Rows (anchor, i, j, s, vertex, bucket, left, class, shingles) in order, of each block the sets first -> links (a, b)."""
    rows = (r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True))
    for (_, i, j), own in groupby(rows, key=lambda r: r[:3]):
        block, sets, links_ = None, [], []
        for s, part in groupby(own, key=lambda r: r[3]):
            if s is None:
                sets = [(r[4], r[5], np.frombuffer(r[8], np.uint64)) for r in part]
                continue
            block = block or _Block(sets, i != j)
            links_ += block.group([(r[4], r[6], r[7]) for r in part])
        if links_:
            a, b = np.array(links_, np.int64).T
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])


def _sets(docs: DataFrame, vertices: DataFrame) -> DataFrame:
    """vertex, shingles of ``vertices`` (vertex, doc_id, key), made from the documents that they name."""
    own = own_prefix(docs)
    names = [own + c for c in ("null", "id", "key")]
    id_ = F.col("doc_id").cast("long")
    parts = (id_.isNull(), F.coalesce(id_, F.lit(0)))
    keyed = docs.select(*[c.alias(n) for c, n in zip((*parts, text_key(docs)), names, strict=True)], F.col("text").cast("string").alias(own + "text"))
    wanted = vertices.select("vertex", *[c.alias(n) for c, n in zip((*parts, F.col("key")), names, strict=True)])

    def run(batches):
        for b in batches:
            for lo in range(0, b.num_rows, DOCS):
                part = b.slice(lo, DOCS)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([shingle_set(t.as_py()).tobytes() for t in part.column(1)], pa.binary())], ["vertex", "shingles"])

    texts = join_lookup(keyed, wanted, names, "inner", KEY_ROWS).select("vertex", own + "text")
    # rows that share an id and a text have the same set
    return texts.mapInArrow(lean(run), "vertex long, shingles binary").dropDuplicates(["vertex"])


def compared(docs: DataFrame, groups_: DataFrame, vertices: DataFrame) -> DataFrame:
    """Links (a, b) between classes that the groups (anchor, s, vertex, n, left, class) bring together, less those that
    others of the same block imply. ``vertices``: vertex, doc_id, key."""
    members = materialize(groups_.select("anchor", "vertex", "n").distinct())
    cuts = members.groupBy("anchor").agg(F.greatest(F.ceil(F.count("*") / BUCKET), F.ceil(F.sum("n") * 8 / BUCKET_BYTES)).alias("cuts")).where("cuts > 1")
    cuts = materialize(cuts)

    def blocks(df):
        """Each row once for every block of its bucket."""
        cut = F.coalesce("cuts", F.lit(1))
        df = join_lookup(df, cuts, "anchor").withColumn("bucket", F.pmod(F.xxhash64("vertex"), cut))
        df = df.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), cut - 1)))
        return df.withColumns({"i": F.least("bucket", "other"), "j": F.greatest("bucket", "other")})

    none = F.lit(None)
    data = _sets(docs, materialize(join_lookup(vertices, materialize(members.select("vertex").distinct()), "vertex", "left_semi", KEY_ROWS)))
    sent = blocks(members).select("anchor", "i", "j", "vertex", "bucket").join(data, "vertex")
    sent = sent.select("anchor", "i", "j", none.cast("long").alias("s"), "vertex", "bucket", none.cast("long").alias("left"), none.cast("long").alias("class"), "shingles")
    dealt = blocks(groups_).select("anchor", "i", "j", "s", "vertex", "bucket", "left", "class", none.cast("binary").alias("shingles"))
    both = sent.union(dealt).repartition("anchor", "i", "j").sortWithinPartitions("anchor", "i", "j", F.col("s").asc_nulls_first())
    return materialize(both.mapInArrow(lean(_within), "a long, b long"))


def _first_pass(docs: DataFrame, distinct: DataFrame) -> DataFrame:
    """Links among what SimHash ties; every tie is a group of two."""
    prints = materialize(distinct.groupBy("fp").agg(F.min("vertex").alias("b")))
    equal = distinct.join(prints, "fp").select(F.col("vertex").alias("a"), "b")
    tied = materialize(links(prints.select("fp"), BITS))
    ends = [prints.select(F.col("fp").alias(x), F.col("b").alias("v" + x)) for x in ("a", "b")]
    near = tied.join(ends[0], "a").join(ends[1], "b").select(F.col("va").alias("a"), F.col("vb").alias("b"))
    ties = materialize(equal.union(near).where("a <> b"))
    two = ties.select(F.col("b").alias("anchor"), F.xxhash64("a", "b").alias("s"), F.explode(F.array("a", "b")).alias("vertex"))
    sized = join_lookup(two, distinct.select("vertex", "n"), "vertex", "inner", KEY_ROWS)
    return compared(docs, materialize(sized.select("anchor", "s", "vertex", "n", F.col("n").alias("left"), F.col("vertex").alias("class"))), distinct)


def leading_shared(docs: DataFrame, copies: DataFrame) -> DataFrame:
    """s, name, n, left of the leading shingles that two or more sets hold; ``copies``: doc_id and key of documents to leave out."""
    width = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    bits = max(1, int(np.ceil(np.log2(4 * width))))
    own = own_prefix(docs)
    id_, names = F.col("doc_id").cast("long"), [own + c for c in ("null", "id", "key")]
    parts = (id_.isNull(), F.coalesce(id_, F.lit(0)))
    keyed = docs.select(F.spark_partition_id().alias(own + "task"), F.col("text").cast("string").alias(own + "text"), *[c.alias(n) for c, n in zip((*parts, text_key(docs)), names, strict=True)])
    left_out = copies.select(*[c.alias(n) for c, n in zip((*parts, F.col("key")), names, strict=True)]).distinct()
    texts = join_lookup(keyed, left_out, names, "left_anti", KEY_ROWS).select(own + "task", own + "text")
    blocks = texts.mapInArrow(lean(_hash_blocks(bits)), BLOCK).repartition("bucket").sortWithinPartitions("bucket")
    answers = blocks.mapInArrow(lean(_shared), BLOCK).repartition("chunk").sortWithinPartitions("chunk", "bucket")
    return answers.mapInArrow(lean(_entries), "s long, name long, n long, left long")


def _second_pass(docs: DataFrame, named: DataFrame, classes: DataFrame) -> DataFrame:
    """Links between the classes (vertex, root), by the leading shingles that two or more of them share."""
    vertices = named.where("row = vertex and n > 0")
    # a copy with the id and the text of its vertex cannot be told from it
    copies = named.where("row <> vertex").select("doc_id", "key").exceptAll(vertices.select("doc_id", "key")) if named.where("row <> vertex").limit(1).count() else named.where("false")
    found = materialize(leading_shared(docs, materialize(copies.select("doc_id", "key"))))
    classed = join_lookup(vertices.select("name", "vertex"), classes, "vertex", "left", KEY_ROWS).select("name", "vertex", F.coalesce("root", "vertex").alias("class"))
    entries = materialize(join_lookup(found, materialize(classed), "name", "inner", KEY_ROWS).select("s", "vertex", "n", "left", "class").distinct())
    met = entries.groupBy("s").agg(F.min("class").alias("anchor"), F.max("class").alias("hi")).where("anchor <> hi").select("s", "anchor")
    groups_ = materialize(join_lookup(entries, materialize(met), "s", "inner", KEY_ROWS).select("anchor", "s", "vertex", "n", "left", "class"))
    return compared(docs, groups_, vertices.select("vertex", "doc_id", "key"))


def groups(docs: DataFrame) -> DataFrame:
    """doc_id, key (hash of the text), root (names the group) of every row of ``docs``."""
    rows = _rows(docs)
    first = rows.groupBy("name").agg(F.min("row").alias("vertex"))
    named = materialize(join_lookup(rows, materialize(first), "name", "inner", KEY_ROWS))
    ties = _first_pass(docs, named.where("row = vertex and n > 0"))
    classes = materialize(connected_components(ties))
    roots = materialize(connected_components(ties.union(_second_pass(docs, named, classes))))
    return join_lookup(named.select("doc_id", "key", "vertex"), roots, "vertex", "left", KEY_ROWS).select("doc_id", "key", F.coalesce("root", "vertex").alias("root"))


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of every group; see the module's head for which."""
    return one_of_each(docs, groups(docs))
