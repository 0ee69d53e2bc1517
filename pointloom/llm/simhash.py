"""SimHash near-duplicate groups by a binary trie self-join.

A document's fingerprint is the bit-wise majority of the XXH64 hashes of its word shingles. Two fingerprints within
``MAX_BITS`` differing bits agree exactly in one of ``MAX_BITS + 1`` blocks of bits, so the join is dealt out by
(block, value): each group is a sub-trie whose leading block is equal, and there the trie is joined with itself. Node
pairs are taken down together, differing bits are added up, and a pair is dropped as soon as they exceed the budget,
or once both nodes lie in one class already. A group yields a spanning forest of its links and never all pairs, so
a group of n fingerprints gives fewer than n rows. Groups above ``HOT`` fingerprints are dealt once more by the
blocks of their other bits. Components are then joined over all groups.

Defined cases: null and empty texts have fingerprint zero and are linked like any other; fewer words than a shingle:
the whole sequence is the only shingle; documents with equal fingerprints form one vertex; a null doc_id is never the
smallest id (a component without any other id has a null component_id); an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.llm.common import join_lookup, lean, materialize, one_of_each, text_key
from pointloom.llm.components import connected_components, unite

SHINGLE, SEED, MAX_BITS = 4, 42, 4
HOT = 1_000_000
#: Words taken at a time, so that a very long text needs bounded memory.
STEP = 1 << 16


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """Of the text's ASCII-lower-cased words; bytes.lower and bytes.split know ASCII only."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    digest, ones, n = xxhash.xxh64_intdigest, np.zeros(64, np.int64), max(1, len(words) - shingle + 1)
    for at in range(0, n, STEP):
        part = words[at : at + STEP + shingle - 1] if n > 1 else words
        line = b" ".join(part)
        ends = np.cumsum(np.fromiter(map(len, part), np.int64, len(part)) + 1)
        k = min(shingle, len(part))
        starts = np.concatenate(([0], ends[:-1]))[: len(part) - k + 1].tolist()
        h = np.array([digest(line[a:b], SEED) for a, b in zip(starts, (ends[k - 1 :] - 1).tolist(), strict=True)], np.uint64)
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    majority = (ones * 2 > n).astype(np.uint8)
    return int(np.packbits(majority, bitorder="little").view(np.int64)[0])


def fingerprints(docs: DataFrame, keyed: bool = False) -> DataFrame:
    """doc_id, fp (64 bits as a signed long), and ``key``, a hash of the text, if asked for."""

    def run(batches):
        for b in batches:
            fp = np.fromiter((fingerprint(t.as_py()) for t in b.column(1)), np.int64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp), *b.columns[2:]], ["doc_id", "fp", "key"][: b.num_columns])

    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), *([text_key(docs)] if keyed else []))
    return rows.mapInArrow(lean(run), "doc_id long, fp long" + (", key long" if keyed else ""))


def trie_links(fp: np.ndarray, budget: int = MAX_BITS, chunk: int = 1 << 15) -> np.ndarray:
    """Class labels of sorted distinct uint64 ``fp``: positions within ``budget`` bits, linked transitively.

    A node is a range of positions that share their leading bits. The frontier of node pairs is expanded in chunks,
    depth first, so memory stays bounded; small pairs are compared outright.
    """
    n = len(fp)
    label = np.arange(n)
    first = np.zeros(1, np.int64)
    stack = [(63, first, first + n, first, first + n, np.zeros(1, np.int8))]
    work, runs = 0, None
    while stack:
        bit, alo, ahi, blo, bhi, err = stack.pop()
        if len(alo) > chunk:
            stack.append((bit, alo[chunk:], ahi[chunk:], blo[chunk:], bhi[chunk:], err[chunk:]))
            alo, ahi, blo, bhi, err = (x[:chunk] for x in (alo, ahi, blo, bhi, err))
        if runs is None or work > n:
            runs, work = np.concatenate(([0], np.cumsum(label[1:] != label[:-1]))), 0
        settled = (runs[alo] == runs[ahi - 1]) & (runs[blo] == runs[bhi - 1]) & (label[alo] == label[blo])
        if settled.any():
            alo, ahi, blo, bhi, err = (x[~settled] for x in (alo, ahi, blo, bhi, err))
        size = (ahi - alo) * (bhi - blo)
        small = size <= 64 if bit >= 0 else np.ones(len(alo), bool)
        if small.any():
            a0, b0, width, total = alo[small], blo[small], (bhi - blo)[small], size[small]
            of = np.repeat(np.arange(len(total)), total)
            k = np.arange(len(of)) - np.repeat(np.cumsum(total) - total, total)
            i, j = a0[of] + k // width[of], b0[of] + k % width[of]
            near = np.bitwise_count(fp[i] ^ fp[j]) <= budget
            label = unite(label, i[near], j[near])
            work += len(of)
        if small.all():
            continue
        alo, ahi, blo, bhi, err = (x[~small] for x in (alo, ahi, blo, bhi, err))
        mask = np.uint64(1 << bit)
        mid_a, mid_b = _split(fp, alo, ahi, mask), _split(fp, blo, bhi, mask)
        same = alo == blo
        ways = [
            (alo, mid_a, mid_b, bhi, err + 1),
            (mid_a[~same], ahi[~same], blo[~same], mid_b[~same], err[~same] + 1),
            (alo, mid_a, blo, mid_b, err),
            (mid_a, ahi, mid_b, bhi, err),
        ]
        nxt = [np.concatenate(x) for x in zip(*ways, strict=True)]
        alive = (nxt[0] < nxt[1]) & (nxt[2] < nxt[3]) & (nxt[4] <= budget)
        work += len(alive)
        if alive.any():
            stack.append((bit - 1, *(x[alive] for x in nxt)))
    return label


def _split(fp, lo, hi, mask):
    """The first position in each range whose bit is set; all bits above are equal within a range."""
    lo, hi = lo.copy(), hi.copy()
    while (open_ := lo < hi).any():
        mid = (lo + hi) >> 1
        one = open_ & ((fp[np.minimum(mid, len(fp) - 1)] & mask) != 0)
        hi = np.where(one, mid, hi)
        lo = np.where(open_ & ~one, mid + 1, lo)
    return lo


def _block_bounds(bits: int, parts: int) -> list[tuple[int, int]]:
    cuts = [bits * k // parts for k in range(parts + 1)]
    return list(zip(cuts[:-1], cuts[1:], strict=True))


def _block(col, lo, hi):
    return F.shiftrightunsigned(col, lo).bitwiseAND(F.lit((1 << (hi - lo)) - 1))


def links(prints: DataFrame, budget: int = MAX_BITS) -> DataFrame:
    """Distinct fingerprints (column ``fp``) -> spanning links (a, b) of the groups of every block."""
    bounds = _block_bounds(64, budget + 1)
    fp = F.col("fp")
    keyed = prints.select(fp, F.posexplode(F.array(*[_block(fp, *x) for x in bounds])).alias("block", "value"))
    hot = materialize(keyed.groupBy("block", "value").count().where(F.col("count") > HOT).select("block", "value", F.lit(True).alias("hot")))
    if hot.limit(1).count():
        # the other bits of a hot group's members hold an equal block as well
        inner = []
        for k in range(len(bounds)):
            lo, hi = bounds[k]
            rest = F.shiftleft(F.shiftrightunsigned(fp, hi), lo).bitwiseOR(_block(fp, 0, lo)) if hi < 64 else _block(fp, 0, lo)
            inner.append(F.array(*[F.concat(F.lit(f"{j}:"), _block(rest, *x).cast("string")) for j, x in enumerate(_block_bounds(64 - (hi - lo), budget + 1))]))
        sub = F.element_at(F.array(*inner), F.col("block") + 1)
        keyed = keyed.join(F.broadcast(hot) if hot.count() < 100_000 else hot, ["block", "value"], "left")
        keyed = keyed.withColumn("sub", F.explode(F.when(F.col("hot"), sub).otherwise(F.array(F.lit("")))))
    else:
        keyed = keyed.withColumn("sub", F.lit(""))

    def run(batches):
        held, last = [], None
        for b in batches:
            if not b.num_rows:
                continue
            f = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            key = list(zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True))
            cuts = [0, *(k for k in range(1, len(key)) if key[k] != key[k - 1]), len(key)]
            done = []
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                if key[lo] != last:
                    done.append(held)
                    held, last = [], key[lo]
                held.append(f[lo:hi])
            yield from _forest(done)
        yield from _forest([held])

    def _forest(groups):
        a, b = [], []
        for held in groups:
            fps = np.concatenate(held) if held else np.zeros(0, np.uint64)
            if len(fps) > 1:
                fps = np.unique(fps)
                label = trie_links(fps, budget)
                tied = label != np.arange(len(fps))
                a.append(fps[tied])
                b.append(fps[label[tied]])
        if a:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a).view(np.int64)), pa.array(np.concatenate(b).view(np.int64))], ["a", "b"])

    dealt = keyed.select("fp", "block", "value", "sub").repartition("block", "value", "sub").sortWithinPartitions("block", "value", "sub")
    return dealt.mapInArrow(lean(run), "a long, b long")


def _components(prints: DataFrame, budget: int) -> tuple[DataFrame, DataFrame]:
    """Of rows with a fingerprint: the distinct ones with their smallest doc_id, and the root of those that have a link."""
    distinct = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), prints.count())
    n = distinct.count()
    # a group gives fewer links than it has members, and a fingerprint is in one group a block
    return distinct, materialize(connected_components(links(distinct.select("fp"), budget), (budget + 1) * n), n)


def groups(docs: DataFrame, budget: int = MAX_BITS) -> DataFrame:
    """doc_id, fp, component_id of every row of ``docs``."""
    prints = materialize(fingerprints(docs))
    distinct, roots = _components(prints, budget)
    tied = distinct.join(roots.withColumnRenamed("vertex", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    smallest = tied.groupBy("root").agg(F.min("least").alias("component_id"))
    by_print = tied.select("fp", "root").join(smallest, "root").select("fp", "component_id")
    return prints.join(by_print, "fp").select("doc_id", "fp", "component_id")


def simhash_report(docs: DataFrame) -> DataFrame:
    out = groups(docs)
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, budget: int = MAX_BITS) -> DataFrame:
    """One row of every group stays: that of the smallest doc_id (null is the largest), of the smallest hash of the text where
    ids repeat, and any one of rows that share both."""
    prints = materialize(fingerprints(docs, True))
    _, roots = _components(prints, budget)
    rooted = join_lookup(prints, roots.withColumnRenamed("vertex", "fp"), "fp")
    return one_of_each(docs, rooted.select("doc_id", "key", F.coalesce("root", "fp").alias("root")))
