"""Exact top-k inner products by norm-bucketed retrieval.

Components become integers, ``floor(scale * x)``, so every product is exact. A task sorts its vectors by length and
cuts them into buckets. With the k-th best score so far, each query has a local cosine threshold in a bucket: that
score over (query length x longest vector of the bucket). Above 1 the query skips the bucket. Up to
``SHARP`` it prunes by length: only vectors long enough for any angle are verified. Above, it prunes by coordinate: the
query's strongest axes bound the cosine that a vector can reach. Whatever remains is verified
by exact products. Thresholds start from the corpus's longest vectors and only ever rise; a candidate is pruned only if
it is strictly below, so ties survive.

Memory is bounded by bytes at every place: a task holds ``HOLD_BYTES`` of candidates, a block of queries is ``QUERY_BYTES``,
and of queries x bucket only a tile of ``TILE_BYTES`` exists at a time. Queries are sent block by block, each a pass
over all rows whose result is appended to one table; a task returns at most k rows a query, and the last selection is
an ordered window limit per query. First thresholds are found in tasks as well.

Defined cases: vectors that are null, empty or hold null or non-finite components take no part, nor do null ids;
vectors of another length than the query's are no candidates; scores beyond 64 bits stop the job (overflow);
fewer than k candidates: all; repeated ids are rows of their own, but never candidates for a query of that id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pointloom.llm.common import lean, materialize, materialize_each
from pointloom.llm.vectors import block, dimensions, usable

K, SCALE = 10, 1024
#: Bytes of queries in a block, of candidates that a task holds, of the longest vectors, and of one tile of scores.
QUERY_BYTES, HOLD_BYTES, SEED_BYTES, TILE_BYTES = 32 << 20, 32 << 20, 2 << 20, 8 << 20
BUCKET_RATIO, BUCKET_ROWS = 0.9, 2048
SHARP, FOCUS = 0.8, 4
#: Of a tile's pairs, the share below which the remaining ones are multiplied one by one.
SPARSE = 1 / 32
#: Products of integers below this, summed over a vector, are exact in double precision.
EXACT = 2.0**53
#: Below every score; its negative exists.
NONE = np.iinfo(np.int64).min + 1
NO_ID = np.iinfo(np.int64).max
_SLACK = 1 - 1e-9


def integers(x: np.ndarray, scale: int = SCALE) -> np.ndarray:
    return np.floor(x * float(scale))


def _fits(q: np.ndarray, p: np.ndarray) -> bool:
    return not q.size or not p.size or np.abs(q).max() * np.abs(p).max() * q.shape[1] < EXACT


def products(q: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Exact integer inner products, as doubles where these hold them, else as int64."""
    if _fits(q, p):
        return q @ p.T
    as_int = np.frompyfunc(int, 1, 1)
    return np.dot(as_int(q).astype(object), as_int(p).astype(object).T).astype(np.int64)


class Best:
    """The k best (score, id) of every query so far; ties go to the smaller id."""

    def __init__(self, n: int, k: int):
        self.k = k
        self.score = np.full((n, k), NONE)
        self.vec = np.full((n, k), NO_ID)

    def add(self, rows: np.ndarray, score: np.ndarray, vec: np.ndarray) -> None:
        """Pairs of a query's number, a score and an id."""
        if not len(rows):
            return
        own = np.unique(rows)
        row = np.concatenate([np.repeat(own, self.k), rows])
        score = np.concatenate([self.score[own].ravel(), score])
        vec = np.concatenate([self.vec[own].ravel(), vec])
        order = np.lexsort((vec, -score, row))
        row = row[order]
        first = np.searchsorted(row, own)
        # every query has k entries already, so k follow its first
        take = order[(first[:, None] + np.arange(self.k)).ravel()]
        self.score[own], self.vec[own] = score[take].reshape(-1, self.k), vec[take].reshape(-1, self.k)


def retrieve(qid: np.ndarray, q: np.ndarray, pid: np.ndarray, p: np.ndarray, floor: np.ndarray, k: int = K) -> Best:
    """The k best of ``p`` for every query; ``floor`` is a score that the answer is known to reach."""
    best, q_len, p_len = Best(len(q), k), np.linalg.norm(q, axis=1), np.linalg.norm(p, axis=1)
    order = np.lexsort((pid, -p_len))
    pid, p, p_len = pid[order], p[order], p_len[order]
    at = 0
    while at < len(p):
        end = min(at + BUCKET_ROWS, int(np.searchsorted(-p_len, -BUCKET_RATIO * p_len[at], side="right")))
        end = max(end, at + 1)
        theta = np.maximum(floor, best.score[:, -1]).astype(np.float64)
        live = np.flatnonzero((theta <= 0) | (theta * _SLACK <= q_len * p_len[at]))
        if not len(live):
            # what follows is shorter still, and thresholds only rise
            break
        # queries that need vectors of about the same length share a tile
        need = np.divide(theta[live], q_len[live], out=np.zeros(len(live)), where=q_len[live] > 0)
        live = live[np.argsort(-need, kind="stable")]
        size = max(1, TILE_BYTES // (8 * (end - at)))
        for lo in range(0, len(live), size):
            _search(best, live[lo : lo + size], qid, q, q_len, pid[at:end], p[at:end], p_len[at:end], floor)
        at = end
    return best


def _search(best: Best, rows, qid, q, q_len, pid, p, p_len, floor) -> None:
    """One tile: some queries against one bucket."""
    theta = np.maximum(floor[rows], best.score[rows, -1])
    longest = q_len[rows] * p_len[0]
    local = np.divide(theta, longest, out=np.zeros(len(rows)), where=longest > 0)
    sharp = local > SHARP
    # length pruning: the tail of the bucket is too short for every query of the tile
    blunt = rows[~sharp]
    if len(blunt):
        need = np.divide(theta[~sharp], q_len[blunt], out=np.zeros(len(blunt)), where=q_len[blunt] > 0) * _SLACK
        stop = int(np.searchsorted(-p_len, -max(0.0, float(need.min())), side="right"))
        if stop:
            score = products(q[blunt], p[:stop])
            _keep(best, blunt, *np.nonzero(score >= theta[~sharp, None]), score, qid, pid)
    # coordinate pruning: on the query's strongest axes the angle bounds what a candidate can reach
    rows, theta, local = rows[sharp], theta[sharp], local[sharp] * _SLACK - 1e-9
    unit = p / np.where(p_len > 0, p_len, 1)[:, None] if len(rows) else p
    step = max(1, TILE_BYTES // (8 * FOCUS * len(p)))
    for lo in range(0, len(rows), step):
        some = rows[lo : lo + step]
        q_unit = q[some] / q_len[some, None]
        focus = np.argsort(-np.abs(q_unit), axis=1)[:, :FOCUS]
        b = np.take_along_axis(q_unit, focus, axis=1)
        a = unit[:, focus]
        rest = np.sqrt(np.maximum(0, 1 - (a**2).sum(axis=2)) * np.maximum(0, 1 - (b**2).sum(axis=1)))
        i, j = np.nonzero(((a * b).sum(axis=2) + rest).T >= local[lo : lo + step, None])
        if len(i) < SPARSE * len(some) * len(p) and _fits(q[some], p):
            parts = range(0, len(i), 1 << 14)
            exact = [np.einsum("ij,ij->i", q[some[i[x : x + (1 << 14)]]], p[j[x : x + (1 << 14)]]) for x in parts]
            exact = np.concatenate(exact) if exact else np.zeros(0)
        else:
            exact = products(q[some], p)[i, j]
        hit = exact >= theta[lo + i]
        i, j = i[hit], j[hit]
        score = exact[hit]
        own = qid[some[i]] != pid[j]
        best.add(some[i[own]], score[own].astype(np.int64), pid[j[own]])


def _keep(best: Best, rows, i, j, score, qid, pid) -> None:
    other = qid[rows[i]] != pid[j]
    i, j = i[other], j[other]
    best.add(rows[i], score[i, j].astype(np.int64), pid[j])


def top_k(embeddings: DataFrame, every: int = 100, k: int = K, scale: int = SCALE, query_bytes: int = QUERY_BYTES) -> DataFrame:
    """query_id, rank, vec_id, score: for every id divisible by ``every``, its k best among all other rows."""
    spark = embeddings.sparkSession
    rows = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v"))
    rows = materialize(rows.where(usable(F.col("v")) & F.col("vec_id").isNotNull()))

    def found():
        for dim in dimensions(rows):
            own = rows.where(F.size("v") == dim)
            norm = F.aggregate("v", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
            head = own.orderBy(norm.desc(), "vec_id").limit(max(k + 1, SEED_BYTES // (8 * dim))).toArrow()
            head = spark.sparkContext.broadcast((head.column("vec_id").to_numpy(), integers(block(head.column("v").combine_chunks()), scale)))
            queries = materialize(own.where(F.col("vec_id") % every == 0))
            # rows are dealt by their place, so that a repeated id does not swell a block; the table makes it the same in every run
            blocks = max(1, -(-queries.count() * 8 * dim // query_bytes))
            place = F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(blocks)).cast("int")
            dealt = materialize(queries.withColumn("block", place).mapInArrow(lean(_seeder(head, k, scale)), "block int, vec_id long, v array<double>, seed long"))
            for n in range(blocks):
                part = dealt.where(F.col("block") == n).toArrow()
                if part.num_rows:
                    sent = spark.sparkContext.broadcast((part.column("vec_id").to_numpy(), block(part.column("v").combine_chunks()), part.column("seed").to_numpy()))
                    yield own.mapInArrow(lean(_searcher(sent, k, scale)), "query_id long, vec_id long, score long")

    best = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    out = materialize_each(spark, found(), "query_id long, vec_id long, score long")
    return out.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _seeder(head, k, scale):
    """Queries -> their integer vectors, and the k-th best score among the longest vectors."""

    def run(batches):
        head_id, head_v = head.value
        for b in batches:
            qid, q = b.column(0).to_numpy(), integers(block(b.column(1)), scale)
            seed = retrieve(qid, q, head_id, head_v, np.full(len(q), NONE), k).score[:, -1]
            v = pa.ListArray.from_arrays(pa.array(np.arange(len(q) + 1, dtype=np.int32) * q.shape[1]), pa.array(q.ravel()))
            yield pa.RecordBatch.from_arrays([b.column(2), pa.array(qid), v, pa.array(seed)], ["block", "vec_id", "v", "seed"])

    return run


def _searcher(sent, k, scale):
    def search(held):
        qid, q, seed = sent.value
        pid, p = np.concatenate([x[0] for x in held]), np.concatenate([x[1] for x in held])
        held.clear()
        best = retrieve(qid, q, pid, p, seed, k)
        row, col = np.nonzero((best.score >= seed[:, None]) & (best.vec < NO_ID))
        return pa.RecordBatch.from_arrays([pa.array(qid[row]), pa.array(best.vec[row, col]), pa.array(best.score[row, col])], ["query_id", "vec_id", "score"])

    def run(batches):
        held, n = [], 0
        for b in batches:
            held.append((b.column(0).to_numpy(), integers(block(b.column(1)), scale)))
            n += held[-1][1].nbytes
            if n >= HOLD_BYTES:
                yield search(held)
                n = 0
        if held:
            yield search(held)

    return run


ORACLE = r"""
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS e FROM embeddings),
s AS (SELECT q.vec_id AS query_id, p.vec_id, list_dot_product(q.e, p.e)::BIGINT AS score
      FROM v q JOIN v p ON q.vec_id % 100 = 0 AND p.vec_id <> q.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
