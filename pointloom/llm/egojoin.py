"""Embedding near-duplicates by the epsilon grid order join.

Unit vectors with cosine >= t are at most ``eps = sqrt(2 - 2t)`` apart. Vectors are rotated to principal axes (fitted on
a bounded sample; the rotation decides only what is skipped, never what is linked), ordered by their grid cells of side
``eps`` on the leading axes, and cut into intervals of that order. An interval keeps the box of its vectors on the leading
axes, with the length of what is left beside these axes as one more coordinate. Interval pairs are found by descending a tree
of boxes, and inside a pair the two sequences are halved again and again; wherever two boxes are provably more than
``eps`` apart, the whole block of pairs is skipped. What is left is compared by matrix products: single precision finds
candidates with a margin, double precision decides.

Intervals are joined in tiles, which are runs of the order: a task joins two tiles, so an interval is sent once a tile that
holds a partner of it, and not once a partner. Vectors are sent in the type that they came in.

Equal vectors (by a 128-bit hash) are one vertex with a count. A task returns each vertex's number of links and a spanning
forest of its links, never all pairs. Components are joined over all tasks.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components link with nothing (n_links 0,
their own component); vectors of different lengths do not link; rows that repeat a vector link with each other; rows
that repeat an id and a vector count as rows; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.llm.common import join_lookup, lean, materialize
from pointloom.llm.components import connected_components, unite
from pointloom.llm.vectors import block, dimensions, usable

COSINE = 0.95
AXES = 8
SAMPLE = 4096
#: Bytes of an interval (as doubles), and the most intervals that the directory of boxes may hold: the interval grows instead.
INTERVAL_BYTES, MAX_INTERVALS = 4 << 20, 100_000
#: Bytes of a tile (as doubles).
TILE_BYTES = 32 << 20
LEAF = 1024
#: Error that a single-precision product of unit vectors stays within.
MARGIN = 2e-5
#: Error of squared distances between boxes: the coordinate of the rest is a root of a difference.
SLACK = 1e-7


def _unit(x: np.ndarray) -> np.ndarray:
    # scaled first, so that squares neither overflow nor vanish
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _axes(sample: np.ndarray, k: int) -> np.ndarray:
    if not len(sample):
        return np.zeros((0, k))
    u = _unit(sample)
    _, vectors = np.linalg.eigh(np.cov(u.T).reshape(u.shape[1], -1) if len(u) > 1 else np.eye(u.shape[1]))
    return vectors[:, ::-1][:, :k]


def _leading(u: np.ndarray, axes: np.ndarray) -> np.ndarray:
    """Coordinates on the axes, and the length of the rest: none of them differs by more than the vectors do."""
    p = u @ axes
    return np.hstack([p, np.sqrt(np.maximum(0, 1 - (p**2).sum(axis=1, keepdims=True)))])


def _apart(lo_a, hi_a, lo_b, hi_b) -> np.ndarray:
    """Squared distance between boxes."""
    gap = np.maximum(0, np.maximum(lo_a - hi_b, lo_b - hi_a))
    return (gap**2).sum(axis=-1)


def partners(lo: np.ndarray, hi: np.ndarray, mine: int, eps: float) -> np.ndarray:
    """The intervals whose boxes are not provably farther than eps from interval ``mine``, by halving the sequence."""
    found, stack = [], [(0, len(lo))]
    while stack:
        a, b = stack.pop()
        if b <= a or _apart(lo[a:b].min(axis=0), hi[a:b].max(axis=0), lo[mine], hi[mine]) > eps**2 + SLACK:
            continue
        if b - a <= 16:
            near = _apart(lo[a:b], hi[a:b], lo[mine], hi[mine]) <= eps**2 + SLACK
            found.append(a + np.flatnonzero(near))
        else:
            stack += [(a, (a + b) // 2), ((a + b) // 2, b)]
    return np.sort(np.concatenate(found)) if found else np.zeros(0, np.int64)


def join_sequences(a, b, cosine: float, same: bool):
    """Links between two sequences of (unit float64, unit float32, leading coordinates): yields position pairs (i, j)."""
    eps2 = 2 - 2 * cosine + SLACK
    stack = [(0, len(a[0]), 0, len(b[0]))]
    while stack:
        a0, a1, b0, b1 = stack.pop()
        if a1 <= a0 or b1 <= b0 or same and b1 <= a0:
            continue
        pa_, pb = a[2][a0:a1], b[2][b0:b1]
        if _apart(pa_.min(axis=0), pa_.max(axis=0), pb.min(axis=0), pb.max(axis=0)) > eps2:
            continue
        if max(a1 - a0, b1 - b0) > LEAF:
            if a1 - a0 >= b1 - b0:
                m = (a0 + a1) // 2
                stack += [(a0, m, b0, b1), (m, a1, b0, b1)]
            else:
                m = (b0 + b1) // 2
                stack += [(a0, a1, b0, m), (a0, a1, m, b1)]
            continue
        i, j = np.nonzero(a[1][a0:a1] @ b[1][b0:b1].T >= np.float32(cosine - MARGIN))
        i, j = i + a0, j + b0
        if same:
            i, j = i[i < j], j[i < j]
        for lo in range(0, len(i), 1 << 16):
            x, y = i[lo : lo + (1 << 16)], j[lo : lo + (1 << 16)]
            linked = np.einsum("ij,ij->i", a[0][x], b[0][y]) >= cosine
            yield x[linked], y[linked]


def _intervals(axes: np.ndarray, length: int):
    """One row an interval of the task's ordered vectors: its place, box, vertices, counts and vectors."""

    def run(batches):
        task, seq, held = TaskContext.get().partitionId(), 0, []

        def row(parts):
            names, n, v = (np.concatenate(x) for x in zip(*parts, strict=True))
            p = _leading(_unit(v.astype(np.float64)), axes)
            return pa.RecordBatch.from_arrays(
                [pa.array([(task << 24) + seq]), pa.array([p.min(axis=0).tolist()]), pa.array([p.max(axis=0).tolist()]), pa.array([names.tobytes()], pa.binary()), pa.array([n.tobytes()], pa.binary()), pa.array([v.tobytes()], pa.binary())],
                ["place", "lo", "hi", "names", "n", "v"],
            )

        for b in batches:
            values = b.column(2).flatten().to_numpy(zero_copy_only=False)
            part = [b.column(0).to_numpy(), b.column(1).to_numpy(), values.reshape(b.num_rows, -1) if b.num_rows else values.reshape(0, 1)]
            while part[0].size:
                free = length - sum(len(x[0]) for x in held)
                held.append([x[:free] for x in part])
                part = [x[free:] for x in part]
                if sum(len(x[0]) for x in held) == length:
                    yield row(held)
                    seq, held = seq + 1, []
        if held:
            yield row(held)

    return run


def _tile_join(cosine: float, axes: np.ndarray, dim: int, kind: str, directory, per_tile: int):
    """Rows of the intervals of one or two tiles, in order -> (name, n_links, root): a spanning forest of the links."""
    eps = float(np.sqrt(2 - 2 * cosine))

    def sequence(v):
        u = _unit(np.frombuffer(v, kind).astype(np.float64).reshape(-1, dim))
        return u, u.astype(np.float32), _leading(u, axes)

    def join(s, t, rows):
        _, lo, hi = directory.value
        at = {mine: k for k, (mine, *_) in enumerate(rows)}
        names = [np.frombuffer(r[1], np.int64) for r in rows]
        n = [np.frombuffer(r[2], np.int64) for r in rows]
        seqs = [sequence(r[3]) for r in rows]
        off = np.concatenate(([0], np.cumsum([len(x) for x in names])))
        every = np.concatenate(names)
        count, label = np.zeros(len(every), np.int64), np.arange(len(every))
        for a in (m for m in at if m // per_tile == s):
            for b in partners(lo, hi, a, eps).tolist():
                if b // per_tile != t or b < a or b not in at:
                    continue
                x, y = at[a], at[b]
                for i, j in join_sequences(seqs[x], seqs[y], cosine, a == b):
                    i, j = i + off[x], j + off[y]
                    np.add.at(count, i, n[y][j - off[y]])
                    np.add.at(count, j, n[x][i - off[x]])
                    label = unite(label, i, j)
        hit = np.flatnonzero(count)
        return pa.RecordBatch.from_arrays([pa.array(every[hit]), pa.array(count[hit]), pa.array(every[label[hit]])], ["name", "n_links", "root"])

    def run(batches):
        rows = (r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True))
        for (s, t), own in groupby(rows, key=lambda r: r[:2]):
            yield join(s, t, [r[2:] for r in own])

    return run


def tile_count(vectors: int, per_tile: int, cores: int) -> int:
    """Tiles of the order: enough that their pairs occupy the cores, or that a tile keeps to its size."""
    pairs = next(t for t in range(1, cores + 2) if t * (t + 1) // 2 >= cores)
    return max(pairs, -(-vectors // per_tile))


def _links(vectors: DataFrame, dim: int, cosine: float) -> DataFrame:
    """name, n_links, root of distinct vectors (name, n, v), all of length ``dim``."""
    spark, eps = vectors.sparkSession, float(np.sqrt(2 - 2 * cosine))
    k = min(AXES, dim)
    sample = vectors.orderBy(F.xxhash64("name")).limit(SAMPLE).select("v").toArrow().column("v").combine_chunks()
    axes = _axes(block(sample), k)
    total = vectors.count()
    tiles = tile_count(total, max(1, TILE_BYTES // (8 * dim)), spark.sparkContext.defaultParallelism)
    # a tile is cut into whole intervals
    length = max(1, min(max(1, INTERVAL_BYTES // (8 * dim)), -(-total // tiles)), -(-total // MAX_INTERVALS))
    single = vectors.schema["v"].dataType.elementType.simpleString() == "float"

    def cells(batches):
        for b in batches:
            # cells as bytes in the order of their numbers
            c = (np.floor(_unit(block(b.column(2))) @ axes / eps).astype(np.int64) + (1 << 31)).astype(">u4")
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([x.tobytes() for x in c], pa.binary())], ["name", "n", "v", "cell"])

    kind = "float" if single else "double"
    placed = vectors.select("name", "n", F.col("v").cast(f"array<{kind}>")).mapInArrow(lean(cells), f"name long, n long, v array<{kind}>, cell binary")
    parts = max(1, -(-total // length))
    ordered = placed.repartitionByRange(parts, "cell", "name").sortWithinPartitions("cell", "name").select("name", "n", "v")
    intervals = materialize(ordered.mapInArrow(lean(_intervals(axes, length)), "place long, lo array<double>, hi array<double>, names binary, n binary, v binary"))
    # at most MAX_INTERVALS boxes and one more a partition
    boxes = sorted((r["place"], r["lo"], r["hi"]) for r in intervals.select("place", "lo", "hi").collect())
    per_tile = max(1, -(-len(boxes) // tiles))
    directory = spark.sparkContext.broadcast((np.array([x[0] for x in boxes]), np.array([x[1] for x in boxes]), np.array([x[2] for x in boxes])))

    def deal(batches):
        places, lo, hi = directory.value
        for b in batches:
            for at, place in enumerate(b.column(0).to_pylist()):
                mine = int(np.searchsorted(places, place))
                for other in sorted({x // per_tile for x in partners(lo, hi, mine, eps).tolist()}):
                    s, t = sorted((mine // per_tile, other))
                    yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([t], pa.int32()), pa.array([mine], pa.int32()), *b.slice(at, 1).columns[1:]], ["s", "t", "mine", "names", "n", "v"])

    dealt = intervals.select("place", "names", "n", "v").mapInArrow(lean(deal), "s int, t int, mine int, names binary, n binary, v binary")
    # pairs of tiles go round the partitions in turn
    width = max(1, min(tiles * (tiles + 1) // 2, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    turn = F.col("t") * (F.col("t").cast("long") + 1) / 2 + F.col("s")
    dealt = dealt.repartitionById(width, F.pmod(turn.cast("long"), F.lit(width)).cast("int")).sortWithinPartitions("s", "t", "mine")
    return dealt.mapInArrow(lean(_tile_join(cosine, axes, dim, "f4" if single else "f8", directory, per_tile)), "name long, n_links long, root long")


def near_duplicates(embeddings: DataFrame, cosine: float = COSINE) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row."""
    v = F.col("embedding")
    ok = usable(v) & F.exists("embedding", lambda x: x != 0) & F.col("vec_id").isNotNull()
    rows = embeddings.select(
        F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"), F.coalesce(ok, F.lit(False)).alias("ok"), F.monotonically_increasing_id().alias("name"),
        F.xxhash64(v).alias("k1"), F.xxhash64(F.lit(1), v).alias("k2"),
    )
    rows = materialize(rows)
    good = rows.where("ok")
    # a vertex is named by a row that holds its vector: ids may repeat
    classes = materialize(good.groupBy("k1", "k2").agg(F.min("name").alias("name"), F.min("vec_id").alias("vec"), F.count("*").alias("n")))
    vertices = materialize(join_lookup(good.select("name", "v"), classes.select("name", "n"), "name", "inner"))
    found = None
    for dim in dimensions(vertices):
        part = _links(vertices.where(F.size("v") == dim).select("name", "n", "v"), dim, cosine)
        found = part if found is None else found.union(part)
    if found is None:
        found = rows.where("false").select("name", F.lit(0).cast("long").alias("n_links"), F.col("name").alias("root"))
    found = materialize(found)
    roots = connected_components(found.select("name", "root").where("name <> root"))
    counted = found.groupBy("name").agg(F.sum("n_links").alias("linked"))
    named = classes.join(counted, "name", "left").join(roots.select(F.col("vertex").alias("name"), "root"), "name", "left").withColumn("root", F.coalesce("root", "name"))
    named = materialize(named.select("k1", "k2", "vec", "n", "linked", "root"))
    smallest = named.groupBy("root").agg(F.min("vec").alias("component_id"))
    named = materialize(named.join(smallest, "root").select("k1", "k2", (F.coalesce("linked", F.lit(0)) + F.col("n") - 1).cast("long").alias("n_links"), "component_id"))
    out = join_lookup(good.select("vec_id", "k1", "k2"), named, ["k1", "k2"], "inner").select("vec_id", "n_links", "component_id")
    alone = rows.where("not ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.union(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


ORACLE = r"""
WITH RECURSIVE v AS (
  SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
u AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS n FROM v),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.vec_id <> b.vec_id AND list_dot_product(a.e, b.e) >= 0.95::DOUBLE * a.n * b.n),
r(a, b) AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT u.vec_id, (SELECT count(*) FROM l WHERE l.a = u.vec_id)::BIGINT AS n_links,
       least(u.vec_id, coalesce((SELECT min(b) FROM r WHERE r.a = u.vec_id), u.vec_id))::BIGINT AS component_id,
       u.vec_id = least(u.vec_id, coalesce((SELECT min(b) FROM r WHERE r.a = u.vec_id), u.vec_id)) AS kept
FROM u
"""
