"""Slot embedding: each voxel times the weight matrix of its slot, averaged over the patch; and position embeddings.

Attributes are micro-units and closed-form weights are hundredths, so a token's numerator over ``100 * L**2`` is an exact
integer and every path gives the same number.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pointloom.functions.fixed import fx6, sql_fx6
from pointloom.operators.patch import PATCH
from pointloom.schema import ATTRIBUTES

#: Multipliers of slot, feature and channel, and the modulus, of the closed-form weights.
FORM = (31, 17, 7, 101)
#: A weight bank beyond this many values is not joined as a table; the kernel path takes it as an array.
BANK_ROWS = 1_000_000


def weight(slot, f, c):
    """Closed-form weight in hundredths, for numbers, arrays or columns."""
    return (FORM[0] * slot + FORM[1] * f + FORM[2] * c) % FORM[3] - FORM[3] // 2


def closed_form(spark: SparkSession, a: int, n_features: int = 12, channels: int = 4) -> DataFrame:
    """The bank as a table (slot, f, c, w)."""
    n = a**3 * n_features * channels
    i = F.col("id")
    bank = spark.range(n).select((i / (n_features * channels)).cast("int").alias("slot"), ((i / channels).cast("int") % n_features).alias("f"), (i % channels).cast("int").alias("c"))
    return bank.withColumn("w", weight(F.col("slot"), F.col("f"), F.col("c")).cast("long"))


def closed_form_array(a: int, n_features: int = 12, channels: int = 4) -> np.ndarray:
    s, f, c = np.meshgrid(np.arange(a**3), np.arange(n_features), np.arange(channels), indexing="ij")
    return weight(s, f, c).astype(np.int64)


def random_init(a: int, n_features: int, channels: int, seed: int = 0) -> np.ndarray:
    return np.random.default_rng(seed).normal(0, math.sqrt(1 / n_features), (a**3, n_features, channels)).astype(np.float32)


def finish(tokens: DataFrame) -> DataFrame:
    """num -> the token in micro-units."""
    n = F.col("n_vox")
    return tokens.select(*PATCH, "n_vox", "c", F.col("num").cast("long").alias("num"), F.floor(F.col("num") / (n * n * 100) + 0.5).cast("long").alias("token_fx"))


def slot_embed(voxels: DataFrame, a: int, channels: int = 4, features: str = "graph", path: str = "onepass") -> DataFrame:
    """Tokens of voxels that have a cell and a slot: (sample_id, ci, cj, ck, n_vox, c, num, token_fx)."""
    return {"sql": _by_join, "onepass": _one_pass, "kernel": _by_kernel}[path](voxels, a, channels, features)


def _by_join(voxels, a, channels, features):
    """The definition: attributes in long form, joined with the bank on (slot, f)."""
    from pyspark.sql import Window

    w = Window.partitionBy(*PATCH)
    fx = {c: fx6(F.col(c)) for c in ATTRIBUTES}
    v = voxels.select(*PATCH, "slot", *[fx[c].alias(c) for c in ATTRIBUTES]).withColumn("n_vox", F.count("*").over(w))
    own = [F.col(c) * F.col("n_vox") for c in ATTRIBUTES]
    if features == "graph":
        v = v.withColumns({f"s{c}": F.sum(c).over(w) for c in "xyz"})
        own += [F.col(c) * F.col("n_vox") - F.col(f"s{c}") for c in "xyz"] + [F.col(f"s{c}") for c in "xyz"]
    n = len(own)
    if a**3 * n * channels > BANK_ROWS:
        raise ValueError("the bank is too large for a table; use the kernel path")
    long = v.select(*PATCH, "slot", "n_vox", F.posexplode(F.array(*own)).alias("f", "val"))
    bank = closed_form(voxels.sparkSession, a, n, channels)
    return finish(long.join(F.broadcast(bank), ["slot", "f"]).groupBy(*PATCH, "n_vox", "c").agg(F.sum(F.col("val") * F.col("w")).alias("num")))


def _one_pass(voxels, a, channels, features):
    """One aggregate a patch. With centre s/L, a token is (sum of (own U + p E) + s/L * sum of (K - E)) / L, where U, E, K are
    the rows of each slot's matrix for own attributes, offsets and centres; the sums are mergeable."""
    fx = {c: fx6(F.col(c)) for c in ATTRIBUTES}
    slot = F.col("slot").cast("long")
    aggs = [F.count("*").alias("n_vox"), *[F.sum(fx[c]).alias(f"s{c}") for c in "xyz"]]
    for ch in range(channels):
        direct = F.lit(0).cast("long")
        for f, c in enumerate(ATTRIBUTES):
            direct = direct + fx[c] * weight(slot, f, ch)
        if features == "graph":
            for j, c in enumerate("xyz"):
                direct = direct + fx[c] * weight(slot, 6 + j, ch)
                aggs.append(F.sum(weight(slot, 9 + j, ch) - weight(slot, 6 + j, ch)).alias(f"k{c}{ch}"))
        aggs.append(F.sum(direct).alias(f"d{ch}"))
    g = voxels.groupBy(*PATCH).agg(*aggs)
    nums = []
    for ch in range(channels):
        num = F.col("n_vox") * F.col(f"d{ch}")
        if features == "graph":
            for c in "xyz":
                num = num + F.col(f"s{c}") * F.col(f"k{c}{ch}")
        nums.append(num)
    return finish(g.select(*PATCH, "n_vox", F.posexplode(F.array(*nums)).alias("c", "num")))


def token_sums(fx: np.ndarray, slot: np.ndarray, patch: np.ndarray, bank: np.ndarray, features: str = "graph"):
    """Exact integer tokens: attributes (n, 6), slots and patch numbers (sorted) -> (voxels a patch, numerators (p, C))."""
    at = np.flatnonzero(np.concatenate(([True], patch[1:] != patch[:-1])))
    n = np.diff(np.append(at, len(patch)))
    each = np.repeat(n, n)[:, None]
    v = fx * each
    if features == "graph":
        s = np.repeat(np.add.reduceat(fx[:, :3], at), n, axis=0)
        v = np.hstack([v, fx[:, :3] * each - s, s])
    return n, np.add.reduceat(np.einsum("if,ifc->ic", v, bank[slot]), at)


def _by_kernel(voxels, a, channels, features):
    """Whole patches in one array operation: rows come together by sample, and the bank travels as an array."""
    n_features = 12 if features == "graph" else 6
    bank = closed_form_array(a, n_features, channels)
    sent = voxels.sparkSession.sparkContext.broadcast(bank)

    def run(batches):
        held = None
        for b in batches:
            t = pa.Table.from_batches([b])
            held = t if held is None else pa.concat_tables([held, t]).combine_chunks()
            key = np.stack([held.column(c).to_numpy() for c in PATCH], axis=1)
            last = int((key != key[-1]).any(axis=1).sum()) if len(key) else 0
            if last:
                yield from emit(held.slice(0, last))
                held = held.slice(last)
        if held is not None and held.num_rows:
            yield from emit(held)

    def emit(t):
        key = np.stack([t.column(c).to_numpy() for c in PATCH], axis=1)
        new = np.concatenate(([True], (key[1:] != key[:-1]).any(axis=1)))
        fx = np.stack([t.column(c).to_numpy() for c in ATTRIBUTES], axis=1)
        n, num = token_sums(fx, t.column("slot").to_numpy(), np.cumsum(new), sent.value, features)
        head, c = np.repeat(key[new], channels, axis=0), np.tile(np.arange(channels), len(n))
        yield pa.RecordBatch.from_arrays([pa.array(head[:, 0]), *[pa.array(head[:, k].astype(np.int32)) for k in (1, 2, 3)], pa.array(np.repeat(n, channels)), pa.array(c.astype(np.int32)), pa.array(num.ravel())], [*PATCH, "n_vox", "c", "num"])

    rows = voxels.select(*PATCH, "slot", *[fx6(F.col(c)).alias(c) for c in ATTRIBUTES]).repartition("sample_id").sortWithinPartitions(*PATCH)
    return finish(rows.mapInArrow(run, "sample_id long, ci int, cj int, ck int, n_vox long, c int, num long"))


def sql_tokens(a: int, channels: int = 4, features: str = "graph", source: str = "cells") -> str:
    """CTEs ``lv`` and ``tok`` by the definition."""
    fx = ", ".join(f"{sql_fx6(c)} AS {c}" for c in ATTRIBUTES)
    own = [f"{c} * n_vox" for c in ATTRIBUTES]
    if features == "graph":
        own += [f"{c} * n_vox - s{c}" for c in "xyz"] + [f"s{c}" for c in "xyz"]
    w = f"(({FORM[0]} * slot + {FORM[1]} * (f - 1) + {FORM[2]} * c) % {FORM[3]} - {FORM[3] // 2})"
    return f"""lv AS (SELECT *, [{', '.join(own)}] AS vec FROM (
      SELECT *, count(*) OVER w AS n_vox, {', '.join(f'(sum({c}) OVER w)::BIGINT AS s{c}' for c in 'xyz')}
      FROM (SELECT sample_id, ci, cj, ck, slot, {fx} FROM {source}) WINDOW w AS (PARTITION BY sample_id, ci, cj, ck))),
    tok AS (SELECT sample_id, ci, cj, ck, n_vox, c, sum(vec[f] * {w})::BIGINT AS num FROM lv, generate_series(1, {len(own)}) a(f), generate_series(0, {channels - 1}) b(c) GROUP BY ALL)"""


SQL_TOKEN_COLUMNS = "sample_id, ci, cj, ck, n_vox::BIGINT AS n_vox, c::INT AS c, num, floor(num / (n_vox * n_vox * 100) + 0.5::DOUBLE)::BIGINT AS token_fx"


# position embedding and attention --------------------------------------------------------------------------------


def gelu(x):
    """Tanh form, for columns."""
    return 0.5 * x * (1 + F.tanh(math.sqrt(2 / math.pi) * (x + 0.044715 * x * x * x)))


def pos_layer(i: int, o: int, which: int) -> float:
    """Closed-form weights of the two position embeddings (0 encoder, 1 decoder)."""
    return ((13 * i + 29 * o + 41 * which) % 23 - 11) / 16


def pos_embed(patches: DataFrame, a: int, size: int, which: int = 0, hidden: int = 3, out: int = 2) -> DataFrame:
    """Two linear layers with a GELU between them, of the corner in units of the grid: + p0.. in micro-units."""
    corner = [F.col(c) * F.lit(a / size) for c in ("ci", "cj", "ck")]
    mid = [gelu(sum((x * pos_layer(i, o, which) for i, x in enumerate(corner)), F.lit(0.0))) for o in range(hidden)]
    held = patches.withColumns({f"h{o}": m for o, m in enumerate(mid)})
    return held.select(*PATCH, *[fx6(sum((F.col(f"h{i}") * pos_layer(i + 3, o, which) for i in range(hidden)), F.lit(0.0))).alias(f"p{o}") for o in range(out)])


def sql_pos(a: int, size: int, which: int = 0, hidden: int = 3, out: int = 2) -> str:
    corner = [f"{c} * {a / size!r}::DOUBLE" for c in ("ci", "cj", "ck")]
    lin = lambda xs, off, o: "0.0::DOUBLE + " + " + ".join(f"{x} * {pos_layer(i + off, o, which)!r}::DOUBLE" for i, x in enumerate(xs))
    pre = ", ".join(f"{lin(corner, 0, o)} AS q{o}" for o in range(hidden))
    act = ", ".join(f"0.5::DOUBLE * q{o} * (1 + tanh({math.sqrt(2 / math.pi)!r}::DOUBLE * (q{o} + 0.044715::DOUBLE * q{o} * q{o} * q{o}))) AS h{o}" for o in range(hidden))
    outs = ", ".join(f"{sql_fx6(lin([f'h{i}' for i in range(hidden)], 3, o))} AS p{o}" for o in range(out))
    return f"SELECT sample_id, ci, cj, ck, {outs} FROM (SELECT *, {act} FROM (SELECT *, {pre} FROM (SELECT DISTINCT sample_id, ci, cj, ck FROM cells)))"


def attention_head(tokens: DataFrame) -> DataFrame:
    """One masked attention head over ragged samples: tokens (sample_id, pos, t array<double>) -> sums in micro-units.

    Only tokens of one sample see each other: the mask is the join's key, so no padding is made.
    """
    q, k = tokens.select("sample_id", F.col("pos").alias("qp"), F.col("t").alias("q")), tokens.select("sample_id", F.col("pos").alias("kp"), F.col("t").alias("k"))
    dot = F.aggregate(F.zip_with("q", "k", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    scores = q.join(k, "sample_id").withColumn("e", F.exp(dot / F.sqrt(F.size("q").cast("double"))))
    return scores.groupBy("sample_id", "qp").agg(F.sum("e").alias("den"), *[F.sum(F.col("e") * F.col("k")[c]).alias(f"n{c}") for c in range(4)]).select(
        "sample_id", F.col("qp").alias("pos"), *[fx6(F.col(f"n{c}") / F.col("den")).alias(f"o{c}") for c in range(4)]
    )
