"""Reconstruction losses as relational programs; a patch is a key, so nothing is compared across patches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.functions.fixed import fx6
from pointloom.operators.patch import PATCH

EPS = 1e-7
#: The nine attributes of the squared error: colours, offsets, centres. Without the graph only colours remain.
RELATIVE = ("r", "g", "b", "dx", "dy", "dz", "cx", "cy", "cz")


def relative_mse(true: DataFrame, pred: DataFrame, features: str = "graph", per_dim: bool = False) -> DataFrame:
    """Per patch: mean over the true voxels of the squared error over the relative attributes, in micro-units, voxels matched by
    slot; a voxel without a prediction is compared with zeros."""
    names = RELATIVE if features == "graph" else RELATIVE[:3]
    t = true.select(*PATCH, "slot", *[F.col(c).alias(f"t_{c}") for c in names])
    p = pred.select(*PATCH, "slot", *[F.col(c).alias(f"p_{c}") for c in names])
    err = F.lit(0.0)
    for c in names:
        d = F.col(f"t_{c}") - F.coalesce(F.col(f"p_{c}"), F.lit(0.0))
        err = err + d * d
    if per_dim:
        err = err / len(names)
    return t.join(p, [*PATCH, "slot"], "left").groupBy(*PATCH).agg((F.sum(fx6(err)) / F.count("*")).alias("mse_fx"))


def chamfer(true: DataFrame, pred: DataFrame) -> DataFrame:
    """Per patch: mean squared distance to the nearest point of the other set, both ways added, in micro-units. The sets may
    differ in size; voxels are told apart by their slot, points without one by their place. A patch without predicted points is as far as its points are from the origin."""
    name = lambda df: F.col("slot") if "slot" in df.columns else F.struct("x", "y", "z")
    t = true.select(*PATCH, F.struct("x", "y", "z").alias("t"), name(true).alias("ti"))
    p = pred.select(*PATCH, F.struct("x", "y", "z").alias("p"), name(pred).alias("pi"))
    d = F.lit(0.0)
    for c in "xyz":
        e = F.col("t")[c] - F.coalesce(F.col("p")[c], F.lit(0.0))
        d = d + e * e
    pairs = t.join(p, list(PATCH), "left").withColumn("d", d)
    ways = [pairs.where(F.col(i).isNotNull()).groupBy(*PATCH, i).agg(F.min("d").alias("d")).groupBy(*PATCH).agg((F.sum(fx6(F.col("d"))) / F.count("*")).alias(f"m_{i}")) for i in ("ti", "pi")]
    return ways[0].join(ways[1], list(PATCH), "left").select(*PATCH, (F.col("m_ti") + F.coalesce("m_pi", F.lit(0.0))).alias("cd_fx"))


def clamp(p):
    return F.greatest(F.lit(EPS), F.least(F.lit(1 - EPS), p))


def occupancy_dense(true: DataFrame, prob: DataFrame, a: int) -> DataFrame:
    """Per patch: binary cross-entropy over all slots; ``prob`` is (slot, p), shared by the patches."""
    slots = true.sparkSession.range(a**3).select(F.col("id").cast("int").alias("slot")).join(F.broadcast(prob), "slot", "left").withColumn("p", clamp(F.coalesce("p", F.lit(0.0))))
    own = true.groupBy(*PATCH).agg(F.collect_set("slot").alias("taken"))
    every = F.broadcast(slots.agg(F.array_sort(F.collect_list(F.struct("slot", "p"))).alias("every")))
    term = lambda s, taken: fx6(F.when(F.array_contains(taken, s["slot"]), -F.log(s["p"])).otherwise(-F.log(1 - s["p"])))
    total = F.aggregate(F.transform("every", lambda s: term(s, F.col("taken"))), F.lit(0).cast("long"), lambda x, y: x + y)
    return own.join(every).select(*PATCH, (total / a**3).alias("occ_fx"))


def occupancy_sparse(true: DataFrame, prob: DataFrame, a: int) -> DataFrame:
    """The same number from occupied slots only: the sum of the empty terms over all slots is shared, and corrected where a
    slot is taken."""
    p = clamp(F.coalesce(F.col("p"), F.lit(0.0)))
    empty, full = fx6(-F.log(1 - p)), fx6(-F.log(p))
    known = prob.withColumns({"e": empty, "f": full})
    rest = fx6(-F.log(1 - F.lit(EPS)))
    total = known.agg((F.coalesce(F.sum("e"), F.lit(0)) + (a**3 - F.count("*")) * rest).alias("every"))
    gain = F.coalesce(F.col("f") - F.col("e"), fx6(-F.log(F.lit(EPS))) - rest)
    own = true.select(*PATCH, "slot").join(F.broadcast(known), "slot", "left").groupBy(*PATCH).agg(F.sum(gain).alias("gain"))
    return own.join(F.broadcast(total)).select(*PATCH, ((F.col("every") + F.col("gain")) / a**3).alias("occ_fx"))


def packed_patches(voxels: DataFrame, names: tuple[str, ...]) -> DataFrame:
    """One row a patch: its voxels' slots and attributes in order of slot."""
    return voxels.groupBy(*PATCH).agg(F.array_sort(F.collect_list(F.struct("slot", *names))).alias("v"))


def patch_terms(true: DataFrame, pred: DataFrame, prob: DataFrame, a: int, features: str = "graph") -> DataFrame:
    """All three terms of every hidden patch in one pass: both sets are packed by patch (the same partitioning, so nothing is
    shuffled to join them) and a task compares the two arrays of a patch. Equal to the three operators above, bit by bit."""
    rel = RELATIVE if features == "graph" else RELATIVE[:3]
    names = tuple(dict.fromkeys(("x", "y", "z", *rel)))
    both = packed_patches(true, names).join(packed_patches(pred, names).withColumnRenamed("v", "w"), list(PATCH), "left")
    # a row a slot
    p = np.zeros(a**3)
    for r in prob.collect():
        p[r["slot"]] = r["p"]
    p = np.clip(p, EPS, 1 - EPS)
    fixed = lambda x: np.floor(x * 1e6 + 0.5).astype(np.int64)
    empty, full = fixed(-np.log(1 - p)), fixed(-np.log(p))
    every = int(empty.sum())

    def squared(d):
        out = np.zeros(d.shape[:-1])
        for k in range(d.shape[-1]):
            out = out + d[..., k] * d[..., k]
        return out

    def sets(column):
        """(slots, attributes, bounds) of a column of arrays of structs; null is no voxel."""
        flat, ends = column.flatten(), np.cumsum(pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False))
        slot = flat.field(0).to_numpy(zero_copy_only=False)
        return slot, np.stack([flat.field(k + 1).to_numpy(zero_copy_only=False) for k in range(len(names))], axis=1).reshape(len(slot), len(names)), np.concatenate(([0], ends)).astype(np.int64)

    rel_at = [names.index(c) for c in rel]

    def run(batches):
        for b in batches:
            (ts, tv, te), (ps, pv, pe) = sets(b.column(len(PATCH))), sets(b.column(len(PATCH) + 1))
            out = []
            for k in range(b.num_rows):
                s, t = ts[te[k] : te[k + 1]], tv[te[k] : te[k + 1]]
                q, w = ps[pe[k] : pe[k + 1]], pv[pe[k] : pe[k + 1]]
                made = np.zeros((len(s), len(rel_at)))
                if len(q):
                    at = np.minimum(np.searchsorted(q, s), len(q) - 1)
                    hit = q[at] == s
                    made[hit] = w[at[hit]][:, rel_at]
                mse = fixed(squared(t[:, rel_at] - made)).sum() / len(s)
                if len(q):
                    d = squared(t[:, None, :3] - w[None, :, :3])
                    cd = fixed(d.min(axis=1)).sum() / len(s) + fixed(d.min(axis=0)).sum() / len(q)
                else:
                    cd = fixed(squared(t[:, :3])).sum() / len(s)
                out.append((mse, cd, (every + int((full[s] - empty[s]).sum())) / a**3))
            columns = zip(*out, strict=True) if out else [()] * 3
            yield pa.RecordBatch.from_arrays([*b.columns[: len(PATCH)], *[pa.array(c, pa.float64()) for c in columns]], [*PATCH, "mse_fx", "cd_fx", "occ_fx"])

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in both.schema if f.name in PATCH)
    return both.select(*PATCH, "v", "w").mapInArrow(run, kinds + ", mse_fx double, cd_fx double, occ_fx double")


def total(true: DataFrame, pred: DataFrame, prob: DataFrame, a: int, terms=("mse", "cd", "occ"), weights=(1, 1, 1), features: str = "graph", reduce: str = "cloud") -> DataFrame:
    """All terms a patch, averaged over the patches of a cloud and then over clouds (``cloud``), or over patches. Every hidden
    patch counts, predicted or not."""
    parts = patch_terms(true, pred, prob, a, features)
    loss = F.lit(0.0)
    for name, w in zip(terms, weights, strict=False):
        loss = loss + F.col(f"{name}_fx") * w
    parts = parts.withColumn("loss_fx", loss)
    cols = ("mse_fx", "cd_fx", "occ_fx", "loss_fx")
    means = [*[(F.sum(F.floor(F.col(c) + 0.5).cast("long")) / F.count("*")).alias(c) for c in cols], F.count("*").alias("n_patches")]
    return parts.agg(*means) if reduce == "patch" else parts.groupBy("sample_id").agg(*means)


def arms_total(parts: DataFrame, arms: dict[str, tuple[str, ...]]) -> DataFrame:
    """Per cloud the mean loss of several arms, each a choice of terms, from the patches' terms: n_patches, l0, l1, ..."""
    loss = [sum((F.col(f"{t}_fx") for t in terms), F.lit(0.0)) for terms in arms.values()]
    return parts.groupBy("sample_id").agg(F.count("*").alias("n_patches"), *[(F.sum(F.floor(x + 0.5).cast("long")) / F.count("*")).alias(f"l{k}") for k, x in enumerate(loss)])


def mean_predictor(visible: DataFrame, hidden: DataFrame, a: int, edge: float) -> tuple[DataFrame, DataFrame]:
    """A prediction without learning: each hidden voxel gets the cloud's mean visible colours, its slot's centre as coordinates,
    and its true slot; slot probabilities are the share of visible patches that hold the slot."""
    colours = visible.groupBy("sample_id").agg(*[(F.sum(fx6(F.col(c))) / F.count("*") / F.lit(1000000.0)).alias(c) for c in "rgb"])
    at = {c: (F.col(k) + 0.5) * edge for c, k in zip("xyz", ("vi", "vj", "vk"), strict=True)}
    pred = hidden.select(*PATCH, "slot", *[at[c].alias(c) for c in "xyz"]).join(colours, "sample_id")
    patches = visible.select(*PATCH).distinct().count()
    prob = visible.groupBy("slot").agg((F.count("*") / F.lit(float(max(1, patches)))).alias("p"))
    return pred, prob


def pixel_mse(pixels: DataFrame, a: int) -> DataFrame:
    """Image loss: squared error of each patch's pixels against the patch's mean, in micro-units a pixel."""
    from pyspark.sql import Window

    w = Window.partitionBy("sample_id", "pu", "pv")
    px = pixels.withColumns({"pu": F.floor(F.col("u") / a).cast("int"), "pv": F.floor(F.col("v") / a).cast("int")})
    px = px.withColumn("m", F.sum(fx6(F.col("value"))).over(w) / F.count("*").over(w) / F.lit(1000000.0))
    d = F.col("value") - F.col("m")
    return px.groupBy("sample_id").agg((F.sum(fx6(d * d)) / F.count("*")).alias("mse_fx"))
