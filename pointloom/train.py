"""Training loops: gradients come from Spark tasks, the optimiser runs on the driver; parameters are small beside the data."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pointloom import nets
from pointloom.functions.fixed import draw
from pointloom.nets import ModelConfig, Var
from pointloom.operators import pixels
from pointloom.operators.baselines import fps_kernel, nearest_kernel
from pointloom.schema import PIECE, keep_freed, pieces, scratch_table

#: Points of a part of a supervised baseline, whose edges take many times the memory of its points.
EDGE_PIECE = 1 << 12
#: Values of a gradient row; larger tensors are cut, so the reduction is spread over tasks.
CHUNK = 1 << 16
#: Precision of a pass of the tasks over trained models; sums of gradients, the optimiser and the parameters are in double precision.
SINGLE = np.float32


def fixed(params: dict[str, np.ndarray], kind=np.float64) -> dict[str, Var]:
    """Parameters of a model that is not trained any more."""
    return {k: Var(np.asarray(v, kind), fixed=True) for k, v in params.items()}


def columns(clouds: DataFrame) -> tuple[str, ...]:
    """The columns that hold the points: packed ones, or the stored form of :mod:`pointloom.operators.pixels`."""
    return pixels.COLUMNS if "at" in clouds.columns else tuple("xyzrgb")


def _clouds(batch: pa.RecordBatch) -> nets.Clouds:
    names = batch.schema.names
    column = lambda c: batch.column(names.index(c))
    ids = column("sample_id").to_numpy()
    sizes = _sizes(batch)
    flat = lambda c: column(c).flatten().to_numpy(zero_copy_only=False)
    if "at" in names:
        pts = pixels.points(ids, *[column(c).to_numpy() for c in pixels.COLUMNS[:3]], sizes, *[flat(c) for c in pixels.COLUMNS[3:]])
    else:
        pts = np.stack([flat(c) for c in "xyzrgb"], 1)
    return nets.Clouds(np.split(pts, np.cumsum(sizes)[:-1]) if len(sizes) else [], ids)


def _sizes(batch: pa.RecordBatch) -> np.ndarray:
    names = batch.schema.names
    return pc.list_value_length(batch.column(names.index("at" if "at" in names else "x"))).to_numpy(zero_copy_only=False)


def _by_size(batch: pa.RecordBatch) -> pa.RecordBatch:
    """Clouds of about the same size stand together, so that little of a padded part is padding."""
    return batch.take(pa.array(np.argsort(_sizes(batch), kind="stable")))


def _parts(batches, clouds: int = 64, most: int = PIECE):
    """Parts of so many clouds and points, as one pass of a model takes them."""
    for b in batches:
        for piece in pieces(b := _by_size(b), _sizes(b), most):
            for lo in range(0, piece.num_rows, clouds):
                yield piece.slice(lo, clouds)


def pack(points: DataFrame) -> DataFrame:
    """Long clouds -> one packed row a sample, points in order of their number."""
    rows = F.array_sort(F.collect_list(F.struct("point_no", *"xyzrgb")))
    return points.groupBy("sample_id").agg(rows.alias("p")).select("sample_id", *[F.col(f"p.{c}").alias(c) for c in "xyzrgb"])


def spark_gradients(batch: DataFrame, params: dict[str, np.ndarray], loss_of, label: str | None = None, per_task: int = 64, most: int = PIECE) -> tuple[float, dict[str, np.ndarray]]:
    """:func:`arm_gradients` of one model, in double precision."""
    return arm_gradients(batch, [params], [loss_of], label, per_task, most, np.float64)[0]


def arm_gradients(batch: DataFrame, params: list[dict[str, np.ndarray]], loss_of: list[Callable], label: str | None = None, per_task: int = 64, most: int = PIECE, kind=SINGLE) -> list[tuple[float, dict[str, np.ndarray]]]:
    """Of every arm the mean loss and gradient over ``batch`` (packed clouds), all in one pass. ``loss_of[arm](clouds, labels, params)``
    runs in the tasks, on ``per_task`` clouds and ``most`` points at a time, which the arms share with their tokens; gradients are cut
    into chunks, summed by chunk in a shuffle of the parameters' size, and collected."""
    sent = batch.sparkSession.sparkContext.broadcast(params)

    def run(batches):
        keep_freed()
        models = [{k: np.asarray(v, kind) for k, v in p.items()} for p in sent.value]
        total, n, loss = [{} for _ in models], 0, [0.0] * len(models)
        for part in _parts(batches, per_task, most):
            labels = part.column(part.schema.names.index(label)).to_numpy(zero_copy_only=False) if label else None
            clouds, k = _clouds(part), part.num_rows
            n += k
            for arm, model in enumerate(models):
                value, grad, _ = nets.gradients(lambda p, arm=arm: loss_of[arm](clouds, labels, p), model)  # noqa: B023
                loss[arm] += value * k
                for name, g in grad.items():
                    total[arm][name] = total[arm].get(name, 0.0) + g.astype(np.float64) * k
        if not n:
            return
        for arm in range(len(models)):
            names, chunks, data = ["#loss"], [0], [np.array([loss[arm], n]).tobytes()]
            for name, g in total[arm].items():
                flat = np.ascontiguousarray(g).ravel()
                for c in range(0, max(1, len(flat)), CHUNK):
                    names.append(name)
                    chunks.append(c // CHUNK)
                    data.append(flat[c : c + CHUNK].tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([arm] * len(names), pa.int32()), pa.array(names), pa.array(chunks, pa.int32()), pa.array(data, pa.binary())], ["arm", "name", "chunk", "data"])

    def add(key, t):
        total = sum(np.frombuffer(x.as_py()) for x in t.column("data"))
        return pa.table({"arm": pa.array([key[0].as_py()], pa.int32()), "name": [key[1].as_py()], "chunk": pa.array([key[2].as_py()], pa.int32()), "data": [total.tobytes()]})

    schema = "arm int, name string, chunk int, data binary"
    cols = ["sample_id", *columns(batch), *([label] if label else [])]
    rows = batch.select(*cols).mapInArrow(run, schema).groupBy("arm", "name", "chunk").applyInArrow(add, schema).collect()
    sent.destroy()
    flat: list[dict[str, list]] = [{} for _ in params]
    for r in sorted(rows, key=lambda r: (r["name"], r["chunk"])):
        flat[r["arm"]].setdefault(r["name"], []).append(np.frombuffer(bytes(r["data"])))
    out = []
    for own, of in zip(params, flat, strict=True):
        if "#loss" not in of:
            out.append((float("nan"), {k: np.zeros_like(v) for k, v in own.items()}))
            continue
        loss, n = of.pop("#loss")[0]
        out.append((loss / n, {k: np.concatenate(v).reshape(own[k].shape) / n for k, v in of.items()}))
    return out


def representatives(clouds: DataFrame, cfg: ModelConfig) -> DataFrame:
    """Packed clouds with one point a voxel, the one that the tokeniser keeps: the tokens are the same, and every step of a training
    finds a fraction of the points. Other columns stay."""

    def run(batches):
        for b in (piece for whole in batches for piece in pieces(whole, _sizes(whole))):
            names, out = b.schema.names, {c: [] for c in "xyzrgb"}
            for pts in _clouds(b):
                kept = pts[nets.voxel_rows(pts, cfg)]
                for k, c in enumerate("xyzrgb"):
                    out[c].append(kept[:, k])
            yield pa.RecordBatch.from_arrays([pa.array(out[c], b.schema.field(c).type) if c in out else b.column(k) for k, c in enumerate(names)], names)

    return clouds.mapInArrow(run, clouds.schema)


def minibatches(clouds: DataFrame, size: int | None, seed: int = 0):
    """(number of minibatches, function of the step): the corpus is dealt once into hash classes of about ``size`` clouds, stored by
    class, so a step reads its class and nothing else. An epoch takes each class once, in an order of its own."""
    n = 1 if size is None else max(1, -(-clouds.count() // size))
    if n == 1:
        return 1, lambda step: clouds
    stored = scratch_table(clouds.withColumn("class", (draw(seed, F.col("sample_id")) % n).cast("int")).repartition("class"), "class")

    def of(step: int) -> DataFrame:
        order = np.random.default_rng([seed, step // n]).permutation(n)
        return stored.where(F.col("class") == int(order[step % n])).drop("class")

    return n, of


def pretrain(clouds: DataFrame, cfg: ModelConfig, steps: int = 6, batch: int | None = 256, percent: int = 60, terms=("mse", "cd", "occ"), lr: float = 5e-4, accum: int = 4, seed: int = 0, params=None):
    """(parameters, losses): masked reconstruction with a cosine rate, in minibatches of ``batch`` clouds (None: all), an update every
    ``accum`` iterations and one at the end. A cloud's mask depends on the epoch, the sample and the cell only."""
    return pretrain_arms(clouds, [(cfg, {"percent": percent, "terms": terms, "params": params})], steps, batch, lr, accum, seed)[0]


def pretrain_arms(clouds: DataFrame, arms: list[tuple[ModelConfig, dict]], steps: int = 6, batch: int | None = 256, lr: float = 5e-4, accum: int = 4, seed: int = 0) -> list[tuple[dict[str, np.ndarray], list[float]]]:
    """:func:`pretrain` for several (config, options), which take each step in one pass over the clouds."""
    models, losses = [o.get("params") or nets.init(cfg, seed) for cfg, o in arms], [[] for _ in arms]
    opts, held, since = [nets.AdamW(lr) for _ in arms], [None] * len(arms), 0
    n, part = minibatches(clouds, batch, seed)
    for step in range(steps):

        def loss_for(cfg, percent=60, terms=("mse", "cd", "occ"), params=None, epoch=step // n):
            def loss_of(batch, labels, p):
                t = nets.tokens_of(batch, cfg)
                return nets.pretrain_loss(t, nets.hide(t, percent, seed + epoch), p, cfg, terms)

            return loss_of

        got, since = arm_gradients(part(step), models, [loss_for(cfg, **{**o, "params": None}) for cfg, o in arms]), since + 1
        for k, (loss, grad) in enumerate(got):
            losses[k].append(loss)
            held[k] = grad if held[k] is None else {name: held[k][name] + g for name, g in grad.items()}
        if since == accum or step + 1 == steps:
            models = [opt.step(p, {k: g / since for k, g in h.items()}, nets.cosine(lr, step, steps)) for opt, p, h in zip(opts, models, held, strict=True)]
            held, since = [None] * len(arms), 0
    return list(zip(models, losses, strict=True))


def finetune(clouds: DataFrame, classes: int, cfg: ModelConfig, steps: int = 8, lr: float = 1e-2, params=None, seed: int = 0):
    """Tokeniser, encoder and a linear head on the class code are trained; the decoder is dropped. ``params`` None: no pre-training."""
    return finetune_arms(clouds, classes, [(cfg, params)], steps, lr, seed)[0]


def finetune_arms(clouds: DataFrame, classes: int, arms: list[tuple[ModelConfig, dict | None]], steps: int = 8, lr: float = 1e-2, seed: int = 0) -> list[tuple[dict[str, np.ndarray], list[float]]]:
    """:func:`finetune` for several (config, parameters), which take each step in one pass over the clouds."""
    models, losses, opts = [], [[] for _ in arms], [nets.AdamW(lr) for _ in arms]
    for cfg, params in arms:
        kept = {k: v for k, v in (params or nets.init(cfg, seed)).items() if not k.startswith(("dec.", "head.", "occ.", "mask", "adapt", "points."))}
        models.append(kept | {"class.w": np.zeros((cfg.width, classes)), "class.b": np.zeros(classes)})

    def loss_for(cfg):
        def loss_of(batch, labels, p):
            _, cls = nets.encode(nets.tokens_of(batch, cfg), p, cfg, "class")
            return nets.cross_entropy(nets.linear(cls, p, "class"), labels.astype(np.int64)), {}

        return loss_of

    for step in range(steps):
        got = arm_gradients(clouds, models, [loss_for(cfg) for cfg, _ in arms], "label")
        for k, (loss, grad) in enumerate(got):
            losses[k].append(loss)
            models[k] = opts[k].step(models[k], grad, nets.cosine(lr, step, steps))
    return list(zip(models, losses, strict=True))


def features(clouds: DataFrame, params: dict[str, np.ndarray], cfg: ModelConfig, keep: tuple[str, ...] = ()) -> DataFrame:
    """Class codes of every sample from the frozen encoder: sample_id, keep..., f array<double>."""
    return features_arms(clouds, [(cfg, params)], keep, np.float64).withColumnRenamed("f0", "f")


def features_arms(clouds: DataFrame, arms: list[tuple[ModelConfig, dict]], keep: tuple[str, ...] = (), kind=SINGLE) -> DataFrame:
    """:func:`features` of several (config, parameters) in one pass: sample_id, keep..., f0, f1, ... of the arms."""
    configs, sent = [cfg for cfg, _ in arms], clouds.sparkSession.sparkContext.broadcast([p for _, p in arms])
    out, names = clouds.select("sample_id", *keep, *columns(clouds)), [f"f{k}" for k in range(len(arms))]
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in out.schema if f.name in ("sample_id", *keep)) + "".join(f", {c} array<double>" for c in names)

    def run(batches):
        keep_freed()
        models = [(cfg, fixed(p, kind)) for cfg, p in zip(configs, sent.value, strict=True)]
        for part in _parts(batches):
            batch, head = _clouds(part), [part.column(k) for k in range(1 + len(keep))]
            codes = [nets.encode(nets.tokens_of(batch, cfg), p, cfg, "class")[1].value.astype(np.float64) for cfg, p in models]
            yield pa.RecordBatch.from_arrays([*head, *[pa.array(list(c), pa.list_(pa.float64())) for c in codes]], ["sample_id", *keep, *names])

    return out.mapInArrow(run, schema)


def accuracy_arms(clouds: DataFrame, arms: list[tuple[ModelConfig, dict]]) -> list[float]:
    """Share of the clouds whose label each fine-tuned (config, parameters) predicts, in one pass of which only counts leave the tasks."""
    configs, sent = [cfg for cfg, _ in arms], clouds.sparkSession.sparkContext.broadcast([p for _, p in arms])

    def run(batches):
        keep_freed()
        models, n, right = [(cfg, fixed(p, SINGLE)) for cfg, p in zip(configs, sent.value, strict=True)], 0, [0] * len(configs)
        for part in _parts(batches):
            batch, labels = _clouds(part), part.column(1).to_numpy()
            n += len(labels)
            for k, (cfg, p) in enumerate(models):
                _, cls = nets.encode(nets.tokens_of(batch, cfg), p, cfg, "class")
                right[k] += int((nets.linear(cls, p, "class").value.argmax(1) == labels).sum())
        yield pa.RecordBatch.from_arrays([pa.array(range(len(models)), pa.int32()), pa.array([n] * len(models), pa.int64()), pa.array(right, pa.int64())], ["arm", "n", "right"])

    rows = clouds.select("sample_id", "label", *columns(clouds)).mapInArrow(run, "arm int, n long, right long")
    got = {r["arm"]: r["right"] / max(1, r["n"]) for r in rows.groupBy("arm").agg(F.sum("n").alias("n"), F.sum("right").alias("right")).collect()}
    return [got.get(k, 0.0) for k in range(len(arms))]


def predict(clouds: DataFrame, params: dict[str, np.ndarray], cfg: ModelConfig, keep: tuple[str, ...] = ("label",)) -> DataFrame:
    """keep..., pred and the class scores of a fine-tuned model."""
    w, b = params["class.w"], params["class.b"]
    rows = features(clouds, params, cfg, keep)
    schema = rows.schema.simpleString()[7:-1] + ", pred int, score array<double>"

    def run(batches):
        for x in batches:
            score = np.stack([v.values.to_numpy() for v in x.column(x.num_columns - 1)]) @ w + b if x.num_rows else np.zeros((0, len(b)))
            yield pa.RecordBatch.from_arrays([*x.columns, pa.array(score.argmax(1).astype(np.int32)), pa.array(list(score), pa.list_(pa.float64()))], [*x.schema.names, "pred", "score"])

    return rows.mapInArrow(run, schema)


def linear_probe(feats: DataFrame, label: str = "label", max_iter: int = 50):
    """Multinomial logistic regression on frozen features (column f)."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    data = feats.select(F.col(label).cast("double").alias("label"), array_to_vector("f").alias("features"))
    return LogisticRegression(maxIter=max_iter, regParam=1e-3).fit(data)


def fewshot(labelled: DataFrame, way: int, shot: int, runs: int, query: int = 5, seed: int = 61) -> DataFrame:
    """Episodes: (run, way, shot, role, sample_id, label). A run draws ``way`` classes and ``shot`` + ``query`` samples of each, all
    by hashed order, ties by number."""
    from pyspark.sql import Window

    each = labelled.select("sample_id", "label").withColumn("run", F.explode(F.sequence(F.lit(1), F.lit(runs))))
    cls = each.select("run", "label").distinct().withColumn("n", F.row_number().over(Window.partitionBy("run").orderBy(draw(seed, F.col("run"), F.col("label")), "label"))).where(F.col("n") <= way)
    own = each.join(cls.select("run", "label"), ["run", "label"])
    order = Window.partitionBy("run", "label").orderBy(draw(seed + 1, F.col("run"), F.col("sample_id")), "sample_id")
    picked = own.withColumn("n", F.row_number().over(order)).where(F.col("n") <= shot + query)
    return picked.select("run", F.lit(way).alias("way"), F.lit(shot).alias("shot"), F.when(F.col("n") <= shot, "support").otherwise("query").alias("role"), "sample_id", "label")


def centroid_episodes(episodes: DataFrame, feats: DataFrame) -> DataFrame:
    """Accuracy of the nearest class centroid in every episode: (way, shot, run, accuracy); each episode is one small group."""
    rows = episodes.join(feats.select("sample_id", "f"), "sample_id")

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["label", "sample_id"])
        x, s = np.stack(pdf.f.to_list()), (pdf.role == "support").to_numpy()
        labels = pdf.label.to_numpy()
        cls = np.unique(labels)
        cent = np.stack([x[s & (labels == c)].mean(0) for c in cls])
        pred = cls[((x[~s][:, None] - cent[None]) ** 2).sum(-1).argmin(1)]
        return pd.DataFrame({"way": [key[0]], "shot": [key[1]], "run": [key[2]], "accuracy": [float((pred == labels[~s]).mean()) if (~s).any() else float("nan")]})

    return rows.groupBy("way", "shot", "run").applyInPandas(run, "way int, shot int, run int, accuracy double")


def trained_episodes(episodes: DataFrame, feats: DataFrame, steps: int = 60, rate: float = 0.5) -> DataFrame:
    """Accuracy of a softmax head trained on each episode's support set: (way, shot, run, accuracy)."""
    rows = episodes.join(feats.select("sample_id", "f"), "sample_id")

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["label", "sample_id"])
        x, s = np.stack(pdf.f.to_list()), (pdf.role == "support").to_numpy()
        x = (x - x[s].mean(0)) / (x[s].std(0) + 1e-6)
        cls, y = np.unique(pdf.label.to_numpy(), return_inverse=True)
        w, gold = np.zeros((x.shape[1] + 1, len(cls))), np.eye(len(cls))[y]
        x = np.hstack([x, np.ones((len(x), 1))])
        for _ in range(steps):
            z = x[s] @ w
            q = np.exp(z - z.max(1, keepdims=True))
            w += rate * (x[s].T @ (gold[s] - q / q.sum(1, keepdims=True)) / s.sum() - 1e-3 * w)
        right = (x[~s] @ w).argmax(1) == y[~s]
        return pd.DataFrame({"way": [key[0]], "shot": [key[1]], "run": [key[2]], "accuracy": [float(right.mean()) if (~s).any() else float("nan")]})

    return rows.groupBy("way", "shot", "run").applyInPandas(run, "way int, shot int, run int, accuracy double")


def point_features(clouds: list[np.ndarray], p: dict[str, Var], cfg: ModelConfig) -> Var:
    """Of every point: the code of its voxel's patch, or of the nearest centre of the fixed-token tokeniser, and its own attributes."""
    t = nets.tokens_of(clouds, cfg)
    codes, _ = nets.encode(t, p, cfg, "tokens")
    at, own = [], np.concatenate(clouds)
    if cfg.group:
        for s, pts in enumerate(clouds):
            mine = np.flatnonzero(t.sample == s)
            near, _ = nearest_kernel(t.corner[mine], pts[:, :3], 1)
            at.append(mine[near[:, 0]])
    else:
        wide = -(-cfg.grid // cfg.patch)
        names = t.sample * wide**3 + t.cell @ np.array([wide * wide, wide, 1])
        for s, pts in enumerate(clouds):
            key = np.clip(np.floor(pts[:, :3] * cfg.grid), 0, cfg.grid - 1).astype(np.int64) // cfg.patch
            at.append(np.searchsorted(names, s * wide**3 + key @ np.array([wide * wide, wide, 1])))
    rows = nets.take(codes, np.concatenate(at))
    both = np.concatenate([rows.value, own], 1)
    return Var(both, ((rows, lambda g: g[:, : rows.value.shape[1]]),))


def segment(clouds: DataFrame, parts: int, cfg: ModelConfig, steps: int = 8, lr: float = 1e-2, params=None, seed: int = 0):
    """Trains a per-point head (column ``zones``: part of each point); (parameters, losses)."""
    rng = np.random.default_rng(seed)
    params = {k: v for k, v in (params or nets.init(cfg, seed)).items() if not k.startswith(("dec.", "head.", "occ.", "mask", "adapt", "points."))}
    params |= {"part1.w": rng.normal(0, 0.1, (cfg.width + 6, 32)), "part1.b": np.zeros(32), "part2.w": rng.normal(0, 0.1, (32, parts)), "part2.b": np.zeros(parts)}
    opt, losses = nets.AdamW(lr), []

    def loss_of(batch, labels, p):
        x = point_features(batch, p, cfg)
        logit = nets.linear(nets.gelu(nets.linear(x, p, "part1")), p, "part2")
        return nets.cross_entropy(logit, np.concatenate(list(labels)).astype(np.int64)), {}

    for step in range(steps):
        loss, grad = spark_gradients(clouds, params, loss_of, "zones")
        losses.append(loss)
        params = opt.step(params, grad, nets.cosine(lr, step, steps))
    return params, losses


def segment_predict(clouds: DataFrame, params, cfg: ModelConfig) -> DataFrame:
    """category, sample_id, label, pred of every point."""
    sent = clouds.sparkSession.sparkContext.broadcast(params)

    def run(batches):
        p = {k: Var(v) for k, v in sent.value.items()}
        for b in _parts(batches):
            batch, names = _clouds(b), b.schema.names
            logit = nets.linear(nets.gelu(nets.linear(point_features(batch, p, cfg), p, "part1")), p, "part2").value
            n = [len(c) for c in batch]
            rep = lambda c: np.repeat(b.column(names.index(c)).to_numpy(), n)
            zones = np.concatenate([z.values.to_numpy() for z in b.column(names.index("zones"))])
            yield pa.RecordBatch.from_arrays([pa.array(rep("category").astype(np.int32)), pa.array(rep("sample_id")), pa.array(zones.astype(np.int32)), pa.array(logit.argmax(1).astype(np.int32))], ["category", "sample_id", "label", "pred"])

    return clouds.select("sample_id", "category", "zones", *"xyzrgb").mapInArrow(run, "category int, sample_id long, label int, pred int")


def supervised_shapes(form, classes: int, width: int = 32) -> dict[str, tuple[int, ...]]:
    """Tensors of a supervised baseline."""
    second = {hierarchical_logits: width + 3, edge_logits: 2 * width}.get(form, width)
    return {"p1.w": (6, width), "p1.b": (width,), "p2.w": (second, width), "p2.b": (width,), "p3.w": (width, width), "p3.b": (width,), "class.w": (width, classes), "class.b": (classes,)}


def supervised(clouds: DataFrame, classes: int, form=None, width: int = 32, steps: int = 8, lr: float = 1e-2, seed: int = 0):
    """Supervised baselines from scratch; (parameters, losses). ``form``: :func:`points_logits` (shared layers on every point, the
    cloud's maximum, a linear head), :func:`hierarchical_logits` or :func:`edge_logits`."""
    rng, form = np.random.default_rng(seed), form or points_logits
    params = {k: np.zeros(s) if k.endswith(".b") or k == "class.w" else rng.normal(0, 1 / np.sqrt(s[0]), s) for k, s in supervised_shapes(form, classes, width).items()}
    opt, losses = nets.AdamW(lr), []

    def loss_of(batch, labels, p):
        return nets.cross_entropy(form(batch, p), labels.astype(np.int64)), {}

    for step in range(steps):
        loss, grad = spark_gradients(clouds, params, loss_of, "label", most=EDGE_PIECE)
        losses.append(loss)
        params = opt.step(params, grad, nets.cosine(lr, step, steps))
    return params, losses


def supervised_predict(clouds: DataFrame, params, form) -> DataFrame:
    """label, pred of every sample."""
    sent = clouds.sparkSession.sparkContext.broadcast(params)

    def run(batches):
        p = {k: Var(v) for k, v in sent.value.items()}
        for part in _parts(batches, most=EDGE_PIECE):
            yield pa.RecordBatch.from_arrays([part.column(1), pa.array(form(_clouds(part), p).value.argmax(1).astype(np.int32))], ["label", "pred"])

    return clouds.select("sample_id", F.col("label").cast("int"), *"xyzrgb").mapInArrow(run, "label int, pred int")


def points_logits(batch: list[np.ndarray], p: dict[str, Var]) -> Var:
    owner = np.repeat(np.arange(len(batch)), [len(c) for c in batch])
    h = nets.relu(nets.linear(nets.relu(nets.linear(Var(np.concatenate(batch)), p, "p1")), p, "p2"))
    return nets.linear(nets.relu(nets.linear(nets.max_by(h, owner, len(batch)), p, "p3")), p, "class")


def _balls(clouds: list[np.ndarray], centres: int, radius: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of clouds (n, 3), whose rows stand one after the other: the sampled centres' rows, and (row, centre) of every point in the ball
    around a centre, by centre. Clouds of one size are worked on side by side."""
    sizes = np.array([len(c) for c in clouds])
    base, found = np.cumsum(sizes) - sizes, [None] * len(clouds)
    order = np.argsort(sizes, kind="stable")
    for same in np.split(order, np.flatnonzero(np.diff(sizes[order])) + 1):
        size = int(sizes[same[0]])
        for lo in range(0, len(same), step := max(1, nets.DISTANCES // max(1, size * min(centres, size)))):
            part = same[lo : lo + step]
            taken, far = nets.centres_of(np.stack([clouds[s] for s in part]), centres)
            for s, at, d in zip(part, taken, far, strict=True):
                found[s] = at, *np.nonzero(d <= radius**2)
    first = np.cumsum([0] + [len(at) for at, _, _ in found])
    places = [np.concatenate(x) for x in zip(*[(at + lo, near + lo, ball + c) for (at, ball, near), lo, c in zip(found, base, first, strict=False)], strict=True)]
    return places[0], places[1], places[2]


def hierarchical_logits(batch: list[np.ndarray], p: dict[str, Var], centres: tuple[int, int] = (16, 4), radius: tuple[float, float] = (0.2, 0.5)) -> Var:
    """Supervised baseline with two levels of sampled centres: the maximum in each ball of points, then in each ball of centres with
    their codes, then over the cloud. The first layer of a level is linear in a point's offset, so it is applied to points and to
    centres, of whose difference the ball's maximum is taken."""
    pts, sizes = np.concatenate(batch), np.array([len(c) for c in batch])
    at, near, ball = _balls([c[:, :3] for c in batch], centres[0], radius[0])
    own = {"p1.w": rows_of(p["p1.w"], 0, 3), "p1.b": nets.constant(np.zeros(p["p1.b"].value.shape), p["p1.b"])}
    best = nets.max_of(nets.linear(nets.constant(pts, p["p1.w"]), p, "p1"), near, ball, len(at))
    h = nets.relu(nets.add(best, nets.scale(nets.linear(nets.constant(pts[at, :3], p["p1.w"]), own, "p1"), -1.0)))
    xyz, cloud = pts[at, :3], np.repeat(np.arange(len(batch)), sizes)[at]
    top, near, ball = _balls([xyz[cloud == s] for s in range(len(batch))], centres[1], radius[1])
    width = h.value.shape[1]
    own = {"p2.w": rows_of(p["p2.w"], width, width + 3), "p2.b": nets.constant(np.zeros(p["p2.b"].value.shape), p["p2.b"])}
    best = nets.max_of(nets.linear(nets.beside(h, nets.constant(xyz, h)), p, "p2"), near, ball, len(top))
    h = nets.relu(nets.add(best, nets.scale(nets.linear(nets.constant(xyz[top], h), own, "p2"), -1.0)))
    return nets.linear(nets.max_by(nets.relu(nets.linear(h, p, "p3")), cloud[top], len(batch)), p, "class")


def rows_of(a: Var, lo: int, hi: int) -> Var:
    """Some rows of a parameter."""
    return nets.at_places(a, slice(lo, hi))


def edge_logits(batch: list[np.ndarray], p: dict[str, Var], k: int = 8) -> Var:
    """Supervised baseline on neighbour graphs: a layer on every edge's offset and the maximum at each point, once among the nearest
    points and once more among those with the nearest codes, then over the cloud. The layer is linear in both ends of an edge and
    rises with its sum, so each end is worked out once a point, and the maximum is taken of the other ends."""
    sizes = np.array([len(c) for c in batch])
    owner, ends = np.repeat(np.arange(len(batch)), sizes), np.cumsum(sizes)

    def edges(codes):
        """(point, neighbour) rows of the graphs of nearest codes, one cloud after the other."""
        a, b = [], []
        for lo, hi in zip(ends - sizes, ends, strict=True):
            near = nearest_rows(codes[lo:hi], k + 1)
            a.append(np.repeat(np.arange(lo, hi), near.shape[1]))
            b.append(near.ravel() + lo)
        return np.concatenate(a), np.concatenate(b)

    def layer(x, name):
        w, wide = p[f"{name}.w"], x.value.shape[1]
        offset = rows_of(w, wide, 2 * wide)
        here = nets.add(nets.matmul(x, nets.add(rows_of(w, 0, wide), nets.scale(offset, -1.0))), p[f"{name}.b"])
        a, b = edges(x.value)
        return nets.relu(nets.add(here, nets.max_of(nets.matmul(x, offset), b, a, len(owner))))

    h = layer(layer(nets.constant(np.concatenate(batch)[:, :3], p["p1.w"]), "p1"), "p2")
    return nets.linear(nets.max_by(nets.relu(nets.linear(h, p, "p3")), owner, len(batch)), p, "class")


def nearest_rows(x: np.ndarray, k: int, step: int = 512) -> np.ndarray:
    """For every row its k nearest rows, itself included, some rows at a time."""
    k, out, square = min(k, len(x)), [], (x**2).sum(1)
    for lo in range(0, len(x), step):
        d = x[lo : lo + step] @ (x.T * -2)
        d += square
        if k > 16:
            out.append(np.argpartition(d, k - 1, axis=1)[:, :k])
            continue
        # a few smallest are found faster one after the other
        row, near = np.arange(len(d)), np.empty((len(d), k), np.int64)
        for j in range(k):
            near[:, j] = d.argmin(1)
            d[row, near[:, j]] = np.inf
        out.append(near)
    return np.concatenate(out) if out else np.zeros((0, k), np.int64)


def save(spark: SparkSession, params: dict[str, np.ndarray], path: str) -> str:
    """Parquet of named tensors in a new version folder; the folder's name is returned."""
    rows = [(k, list(map(int, v.shape)), bytearray(np.ascontiguousarray(v, np.float64).tobytes())) for k, v in params.items()]
    out = f"{path}/version={uuid.uuid4().hex}"
    spark.createDataFrame(rows, "name string, shape array<int>, data binary").coalesce(1).write.parquet(out)
    return out


def restore(spark: SparkSession, path: str) -> dict[str, np.ndarray]:
    return {r["name"]: np.frombuffer(bytes(r["data"])).reshape(r["shape"]).copy() for r in spark.read.parquet(path).collect()}
