"""The experiment workloads on stand-in corpora. Accuracies say that the machinery works; they are not comparable with the
published ones, which come from other data and much larger models. All runners give (workload, arm, metric, value, stderr)."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pointloom import nets, train
from pointloom.functions.fixed import draw
from pointloom.operators import augment, baselines, corpora, lift, measure, pixels
from pointloom.operators.tokenizer import CentreTokenizer, VoxelTokenizer
from pointloom.schema import ARMS, G32, keep_freed, load, pieces, scratch_table

FIXED = replace(nets.TINY, group=8)
#: Documents of a file of stored clouds: some 10 MB, which a scan takes as a task of its own.
FILE_DOCUMENTS = 10_000


def report(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    number = lambda r, k: float(r[k]) if len(r) > k and r[k] is not None else None
    return spark.createDataFrame([(*r[:3], number(r, 3), number(r, 4)) for r in rows], ARMS)


RHO, TAU, augmented = pixels.RHO, pixels.TAU, pixels.augmented
#: Depth teachers of the lifted corpus.
TEACHERS = {"near": lift.BlurTeacher(1), "wide": lift.BlurTeacher(3), "vowels": lift.KernelTeacher(lambda cps: corpora.image_colours(cps)[1])}
def _labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sample_id, label, is_test, text of every document. A language that is not among the four counts as the first."""
    docs = load(spark, sf_dir, "documents")
    label = F.greatest(F.lit(0), F.coalesce(F.array_position(F.array(*[F.lit(x) for x in ("de", "en", "es", "fr")]), F.col("lang")), F.lit(0)).cast("int") - 1)
    side = F.coalesce(F.conv(F.substring(F.md5("text"), 1, 8), 16, 10).cast("long") % 5 == 0, F.lit(False))
    return docs.select(F.col("doc_id").alias("sample_id"), label.alias("label"), side.alias("is_test"), "text")


def _dealt(docs: DataFrame) -> DataFrame:
    """Documents dealt out by number to a multiple of the cores, so that lifting, and every step that reads what it stored, keeps
    all cores busy to the end."""
    cores = docs.sparkSession.sparkContext.defaultParallelism
    return docs.repartition(cores * max(1, -(-docs.count() // (cores * FILE_DOCUMENTS))), "sample_id")


def _in_pieces(batches):
    """Parts of a batch of documents by their characters: a point takes 48 bytes, a character of text about one."""
    for b in batches:
        yield from pieces(b, pc.utf8_length(b.column(3)))


def document_clouds(spark: SparkSession, sf_dir: str, points: int | None = None, teacher: str = "near", rho: float = RHO, tau: float = TAU) -> DataFrame:
    """Lifted and augmented documents, packed: sample_id, x..b, language as label, and the split by text hash. Every document is a
    cloud; one without text has no points, and its class token alone speaks for it. ``points``: at most so many pixels of a cloud, drawn
    by the sample's number, as the fixed-size arm has it."""
    model = TEACHERS[teacher]

    def run(batches):
        for b in _in_pieces(batches):
            out = [[] for _ in range(6)]
            for sample, text in zip(b.column(0).to_pylist(), b.column(3).to_pylist(), strict=True):
                cps, at = pixels.code_points(text), None
                if points and len(cps) > points:
                    # all other pixels are left out before they are lifted
                    at = np.sort(np.random.default_rng(sample).permutation(len(cps))[:points])
                pts = np.stack(lift.lifted(cps, model, at), 1)
                pts = augmented(pts, sample, rho=rho, tau=tau)
                for c in range(6):
                    out[c].append(pts[:, c])
            yield pa.RecordBatch.from_arrays([*b.columns[:3], *[pa.array(x, pa.list_(pa.float64())) for x in out]], ["sample_id", "label", "is_test", *"xyzrgb"])

    return _dealt(_labelled(spark, sf_dir)).mapInArrow(run, "sample_id long, label int, is_test boolean, " + ", ".join(f"{c} array<double>" for c in "xyzrgb"))


def training_clouds(spark: SparkSession, sf_dir: str, cfg: nets.ModelConfig = nets.TINY, teacher: str = "near", rho: float = RHO, tau: float = TAU) -> DataFrame:
    """:func:`document_clouds` with one point a voxel, stored once in the form of :mod:`pointloom.operators.pixels`."""
    return training_arms(spark, sf_dir, ((rho, tau),), cfg, teacher)[0]


def training_arms(spark: SparkSession, sf_dir: str, moves, cfg: nets.ModelConfig = nets.TINY, teacher: str = "near") -> list[DataFrame]:
    """:func:`training_clouds` of several (rho, tau), stored side by side: the documents are read, lifted and turned once."""
    run = stored_form(TEACHERS[teacher], cfg, moves)
    schema = ", ".join(f"{name}{k} {kind}" for k in range(len(moves)) for name, kind in (c.split() for c in pixels.SCHEMA.split(", ")))
    stored = scratch_table(_dealt(_labelled(spark, sf_dir)).mapInArrow(run, f"sample_id long, label int, is_test boolean, {schema}"))
    return [stored.select("sample_id", "label", "is_test", *[F.col(f"{c}{k}").alias(c) for c in pixels.COLUMNS]) for k in range(len(moves))]


def stored_form(model, cfg: nets.ModelConfig, moves=((RHO, TAU),)):
    def run(batches):
        keep_freed()
        for b in _in_pieces(batches):
            kept = pixels.kept(b.column(0).to_pylist(), b.column(3).to_pylist(), model, lambda columns: nets.voxel_rows_of(columns, cfg), moves)
            yield pa.RecordBatch.from_arrays([*b.columns[:3], *[c for own in kept for c in own]], ["sample_id", "label", "is_test", *[f"{c}{k}" for k in range(len(moves)) for c in pixels.COLUMNS]])

    return run


def smallest_cloud(clouds: DataFrame, least: int) -> int:
    """Points of the smallest cloud that has ``least`` or more, to which the fixed-token arm cuts all larger ones."""
    n = F.size("x")
    return clouds.where(n >= least).agg(F.min(n)).first()[0] or least


def smallest_document(spark: SparkSession, sf_dir: str) -> int:
    """The same for the documents, whose pixels are their characters."""
    n = F.length("text")
    return load(spark, sf_dir, "documents").where(n >= FIXED.group).agg(F.min(n)).first()[0] or FIXED.group


def shape_samples(spark: SparkSession, sf_dir: str, level: str = "supplier", background: bool = True, points: int | None = None, classes: int = 10, copies: int = 0) -> DataFrame:
    """Packed shape clouds with label (family, or family x aspect), category, zones, and a split by hashed sample."""
    pts = corpora.shape_clouds(spark, sf_dir, level, background)
    if copies:
        pts = augment.perturb(pts, copies).withColumn("sample_id", F.col("sample_id") * 100 + F.col("copy"))
        pts = pts.withColumns({c: F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col(c))) for c in "xyz"})
    pts = baselines.downsample(pts, points) if points else pts
    label = F.col("family") if classes == 10 else F.col("family") * 4 + F.col("aspect")
    rows = F.array_sort(F.collect_list(F.struct("point_no", *"xyzrgb", "zone")))
    g = pts.groupBy("sample_id").agg(rows.alias("p"), F.first(label).cast("int").alias("label"), F.first("family").cast("int").alias("category"))
    origin = F.floor(F.col("sample_id") / 100) if copies else F.col("sample_id")
    return g.select("sample_id", "label", "category", (draw(71, origin) % 5 == 0).alias("is_test"), *[F.col(f"p.{c}").alias(c) for c in "xyzrgb"], F.col("p.zone").alias("zones"))


def _accuracy(pred: DataFrame) -> float:
    n, right = pred.agg(F.count("*"), F.sum((F.col("label") == F.col("pred")).cast("long"))).first()
    return (right or 0) / max(1, n)


def fit_and_score(data: DataFrame, classes: int, cfg: nets.ModelConfig, params=None, steps: int = 8, lr: float = 1e-2) -> float:
    return fit_arms(data, classes, [(cfg, params)], steps, lr)[0]


def fit_arms(data: DataFrame, classes: int, arms: list[tuple], steps: int = 8, lr: float = 1e-2) -> list[float]:
    """Accuracies of several (config, parameters) after fine-tuning on the same data."""
    models = train.finetune_arms(data.where(~F.col("is_test")), classes, arms, steps, lr)
    return train.accuracy_arms(data.where("is_test"), [(cfg, model) for (cfg, _), (model, _) in zip(arms, models, strict=True)])


def probe_accuracy(data: DataFrame, cfg: nets.ModelConfig, params) -> float:
    return probe_arms(data, [(cfg, params)])[0]


def side_by_side(*jobs) -> list:
    """Results of jobs that do not need each other: one's tasks run where another's have left cores idle."""
    with ThreadPoolExecutor(max(1, len(jobs))) as pool:
        return [f.result() for f in [pool.submit(job) for job in jobs]]


def probe_arms(data: DataFrame, arms: list[tuple]) -> list[float]:
    """Accuracies of linear probes on the frozen features of several (config, parameters): one pass makes all features, and the
    regressions, many short jobs each, run side by side."""
    from pyspark.ml.functions import array_to_vector

    f = scratch_table(train.features_arms(data, arms, ("label", "is_test")))

    def one(k: int) -> float:
        own = f.select("label", "is_test", F.col(f"f{k}").alias("f"))
        model = train.linear_probe(own.where(~F.col("is_test")))
        out = model.transform(own.where("is_test").select("label", array_to_vector("f").alias("features")))
        return _accuracy(out.select("label", F.col("prediction").cast("int").alias("pred")))

    return side_by_side(*[lambda k=k: one(k) for k in range(len(arms))])


def pretrained(clouds: DataFrame, cfg: nets.ModelConfig, steps: int, **options):
    """A short run of the published procedure: the whole corpus a step, and a rate that fits the tiny models."""
    return pretrained_arms(clouds, [(cfg, options)], steps)[0]


def pretrained_arms(clouds: DataFrame, arms: list[tuple], steps: int) -> list[tuple]:
    """The same for several (config, options) on one corpus."""
    return train.pretrain_arms(clouds, arms, steps, None, 5e-3, 1)


def majority(data: DataFrame) -> float:
    return measure.chance(data.where("is_test").select("label")).first()["majority"] or 0.0


def w01_tokenizer_cost(spark, sf_dir, levels=("part", "supplier", "nation", "region"), centres: bool = True) -> DataFrame:
    """Wall time and shuffles of both tokenisers by cloud size: on points of lineitem rows, and on documents by the digits of their
    number of characters. The centre-neighbour arm runs at its own sizes, and once more with centres in proportion to
    the points, where its cost is quadratic; the latter on clouds up to the supplier's size.

    Clouds of documents are packed rows, which both tokenisers take in one map without a shuffle. All their points would take fifty times the
    documents' bytes, so they are lifted on the way to the tokens; what that costs by itself is the arm "lift"."""
    rows = []

    def timed(arm: str, tokens: DataFrame) -> None:
        rows.extend(("w01", arm, k, float(v)) for k, v in measure.stage_cost(tokens).items())

    for level in levels:
        # points are made once, so that the arms are timed and not the corpus
        pts = scratch_table(corpora.lineitem_clouds(spark, sf_dir, level).select("sample_id", "point_no", *"xyzrgb"))
        timed(f"voxel, {level}", VoxelTokenizer(G32).transform(pts))
        if centres:
            timed(f"centre, {level}", CentreTokenizer().transform(pts))
            if level in ("part", "supplier"):
                mean = pts.groupBy("sample_id").count().agg(F.avg("count")).first()[0] or 1
                timed(f"centre, same density, {level}", CentreTokenizer(max(1, int(mean // measure.CNT_DENSITY)), measure.NEIGHBOURS).transform(pts))
    digits = F.length(F.coalesce(F.length("text"), F.lit(0)).cast("string"))
    docs = scratch_table(_dealt(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"), "text")).withColumn("digits", digits), "digits")
    for (k,) in sorted(docs.select("digits").distinct().collect()):
        own = docs.where(F.col("digits") == k)
        timed(f"lift, documents of {k} digits", lift.depth_table(own, "sample_id", "text"))
        timed(f"voxel, documents of {k} digits", VoxelTokenizer(G32).transform_texts(own, "sample_id", "text"))
        if centres:
            timed(f"centre, documents of {k} digits", CentreTokenizer().transform_texts(own, "sample_id", "text"))
    return report(spark, rows)


def corpus_texts(spark, sf_dir) -> dict[str, tuple[DataFrame, str, str]]:
    """(table, key, text) of every table that holds texts; a conversation's turn is an image."""
    talks = load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("key"), "text")
    out = {name: (load(spark, sf_dir, name), key, text) for name, key, text in (("documents", "doc_id", "text"), ("pages", "page_id", "html"), ("benchmark", "item_id", "text"))}
    return out | {"conversations": (talks, "key", "text")}


def corpus_parts(spark, sf_dir, teacher: str = "near") -> dict[str, DataFrame]:
    """Packed clouds (sample_id, n, x..b) of every table that holds texts or vectors."""
    out = {name: lift.lift_packed(corpora.packed_rasters(*source), TEACHERS[teacher]) for name, source in corpus_texts(spark, sf_dir).items()}
    vectors = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), F.transform("embedding", lambda v: (v.cast("double") + 1) / 2).alias("v"))
    at = lambda f: F.transform(F.sequence(F.lit(0), F.lit(63)), f)
    zero = at(lambda i: F.lit(0.0))
    out["vectors"] = vectors.select(
        "sample_id", F.lit(64).alias("n"), at(lambda i: (i % 8 + 0.5) / 8).alias("x"), F.col("v").alias("y"), at(lambda i: 1 - (F.floor(i / 8) + 0.5) / 8).alias("z"), F.col("v").alias("r"), zero.alias("g"), zero.alias("b")
    )
    return out


def w02_build_corpus(spark, sf_dir, path: str | None = None, teachers=("near", "wide", "vowels")) -> DataFrame:
    """The lifted corpus of all tables, with every depth teacher: clouds, points, the largest cloud and the sum of depths (micro-units) a
    table. Written to ``path`` if one is given, without a shuffle."""
    rows, texts = [], corpus_texts(spark, sf_dir)
    for teacher in teachers:
        for table, clouds in corpus_parts(spark, sf_dir, teacher).items():
            if teacher != teachers[0] and table == "vectors":
                continue
            if path:
                clouds.withColumns({"teacher": F.lit(teacher), "corpus": F.lit(table)}).write.mode("append").partitionBy("teacher", "corpus").parquet(path)
            if table in texts:
                # the same clouds, of which only the sums leave the tasks
                sums = lift.depth_table(*texts[table], TEACHERS[teacher])
            else:
                sums = clouds.select("n", F.aggregate("y", F.lit(0).cast("long"), lambda s, y: s + F.floor(y * 1000000 + 0.5).cast("long")).alias("sum_depth"))
            n, total, most, deep = sums.agg(F.count("*"), F.sum("n"), F.max("n"), F.sum("sum_depth")).first()
            rows += [("w02", f"{table} {teacher}", k, float(v or 0)) for k, v in (("clouds", n), ("points", total), ("largest", most), ("depth_fx", deep))]
    return report(spark, rows)


def w03_cross_table(spark, sf_dir, steps: int = 6) -> DataFrame:
    """Method x pre-training corpus, transferred to three splits of shape clouds; the arm "none" is not pre-trained, and the supervised
    arms start from scratch. The fixed-token method sees every corpus cut down to its smallest cloud."""
    makes = {
        "background": lambda: scratch_table(shape_samples(spark, sf_dir)),
        "object": lambda: scratch_table(shape_samples(spark, sf_dir, background=False)),
        "perturbed": lambda: scratch_table(shape_samples(spark, sf_dir, copies=5)),
        "lifted": lambda: training_clouds(spark, sf_dir),
        "cut": lambda: scratch_table(document_clouds(spark, sf_dir, smallest_document(spark, sf_dir))),
        "shapes": lambda: scratch_table(shape_samples(spark, sf_dir, "part", False, 32)),
    }
    made = dict(zip(makes, side_by_side(*makes.values()), strict=True))
    splits = {k: made[k] for k in ("background", "object", "perturbed")}
    size = min(side_by_side(*[lambda v=v: smallest_cloud(v, FIXED.group) for v in splits.values()]))
    small = dict(zip(splits, side_by_side(*[lambda v=v: scratch_table(cut_down(v, size)) for v in splits.values()]), strict=True))

    def chances() -> list[tuple]:
        return [("w03", "majority", split, majority(data)) for split, data in splits.items()]

    def transferred(method: str, cfg: nets.ModelConfig, corpora_: dict, data_: dict) -> list[tuple]:
        got = side_by_side(*[lambda clouds=clouds: pretrained(clouds, cfg, steps) for clouds in corpora_.values()])
        models, rows = {**dict(zip(corpora_, got, strict=True)), "none": (None, [])}, []
        # all models of a method pass over a split together
        scores = side_by_side(*[lambda data=data: fit_arms(data, 10, [(cfg, params) for params, _ in models.values()], steps) for data in data_.values()])
        for k, (name, (_, losses)) in enumerate(models.items()):
            rows += [("w03", f"{method} {name}", "first_loss", losses[0]), ("w03", f"{method} {name}", "last_loss", losses[-1])] if losses else []
            rows += [("w03", f"{method} {name}", split, own[k]) for split, own in zip(data_, scores, strict=True)]
        return rows

    def scratch(name: str, form, split: str) -> list[tuple]:
        params, _ = train.supervised(small[split].where(~F.col("is_test")), 10, form, steps=steps)
        return [("w03", f"supervised {name}", split, _accuracy(train.supervised_predict(small[split].where("is_test"), params, form)))]

    forms = {"points": train.points_logits, "hierarchical": train.hierarchical_logits, "edge graph": train.edge_logits}
    parts = side_by_side(
        chances,
        lambda: transferred("voxel", nets.TINY, {"lifted": made["lifted"], "shapes": made["shapes"]}, splits),
        lambda: transferred("fixed", FIXED, {"lifted": made["cut"], "shapes": made["shapes"]}, small),
        *[lambda name=name, form=form, split=split: scratch(name, form, split) for name, form in forms.items() for split in splits],
    )
    return report(spark, [row for rows in parts for row in rows])


def cut_down(packed: DataFrame, n: int) -> DataFrame:
    """At most ``n`` points of every packed cloud, drawn by the sample's number."""
    names = [c for c in packed.columns if c in (*"xyzrgb", "zones")]

    def run(batches):
        for b in batches:
            cols = {c: [] for c in names}
            for k, sample in enumerate(b.column(b.schema.names.index("sample_id")).to_pylist()):
                rows = [b.column(b.schema.names.index(c))[k].values.to_numpy(zero_copy_only=False) for c in names]
                at = np.sort(np.random.default_rng(sample).permutation(len(rows[0]))[:n])
                for c, x in zip(names, rows, strict=True):
                    cols[c].append(x[at])
            yield pa.RecordBatch.from_arrays([pa.array(cols[c], b.schema.field(c).type) if c in cols else b.column(k) for k, c in enumerate(b.schema.names)], b.schema.names)

    return packed.mapInArrow(run, packed.schema)


def w04_model_scaling(spark, sf_dir, steps: int = 6) -> DataFrame:
    clouds, data = training_clouds(spark, sf_dir), scratch_table(shape_samples(spark, sf_dir))
    rows = [("w04", "majority", "accuracy", majority(data))]
    arms = {"narrow": nets.TINY, "wide": nets.SMALL_TINY, "deep": replace(nets.TINY, blocks=3)}
    got = pretrained_arms(clouds, [(cfg, {}) for cfg in arms.values()], steps)
    scores = fit_arms(data, 10, [(cfg, params) for cfg, (params, _) in zip(arms.values(), got, strict=True)], steps)
    for (name, cfg), (_, losses), score in zip(arms.items(), got, scores, strict=True):
        rows += [("w04", name, "accuracy", score), ("w04", name, "parameters", float(cfg.n_params())), ("w04", name, "first_loss", losses[0]), ("w04", name, "last_loss", losses[-1])]
    rows += [("w04", name, "parameters", float(cfg.n_params())) for name, cfg in (("S", nets.S), ("B", nets.B), ("L", nets.L))]
    return report(spark, rows)


def raw_features(packed: DataFrame) -> DataFrame:
    """Mean and deviation of every attribute of a cloud: what a baseline without any model sees."""
    stats = []
    for c in "xyzrgb":
        n = F.greatest(F.lit(1), F.size(c))
        mean = F.aggregate(c, F.lit(0.0), lambda s, v: s + v) / n
        square = F.aggregate(c, F.lit(0.0), lambda s, v: s + v * v) / n
        stats += [mean, F.sqrt(F.greatest(F.lit(0.0), square - mean * mean))]
    return packed.select("sample_id", "label", F.array(*stats).alias("f"))


def w05_fewshot(spark, sf_dir, runs: int = 10, steps: int = 6) -> DataFrame:
    """Episodes on frozen features of shape clouds: of a pre-trained encoder, of a random one and of plain attribute statistics, by the
    nearest centroid and by a trained head; and on vectors whose label carries no signal."""
    shapes = scratch_table(shape_samples(spark, sf_dir))
    model, _ = pretrained(training_clouds(spark, sf_dir), nets.TINY, steps)
    vectors = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), "label", F.col("embedding").cast("array<double>").alias("f"))
    feats = {"pretrained": train.features(shapes, model, nets.TINY, ("label",)), "random": train.features(shapes, nets.init(nets.TINY), nets.TINY, ("label",)), "attributes": raw_features(shapes), "control": vectors}
    rows = []
    for arm, data in feats.items():
        data = scratch_table(data.select("sample_id", F.col("label").cast("int").alias("label"), "f"))
        episodes = None
        for way in (5, 10):
            for shot in (10, 20):
                e = train.fewshot(data.select("sample_id", "label"), way, shot, runs)
                episodes = e if episodes is None else episodes.union(e)
        episodes = scratch_table(episodes)
        for head, run in (("centroid", train.centroid_episodes), ("trained head", train.trained_episodes)):
            for got in measure.mean_se(run(episodes, data).where("not isnan(accuracy)"), ["way", "shot"], "accuracy").orderBy("way", "shot").collect():
                rows.append(("w05", f"{arm}, {head}", f"{got['way']} way {got['shot']} shot", got["mean"], got["se"]))
    return report(spark, rows)


def w06_cad_voting(spark, sf_dir, rounds: int = 3, steps: int = 6) -> DataFrame:
    """40 classes (family x aspect) with as many points a cloud as the smallest has; scores of perturbed copies are averaged."""
    whole = scratch_table(shape_samples(spark, sf_dir, classes=40, background=False))
    size = smallest_cloud(whole, 1)
    data = scratch_table(cut_down(whole, size))
    model, _ = train.finetune(data.where(~F.col("is_test")), 40, nets.TINY, steps)
    single = _accuracy(train.predict(data.where("is_test"), model, nets.TINY))
    voted = _accuracy(voted_labels(spark, sf_dir, model, rounds, 40, size))
    return report(spark, [("w06", "majority", "accuracy", majority(data)), ("w06", "single", "accuracy", single), ("w06", f"voted {rounds}", "accuracy", voted), ("w06", "single", "points", float(size))])


def voted_labels(spark, sf_dir, model, rounds: int, classes: int, size: int) -> DataFrame:
    copies = cut_down(shape_samples(spark, sf_dir, classes=classes, background=False, copies=rounds).where("is_test"), size)
    scores = train.predict(copies, model, nets.TINY, ("label",)).select(F.floor(F.col("sample_id") / 100).alias("sample_id"), "label", F.posexplode("score").alias("class", "s"))
    best = measure.vote(scores.select("sample_id", "class", F.floor(F.col("s") * 1000000).cast("long").alias("score_fx")))
    return best.join(scores.select("sample_id", "label").distinct(), "sample_id").select("sample_id", "label", "pred")


def w07_part_segmentation(spark, sf_dir, steps: int = 10) -> DataFrame:
    """Parts of points by features of the voxel tokeniser and of the centre-neighbour one."""
    data, rows = scratch_table(shape_samples(spark, sf_dir, background=False)), []
    for arm, cfg in (("voxel", nets.TINY), ("centre", FIXED)):
        model, losses = train.segment(data.where(~F.col("is_test")), 3, cfg, steps)
        got = measure.miou(train.segment_predict(data.where("is_test"), model, cfg)).first()
        rows += [("w07", arm, "class_miou", (got["class_miou_fx"] or 0) / 1e6), ("w07", arm, "instance_miou", (got["instance_miou_fx"] or 0) / 1e6), ("w07", arm, "first_loss", losses[0]), ("w07", arm, "last_loss", losses[-1])]
    return report(spark, rows)


def _ablate(spark, name, arms, make, data: DataFrame, steps: int) -> DataFrame:
    """make(arm) -> (clouds, config, pretrain options). Arms on the same clouds are pre-trained together, and all are fine-tuned and
    probed together on the labelled ``data``."""
    made, corpora_ = [make(arm) for arm in arms], {}
    for k, (clouds, _, _) in enumerate(made):
        corpora_.setdefault(id(clouds), []).append(k)
    groups, got = list(corpora_.values()), {}
    for own, models in zip(groups, side_by_side(*[lambda own=own: pretrained_arms(made[own[0]][0], [made[k][1:] for k in own], steps) for own in groups]), strict=True):
        got |= dict(zip(own, models, strict=True))
    models = [(made[k][1], got[k][0]) for k in range(len(made))]
    fitted, probed = side_by_side(lambda: fit_arms(data, 4, models, steps), lambda: probe_arms(data, models))
    scores, rows = list(zip(arms, fitted, probed, strict=True)), []
    for k, (arm, ft, lin) in enumerate(scores):
        rows += [(name, str(arm), "ft", ft), (name, str(arm), "lin", lin), (name, str(arm), "first_loss", got[k][1][0]), (name, str(arm), "last_loss", got[k][1][-1])]
    return report(spark, [(name, "majority", "ft", majority(data)), *rows])


def w08a_mask_ratio(spark, sf_dir, steps: int = 6, ratios=(15, 30, 45, 60, 75, 90)) -> DataFrame:
    d = training_clouds(spark, sf_dir)
    return _ablate(spark, "w08a", ratios, lambda r: (d, nets.TINY, {"percent": r}), d, steps)


def w08b_augmentation(spark, sf_dir, steps: int = 6) -> DataFrame:
    arms = {"none": (1.0, 0.0), "3/4": (3 / 4, 0.0), "2/3": (2 / 3, 0.0), "1/2": (1 / 2, 0.0), "1/2+T": (1 / 2, 1 / 2)}
    # documents are lifted once for all arms and for the data, which may be one of them
    moves = list(dict.fromkeys([(RHO, TAU), *arms.values()]))
    clouds = dict(zip(moves, training_arms(spark, sf_dir, moves), strict=True))
    return _ablate(spark, "w08b", arms, lambda a: (clouds[arms[a]], nets.TINY, {}), clouds[RHO, TAU], steps)


def w08c_attributes_losses(spark, sf_dir, steps: int = 6) -> DataFrame:
    d = training_clouds(spark, sf_dir)
    arms = {"graph mse": ("graph", ("mse",)), "graph mse+cd": ("graph", ("mse", "cd")), "graph all": ("graph", ("mse", "cd", "occ")), "origin all": ("origin", ("mse", "cd", "occ"))}
    return _ablate(spark, "w08c", arms, lambda a: (d, replace(nets.TINY, features=arms[a][0]), {"terms": arms[a][1]}), d, steps)


def w08d_corpus_size(spark, sf_dir, steps: int = 6, thousandths=(10, 20, 40, 80, 420, 1000)) -> DataFrame:
    d = training_clouds(spark, sf_dir)
    return _ablate(spark, "w08d", thousandths, lambda t: (corpora.subset(d, t), nets.TINY, {}), d, steps)


def w09_ragged_vs_fixed(spark, sf_dir, steps: int = 6) -> DataFrame:
    """Whole ragged clouds with voxel tokens; the same clouds cut down to the smallest one, with voxel tokens and with centre tokens."""
    whole, rows = training_clouds(spark, sf_dir), []
    few = smallest_document(spark, sf_dir)
    cut = scratch_table(document_clouds(spark, sf_dir, few))
    for d, arms in ((whole, {"ragged voxel": nets.TINY}), (cut, {"fixed voxel": nets.TINY, "fixed centre": FIXED})):
        got = pretrained_arms(d, [(cfg, {}) for cfg in arms.values()], steps)
        lin = probe_arms(d, [(cfg, params) for cfg, (params, _) in zip(arms.values(), got, strict=True)])
        for arm, (_, losses), value in zip(arms, got, lin, strict=True):
            rows += [("w09", arm, "lin", value), ("w09", arm, "first_loss", losses[0]), ("w09", arm, "last_loss", losses[-1])]
    return report(spark, [("w09", "majority", "lin", majority(whole)), ("w09", "fixed", "points", float(few)), *rows])


def w10_stream_tokens(spark, sf_dir) -> DataFrame:
    """Voxels of the event stream equal those of one batch."""
    from pointloom.plans.catalogue import stream_voxels_equals_batch
    from pointloom.streaming import tokens

    began = time.time()
    a = stream_voxels_equals_batch(spark, sf_dir)
    b = tokens.voxel_counts(tokens.batch_points(spark, sf_dir))
    return report(spark, [("w10", "stream", "rows", float(a.count())), ("w10", "stream", "different", float(a.exceptAll(b).count() + b.exceptAll(a).count())), ("w10", "stream", "seconds", time.time() - began)])


# learned queries ---------------------------------------------------------------------------------------------------


def _trace(spark, losses):
    return spark.createDataFrame([(k, float(x)) for k, x in enumerate(losses)], "step int, loss double")


def pretrain_tiny(spark, sf_dir):
    return _trace(spark, pretrained(training_clouds(spark, sf_dir), nets.TINY, 6)[1])


def pretrain_fixed_token_tiny(spark, sf_dir):
    """On clouds cut down to the smallest one, as the fixed-token method needs."""
    few = smallest_document(spark, sf_dir)
    return _trace(spark, pretrained(scratch_table(document_clouds(spark, sf_dir, few)), FIXED, 6)[1])


def pretrain_minibatches(spark, sf_dir):
    """The published procedure: minibatches, an update every four iterations, rate 5e-4."""
    return _trace(spark, train.pretrain(training_clouds(spark, sf_dir), nets.TINY, 8, batch=64)[1])


def finetune_tiny(spark, sf_dir):
    return _trace(spark, train.finetune(training_clouds(spark, sf_dir).where(~F.col("is_test")), 4, nets.TINY, 6)[1])


def linear_probe_lang(spark, sf_dir):
    """A linear probe on a random and on a pre-trained encoder, beside the largest class."""
    d = training_clouds(spark, sf_dir)
    model, _ = pretrained(d, nets.TINY, 6)
    got = probe_arms(d, [(nets.TINY, nets.init(nets.TINY)), (nets.TINY, model)])
    rows = [("probe", name, "accuracy", value) for name, value in zip(("random encoder", "pre-trained encoder"), got, strict=True)]
    return report(spark, [*rows, ("probe", "majority", "accuracy", majority(d))])


def segment_tiny(spark, sf_dir):
    return w07_part_segmentation(spark, sf_dir, 4)


def vote_finetuned(spark, sf_dir):
    return w06_cad_voting(spark, sf_dir, 3, 4)


def _supervised_query(form, steps):
    def run(spark, sf_dir):
        d = scratch_table(shape_samples(spark, sf_dir, background=False).where(~F.col("is_test")))
        return _trace(spark, train.supervised(d, 10, form, steps=steps)[1])

    return run


SHORT = 3
LEARNED = {f.__name__: f for f in (pretrain_tiny, pretrain_fixed_token_tiny, pretrain_minibatches, finetune_tiny, linear_probe_lang, segment_tiny, vote_finetuned, w02_build_corpus, w05_fewshot, w10_stream_tokens)}
LEARNED |= {"supervised_pointnet": _supervised_query(train.points_logits, 6), "supervised_hierarchical": _supervised_query(train.hierarchical_logits, 4), "supervised_edge_graph": _supervised_query(train.edge_logits, 4)}
#: All experiments; the registered queries take ``SHORT`` optimiser steps an arm, :mod:`bench_workloads` as many as it is told.
EXPERIMENTS = {f.__name__: f for f in (w01_tokenizer_cost, w02_build_corpus, w03_cross_table, w04_model_scaling, w05_fewshot, w06_cad_voting, w07_part_segmentation, w08a_mask_ratio, w08b_augmentation, w08c_attributes_losses, w08d_corpus_size, w09_ragged_vs_fixed, w10_stream_tokens)}
LEARNED |= {n: (lambda spark, sf_dir, f=EXPERIMENTS[n]: f(spark, sf_dir, steps=SHORT)) for n in ("w03_cross_table", "w04_model_scaling", "w08a_mask_ratio", "w08b_augmentation", "w08c_attributes_losses", "w08d_corpus_size", "w09_ragged_vs_fixed")}
LEARNED["w01_tokenizer_cost"] = w01_tokenizer_cost
