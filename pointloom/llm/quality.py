"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics are taken from the whole text. Features are binned once; every tree has the full binary shape, so the
forest is three flat arrays (feature, bin, leaf) and all rows walk all trees level by level with array indexing.

The model is fitted on at most ``MAX_TRAIN`` labelled rows, those with the smallest hash of their id (a bounded
sample, the same at any cluster size). Labels, language, source and ids never enter the statistics.

Defined cases: null and empty texts have all statistics zero and are scored like any other; labels that are null or
other than 0/1 are ignored, repeated labels of an id count once (the largest), and of documents that share an id the one with
the smallest hash of its text is learned from; with no labelled rows every score is
0.5, with one class only its prior; an empty table gives an empty result; :func:`keep_good` keeps columns and repeats.
"""

from __future__ import annotations

from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pointloom.llm.common import lean, text_key

MAX_TRAIN = 20_000
THRESHOLD = 0.7
TREES, DEPTH, BINS, RATE, L2 = 60, 4, 64, 0.2, 1.0

_UPPER = bytes(range(65, 91))
_DIGITS = bytes(range(48, 58))
_HIGH = bytes(range(128, 256))
_STOPS = b".,;:"
_MARKS = b"#$%&*@^~=+<>_/\\{}[]"
N_STATS = 18


def statistics(text: str | None) -> list[float]:
    raw = (text or "").encode()
    words = raw.split()
    if not words:
        return [0.0] * N_STATS
    n, w, lines = len(raw), len(words), raw.split(b"\n")
    count = lambda chars: n - len(raw.translate(None, chars))
    again = sum(map(eq, words, words[1:]))
    return [
        np.log1p(n), np.log1p(w), n / w, max(map(len, words)) / 10, len(lines) / w, len(set(lines)) / len(lines), len(set(words)) / w,
        len(set(words)) / w**0.7, again / w, count(_UPPER) / n, count(_DIGITS) / n, count(_HIGH) / n, count(_STOPS) / n, raw.count(b"!") / n,
        raw.count(b"|") / n, count(_MARKS) / n, raw.count(b"?") / n, sum(x.endswith(b".") for x in lines) / len(lines),
    ]


def matrix(texts) -> np.ndarray:
    return np.array([statistics(t) for t in texts], np.float32).reshape(-1, N_STATS)


class Forest:
    def __init__(self, edges, feature, cut, leaf, base):
        self.edges, self.feature, self.cut, self.leaf, self.base = edges, feature, cut, leaf, base

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, k], side="left") for k, e in enumerate(self.edges)], axis=1).astype(np.uint8) if len(self.edges) else np.zeros((len(x), 0), np.uint8)

    def score(self, x: np.ndarray, step: int = 4096) -> np.ndarray:
        out = np.full(len(x), self.base)
        if len(self.feature):
            tree = np.arange(len(self.feature))
            for lo in range(0, len(x), step):
                b = self.bins(x[lo : lo + step])
                row = np.arange(len(b))[:, None]
                node = np.zeros((len(b), len(tree)), np.int64)
                for _ in range(DEPTH):
                    node = 2 * node + 1 + (b[row, self.feature[tree, node]] > self.cut[tree, node])
                out[lo : lo + step] += self.leaf[tree, node - (2**DEPTH - 1)].sum(axis=1)
        return 1 / (1 + np.exp(-out))


def fit(x: np.ndarray, y: np.ndarray, trees: int = TREES) -> Forest:
    """Newton boosting of the logistic loss on per-node gradient histograms."""
    n_inner, none = 2**DEPTH - 1, np.zeros((0, 1))
    if not len(y) or y.min() == y.max():
        prior = (y.sum() + 0.5) / (len(y) + 1) if len(y) else 0.5
        return Forest([], none, none, none, float(np.log(prior / (1 - prior))))
    edges = [np.unique(np.quantile(x[:, k], np.linspace(0, 1, BINS + 1)[1:-1])).astype(np.float32) for k in range(x.shape[1])]
    model = Forest(edges, np.zeros((trees, n_inner), np.int64), np.full((trees, n_inner), BINS, np.int64), np.zeros((trees, 2**DEPTH)), float(np.log(y.mean() / (1 - y.mean()))))
    b = model.bins(x).astype(np.int64)
    raw, rows = np.full(len(y), model.base), np.arange(len(y))
    for t in range(trees):
        p = 1 / (1 + np.exp(-raw))
        g, h, node = p - y, p * (1 - p), np.zeros(len(y), np.int64)
        for level in range(DEPTH):
            first, wide = 2**level - 1, 2**level
            at = (node - first) * BINS
            gain = np.full((x.shape[1], wide, BINS), -np.inf)
            for k in range(x.shape[1]):
                gl = np.bincount(at + b[:, k], g, wide * BINS).reshape(wide, BINS).cumsum(axis=1)
                hl = np.bincount(at + b[:, k], h, wide * BINS).reshape(wide, BINS).cumsum(axis=1)
                gr, hr = gl[:, -1:] - gl, hl[:, -1:] - hl
                gain[k] = np.where((hl > 0.5) & (hr > 0.5), gl**2 / (hl + L2) + gr**2 / (hr + L2) - gl[:, -1:] ** 2 / (hl[:, -1:] + L2), -np.inf)
            flat = gain.transpose(1, 0, 2).reshape(wide, -1)
            best = flat.argmax(axis=1)
            good = flat[np.arange(wide), best] > 1e-9
            model.feature[t, first : first + wide] = np.where(good, best // BINS, 0)
            model.cut[t, first : first + wide] = np.where(good, best % BINS, BINS)
            node = 2 * node + 1 + (b[rows, model.feature[t, node]] > model.cut[t, node])
        leaf = node - n_inner
        step = -np.bincount(leaf, g, 2**DEPTH) / (np.bincount(leaf, h, 2**DEPTH) + L2) * RATE
        model.leaf[t] = step
        raw += step[leaf]
    return model


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, max_train: int = MAX_TRAIN) -> Forest:
    known = labels.select(F.col("doc_id").cast("long"), "quality").where("quality in (0, 1) and doc_id is not null").where(~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("quality").alias("quality"))
    sample = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_train)

    def run(batches):
        for b in batches:
            x = matrix(b.column(0).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(1), pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), N_STATS).cast(pa.list_(pa.float32())), *b.columns[2:]], ["y", "x", "id", "key"])

    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string").alias("text"), text_key(docs))
    rows = texts.join(F.broadcast(sample), "doc_id").select("text", F.col("quality").cast("int"), "doc_id", "key").mapInArrow(lean(run), "y int, x array<float>, id long, key long")
    # one row of an id, so that no more than max_train reach the driver
    got = rows.groupBy("id").agg(F.min(F.struct("key", "y", "x")).alias("r")).select("r.y", "r.x").toArrow()
    x = np.array(got.column("x").to_pylist(), np.float32).reshape(-1, N_STATS)
    y = np.array(got.column("y").to_pylist(), np.float64)
    order = np.lexsort((*x.T, y))  # the fit does not depend on the order in which tasks end
    return fit(x[order], y[order])


def _scorer(model: Forest, at: int, keep: bool):
    def run(batches):
        for b in batches:
            s = model.score(matrix(b.column(at).to_pylist()))
            if keep:
                yield b.filter(pa.array(s >= THRESHOLD))
            else:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(s), pa.array((s >= THRESHOLD).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return run


def quality_report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = train(docs, labels)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), held_out(F.col("doc_id")).alias("held_out"))
    return rows.mapInArrow(lean(_scorer(model, 1, False)), "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose text is predicted to be of quality 1."""
    nullable = T.StructType([T.StructField(f.name, f.dataType, True) for f in docs.schema])
    return docs.mapInArrow(lean(_scorer(train(docs, labels), docs.columns.index("text"), True)), nullable)
