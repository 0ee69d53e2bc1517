"""Connected components of an edge table, and the union of pairs inside one task."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.llm.common import materialize


def unite(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Merge the classes of the pairs (i, j); ``label`` maps each position to the smallest position of its class."""
    while True:
        a, b = label[i], label[j]
        apart = a != b
        if not apart.any():
            return label
        i, j, a, b = i[apart], j[apart], a[apart], b[apart]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = label[label]
            if np.array_equal(up, label):
                break
            label = up


def _toward_min(edges: DataFrame) -> DataFrame:
    """Each vertex's larger neighbours are tied to the smallest vertex that it sees."""
    both = edges.union(edges.select("b", "a")).toDF("u", "v")
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))


def _flatten(edges: DataFrame) -> DataFrame:
    """Each vertex and its smaller neighbours are tied to the smallest of them."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    tied = edges.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return tied.union(least.select("a", F.col("m").alias("b"))).distinct()


def connected_components(edges: DataFrame, most_edges: int | None = None) -> DataFrame:
    """(vertex, root) for every vertex that has an edge; root is the smallest vertex of its component.

    ``edges`` has two long columns; loops, repeats and both directions are allowed. The two steps are repeated until
    the edges are stars around the roots, in rounds that grow with the logarithm of the input. Only a row count and
    a checksum reach the driver. Minima are combined before they are shuffled, and the joins are plain equi-joins,
    so a hub with very many neighbours is split by adaptive execution. ``most_edges``: a bound of the number of rows, if known.
    """
    a, b = edges.columns
    now = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).distinct()
    now, seen = materialize(now, most_edges), None
    while True:
        sign = tuple(now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if sign == seen or sign[0] == 0:
            return now.select(F.col("a").alias("vertex"), F.col("b").alias("root")).union(now.select("b", "b").distinct())
        seen = sign
        # a step gives at most an edge for each that it gets and one more a vertex
        now = materialize(_flatten(_toward_min(now)), 3 * sign[0])
