"""The two tokenisers end to end."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom import kernels
from pointloom.operators import embed, lift, patch, voxel
from pointloom.operators.pixels import code_points
from pointloom.schema import AXES, G224, PIECE, GridSpec, keep_freed, pieces

#: Stands for a null key among whole numbers.
NO_KEY = -(1 << 63)


def _over_texts(texts: DataFrame, key: str, text: str, teacher, tokens: Callable[[np.ndarray, list[np.ndarray]], pa.RecordBatch], schema: str) -> DataFrame:
    """Texts lifted to clouds (6, size) and handed to ``tokens`` with their keys, some at a time: one map, nothing is shuffled."""
    teacher = teacher or lift.BlurTeacher(1)

    def run(batches):
        keep_freed()
        for b in (part for whole in batches for part in pieces(whole, pc.utf8_length(whole.column(1)))):
            clouds = [np.stack(lift.lifted(code_points(t), teacher)) for t in b.column(1).to_pylist()]
            yield tokens(b.column(0).fill_null(NO_KEY).to_numpy(), clouds)

    return texts.select(F.col(key).cast("long"), text).mapInArrow(run, schema)


def _keys(samples: np.ndarray, times) -> pa.Array:
    """Each sample's key as often as it has rows."""
    keys = np.repeat(samples, times)
    return pa.array(keys, pa.int64(), mask=keys == NO_KEY)


def _sorted_clouds(batches, most: int = PIECE) -> Iterator[tuple[np.ndarray, list[np.ndarray]]]:
    """Keys and coordinates (3, size) of whole clouds, some ``most`` points at a time, of rows (sample_id, point_no, x, y, z) sorted by the
    first two; of rows with one number the first counts."""
    ids, clouds, waiting, parts, last = [], [], 0, [], None
    for b in batches:
        if not b.num_rows:
            continue
        sample, no = (b.column(j).fill_null(NO_KEY).to_numpy() for j in (0, 1))
        xyz = np.stack([b.column(j).to_numpy(zero_copy_only=False) for j in (2, 3, 4)])
        new = np.concatenate(([last is None or last[0] != sample[0]], sample[1:] != sample[:-1]))
        fresh = new | np.concatenate(([last is None or last[1] != no[0]], no[1:] != no[:-1]))
        last = (sample[-1], no[-1])
        cuts = np.flatnonzero(new)
        for lo, hi in zip([0, *cuts], [*cuts, len(new)], strict=True):
            if parts and lo < len(new) and new[lo]:
                clouds.append(parts[0] if len(parts) == 1 else np.concatenate(parts, axis=1))
                waiting, parts = waiting + clouds[-1].shape[1], []
                if waiting >= most:
                    yield np.array(ids), clouds
                    ids, clouds, waiting = [], [], 0
            if lo < hi:
                if new[lo]:
                    ids.append(sample[lo])
                parts.append(xyz[:, lo:hi][:, fresh[lo:hi]])
    if parts:
        clouds.append(np.concatenate(parts, axis=1))
        yield np.array(ids), clouds


@dataclass(frozen=True)
class VoxelTokenizer:
    """Voxelise, cut into patches, embed by slot: a ragged number of tokens a cloud, linear in its points.

    ``co_locate``: ship the points once by sample (few points a voxel), or let partial aggregation shrink them before the first
    exchange (many points a voxel). See :mod:`pointloom.plans.planner`.
    """

    grid: GridSpec = G224
    channels: int = 4
    rep: str = "argmax"
    features: str = "graph"
    path: str = "onepass"
    co_locate: bool = False

    def voxels(self, points: DataFrame) -> DataFrame:
        points = points.repartition("sample_id") if self.co_locate else points
        return patch.with_slot(voxel.voxelize(voxel.assign(points, self.grid), self.rep), self.grid.patch)

    def transform(self, points: DataFrame) -> DataFrame:
        return embed.slot_embed(self.voxels(points), self.grid.patch, self.channels, self.features, self.path)

    def transform_texts(self, texts: DataFrame, key: str, text: str, teacher=None) -> DataFrame:
        """The same tokens of the clouds of texts, each of them a packed row."""
        if self.rep != "argmax":
            raise ValueError("packed clouds keep the point with the largest sum of attributes")
        grid, channels, features = self.grid, self.channels, self.features

        def tokens(samples, clouds):
            found = [kernels.packed_patches(pts.T, grid, channels, features) for pts in clouds]
            cell, n, num = (np.concatenate([f[j] for f in found]) for j in range(3))
            columns = [_keys(samples, [len(f[1]) * channels for f in found]), *[pa.array(np.repeat(cell[:, j], channels).astype(np.int32)) for j in range(3)]]
            return pa.RecordBatch.from_arrays([*columns, pa.array(np.repeat(n, channels)), pa.array(np.tile(np.arange(channels, dtype=np.int32), len(n))), pa.array(num.ravel())], [*patch.PATCH, "n_vox", "c", "num"])

        return embed.finish(_over_texts(texts, key, text, teacher, tokens, "sample_id long, ci int, cj int, ck int, n_vox long, c int, num long"))


def sequences(tokens: DataFrame) -> DataFrame:
    """One row a cloud: its tokens in order of cell, each an array of channels with its position."""
    one = tokens.groupBy("sample_id", "ci", "cj", "ck").agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "token_fx"))), lambda t: t["token_fx"] / 1000000.0).alias("tok"))
    rows = one.groupBy("sample_id").agg(F.array_sort(F.collect_list(F.struct(F.struct("ci", "cj", "ck").alias("pos"), "tok"))).alias("tokens"))
    return rows.withColumn("n_tokens", F.size("tokens"))


@dataclass(frozen=True)
class CentreTokenizer:
    """Sample centres, group neighbours, embed by a small point network: a fixed number of tokens a cloud. A cloud's points come together
    once and only its tokens leave the task; :mod:`pointloom.operators.baselines` has the three steps as operators of their own."""

    centres: int = 64
    neighbours: int = 32
    SCHEMA = "sample_id long, rank int, t0 long, t1 long, t2 long"

    def tokens(self, samples: np.ndarray, clouds: list[np.ndarray]) -> pa.RecordBatch:
        made = kernels.centre_tokens([pts[:3] for pts in clouds], self.centres, self.neighbours)
        sizes = [len(t) for t in made]
        ranks = np.concatenate([np.arange(1, k + 1, dtype=np.int32) for k in sizes] or [np.zeros(0, np.int32)])
        values = np.concatenate(made or [np.zeros((0, 3), np.int64)])
        return pa.RecordBatch.from_arrays([_keys(samples, sizes), pa.array(ranks), *[pa.array(values[:, j]) for j in range(3)]], ["sample_id", "rank", "t0", "t1", "t2"])

    def transform(self, points: DataFrame) -> DataFrame:
        def run(batches):
            keep_freed()
            for samples, clouds in _sorted_clouds(batches):
                yield self.tokens(samples, clouds)

        own = points.select("sample_id", "point_no", *AXES).repartition("sample_id")
        return own.sortWithinPartitions("sample_id", F.col("point_no").asc_nulls_last()).mapInArrow(run, self.SCHEMA)

    def transform_texts(self, texts: DataFrame, key: str, text: str, teacher=None) -> DataFrame:
        """The same tokens of the clouds of texts, each of them a packed row."""
        return _over_texts(texts, key, text, teacher, self.tokens, self.SCHEMA)
