"""Choice of the physical layout of a tokenising plan from a few facts about the corpus."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.operators import voxel
from pointloom.operators.tokenizer import VoxelTokenizer
from pointloom.schema import GridSpec


@dataclass(frozen=True)
class TokenPlan:
    """A tokenising plan: grid, representative, attributes, channels, and the share of patches that is hidden before embedding."""

    grid: GridSpec
    rep: str = "argmax"
    features: str = "graph"
    channels: int = 4
    points_per_voxel: float = 1.0
    samples: int = 1_000_000
    cores: int = 8

    def tokenizer(self) -> VoxelTokenizer:
        """Ship rows once by sample where voxels hardly shrink the data and there are enough samples to fill the cores; else
        aggregate before the exchange. A bank too large for a table or for generated code goes to the array kernel."""
        few = self.points_per_voxel < 2 and self.samples >= 4 * self.cores
        path = "onepass" if self.channels <= 8 else "kernel"
        return VoxelTokenizer(self.grid, self.channels, self.rep, self.features, path, co_locate=few)

    def explain(self) -> str:
        t = self.tokenizer()
        return f"grid {t.grid.size}/{t.grid.patch}, {t.rep}, {t.features}, path {t.path}, " + ("one exchange by sample" if t.co_locate else "partial aggregation, then exchange by voxel and by patch")


def plan_for(points: DataFrame, grid: GridSpec, **options) -> TokenPlan:
    """Measure points a voxel and samples by one sketch pass (approximate distinct counts)."""
    keyed = voxel.assign(points, grid)
    n, m, s = keyed.agg(F.count("*"), F.approx_count_distinct(F.struct("sample_id", *voxel.KEY)), F.approx_count_distinct("sample_id")).first()
    return replace(TokenPlan(grid, **options), points_per_voxel=n / max(1, m), samples=s, cores=points.sparkSession.sparkContext.defaultParallelism)
