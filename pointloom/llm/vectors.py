"""What the two vector operators share: reading vectors, and telling which rows take part."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def usable(vector: Column) -> Column:
    """Neither null nor holding null or non-finite components; an empty vector is not usable."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & ~F.coalesce(bad, F.lit(True))


def block(column: pa.Array) -> np.ndarray:
    """A column of equally long vectors as a float64 matrix."""
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return values.reshape(len(column), -1) if len(column) else values.reshape(0, 1)


def dimensions(df: DataFrame) -> list[int]:
    """The vector lengths that occur; a corpus has one or a few."""
    return sorted(r[0] for r in df.select(F.size("v")).distinct().collect())
