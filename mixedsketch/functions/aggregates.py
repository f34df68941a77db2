"""A Count-Min matrix as an aggregate, for ad-hoc use in ``groupBy(...).agg(...)``.

A convenience: groups are brought together in one task each, so long streams
use ``operators.cm.build`` instead, which adds up cells.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql.functions import pandas_udf

from ..spec import SketchSpec
from .hashing import row_hashes_np


def cm_agg(spec: SketchSpec):
    """Aggregate of (key, weight) to the H * K counters of one matrix, row after row."""

    @pandas_udf("array<bigint>")
    def matrix(keys: pd.Series, weights: pd.Series) -> list:
        at = row_hashes_np(keys.to_numpy(), spec) + np.arange(spec.H) * spec.K
        counts = np.zeros(spec.H * spec.K, dtype=np.int64)
        np.add.at(counts, at, weights.to_numpy()[:, None])
        return counts.tolist()

    return matrix
