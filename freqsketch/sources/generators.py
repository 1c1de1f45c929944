"""Item streams with a chosen skew, the same in every engine."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SCALE = 10**9


def rank_thresholds(n: int, alpha: float) -> np.ndarray:
    """Running sums of integer weights round(10^9 * r^-alpha) of the ranks 1..n."""
    r = np.arange(1, n + 1, dtype=float)
    return np.cumsum(np.floor(SCALE * r**-alpha + 0.5).astype(np.int64))


def uniform_draw(pos: Column, seed: int, total: int) -> Column:
    digits = F.substring(F.md5(F.concat(F.lit(f"{seed}:"), pos.cast("string"))), 1, 15)
    return F.conv(digits, 16, 10).cast("long") % total


def zipf_stream(positions: DataFrame, pos: str, n: int, alpha: float, seed: int = 7) -> DataFrame:
    """(pos, item): items 1..n, item r with a share near r^-alpha; 0 is uniform.

    Thresholds travel in the closure: 8 n bytes, so n should stay below a few million."""
    limits = rank_thresholds(n, alpha)

    @F.pandas_udf("long")
    def rank(u):
        import pandas as pd

        return pd.Series(np.searchsorted(limits, u.to_numpy(), side="right") + 1)

    return positions.select(F.col(pos).alias("pos"), rank(uniform_draw(F.col(pos), seed, int(limits[-1]))).alias("item"))


def power_law_items(positions: DataFrame, pos: str, n: int, alpha: float, seed: int = 7) -> DataFrame:
    """Truncated power law by inversion of its continuous form: approximate, without any table
    and inside code generation; for universes too large for ``zipf_stream``."""
    u = (F.xxhash64(F.lit(seed), F.col(pos)).bitwiseAND((1 << 53) - 1) + 0.5) / float(1 << 53)
    if alpha == 0:
        x = u * n
    elif alpha == 1:
        x = F.exp(u * float(np.log(n)))
    else:
        x = F.pow(1 + u * (float(n) ** (1 - alpha) - 1), 1 / (1 - alpha))
    return positions.select(F.col(pos).alias("pos"), F.least(F.lit(n), F.greatest(F.lit(1), F.floor(x).cast("long"))).alias("item"))


