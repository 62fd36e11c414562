"""Larger tables by resampling with replacement and noise on continuous columns, without Python and without a shuffle."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def upsample(df: DataFrame, times: int, noise: dict[str, float] | None = None, seed: int = 42) -> DataFrame:
    """``times`` rows per row on average, drawn with replacement. ``noise``: column -> half width; the shift hangs on a hash of the row and its copy, so reruns agree. Integer and category columns stay."""
    drawn = df.sample(withReplacement=True, fraction=float(times), seed=seed)
    if not noise:
        return drawn
    drawn = drawn.withColumn("copy_no", F.monotonically_increasing_id())
    for i, (c, half) in enumerate(noise.items()):
        shift = (F.pmod(F.xxhash64("copy_no", F.lit(seed + i)), F.lit(1 << 20)) / float(1 << 20) - 0.5) * 2 * half
        drawn = drawn.withColumn(c, F.col(c) + shift)
    return drawn.drop("copy_no")
