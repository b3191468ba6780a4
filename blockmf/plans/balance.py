"""The share alpha of the ratings that wide lanes get, so that both kinds need the same time."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Time = Callable[[float], float]


def total_time(wide: Time, narrow: Time, nnz: float, alpha: float, n: int, w: int) -> float:
    """Time of a share: the slower of both kinds, each divided among its lanes."""
    a = wide(alpha * nnz) / w if w else 0.0
    b = narrow((1 - alpha) * nnz) / n if n else 0.0
    return max(a, b)


def per_block(f: Time, blocks: int) -> Time:
    """Time of a share that is worked on in `blocks` equal blocks: saturation then counts per block."""
    return lambda size: blocks * f(size / blocks)


def balance(wide: Time, narrow: Time, nnz: float, n: int, w: int, method: str = "bisect", steps: int = 1000) -> float:
    """alpha in [0, 1] with the least gap between both kinds. No wide lanes: 0; no narrow lanes: 1."""
    if not w or not n:
        return 0.0 if not w else 1.0
    gap = lambda a: wide(a * nnz) / w - narrow((1 - a) * nnz) / n
    if method == "grid":
        return min((abs(gap(i / steps)), i / steps) for i in range(steps + 1))[1]
    lo, hi = 0.0, 1.0
    if gap(hi) <= 0:
        return 1.0
    for _ in range(60):  # both times are monotone in alpha, so the gap is
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if gap(mid) < 0 else (lo, mid)
    return (lo + hi) / 2


def balance_lines(wide: tuple[float, float], narrow: tuple[float, float], nnz: float, n: int, w: int) -> float:
    """Closed form for two straight lines (slope, intercept)."""
    (aw, bw), (an, bn) = wide, narrow
    alpha = ((an * nnz + bn) / n - bw / w) / (nnz * (aw / w + an / n))
    return min(1.0, max(0.0, alpha))


def balance_grid(fits: DataFrame, nnz: int, n: int, w: int, steps: int = 200) -> DataFrame:
    """One row (alpha, gap, seconds) from a table of line fits (kind, a, b): the grid as rows, the least gap by min_by."""
    line = fits.groupBy().pivot("kind", ["narrow", "wide"]).agg(F.first("a").alias("a"), F.first("b").alias("b"))
    grid = line.select("*", F.explode(F.sequence(F.lit(0), F.lit(steps))).alias("i")).withColumn("alpha", F.col("i") / steps)
    tw = (F.col("wide_a") * F.col("alpha") * nnz + F.col("wide_b")) / w
    tn = (F.col("narrow_a") * (1 - F.col("alpha")) * nnz + F.col("narrow_b")) / n
    timed = grid.withColumn("gap", F.abs(tw - tn)).withColumn("seconds", F.greatest(tw, tn))
    return timed.agg(F.min_by("alpha", "gap").alias("alpha"), F.min("gap").alias("gap"), F.min_by("seconds", "gap").alias("seconds"))
