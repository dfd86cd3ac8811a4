"""Accuracy: squared error against the true counts, its ideal, and the samplers' bounds."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.operators.hist import WaveletHistogram


def energy(freq: DataFrame) -> int:
    """Sum of squared counts, exact."""
    return int(freq.agg(F.coalesce(F.sum(F.col("cnt").cast("decimal(19,0)") * F.col("cnt").cast("decimal(19,0)")), F.lit(0))).first()[0])


def sse_brute(freq: DataFrame, hist: WaveletHistogram) -> float:
    """Squared error over all u positions by reconstruction: positions with counts one by one, the empty rest of each piece at once."""
    spark = freq.sparkSession
    pieces = spark.createDataFrame(hist.pieces(), "lo bigint, hi bigint, estimate double")
    joined = freq.join(F.broadcast(pieces), (F.col("pos") >= F.col("lo")) & (F.col("pos") < F.col("hi")))
    hit = joined.agg(F.coalesce(F.sum((F.col("cnt") - F.col("estimate")) ** 2 - F.col("estimate") ** 2), F.lit(0.0))).first()[0]
    return float(hit + sum((hi - lo) * e * e for lo, hi, e in hist.pieces()))


def sse(total_energy: float, true: DataFrame, estimate: DataFrame) -> DataFrame:
    """Squared error by the orthonormal basis: energy - sum of kept w^2 + sum of (estimate - w)^2.

    true: (coef_id, value) of all nonzero coefficients; estimate: (coef_id, value) kept.
    """
    both = estimate.select("coef_id", F.col("value").alias("est")).join(true.select("coef_id", F.col("value").alias("w")), "coef_id", "left")
    w = F.coalesce("w", F.lit(0.0))
    return both.agg((F.lit(float(total_energy)) + F.coalesce(F.sum((F.col("est") - w) ** 2 - w**2), F.lit(0.0))).alias("sse"))


def ideal_sse(total_energy: float, top: DataFrame) -> float:
    """The least squared error of k terms: what the k largest leave."""
    return float(total_energy - (top.agg(F.sum(F.col("value") ** 2)).first()[0] or 0.0))


def relative(error: float, total_energy: float) -> float:
    return error / total_energy if total_energy else 0.0


def recall(estimate: DataFrame, exact: DataFrame) -> float:
    """Share of the exact coefficients that the estimate kept."""
    n = exact.count()
    return exact.select("coef_id").join(estimate.select("coef_id"), "coef_id", "left_semi").count() / n if n else 1.0


def bounds(n: int, m: int, eps: float) -> dict[str, float]:
    """What the theory promises.

    The deviation of a count estimate counts both levels here, so it is sqrt(2) eps n, where
    one level alone has eps n.
    """
    return {
        "sample": 1 / eps**2,
        "sd_sampled_count": 1 / eps,
        "sd_count": math.sqrt(2) * eps * n,
        "sd_count_second_level": eps * n,
        "floor_pairs": m / eps,
        "floor_pairs_per_site": 1 / eps,
        "floor_bias": eps * n,
        "two_stage_pairs": 2 * math.sqrt(m) / eps,
    }


def coefficient_variance_bound(sampled_in_support: float, n: int, m: int, eps: float, level: int, log2u: int, counts_in_support: float | None = None) -> float:
    """Bound on an estimated coefficient's variance, in the sample's counts: eps^3 n^2 2^j / (u sqrt m) times their sum.

    With counts_in_support (true counts) the first level's part is added.
    """
    share = 2.0**level / 2.0**log2u
    second = eps**3 * n * n * share / math.sqrt(m) * sampled_in_support
    if counts_in_support is None:
        return second
    p = min(1.0, 1 / (eps * eps * n))
    return second + counts_in_support * (1 - p) / p * share


def trials(freq: DataFrame, runs: list[DataFrame]) -> DataFrame:
    """Bias and deviation of count estimates (pos, v_hat) over runs: a position a run doesn't have is 0 there."""
    every = None
    for r in runs:
        part = r.select("pos", "v_hat")
        every = part if every is None else every.unionByName(part)
    n = len(runs)
    sums = every.groupBy("pos").agg(F.sum("v_hat").alias("s"), F.sum(F.col("v_hat") ** 2).alias("q"))
    return freq.join(sums, "pos", "left").select("pos", "cnt", (F.coalesce("s", F.lit(0.0)) / n - F.col("cnt")).alias("bias"), F.sqrt(F.greatest(F.lit(0.0), F.coalesce("q", F.lit(0.0)) / n - (F.coalesce("s", F.lit(0.0)) / n) ** 2)).alias("sd"))


def coef_variance(runs: list[DataFrame]) -> DataFrame:
    """Mean and variance of each coefficient over runs of (coef_id, value), missing ones 0."""
    every, n = None, len(runs)
    for r in runs:
        part = r.select("coef_id", "value")
        every = part if every is None else every.unionByName(part)
    mean = F.sum("value") / n
    return every.groupBy("coef_id").agg(mean.alias("mean"), (F.sum(F.col("value") ** 2) / n - mean * mean).alias("variance"))
