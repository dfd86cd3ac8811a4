"""Summaries from samples.

First level: each record with probability p = 1 / (eps^2 n), at most 1, by a coin that is a
hash of its row id, or exactly round(p n_j) records of each site.  What a site then sends:

* uniform: every sampled key, or with precombine each key with its count;
* floor: (key, count) where count >= eps t_j, t_j being the site's sample size;
* two-stage: (key, count) where count >= 1 / (eps sqrt m), else a bare key with
  probability eps sqrt(m) count.  The sum of sent counts plus bare keys / (eps sqrt m) is an
  unbiased estimate of the sampled count, and 1 / p of it of the count.

Records with a null key are left out before; repeated rows are records each, told apart by
their row ids (equal ids share a coin); an empty table gives p = 1 and an empty summary.

Coins are integers from md5, the same in any engine and under any partitioning; with
fast=True they are xxhash64, which is what large runs want.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavesum.functions import haar

SEED = 42


@dataclass(frozen=True)
class Plan:
    """Sizes fixed before a run: n records, m sites, eps."""

    n: int
    m: int
    eps: float

    @property
    def p(self) -> float:
        return min(1.0, 1.0 / (self.eps * self.eps * self.n)) if self.n else 1.0

    @property
    def coin(self) -> int:
        return math.floor(self.p * 4294967296)

    @property
    def weight(self) -> float:
        """eps sqrt m, the second level's rate for a count of one."""
        return self.eps * math.sqrt(self.m)

    @property
    def weight_coin(self) -> int:
        return math.floor(min(1.0, self.weight) * 4294967296)


def h32(*parts: Column | int, fast: bool = False) -> Column:
    """32 hash bits of the parts as text joined by colons, as a long."""
    text = F.concat_ws(":", *[F.lit(str(p)) if isinstance(p, int) else p.cast("string") for p in parts])
    if fast:
        return F.call_function("shiftrightunsigned", F.xxhash64(text), F.lit(32))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def level1(keyed: DataFrame, plan: Plan, design: str = "coin", seed: int = SEED, fast: bool = False) -> DataFrame:
    """Sampled records (site, pos).  keyed has row_id."""
    if plan.p >= 1:
        return keyed.select("site", "pos")
    if design == "coin":
        return keyed.filter(h32(F.col("row_id"), seed, 1, fast=fast) < plan.coin).select("site", "pos")
    if design != "wor":
        raise ValueError("design is coin or wor")
    # hashes far over a site's share are left out before the rest are ranked; too few left, which is next to impossible, raises
    sizes = keyed.groupBy("site").agg(F.count("*").alias("n")).select("site", F.round(F.lit(plan.p) * F.col("n")).alias("take"), (F.lit(4294967296.0) * (2 * plan.p + 64 / F.col("n"))).alias("reach"))
    near = keyed.withColumn("h", h32(F.col("row_id"), seed, 1, fast=fast)).join(F.broadcast(sizes), "site").filter("h < reach")
    order = Window.partitionBy("site").orderBy("h", "row_id")
    ranked = near.withColumns({"rank": F.row_number().over(order), "left": F.count("*").over(Window.partitionBy("site"))})
    enough = F.when(F.col("left") >= F.col("take"), F.col("rank") <= F.col("take")).otherwise(F.raise_error(F.lit("a site's sample is short")).cast("boolean"))
    return ranked.filter(enough).select("site", "pos")


def sample_freq(sampled: DataFrame) -> DataFrame:
    return sampled.groupBy("site", "pos").agg(F.count("*").alias("scnt"))


def uniform_messages(sampled: DataFrame, precombine: bool = False) -> DataFrame:
    """(site, pos, cnt): one row a sampled record, or a row a key and site."""
    return sample_freq(sampled).withColumnRenamed("scnt", "cnt") if precombine else sampled.select("site", "pos", F.lit(1).cast("long").alias("cnt"))


def floor_messages(counts: DataFrame, plan: Plan) -> DataFrame:
    """(site, pos, cnt) of the keys that are at least the share eps of their site's sample."""
    sizes = counts.groupBy("site").agg(F.sum("scnt").alias("t"))
    return counts.join(F.broadcast(sizes), "site").filter(F.col("scnt") >= F.lit(plan.eps) * F.col("t")).select("site", "pos", F.col("scnt").alias("cnt"))


def two_stage_messages(counts: DataFrame, plan: Plan, seed: int = SEED, fast: bool = False) -> DataFrame:
    """(site, pos, cnt): cnt is null in a bare key.  Expressions only, no shuffle."""
    sure = F.col("scnt") * F.lit(plan.weight) >= 1
    coin = h32(F.col("site"), F.col("pos"), seed, 2, fast=fast) < F.col("scnt") * F.lit(plan.weight_coin)
    return counts.filter(sure | coin).select("site", "pos", F.when(sure, F.col("scnt")).alias("cnt"))


def totals(messages: DataFrame) -> DataFrame:
    """(pos, rho, bare): the method's one shuffle, of what was sent."""
    return messages.groupBy("pos").agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("rho"), F.sum(F.col("cnt").isNull().cast("long")).alias("bare"))


def estimates(total: DataFrame, plan: Plan) -> DataFrame:
    """(pos, s_hat, v_hat)."""
    s = F.col("rho") + F.col("bare") / F.lit(plan.weight)
    return total.select("pos", s.alias("s_hat"), (s / F.lit(plan.p)).alias("v_hat"))


def coefficients(total: DataFrame, plan: Plan, log2u: int) -> DataFrame:
    """(coef_id, level, value): exact integer transforms of both parts, combined at the end."""
    parts = haar.by_basis(total, log2u, ("rho", "bare"), out=("rho", "bare"))
    scale = F.sqrt(F.pow(F.lit(2.0), F.greatest(F.col("level"), F.lit(0)) - F.lit(log2u)))
    return parts.select("coef_id", "level", ((F.col("rho") + F.col("bare") / F.lit(plan.weight)) / F.lit(plan.p) * scale).alias("value"))


def best_k(coefs: DataFrame, k: int) -> DataFrame:
    """Estimates rank by magnitude to 9 digits, then id."""
    return coefs.filter(F.round("value", 9) != 0).orderBy(F.round(F.abs("value"), 9).desc(), "coef_id").limit(k)


def messages(method: str, keyed: DataFrame, plan: Plan, seed: int = SEED, design: str = "coin", fast: bool = False) -> DataFrame:
    """What the sites send under a method: uniform, precombine, floor or two_stage."""
    sampled = level1(keyed, plan, design, seed, fast)
    if method == "uniform":
        return uniform_messages(sampled)
    counts = sample_freq(sampled)
    if method == "precombine":
        return uniform_messages(sampled, precombine=True)
    if method == "floor":
        return floor_messages(counts, plan)
    if method == "two_stage":
        return two_stage_messages(counts, plan, seed, fast)
    raise ValueError(method)


def histogram(method: str, keyed: DataFrame, plan: Plan, log2u: int, k: int = 30, seed: int = SEED, design: str = "coin", fast: bool = False) -> DataFrame:
    """(coef_id, level, value) of the k best estimated coefficients."""
    return best_k(coefficients(totals(messages(method, keyed, plan, seed, design, fast)), plan, log2u), k)


def coarsen_grid(cells: DataFrame, axes: int, t: int) -> DataFrame:
    """Cells of a grid t times coarser on each axis, for data too sparse to be sampled well."""
    return cells.withColumns({f"pos_{a}": F.floor(F.col(f"pos_{a}") / t).cast("long") for a in range(1, axes + 1)})


def two_stage_nd(cells: DataFrame, plan: Plan, log2us: list[int], k: int = 30, seed: int = SEED) -> DataFrame:
    """Two-stage sampling of d-dimensional cells (site, pos_1, .., row_id)."""
    names = [f"pos_{a}" for a in range(1, len(log2us) + 1)]
    kept = cells if plan.p >= 1 else cells.filter(h32(F.col("row_id"), seed, 1) < plan.coin)
    counts = kept.groupBy("site", *names).agg(F.count("*").alias("scnt"))
    sure = F.col("scnt") * F.lit(plan.weight) >= 1
    coin = h32(F.col("site"), *[F.col(n) for n in names], seed, 2) < F.col("scnt") * F.lit(plan.weight_coin)
    sent = counts.filter(sure | coin).select(*names, F.when(sure, F.col("scnt")).alias("cnt"))
    total = sent.groupBy(*names).agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("rho"), F.sum(F.col("cnt").isNull().cast("long")).alias("bare"))
    parts = haar.by_basis_nd(total, log2us, ("rho", "bare"))
    weight = F.lit(0)
    for a in range(1, len(log2us) + 1):
        weight = weight + F.greatest(F.col(f"l_{a}"), F.lit(0))
    value = (F.col("rho") + F.col("bare") / F.lit(plan.weight)) / F.lit(plan.p) * F.sqrt(F.pow(F.lit(2.0), weight - F.lit(sum(log2us))))
    ids = [F.col(f"c_{a}") for a in range(1, len(log2us) + 1)]
    return parts.select(*ids, value.alias("value")).orderBy(F.round(F.abs("value"), 9).desc(), *ids).limit(k)
