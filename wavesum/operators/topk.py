"""Exact distributed top-k by threshold rounds.

Input: scores (site, item, score, value), an absent pair being 0.  `score` is the exact
integer, `value` its real magnitude for thresholds (they differ by a factor that belongs to
the item).  Output: the k items of largest |sum of value|.

`signed` follows the magnitudes of sums of any sign.  What the text leaves open is settled
here: bounds are clamped at zero, since an unsent pair can be an implicit 0; a site's two
lists are united; with fewer than k positive floors the second threshold is 0 and every
nonzero is sent; thresholds over-send by a hair (1e-9), and the final order is exact.  The
coordinator keeps sums instead of a bit per site: bound = partial + sum of all sites' bounds
- sum of the bounds of those that sent.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wavesum.functions.tables import materialize

SLACK = 1e-9
#: Bytes of a message pair: 4 of id, 8 of value; and 4 of site, where lists are marked.
PAIR = 12


@dataclass
class Later:
    """A figure that is counted when it's asked for."""

    count: Callable[[], int]


@dataclass
class TopkResult:
    """items: (item, score, value); phases: what each round sent and decided."""

    items: DataFrame
    rounds: list[dict] = field(default_factory=list)

    @property
    def phases(self) -> list[dict]:
        for p in self.rounds:
            if isinstance(p.get("pairs"), Later):
                p["pairs"] = p["pairs"].count()
        return self.rounds

    @property
    def pairs(self) -> int:
        return sum(p.get("pairs", 0) for p in self.phases)


#: Rows up to which a side of a join is broadcast: sites' bounds and candidates, some 50 bytes each.
FEW = 1_000_000


def extremes(scores: DataFrame, k: int, ready: bool = False) -> tuple[DataFrame, DataFrame]:
    """Scores with `first` (sent in round 1) and the sites' bounds (site, hi, lo, ..), both materialized; ready: the scores are already.

    hi, lo: the k-th highest and lowest scores, or 0 where a site has fewer, clamped at 0.
    Only rows marked `cand`, if there is such a mark, are ranked; whether a row is sent
    follows from comparing it with its site's k-th rows, by value, item and part.
    """
    state = scores if ready else materialize(scores, "topk-state")
    part = F.col("part") if "part" in state.columns else F.lit(0)
    down, up = Window.partitionBy("site").orderBy(F.desc("value"), "item", part), Window.partitionBy("site").orderBy("value", "item", part)
    some = state.filter("cand").drop("cand") if "cand" in state.columns else state
    ranked = some.withColumns({"d": F.row_number().over(down), "u": F.row_number().over(up)}).filter((F.col("d") <= k) | (F.col("u") <= k))
    at = lambda r, c: F.max(F.when(F.col(r) == k, F.col(c) if isinstance(c, str) else c))
    bounds = ranked.groupBy("site").agg(at("d", "value").alias("high"), at("d", "item").alias("high_item"), at("d", part).alias("high_part"), at("u", "value").alias("low"), at("u", "item").alias("low_item"), at("u", part).alias("low_part"), F.count("*").alias("sent"))
    zero = F.lit(0.0)
    bounds = materialize(bounds.withColumns({"hi": F.greatest(zero, F.coalesce("high", zero)), "lo": F.least(zero, F.coalesce("low", zero))}), "topk-bounds")
    small = few(bounds)
    value, item = F.col("value"), F.col("item")
    # two parts of an item may have one value: only as many rows go as have been ranked
    upto = lambda end: (item < F.col(f"{end}_item")) | ((item == F.col(f"{end}_item")) & (part <= F.col(f"{end}_part")))
    above = F.col("high").isNull() | (value > F.col("high")) | ((value == F.col("high")) & upto("high"))
    below = (value < F.col("low")) | ((value == F.col("low")) & upto("low"))
    marked = state.join(small.drop("hi", "lo", "sent"), "site").select("site", "item", *parts_of(state), "score", "value", (above | F.coalesce(below, F.lit(False))).alias("first"))
    return marked, bounds


def parts_of(state: DataFrame) -> list[str]:
    return ["part"] if "part" in state.columns else []


def few(sites: DataFrame) -> DataFrame:
    """Sites' bounds as a broadcast side while they are few: the table's size is known from its files."""
    size = int(str(sites._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return F.broadcast(sites) if size <= 50 * FEW else sites


def sums_of(bounds: DataFrame) -> tuple[float, float]:
    """Sums of the upper and the lower bounds of all sites."""
    return tuple(bounds.agg(F.coalesce(F.sum("hi"), F.lit(0.0)), F.coalesce(F.sum("lo"), F.lit(0.0))).first())


def with_bounds(messages: DataFrame, bounds: DataFrame, total: tuple[float, float] | None = None) -> DataFrame:
    """(item, partial, low, high, floor, n) of every item that some site sent; n: of how many messages."""
    all_hi, all_lo = total or sums_of(bounds)
    joined = messages.join(few(bounds.select("site", "hi", "lo")), "site")
    per = joined.groupBy("item").agg(F.sum("value").alias("partial"), F.sum("hi").alias("seen_hi"), F.sum("lo").alias("seen_lo"), F.count("*").alias("n"))
    per = per.select("item", "partial", (F.col("partial") + F.lit(all_lo) - F.col("seen_lo")).alias("low"), (F.col("partial") + F.lit(all_hi) - F.col("seen_hi")).alias("high"), "n")
    return per.withColumn("floor", F.when((F.col("low") <= 0) & (F.col("high") >= 0), 0.0).otherwise(F.least(F.abs("low"), F.abs("high"))))


def kth(df: DataFrame, column: str, k: int) -> float:
    """The k-th largest value, 0 if there are fewer: k rows on the driver."""
    top = [r[0] for r in df.select(column).orderBy(F.desc(column)).limit(k).collect()]
    return float(top[-1]) if len(top) == k else 0.0


@dataclass
class FirstRound:
    """What the first round leaves: the state with its marks, the sites' bounds, how many sites and pairs, the threshold."""

    state: DataFrame
    bounds: DataFrame
    sites: int
    pairs: int
    t1: float


def first_round(scores: DataFrame, k: int, m: int | None = None, send: int | None = None, ready: bool = False) -> FirstRound:
    """m: the number of sites, at least those that have scores; more are sites without any."""
    state, bounds = extremes(scores, send or k, ready)
    sites, pairs, hi, lo = bounds.agg(F.count("*"), F.coalesce(F.sum("sent"), F.lit(0)), F.coalesce(F.sum("hi"), F.lit(0.0)), F.coalesce(F.sum("lo"), F.lit(0.0))).first()
    if m is not None and m < sites:
        raise ValueError(f"{sites} sites have scores, more than m = {m}: the bounds would not hold")
    t1 = kth(with_bounds(state.filter("first"), bounds, (hi, lo)), "floor", k)
    return FirstRound(state, bounds, m or max(1, sites), int(pairs), t1)


def signed(scores: DataFrame, k: int, m: int | None = None, tight: bool = True, resend: bool = False, fanout: int | None = None, stop_after: int = 3, order: list | None = None, first: FirstRound | None = None, ready: bool = False) -> TopkResult:
    """Three rounds over one materialized state.

    tight: bounds of both rounds are intersected.  resend: pairs are sent again where a later
    round asks for them (for comparison of costs; the result is the same).  fanout: that many
    extremes, k at least, go out in round 1.  stop_after=2: no third round, the estimate is
    the middle of the bounds, with columns low and high.  order: exact sort of the summed
    items, by |value| and item otherwise.  first: a first round that was made before.

    Scores are of distinct (site, item) without nulls; ties go by `order`, then to the lower
    item; a table without scores gives no items.  ready: the scores are materialized.  With a
    column `part` items are bounded as a whole, and the last round sums their parts.
    """
    one = first or first_round(scores, k, m, max(k, fanout or k), ready)
    state, m, t1 = one.state, one.sites, one.t1
    phases = [{"phase": 1, "pairs": one.pairs, "t1": t1}]

    reach = t1 / m
    second = F.abs("value") >= reach * (1 - SLACK) if t1 > 0 else F.lit(True)
    sent = F.col("first") | second
    edge = F.lit(reach)
    later = one.bounds.select("site", (F.least("hi", edge) if tight else edge).alias("hi"), (F.greatest("lo", -edge) if tight else -edge).alias("lo"))
    refined = materialize(with_bounds(state.filter(sent), later), "topk-refined")
    t2 = kth(refined, "floor", k)
    if tight:
        t2 = max(t1, t2)
    hopeful = F.greatest(F.abs("low"), F.abs("high")) >= t2 * (1 - SLACK)
    got, size = refined.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count_if(hopeful)).first()
    again = state.filter(second).count() if resend else got - one.pairs
    left = refined.filter(hopeful)
    phases.append({"phase": 2, "pairs": again, "t1_over_m": reach, "t2": t2, "candidates": size, "down_bytes": 8 * m})
    if stop_after == 2:
        middle = ((F.col("low") + F.col("high")) / 2).alias("value")
        return TopkResult(left.select("item", middle, "low", "high").orderBy(F.round(F.abs("value"), 9).desc(), "item").limit(k), phases)

    wanted = left.select("item")
    third = state.join(F.broadcast(wanted) if size <= FEW else wanted, "item", "left_semi")
    sums = third.groupBy("item", *parts_of(state)).agg(F.sum("score").cast("long").alias("score"), F.sum("value").alias("value"), F.count_if(F.lit(True) if resend else ~sent).alias("n"))
    if size > FEW:
        sums = materialize(sums, "topk-sums")
    phases.append({"phase": 3, "pairs": Later(lambda: int(sums.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])), "down_bytes": 4 * size * m})
    return TopkResult(sums.drop("n").orderBy(*(order or [F.abs("value").desc()]), "item").limit(k), phases)


def nonneg(scores: DataFrame, k: int, m: int | None = None) -> TopkResult:
    """The uniform-threshold rounds for scores of zero and more: partial sums are lower bounds.

    Raises on a negative score, where they aren't.
    """
    low = scores.agg(F.min("value")).first()[0]
    if low is not None and low < 0:
        raise ValueError("scores must not be negative; use signed()")
    w = Window.partitionBy("site").orderBy(F.desc("value"), "item")
    state = materialize(scores.withColumn("first", F.row_number().over(w) <= k), "topk-state")
    m = m or max(1, state.select("site").distinct().count())
    one = state.filter("first")
    t1 = kth(one.groupBy("item").agg(F.sum("value").alias("partial")), "partial", k)
    sent = F.col("first") | (F.col("value") >= t1 / m * (1 - SLACK))
    seen = materialize(state.filter(sent).groupBy("item").agg(F.sum("value").alias("partial"), F.count("*").alias("n")), "topk-refined")
    t2 = kth(seen, "partial", k)
    left = seen.filter(F.col("partial") + (m - F.col("n")) * (t1 / m) >= t2 * (1 - SLACK)).select("item")
    size = left.count()
    third = state.join(F.broadcast(left) if size <= FEW else left, "item", "left_semi")
    phases = [{"phase": 1, "pairs": one.count(), "t1": t1}, {"phase": 2, "pairs": state.filter(sent & ~F.col("first")).count(), "t2": t2, "candidates": size}, {"phase": 3, "pairs": third.filter(~sent).count()}]
    sums = third.groupBy("item").agg(F.sum("score").cast("long").alias("score"), F.sum("value").alias("value"))
    return TopkResult(sums.orderBy(F.desc("value"), "item").limit(k), phases)
