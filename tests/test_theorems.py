"""What the samplers promise, over 200 seeds in one job each."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from wavesum.functions import haar
from wavesum.operators import sample
from wavesum.operators.freq import global_freq
from wavesum.plans import accuracy

SEEDS, LOG2U, N, SITES = 200, 6, 4000, 4


@pytest.fixture(scope="module")
def keyed(spark):
    rng = np.random.default_rng(8)
    pos = np.minimum((rng.pareto(1.1, N) * 3).astype(int), (1 << LOG2U) - 1)
    return spark.createDataFrame([(int(i % SITES), int(p), str(i)) for i, p in enumerate(pos)], "site bigint, pos bigint, row_id string").cache()


@pytest.fixture(scope="module")
def true(keyed):
    out = np.zeros(1 << LOG2U)
    for r in global_freq(keyed).collect():
        out[r.pos] = r.cnt
    return out


def seeded(spark, df):
    return df.crossJoin(spark.range(SEEDS).withColumnRenamed("id", "seed"))


def two_stage_sums(spark, counts, plan):
    """(seeds, positions) estimates of the sampled counts (site, pos, scnt[, seed])."""
    if "seed" not in counts.columns:
        counts = seeded(spark, counts)
    sure = F.col("scnt") * F.lit(plan.weight) >= 1
    coin = sample.h32(F.col("site"), F.col("pos"), F.col("seed"), 2) < F.col("scnt") * F.lit(plan.weight_coin)
    sent = counts.filter(sure | coin).groupBy("seed", "pos").agg(F.sum(F.when(sure, F.col("scnt")).otherwise(F.lit(1 / plan.weight))).alias("s"), F.count("*").alias("n"))
    out, pairs = np.zeros((SEEDS, 1 << LOG2U)), np.zeros(SEEDS)
    for r in sent.collect():
        out[r.seed, r.pos] = r.s
        pairs[r.seed] += r.n
    return out, pairs


def test_second_level_is_unbiased_within_its_deviation(spark, keyed, true):
    plan = sample.Plan(N, SITES, 0.05)
    counts = sample.sample_freq(keyed.select("site", "pos"))
    got, pairs = two_stage_sums(spark, counts, plan)
    sd = 1 / plan.eps
    assert (np.abs(got.mean(0) - true) <= 4.5 * sd / math.sqrt(SEEDS)).all()
    assert (got.std(0) <= 1.1 * sd).all()
    # as many certain pairs at most as bare ones are expected, for each sampled record eps sqrt(m)
    assert pairs.mean() <= 2 * plan.weight * N


def test_both_levels_are_unbiased_within_their_deviation(spark, keyed, true):
    plan = sample.Plan(N, SITES, 0.05)
    assert plan.p < 0.2
    first = seeded(spark, keyed).filter(sample.h32(F.col("row_id"), F.col("seed"), 1) < plan.coin)
    counts = first.groupBy("seed", "site", "pos").agg(F.count("*").alias("scnt"))
    got, pairs = two_stage_sums(spark, counts, plan)
    got /= plan.p
    assert pairs.mean() <= accuracy.bounds(N, SITES, plan.eps)["two_stage_pairs"]
    sd = accuracy.bounds(N, SITES, plan.eps)["sd_count"]
    assert (np.abs(got.mean(0) - true) <= 4.5 * sd / math.sqrt(SEEDS)).all()
    assert (got.std(0) <= 1.1 * sd).all()


def test_floor_errs_by_its_bias_at_most_and_downwards(spark, keyed, true):
    plan = sample.Plan(N, SITES, 0.05)
    counts = sample.sample_freq(keyed.select("site", "pos"))  # everything sampled: what is left is the floor's bias
    sent = sample.floor_messages(counts, plan)
    got = np.zeros(1 << LOG2U)
    for r in sample.totals(sent).collect():
        got[r.pos] = r.rho
    assert (got <= true).all() and (true - got).max() <= accuracy.bounds(N, SITES, plan.eps)["floor_bias"] and (true - got).max() > 0
    per_site = {r.site: r["count"] for r in sent.groupBy("site").count().collect()}
    assert max(per_site.values()) <= 1 / plan.eps


def test_coefficients_keep_their_variance_bound_at_every_level(spark, keyed, true):
    plan = sample.Plan(N, SITES, 0.05)
    sampled = keyed.filter(sample.h32(F.col("row_id"), 42, 1) < plan.coin)
    counts = sample.sample_freq(sampled.select("site", "pos"))
    size = np.zeros(1 << LOG2U)
    for r in counts.groupBy("pos").agg(F.sum("scnt").alias("n")).collect():
        size[r.pos] = r.n
    got = two_stage_sums(spark, counts, plan)[0] / plan.p
    coefs = np.array([haar.dense(x) for x in got])
    truth = haar.dense(size / plan.p)
    checked = 0
    for i in range(1 << LOG2U):
        level = 0 if i == 0 else i.bit_length() - 1
        width = (1 << LOG2U) >> level
        block = 0 if i == 0 else i - (1 << level)
        bound = accuracy.coefficient_variance_bound(size[block * width : (block + 1) * width].sum(), N, SITES, plan.eps, level, LOG2U)
        assert coefs[:, i].var() <= 1.3 * bound + 1e-9, (i, level)
        assert abs(coefs[:, i].mean() - truth[i]) <= 4.5 * math.sqrt(bound / SEEDS) + 1e-9
        checked += bound > 0
    assert checked > 20


def test_fixed_size_and_coin_designs_agree_on_average(spark, keyed, true):
    plan = sample.Plan(N, SITES, 0.05)
    fixed = sample.level1(keyed, plan, "wor").count()
    assert fixed == sum(round(plan.p * N / SITES) for _ in range(SITES))
    coin = seeded(spark, keyed.select("row_id")).filter(sample.h32(F.col("row_id"), F.col("seed"), 1) < plan.coin).count() / SEEDS
    assert abs(coin - plan.p * N) <= 4.5 * math.sqrt(N * plan.p * (1 - plan.p) / SEEDS)


def test_domains_of_32_bits(spark):
    from wavesum.operators import exact, sketch
    from wavesum.sources.gen import zipf_positions

    rows = spark.range(2000).selectExpr("id % 4 AS site", "cast(id AS string) AS row_id")
    df = zipf_positions(rows, 1.1, 32).cache()
    low, high, kinds = df.selectExpr("min(pos)", "max(pos)", "count(distinct pos)").first()
    assert 0 <= low and 1 << 31 < high < 1 << 32 and kinds > 100
    want = [(r.coef_id, r["diff"]) for r in exact.ship_counts(df, 32, 10).collect()]
    assert [(r.coef_id, r["diff"]) for r in exact.ship_coefs(df, 32, 10).collect()] == want
    assert [(r.coef_id, r["diff"]) for r in exact.signed_topk(df, 32, 10, 4).items.collect()] == want
    local = exact.local_coefs(df, 32).withColumn("value", haar.value_of(F.col("diff"), F.col("level"), 32))
    top, _ = sketch.ship_sketch(local, 32, 10, bytes_total=2_000_000)
    assert len({i for i, _ in top} & {i for i, _ in want}) >= 5
    # ids a multiple of the prime apart don't share their cells
    x = np.array([5, 5 + sketch.PRIME, 5 + 2 * sketch.PRIME])
    assert len(set(sketch.hashed(x, (12345, 678)).tolist())) == 3
    got = [r.h for r in spark.createDataFrame([(int(i),) for i in x], "x bigint").select(sketch.hash_column(F.col("x"), (12345, 678)).alias("h")).collect()]
    assert got == sketch.hashed(x, (12345, 678)).tolist()
    with pytest.raises(ValueError, match="bounds would not hold"):
        exact.signed_topk(df, 32, 10, 2)


def test_subtrees_of_a_site_give_its_coefficients(spark, keyed):
    from wavesum.operators.freq import local_freq

    whole = haar.local_sparse(local_freq(keyed), LOG2U)
    parts = haar.local_sparse(local_freq(keyed), LOG2U, k=3, subtree_log2=2)
    key = lambda df: {(r.site, r.coef_id, r.level): r["diff"] for r in df.collect()}
    assert key(whole) == key(parts)
    marked = {(r.site, r.coef_id) for r in parts.filter("cand").collect()}
    for site in range(SITES):
        mine = [(r["diff"] * math.sqrt(2.0 ** (max(r.level, 0) - LOG2U)), r.coef_id) for r in whole.filter(F.col("site") == site).collect()]
        for order in (lambda x: (-x[0], x[1]), lambda x: (x[0], x[1])):
            assert all((site, i) in marked for _, i in sorted(mine, key=order)[:3])
