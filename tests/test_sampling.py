import numpy as np
import pytest
from pyspark.sql import functions as F

from wavesum.functions import haar
from wavesum.operators import exact, sample, sketch
from wavesum.operators.freq import global_freq, merge
from wavesum.operators.hist import WaveletHistogram
from wavesum.plans import accuracy, cost


@pytest.fixture(scope="module")
def keyed(spark):
    rng = np.random.default_rng(3)
    pos = np.minimum((rng.pareto(1.1, 4000) * 3).astype(int), 63)
    return spark.createDataFrame([(int(i % 4), int(p), str(i)) for i, p in enumerate(pos)], "site bigint, pos bigint, row_id string").cache()


def test_exact_methods_agree(keyed):
    want = exact.centralized(keyed, 6, 10)
    for df in (exact.ship_counts(keyed, 6, 10), exact.ship_coefs(keyed, 6, 10), exact.signed_topk(keyed, 6, 10, 4).items, exact.planned(keyed, 6, 10, 4)[1]):
        got = [(r.coef_id, r.value) for r in df.collect()]
        assert [i for i, _ in got] == [i for i, _ in want]
        assert np.allclose([v for _, v in got], [v for _, v in want])


def test_second_level_is_unbiased_and_within_bounds(spark, keyed):
    counts = sample.sample_freq(keyed.select("site", "pos"))
    plan = sample.Plan(4000, 4, 0.05)
    true = {r.pos: r.cnt for r in global_freq(keyed).collect()}
    runs = []
    for s in range(40):
        sent = sample.two_stage_messages(counts, plan, seed=s)
        runs.append(sample.totals(sent).withColumn("run", F.lit(s)))
    every = runs[0]
    for r in runs[1:]:
        every = every.unionByName(r)
    got = {}
    for r in every.collect():
        got.setdefault(r.pos, np.zeros(40))[r.run] = r.rho + r.bare / plan.weight
    for pos, n in true.items():
        x = got.get(pos, np.zeros(40))
        assert abs(x.mean() - n) <= 4.5 * (1 / plan.eps) / 40**0.5
        assert x.std() <= 1.3 / plan.eps
    assert counts.count() > 0 and sample.two_stage_messages(counts, plan).count() <= 2 * 1.5 * plan.m**0.5 / plan.eps


def test_floor_bounds(keyed):
    plan = sample.Plan(4000, 4, 0.05)
    counts = sample.sample_freq(sample.level1(keyed, plan))
    sent = sample.floor_messages(counts, plan)
    assert sent.groupBy("site").count().agg(F.max("count")).first()[0] <= 1 / plan.eps
    full = {r.pos: r.rho for r in sample.totals(sample.uniform_messages(keyed.select("site", "pos"))).collect()}
    assert sum(full.values()) == 4000


def test_designs(keyed):
    plan = sample.Plan(4000, 4, 0.05)
    assert plan.p == pytest.approx(0.1)
    assert sample.level1(keyed, plan, "wor").count() == 400
    assert 300 <= sample.level1(keyed, plan).count() <= 500
    assert 300 <= sample.level1(keyed, plan, fast=True).count() <= 500
    assert sample.Plan(10, 4, 0.01).p == 1


def test_errors_agree(keyed):
    freq = global_freq(keyed)
    top = exact.ship_counts(keyed, 6, 5)
    h = WaveletHistogram.of(top, 6)
    e = accuracy.energy(freq)
    true = haar.by_basis(freq, 6).select("coef_id", haar.value_of(F.col("diff"), F.col("level"), 6).alias("value"))
    brute = accuracy.sse_brute(freq, h)
    assert brute == pytest.approx(accuracy.sse(e, true, top).first()[0]) == pytest.approx(accuracy.ideal_sse(e, top))
    assert accuracy.recall(top, top) == 1 and 0 <= accuracy.relative(brute, e) < 1
    assert merge(freq, freq).agg(F.sum("cnt")).first()[0] == 8000


def test_sketches(spark, keyed):
    local = exact.local_coefs(keyed, 6).withColumn("value", haar.value_of(F.col("diff"), F.col("level"), 6))
    want = {r.coef_id: r.value for r in exact.ship_counts(keyed, 6, 5).collect()}
    for kind in ("group", "tow"):
        top, _ = sketch.ship_sketch(local, 6, 10, kind, 60_000)
        got = dict(top)
        assert sum(i in got for i in want) >= 3
        assert got[1] == pytest.approx(want[1], rel=0.2)
    g = sketch.GroupSketch(6)
    parts = g.merge(g.cells(local, "diff", by=("site",)))
    whole = g.cells(haar.by_basis(global_freq(keyed), 6), "diff")
    key = lambda df: {(r.lvl, r.row, r.bucket, r.sub): r.val for r in df.collect() if r.val}
    assert key(parts) == key(whole)


def test_costs(spark, keyed):
    plan = sample.Plan(4000, 4, 0.05)
    ledger = cost.Ledger().record("up", sample.messages("two_stage", keyed, plan), "two_stage").broadcast("down", 32)
    assert ledger.bytes >= 4 * ledger.pairs + 32
    sizes = cost.worked_sizes(1000, 1e-4)
    assert sizes["uniform"] == pytest.approx(4e8) and sizes["floor"] == pytest.approx(4e7) and sizes["two_stage_pairs"] == pytest.approx(632455.5, rel=1e-3)
    assert cost.model(1, 12_500_000, 0.5) == pytest.approx(3)
    _, seconds = cost.timed(lambda: cost.force(keyed))
    assert seconds > 0
    b = accuracy.bounds(1000, 4, 0.1)
    assert b["two_stage_pairs"] == 40 and accuracy.coefficient_variance_bound(10, 1000, 4, 0.1, 0, 6) > 0


def test_physical_shuffle(spark, keyed):
    got = cost.physical(spark, lambda: keyed.groupBy("pos").count().collect())
    assert got["stages"] >= 1 and got["shuffle_records"] > 0
