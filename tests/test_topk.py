import random

import pytest

from wavesum.operators import topk


def scores(spark, sites):
    rows = [(s, i, v, float(v)) for s, items in enumerate(sites) for i, v in items.items() if v]
    return spark.createDataFrame(rows, "site bigint, item bigint, score bigint, value double")


def best(sites, k):
    total = {}
    for items in sites:
        for i, v in items.items():
            total[i] = total.get(i, 0) + v
    return sorted(total.items(), key=lambda x: (-abs(x[1]), x[0]))[:k]


def test_worked_example(spark):
    sites = [{1: 10, 2: -9, 3: 1}, {1: -10, 2: 2, 3: 8}]
    got = topk.signed(scores(spark, sites), 1, 2)
    assert [(r.item, r.score) for r in got.items.collect()] == [(3, 9)]
    assert got.phases[0]["t1"] == 1 and got.phases[1]["t2"] == 9 and got.phases[1]["candidates"] == 1
    with pytest.raises(ValueError):
        topk.nonneg(scores(spark, sites), 1, 2)


def test_implicit_zeros(spark):
    sites = [{1: -3, 2: -8}, {3: 5, 4: 1}]
    assert [(r.item, r.score) for r in topk.signed(scores(spark, sites), 1, 2).items.collect()] == [(2, -8)]
    state, bounds = topk.extremes(scores(spark, sites), 1)
    seen = {r.item: (r.low, r.high) for r in topk.with_bounds(state.filter("first"), bounds).collect()}
    assert seen[3][1] >= 5


@pytest.mark.parametrize("seed", range(4))
def test_random_signed(spark, seed):
    rng = random.Random(seed)
    sites = [{i: rng.choice([-1, 1]) * int(rng.paretovariate(0.9)) for i in rng.sample(range(40), rng.randrange(0, 25))} for _ in range(rng.choice([1, 3, 6]))]
    k = rng.choice([1, 3, 60])
    df = scores(spark, sites)
    want = [x for x in best(sites, k) if x[1]]
    for options in ({}, {"tight": False}, {"resend": True}, {"fanout": 2 * k}):
        got = [(r.item, r.score) for r in topk.signed(df, k, max(1, len(sites)), **options).items.collect() if r.score]
        assert got == want
    once, again = (topk.signed(df, k, max(1, len(sites)), resend=r).pairs for r in (False, True))
    assert once <= again and once <= df.count()


def test_nonneg(spark):
    rng = random.Random(9)
    sites = [{i: rng.randrange(1, 30) for i in rng.sample(range(30), 20)} for _ in range(5)]
    got = [(r.item, r.score) for r in topk.nonneg(scores(spark, sites), 5, 5).items.collect()]
    assert got == best(sites, 5)
    low = topk.signed(scores(spark, sites), 5, 5, stop_after=2).items.collect()
    total = dict(best(sites, 99))
    assert all(r.low - 1e-9 <= total[r.item] <= r.high + 1e-9 for r in low)


def test_empty(spark):
    assert topk.signed(scores(spark, []), 3, 2).items.count() == 0


def test_a_site_sends_as_many_rows_as_are_ranked(spark):
    """Two parts of one item with the same value, one of them the k-th: the other is not sent in the first round."""
    rows = [(0, 5, 0, 3, 3.0), (0, 5, 2, 3, 3.0), (0, 9, 0, 1, 1.0), (1, 5, 0, -3, -3.0), (1, 5, 2, -3, -3.0), (1, 7, 0, 1, 1.0)]
    scores = spark.createDataFrame(rows, "site bigint, item bigint, part int, score bigint, value double")
    state, bounds = topk.extremes(scores, 1)
    first = {(r.site, r.item, r.part) for r in state.filter("first").collect()}
    assert first == {(0, 5, 0), (0, 9, 0), (1, 7, 0), (1, 5, 0)}
    assert sum(r.sent for r in bounds.collect()) == len(first)
