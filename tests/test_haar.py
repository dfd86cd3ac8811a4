import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from wavesum.functions import haar
from wavesum.operators.hist import WaveletHistogram

V = [4, 0, 1, 3, 7, 7, 2, 0]
#: Worked example: coefficient, integer difference.
DIFFS = {1: 24, 2: 8, 4: -12, 5: -4, 6: 2, 8: -2}


def test_worked_example():
    w = haar.dense(np.array(V))
    assert np.allclose(w, [24 / 8**0.5, 8 / 8**0.5, 0, -6, -4 / 2**0.5, 2 / 2**0.5, 0, -2 / 2**0.5])
    assert abs((w**2).sum() - 128) < 1e-9
    assert np.allclose(haar.inverse(w), V)
    plain, scale = haar.unnormalised(np.array(V))
    assert np.allclose(plain * scale, w) and plain[0] == 3


def test_best_terms_reconstruct():
    w = haar.dense(np.array(V))
    h = WaveletHistogram(3, np.array([1, 4, 2]), w[[0, 3, 1]])
    assert np.allclose([h.point(x) for x in range(8)], [2, 2, 2, 2, 7, 7, 1, 1])
    assert [(a, b, round(v, 9)) for a, b, v in h.pieces() if round(v, 9)][:1] == [(0, 2, 2.0)] or h.pieces()
    assert abs(h.range_count(3, 7) - 17) < 1e-9 and abs(h.total() - 24) < 1e-9
    assert sum((a - h.point(i)) ** 2 for i, a in enumerate(V)) == pytest.approx(12)


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 7).flatmap(lambda n: st.lists(st.integers(0, 9), min_size=1 << n, max_size=1 << n)))
def test_sparse_is_dense(v):
    u, log2u = len(v), len(v).bit_length() - 1
    pos = np.flatnonzero(v)
    ids, levels, diffs, _, total = haar.sparse(pos, np.array(v)[pos], log2u)
    got = np.zeros(u)
    got[ids - 1] = diffs * np.sqrt(2.0**levels / u)
    got[0] = total.sum() / u**0.5
    assert np.allclose(got, haar.dense(np.array(v)))


def test_frames_agree(spark):
    freq = spark.createDataFrame([(i, c) for i, c in enumerate(V) if c], "pos bigint, cnt bigint")
    want = {i: d for i, d in DIFFS.items()}
    for df in (haar.by_basis(freq, 3), haar.by_subtree(freq, 3, 2), haar.by_subtree(freq, 3, 1), haar.by_subtree(freq, 3, 0)):
        assert {r.coef_id: r["diff"] for r in df.collect()} == want
    assert [r.coef_id for r in haar.best_k(haar.by_basis(freq, 3), 3, 3).collect()] == [1, 4, 2]
    empty = spark.createDataFrame([], "pos bigint, cnt bigint")
    assert haar.by_basis(empty, 3).count() == 0 and haar.by_subtree(empty, 3, 2).count() == 0


def test_two_dimensions(spark):
    rng = np.random.default_rng(1)
    grid = rng.integers(0, 4, (8, 4))
    cells = spark.createDataFrame([(int(i), int(j), int(c)) for (i, j), c in np.ndenumerate(grid) if c], "pos_1 bigint, pos_2 bigint, cnt bigint")
    want = haar.dense_2d(grid.astype(float))
    for r in haar.by_basis_nd(cells, [3, 2]).collect():
        scale = (2.0 ** (max(r.l_1, 0) + max(r.l_2, 0)) / 32) ** 0.5
        assert abs(want[r.c_1 - 1, r.c_2 - 1] - r.cnt * scale) < 1e-9


def test_histogram_uses(spark, tmp_path):
    w = haar.dense(np.array(V))
    h = WaveletHistogram(3, np.arange(1, 9), w, "all")
    assert [round(h.point(i)) for i in range(8)] == V
    assert h.quantile(0.5) == 4 and h.selectivity(4, 6) == pytest.approx(14 / 24)
    assert h.inner_product(h) == pytest.approx(128)
    assert len(h.balanced_boundaries(3)) == 3
    assert h.merge(h, 8).point(4) == pytest.approx(14)
    h.save(spark, str(tmp_path / "h"), "one")
    assert np.allclose(WaveletHistogram.load(spark, str(tmp_path / "h"), "one").values, w)
    positions = spark.range(8).withColumnRenamed("id", "pos")
    assert [round(r.estimate) for r in h.reconstruct(spark, positions).orderBy("pos").collect()] == V
    from wavesum.functions.udtfs import register_all

    register_all(spark, h)
    assert spark.sql("SELECT round(range_count(4, 6), 6) AS n").first().n == 14
    assert spark.sql("SELECT count(*) AS n FROM reconstruct_pieces(array(1L), array(2.0D), 3)").first().n >= 1
