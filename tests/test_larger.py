"""Queries whose keys run past the domain of their SQL, and figures that come from a table."""

import pytest

import __spark_entry__ as entry
from tests.test_queries import TABLES, norm

PAST = ["ablation_resend_tight", "approx_topk_words", "bandwidth_methods", "cand_semi", "coef_overlap", "comm_ship_coefs", "cost_at_error_log_user_type", "cost_at_error_user", "energy_parseval", "incremental_freq", "join_size_returned", "log_eps_user_type", "log_methods_pair", "log_methods_user_type", "signed_topk_partkey"]


@pytest.fixture(scope="module")
def larger(spark, tmp_path_factory):
    """Small tables, twice, the second time with keys past 2^11 parts, 2^8 users and values of 2^9."""
    import os
    import shutil

    source, folder = "/root/testdata/sf0.001", tmp_path_factory.mktemp("larger")
    if not os.path.isdir(source):
        pytest.skip("needs the given tables")
    shift = {
        "lineitem": "l_orderkey + 10000 as l_orderkey, l_partkey + 5000 as l_partkey, l_suppkey + 300 as l_suppkey",
        "events": "event_id + 100000 as event_id, user_id + 700 as user_id, value + 900 as value",
    }
    for t in TABLES:
        if t not in shift:
            shutil.copy(f"{source}/{t}.parquet", folder)
            continue
        df = spark.read.parquet(f"{source}/{t}.parquet")
        moved = [e.strip() for e in shift[t].split(",")]
        names = [e.split(" as ")[1] for e in moved]
        more = df.selectExpr(*[moved[names.index(c)] if c in names else c for c in df.columns])
        more = more.select(*[more[c].cast(df.schema[c].dataType) for c in df.columns])
        df.unionByName(more).coalesce(1).write.parquet(str(folder / f"{t}.parquet"))
    return str(folder)


@pytest.mark.parametrize("name", PAST)
def test_as_its_sql_past_the_domain(spark, larger, name):
    import os

    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        path = f"{larger}/{t}.parquet"
        con.execute(f"create view {t} as select * from '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    df = entry.queries()[name](spark, larger)
    cols = sorted(df.columns)
    cur = con.execute(entry.oracle_sql()[name])
    have = [d[0] for d in cur.description]
    want = [tuple(r[have.index(c)] for c in cols) for r in cur.fetchall()]
    assert norm(tuple(r[c] for c in cols) for r in df.collect()) == norm(want)


def test_worked_sizes_follow_the_table(spark, tmp_path):
    spark.range(4).selectExpr("id * 7 as l_orderkey").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = {r.quantity: r.bytes for r in entry.queries()["bounds_worked_sizes"](spark, str(tmp_path)).collect()}
    assert got == pytest.approx({"uniform": 4e8, "floor": 1.6e5, "two_stage": 1.6e5, "two_stage_pairs": 4e4})


def test_terms_of_one_id_are_added_in_a_join_size():
    import numpy as np

    from wavesum.operators.hist import WaveletHistogram

    a, b = (WaveletHistogram(3, np.array(i), np.array(v)) for i, v in (([2, 5, 5], [1.0, 2.0, 3.0]), ([5, 2], [10.0, 1.0])))
    assert a.inner_product(b) == b.inner_product(a) == 51


def test_timed_counts_what_a_method_sends_once(spark, monkeypatch):
    import os

    from wavesum.functions.keys import spec
    from wavesum.plans import experiments

    folder = "/root/testdata/sf0.001"
    if not os.path.isdir(folder):
        pytest.skip("needs the given tables")
    calls, method = [], experiments.Run.method
    monkeypatch.setattr(experiments.Run, "method", lambda self, name, *a, **k: calls.append(name) or method(self, name, *a, **k))
    got = experiments.timed(spark, folder, experiments.Setting(spec("quantity"), 4), ("ship_counts", "ship_counts_physical")).collect()
    assert calls == ["ship_counts"]
    assert got[0][3:] == got[1][3:] and got[0].pairs > 0
