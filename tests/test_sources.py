import pytest

from wavesum.functions.keys import Domain, KeySpec, dense_rank_ids, physical_sites, project, super_site
from wavesum.sources.gen import delimited_file, fixed_file, zipf_positions
from wavesum.sources.readers import register_sources


def test_fixed(spark):
    register_sources(spark)
    path = fixed_file(spark.range(1000).selectExpr("id * 3 AS k"), 16)
    df = spark.read.format("fixed_sample").option("path", path).option("record", 16).option("p", 0.1).option("split", 4000).load().collect()
    assert len({r.ordinal for r in df}) == len(df) and 95 <= len(df) <= 105
    assert all(r.pos == 3 * r.ordinal for r in df)
    assert spark.sparkContext.binaryRecords(path, 16).count() == 1000


@pytest.mark.parametrize("unbias", ["false", "true"])
def test_delimited(spark, unbias):
    register_sources(spark)
    texts = spark.createDataFrame([("x" * (i % 50 + 1) + str(i),) for i in range(500)], "t string").coalesce(1)
    path = delimited_file(texts)
    df = spark.read.format("delimited_sample").option("path", path).option("p", 0.2).option("split", 4000).option("unbias", unbias).option("n_records", 100).load().collect()
    assert len({r.offset for r in df}) == len(df) > 40
    want = {r.t for r in texts.collect()}
    assert all(r.record in want and r.length == len(r.record) for r in df)


def test_a_split_short_of_records_is_read_through(spark):
    """One record takes nearly all bytes, so draws hardly ever meet the others."""
    register_sources(spark)
    texts = spark.createDataFrame([("x" * 200_000,), *((f"short{i}",) for i in range(30))], "t string").coalesce(1)
    path = delimited_file(texts)
    load = lambda n: spark.read.format("delimited_sample").option("path", path).option("p", 1.0).option("n_records", n).load()
    assert load(31).count() == 31 and load(20).select("offset").distinct().count() == 20
    assert load(50).count() == 31  # there are no more


def test_estimates_of_records_in_a_split():
    from wavesum.sources.readers import DelimitedReader

    of = lambda stat: DelimitedReader({"path": "x", "stat": stat}).estimated([10, 10, 40], 1200)
    assert (of("avg"), of("median"), of("min")) == (60, 120, 120)
    assert DelimitedReader({"path": "x", "n_records": "7"}).estimated([], 1200) == 7


def test_min_gap_and_unbiased_lengths(spark):
    register_sources(spark)
    texts = spark.createDataFrame([("x" * (400 if i % 2 else 20),) for i in range(400)], "t string").coalesce(1)
    path = delimited_file(texts)
    load = lambda **o: spark.read.format("delimited_sample").options(path=path, p="0.2", n_records="400", **o).load()
    far = sorted((r.offset, r.length) for r in load(min_gap="500").collect())
    assert len(far) == 80
    long = {u: load(unbias=u).filter("length > 100").count() for u in ("false", "true")}
    assert long["false"] > 65 and 25 <= long["true"] <= 55


def test_only_drawn_records_are_fetched(spark, tmp_path):
    from wavesum.sources.readers import FixedReader, files

    path = fixed_file(spark.range(20_000).selectExpr("id AS k").coalesce(1), 100)
    reader = FixedReader({"path": path, "record": "100", "p": "0.01", "gap": "0"})
    got = [b for part in reader.partitions() for b in reader.read(part)]
    assert sum(b.num_rows for b in got) == 200 and reader.bytes_read == 800
    assert sum(size for _, size in files(path)) == 2_000_000
    assert all(p == o for b in got for p, o in zip(b.column("pos").to_pylist(), b.column("ordinal").to_pylist()))


def test_parquet(spark, tmp_path):
    register_sources(spark)
    path = str(tmp_path / "t")
    spark.range(2000).coalesce(1).write.parquet(path)
    df = spark.read.format("parquet_ordinal_sample").option("path", path).option("column", "id").option("p", 0.05).load().collect()
    assert len(df) == 100 and all(r.pos == r.ordinal for r in df)


def test_keys(spark, tmp_path):
    df = spark.createDataFrame([(1, 5.0), (2, None), (3, 99.0)], "id bigint, x double")
    key = KeySpec("x", "t", "cast(floor(x) as bigint)", 4, "id % {m}", "id")
    assert [tuple(r) for r in project(df, key, 2, clip=True).orderBy("pos").collect()] == [(1, 5), (1, 15)]
    with pytest.raises(Exception, match="outside its domain"):
        project(df, key, 2).collect()
    assert df.select(Domain(8, origin=1, step=0.5).position(df.x).alias("p")).collect()[0].p == 8
    words = spark.createDataFrame([(w,) for w in "b a c a é z b".split()], "w string")
    assert {r.value: r.pos for r in dense_rank_ids(words, "w").collect()} == {"a": 0, "b": 1, "c": 2, "z": 3, "é": 4}
    spark.range(100).repartition(3).write.parquet(str(tmp_path / "p"))
    back = spark.read.parquet(str(tmp_path / "p"))
    assert back.select(physical_sites(back)).distinct().count() == 3
    assert back.select(super_site(back.id, 2)).distinct().count() == 2


def test_zipf(spark):
    rows = spark.range(3000).selectExpr("id % 4 AS site", "cast(id AS string) AS row_id")
    top = [zipf_positions(rows, a, 10).groupBy("pos").count().agg({"count": "max"}).first()[0] for a in (0.8, 1.4)]
    assert top[0] < top[1]
    assert zipf_positions(rows, 1.1, 10).filter("pos < 0 or pos >= 1024").count() == 0
