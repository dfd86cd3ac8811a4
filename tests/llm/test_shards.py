"""The query's shards as they lie in the shared folder."""

import collections
import glob
import zlib


def test_query_writes_the_texts_in_slot_order(spark, docs, rows, monkeypatch, tmp_path):
    from wavesum.llm import common, sharding

    monkeypatch.setattr(common, "shared_dir", lambda _: str(tmp_path))
    monkeypatch.setattr(sharding, "shared_dir", lambda _: str(tmp_path), raising=False)
    got = sharding.shard_documents(docs, 3, bucket_bytes=4000).collect()
    (path,) = glob.glob(f"{tmp_path}/shards-*")
    assert sorted(x.rsplit("/", 1)[1] for x in glob.glob(f"{path}/shard=*")) == ["shard=0", "shard=1", "shard=2"]
    back = spark.read.parquet(path).collect()
    text = lambda r: (r.doc_id, r.text, r.extra, r["Bucket"])
    assert collections.Counter(map(text, back)) == collections.Counter((r[0], r[1], r[5], r[6]) for r in rows)
    slot = collections.defaultdict(list)
    for r in sorted(back, key=lambda r: (r.shard, r["_bucket"], r.mix)):
        slot[r.shard].append((r.doc_id, zlib.crc32((r.text or "").encode())))
    for shard, want in slot.items():
        assert [(r.doc_id, r.text_crc32) for r in sorted(got, key=lambda r: r.slot) if r.shard == shard] == want


def test_buckets_are_sized_by_bytes(spark):
    from wavesum.llm.sharding import scatter

    df = spark.createDataFrame([(i, "x" * 10_000) for i in range(200)], "doc_id bigint, text string")
    cut, (shard, bucket, _) = scatter(df, 2, 50_000, 100_000, 1, "text")
    n = [r["count"] for r in cut.groupBy(shard, bucket).count().collect()]
    assert len(n) > 15 and max(n) < 30


def test_slots_follow_from_the_seed_alone(spark, docs):
    from wavesum.llm.sharding import shard_documents

    def slots(df):
        return sorted(((r.shard, r.slot, str(r.doc_id), r.text_crc32) for r in shard_documents(df, 3, bucket_rows=40).collect()))

    want = slots(docs)
    old = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.enabled")}
    try:
        for n, adaptive in ((1, "true"), (13, "false"), (7, "true")):
            spark.conf.set("spark.sql.shuffle.partitions", str(n))
            spark.conf.set("spark.sql.adaptive.enabled", adaptive)
            assert slots(docs.repartition(n + 2)) == want
    finally:
        for k, v in old.items():
            spark.conf.set(k, v)


def test_a_hot_id_of_equal_rows_fills_no_bucket(spark):
    from wavesum.llm.sharding import scatter

    df = spark.createDataFrame([(7, "same")] * 900 + [(i, "x") for i in range(100, 1000)], "doc_id bigint, text string").repartition(5)
    cut, (shard, bucket, _) = scatter(df, 2, 100, 1 << 30, 1, "text")
    assert cut.columns == ["doc_id", "text", shard, bucket, "mix"]
    n = [r["count"] for r in cut.groupBy(shard, bucket).count().collect()]
    assert sum(n) == 1800 and max(n) < 260
