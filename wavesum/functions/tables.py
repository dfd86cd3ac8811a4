"""Reading the given tables, and tables between the rounds of a method."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_local: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which all executors share; a temporary folder only with a local master."""
    conf = spark.sparkContext.getConf()
    if base := conf.get("spark.checkpoint.dir"):
        return base.rstrip("/")
    if "cluster" in (master := conf.get("spark.master", "local")) or not master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if not _local:
        _local.append(tempfile.mkdtemp(prefix="wavesum-rounds-"))
    return _local[0]


#: Tables that this process has written and not removed.
_tables: list[str] = []


def cleanup(spark: SparkSession) -> int:
    """Removes the tables that `materialize` has made; to be called when nothing that reads them is wanted any more."""
    gone = 0
    while _tables:
        path = spark._jvm.org.apache.hadoop.fs.Path(_tables.pop())
        gone += path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    return gone


def materialize(df: DataFrame, name: str) -> DataFrame:
    """df written to the shared folder and read back: later rounds don't compute it again, and lost executors don't matter."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    _tables.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dealt(df: DataFrame) -> DataFrame:
    """df, its rows dealt out where its files are fewer than the cores: a file of one row group is read by one task."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if len(df.inputFiles()) < cores else df


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, ord, word): every white-space token of the documents and its place."""
    text = F.split(F.trim("text"), r"\s+")
    texts = dealt(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").filter("text is not null"))
    return texts.select("doc_id", F.posexplode(text).alias("ord", "word")).filter("word <> ''")


def word_counts(spark: SparkSession, sf_dir: str, key, m: int) -> DataFrame:
    """(site, pos, cnt): tokens counted by site and word before anything moves; a position is the word's rank.

    One pass over the texts; the ranks and their join see a row for each word and site.
    """
    from wavesum.functions.keys import dense_rank_ids

    tokens = words(spark, sf_dir).select(F.expr(key.site.format(m=m)).cast("long").alias("site"), "word")
    counts = materialize(tokens.groupBy("site", "word").agg(F.count("*").alias("cnt")), "word-counts")
    ranks = dense_rank_ids(counts, "word").withColumnRenamed("value", "word")
    return counts.join(ranks, "word").select("site", "pos", "cnt")


def word_positions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, ord, pos): tokens as ranks of the words, for methods that sample single tokens."""
    from wavesum.functions.keys import dense_rank_ids

    tokens = words(spark, sf_dir)
    ranks = dense_rank_ids(tokens.select("word").distinct(), "word").withColumnRenamed("value", "word")
    # a hot word is one key of the join: the ranks are broadcast while they're few
    ranks = F.broadcast(ranks) if ranks.count() <= 1_000_000 else ranks
    return tokens.join(ranks, "word").select("doc_id", "ord", "pos")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return word_positions(spark, sf_dir) if name == "words" else spark.read.parquet(f"{sf_dir}/{name}.parquet")
