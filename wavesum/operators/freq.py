"""Frequency vectors, global and by site."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavesum.functions.keys import KeySpec, project
from wavesum.functions.tables import table, word_counts


def rows(spark: SparkSession, sf_dir: str, key: KeySpec, m: int, row_id: bool = False) -> DataFrame:
    """(site, pos[, row_id]) records; words without row ids come counted by site, as (site, pos, cnt)."""
    if key.table == "words" and not row_id:
        return word_counts(spark, sf_dir, key, m)
    return project(table(spark, sf_dir, key.table), key, m, row_id)


def _count(keyed: DataFrame):
    return (F.sum("cnt").cast("long") if "cnt" in keyed.columns else F.count("*")).alias("cnt")


def global_freq(keyed: DataFrame) -> DataFrame:
    """(pos, cnt): partial counts in the scan's tasks, then one shuffle of them."""
    return keyed.groupBy("pos").agg(_count(keyed))


def local_freq(keyed: DataFrame) -> DataFrame:
    """(site, pos, cnt)."""
    return keyed.groupBy("site", "pos").agg(_count(keyed))


def merge(*freqs: DataFrame) -> DataFrame:
    """Counts of several parts added up."""
    out = freqs[0]
    for f in freqs[1:]:
        out = out.unionByName(f)
    return out.groupBy("pos").agg(F.sum("cnt").cast("long").alias("cnt"))
