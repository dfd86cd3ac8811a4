"""Connected components of a graph of links, by large-star and small-star rounds over tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.llm.common import written


def _state(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(links: DataFrame) -> DataFrame:
    """(a, b) for every node a that isn't the smallest of its component, b being the smallest.

    links: (a, b) of long ids, any order, repeats and loops allowed; null ends are dropped.
    Every round leaves at most as many links as before and is written to the shared folder;
    it ends when a round changes nothing, after about the logarithm of the longest path in
    rounds.  A node with very many links is one key of a join, which adaptive execution splits.
    """
    links = written(links.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    seen = _state(links)
    while seen[0]:
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.join(least, "a").filter("b > a and b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        # a node that is its neighbours' least keeps its links through them
        large = large.distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a")
        links = written(small.filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b"))).distinct(), "links")
        now = _state(links)
        if now == seen:
            return links
        seen = now
    return links
