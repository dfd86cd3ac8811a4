"""Keys, domains and sites: how a table becomes (site, pos) rows.

A record's key is mapped to a 0-based position in a domain of 2^log2u values; a site stands
for a split of the data and is always a column, never a partition number, because adaptive
execution may merge or split partitions.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Domain:
    """2^log2u positions; a raw value x is at floor((x - origin) / step)."""

    log2u: int
    origin: float = 0
    step: float = 1

    @property
    def size(self) -> int:
        return 1 << self.log2u

    def position(self, value: Column) -> Column:
        if self.origin == 0 and self.step == 1:
            return F.floor(value).cast("long")
        return F.floor((value - F.lit(self.origin)) / F.lit(self.step)).cast("long")


@dataclass(frozen=True)
class KeySpec:
    """Where a key comes from.

    position and row_id: SQL over the table; site: SQL with {m}, the number of sites.
    Both engines read the same text, so it sticks to what they share.  beyond: positions past
    the domain are no error; they make further blocks of its width, whose ids go on counting.
    """

    name: str
    table: str
    position: str
    log2u: int
    site: str
    row_id: str
    beyond: bool = False

    @property
    def domain(self) -> Domain:
        return Domain(self.log2u)

    def at(self, **changes) -> KeySpec:
        return replace(self, **changes)


def spec(name: str, sf: str = "0.01") -> KeySpec:
    """The key specifications of the given tables, with the domain for a scale."""
    at = {"0.001": 0, "0.01": 1, "0.1": 2}[sf]
    line, order, event = "l_orderkey % {m}", "o_orderkey % {m}", "event_id % {m}"
    line_id = "concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey)"
    part, pair = (8, 11, 15)[at], (12, 18, 25)[at]
    all_ = {
        "partkey": ("lineitem", "l_partkey", part, line, line_id),
        "suppkey": ("lineitem", "l_suppkey", (4, 7, 10)[at], line, line_id),
        "quantity": ("lineitem", "cast(l_quantity as bigint)", 6, line, line_id),
        "shipday": ("lineitem", "cast(datediff({day}) as bigint)", 12, line, line_id),
        "price": ("lineitem", "cast(floor(l_extendedprice) as bigint)", 17, line, line_id),
        "pair": ("lineitem", f"l_suppkey * {1 << part} + l_partkey", pair, line, line_id),
        "custkey": ("orders", "o_custkey", (8, 11, 14)[at], order, "o_orderkey"),
        "user": ("events", "user_id", (4, 8, 11)[at], event, "event_id"),
        "value": ("events", "cast(floor(value) as bigint)", (9, 9, 10)[at], event, "event_id"),
        "value_cents": ("events", "cast(floor(value * 100) as bigint)", (15, 16, 16)[at], event, "event_id"),
        "nchars": ("documents", "n_chars", (15, 16, 17)[at], "doc_id % {m}", "doc_id"),
        "words": ("words", "pos", (15, 17, 19)[at], "doc_id % {m}", "concat_ws(':', doc_id, ord)"),
    }
    return KeySpec(name, *all_[name])


def spark_text(text: str) -> str:
    return text.replace("{day}", "l_shipdate, timestamp'1992-01-01'")


def duck_text(text: str) -> str:
    return text.replace("datediff({day})", "datediff('day', timestamp '1992-01-01', l_shipdate)")


def scale_of(sf_dir: str) -> str | None:
    """The scale in the name of one of the given folders, else None."""
    name = sf_dir.rstrip("/").rpartition("/")[2]
    return name[2:] if name in ("sf0.001", "sf0.01", "sf0.1") else None


def spec_for(spark, sf_dir: str, name: str) -> KeySpec:
    """The key of a folder: domains of the given folders are listed, others follow from the largest position there."""
    if scale := scale_of(sf_dir):
        return spec(name, scale)
    key = spec(name)
    if name == "words":
        from wavesum.functions.tables import words

        most = words(spark, sf_dir).agg(F.count_distinct("word")).first()[0]
    elif name == "pair":
        low = spec_for(spark, sf_dir, "partkey").log2u
        key = key.at(position=f"l_suppkey * {1 << low} + l_partkey")
        most = _most(spark, sf_dir, key) + 1
    else:
        most = _most(spark, sf_dir, key) + 1
    return key.at(log2u=max(1, (most - 1).bit_length()))


def _most(spark, sf_dir: str, key: KeySpec) -> int:
    """The largest position of a key; a negative one is outside any domain."""
    low, high = spark.read.parquet(f"{sf_dir}/{key.table}.parquet").agg(F.min(F.expr(spark_text(key.position))), F.max(F.expr(spark_text(key.position)))).first()
    if low is not None and low < 0:
        raise ValueError(f"{key.name} has positions under 0")
    return int(high or 0)


def project(df: DataFrame, key: KeySpec, m: int, row_id: bool = False, clip: bool = False, check: bool = True) -> DataFrame:
    """(site, pos[, row_id]) of every record with a key; only the columns needed are read.

    Null keys are left out.  A position outside the domain raises, or with clip moves to
    its nearest end; a key with `beyond` has no upper end.
    """
    pos = F.expr(spark_text(key.position)).cast("long")
    top = (1 << key.log2u) - 1
    if clip:
        # greatest and least pass nulls over, so a null key is kept null apart
        pos = F.when(pos.isNotNull(), F.least(F.greatest(pos, F.lit(0)), F.lit(top)))
    elif check:
        inside = pos >= 0 if key.beyond else pos.between(0, top)
        pos = F.when(inside | pos.isNull(), pos).otherwise(F.raise_error(F.concat(F.lit(f"{key.name} outside its domain: "), pos.cast("string"))).cast("long"))
    cols = [F.expr(key.site.format(m=m)).cast("long").alias("site"), pos.alias("pos")]
    if row_id:
        cols.append(F.expr(key.row_id).cast("string").alias("row_id"))
    return df.select(*cols).filter("pos is not null")


def physical_sites(df: DataFrame) -> Column:
    """A site for each piece of a file that a scan reads: its path and first byte."""
    return F.xxhash64(F.col("_metadata.file_path"), F.col("_metadata.file_block_start")).alias("site")


def super_site(site: Column, most: int) -> Column:
    """Sites merged into at most `most`: linearity lets a site be any union of splits."""
    return F.pmod(site, F.lit(most)).alias("site")


def dense_rank_ids(values: DataFrame, column: str) -> DataFrame:
    """(value, pos): 0-based rank of each distinct value in binary order.

    A range sort numbers the rows inside its partitions; the partitions' sizes, one row
    each, are summed up before them, so there's no window over everything.
    """
    from wavesum.functions.tables import materialize

    ordered = values.select(F.col(column).alias("value")).filter("value is not null").distinct().repartitionByRange("value").sortWithinPartitions("value")
    numbered = materialize(ordered.select("value", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("at")), "ranks")
    from pyspark.sql import Window

    sizes = numbered.groupBy("part").agg(F.count("*").alias("n"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    return numbered.join(F.broadcast(starts), "part").select("value", (F.col("start") + F.col("at")).cast("long").alias("pos"))
