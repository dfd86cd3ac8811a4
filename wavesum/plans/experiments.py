"""The experiments: every method on one table and setting, as a run in Spark and as SQL text.

A setting is a key over a table, m sites, k and eps.  For each method a run gives the pairs
and bytes that the sites send, and the squared error of its k terms over the energy; timed,
the seconds too.  The SQL text gives the same figures, for methods that SQL can express.
"""

from __future__ import annotations

import time
import uuid
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavesum.functions import haar
from wavesum.functions.keys import KeySpec, project
from wavesum.functions.tables import materialize, table
from wavesum.operators import exact, sample, sketch
from wavesum.operators.freq import global_freq, local_freq, rows
from wavesum.plans import accuracy, duck
from wavesum.plans.cost import WIDTHS, physical

EXACT = ("ship_counts", "ship_coefs", "signed_topk")
SAMPLERS = ("uniform", "precombine", "floor", "two_stage")
SCHEMA = "method string, pairs bigint, bytes bigint, sse_share double"


@dataclass(frozen=True)
class Setting:
    """source: Spark SQL over the given table, in {table}; None is the table itself.  duck_source: the same where the text differs."""

    key: KeySpec
    m: int = 16
    k: int = 30
    eps: float = 0.02
    source: str | None = None
    duck_source: str | None = None

    def at(self, **changes) -> Setting:
        return replace(self, **changes)

    def rows(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """(site, pos, row_id)."""
        df = table(spark, sf_dir, self.key.table)
        if self.source:
            df = spark.sql(self.source, table=df)
        out = project(df, self.key, self.m, row_id=True)
        return materialize(out, "setting-rows") if self.source else out  # made keys are data, not part of a method

    def sql_key(self) -> KeySpec:
        text = self.duck_source or self.source
        return self.key.at(table=f"({text.format(table=self.key.table)})") if text else self.key

    def run(self, spark: SparkSession, sf_dir: str) -> Run:
        counted = local_freq(rows(spark, sf_dir, self.key, self.m)) if self.key.table == "words" else None
        return Run(self.rows(spark, sf_dir), self, counted)


class Run:
    """One setting's data, made once for all its methods."""

    def __init__(self, keyed: DataFrame, setting: Setting, site_counts: DataFrame | None = None):
        self.keyed, self.s = keyed, setting
        self.local = materialize(site_counts if site_counts is not None else local_freq(keyed), "run-local")
        self.freq = global_freq(self.local)
        total = self.freq.agg(F.coalesce(F.sum("cnt"), F.lit(0)), F.coalesce(F.sum(F.col("cnt").cast("decimal(19,0)") * F.col("cnt").cast("decimal(19,0)")), F.lit(0)), F.max("pos")).first()
        self.n, self.energy = int(total[0]), float(total[1])
        self.past = (total[2] or 0) >= setting.key.domain.size
        self._true = self._sampled = None
        self.seconds: dict[str, float] = {}

    @property
    def true(self) -> DataFrame:
        """(coef_id, level, diff, value) of all coefficients."""
        if self._true is None:
            coefs = haar.by_subtree(self.freq, self.s.key.log2u)
            self._true = materialize(coefs.withColumn("value", haar.value_of(F.col("diff"), F.col("level"), self.s.key.log2u)), "run-true")
        return self._true

    def sampled(self, eps: float) -> tuple[sample.Plan, DataFrame]:
        """The first level, which all samplers share."""
        plan = sample.Plan(self.n, self.s.m, eps)
        if self._sampled is None or self._sampled[0] != plan:
            self._sampled = plan, materialize(sample.sample_freq(sample.level1(self.keyed, plan)), "run-sample")
        return self._sampled

    def share(self, top: DataFrame) -> float:
        sse = accuracy.sse(self.energy, self.true, top).select(F.round("sse", 3)).first()[0]
        return round(sse / self.energy, 6) if self.energy else 0.0

    def shares(self, ranked: DataFrame, ks: tuple[int, ...]) -> dict[int, float]:
        """Error shares of the first k of `ranked` (coef_id, value, best first), for several k: at most max(ks) rows."""
        best = [(r.coef_id, r.value) for r in ranked.limit(max(ks)).collect()]
        frame = self.keyed.sparkSession.createDataFrame([(c, float(v)) for c, v in best], "coef_id bigint, est double")
        true = {r.coef_id: r.value for r in self.true.join(F.broadcast(frame), "coef_id").select("coef_id", "value").collect()}
        out, error = {}, self.energy
        for i, (c, v) in enumerate(best, 1):
            w = true.get(c, 0.0)
            error += (v - w) ** 2 - w**2
            if i in ks:
                out[i] = error
        return {k: round(round(out.get(k, error), 3) / self.energy, 6) if self.energy else 0.0 for k in ks}

    def exact_top(self, k: int) -> DataFrame:
        return haar.best_k(self.true.select("coef_id", "level", "diff"), k, self.s.key.log2u)

    def messages(self, method: str, eps: float) -> tuple[int, int, DataFrame | None]:
        """Pairs, bytes, and what is sent."""
        plan, counts = self.sampled(eps)
        if method == "uniform":
            n = int(counts.agg(F.coalesce(F.sum("scnt"), F.lit(0))).first()[0])
            return n, n * WIDTHS["keys"], counts.select("site", "pos", F.col("scnt").alias("cnt"))  # the sum of what is sent
        sent = {"precombine": lambda: counts.select("site", "pos", F.col("scnt").alias("cnt")), "floor": lambda: sample.floor_messages(counts, plan), "two_stage": lambda: sample.two_stage_messages(counts, plan)}[method]()
        pairs, bare = sent.agg(F.count("*"), F.count_if(F.col("cnt").isNull())).first()
        return pairs, pairs * WIDTHS["counts"] - bare * (WIDTHS["counts"] - WIDTHS["keys"]), sent

    def estimates(self, sent: DataFrame, eps: float, k: int) -> DataFrame:
        plan, _ = self.sampled(eps)
        return sample.best_k(sample.coefficients(sample.totals(sent), plan, self.s.key.log2u), k)

    def coefs(self, k: int) -> DataFrame:
        return haar.local_sparse(self.local, self.s.key.log2u, k)

    def method(self, name: str, k: int | None = None, eps: float | None = None, bytes_total: int | None = None) -> tuple[str, int, int, float]:
        """(method, pairs, bytes, sse_share)."""
        k, eps, began = k or self.s.k, eps or self.s.eps, time.perf_counter()
        if name == "ship_counts":
            pairs = self.local.count()
            out = pairs, pairs * WIDTHS["counts"], self.share(self.exact_top(k))
        elif name == "ship_coefs":
            pairs = self.coefs(0).count()
            out = pairs, pairs * WIDTHS["coefs"], self.share(self.exact_top(k))
        elif name == "signed_topk":
            got = exact.signed_topk_of(self.coefs(k), self.s.key.log2u, k, self.s.m, by_id=True)
            if self.past:  # the costs are those of messages by id, which may miss a term there
                got.items = exact.signed_topk_of(self.coefs(k), self.s.key.log2u, k, self.s.m).items
            out = got.pairs, got.pairs * WIDTHS["marked"] + sum(p.get("down_bytes", 0) for p in got.phases), self.share(got.items)
        elif name == "sketch":
            values = self.coefs(0).select("site", "coef_id", haar.value_of(F.col("diff"), F.col("level"), self.s.key.log2u).alias("value"))
            top, cells = sketch.ship_sketch(values, self.s.key.log2u, k, bytes_total=bytes_total)
            pairs = cells.count()
            out = pairs, pairs * WIDTHS["cells"], self.share(self.keyed.sparkSession.createDataFrame(top, "coef_id bigint, value double"))
        else:
            pairs, size, sent = self.messages(name, eps)
            out = pairs, size, self.share(self.estimates(sent, eps, k))
        self.seconds[name] = time.perf_counter() - began
        return (name, int(out[0]), int(out[1]), float(out[2]))


def timed(spark: SparkSession, sf_dir: str, s: Setting, methods: tuple[str, ...]) -> DataFrame:
    """Each method by itself, from the table to its k terms: (method, seconds, shuffle_bytes, pairs, bytes, sse_share).

    Methods named `.._physical` read the key from m files, whose scan tasks are the sites; what
    they send is that of the method with m sites, up to the split.
    """
    out, pieces, made = [], None, s.rows(spark, sf_dir) if s.source else None
    if any(name.endswith("_physical") for name in methods):
        from wavesum.functions.tables import shared_folder
        from wavesum.sources.gen import splits_parquet

        # the key in as many files as there are sites, so that scan tasks are sites
        pieces = splits_parquet((s.rows(spark, sf_dir) if made is None else made).select("pos"), f"{shared_folder(spark)}/pieces-{uuid.uuid4().hex}", s.m)

    def alone(name: str) -> None:
        if name.endswith("_physical"):
            df = spark.read.parquet(pieces)
            if name == "ship_counts_physical":
                exact.ship_counts(df, s.key.log2u, s.k).collect()
            else:
                exact.signed_topk_physical(df, "pos", s.key.log2u, s.k).items.collect()
            return
        if made is not None:
            keyed = made
        else:
            keyed = rows(spark, sf_dir, s.key, s.m) if name in (*EXACT, "sketch") else s.rows(spark, sf_dir)
        if name == "ship_counts":
            top = exact.ship_counts(keyed, s.key.log2u, s.k)
        elif name == "ship_coefs":
            top = exact.ship_coefs(keyed, s.key.log2u, s.k)
        elif name == "signed_topk":
            top = exact.signed_topk(keyed, s.key.log2u, s.k, s.m).items
        elif name == "sketch":
            local = exact.local_coefs(keyed, s.key.log2u)
            sketch.ship_sketch(local.select("site", "coef_id", haar.value_of(F.col("diff"), F.col("level"), s.key.log2u).alias("value")), s.key.log2u, s.k)
            return
        else:
            n = spark.read.parquet(f"{sf_dir}/{s.key.table}.parquet").count() if s.key.table != "words" and not s.source else keyed.count()  # from footers
            top = sample.histogram(name, keyed, sample.Plan(n, s.m, s.eps), s.key.log2u, s.k, fast=True)
        top.collect()

    for name in methods:
        began = time.perf_counter()
        stages = physical(spark, lambda name=name: alone(name))
        out.append((name, time.perf_counter() - began, stages["shuffle_write"]))
    run, sizes = s.run(spark, sf_dir), {}
    for name in methods:  # a physical run sends what its method sends, so that is counted once
        base = name.removesuffix("_physical")
        sizes[name] = sizes[base] if base in sizes else run.method(base)[1:]
    return spark.createDataFrame([(name, took, int(size), *sizes[name]) for name, took, size in out], "method string, seconds double, shuffle_bytes bigint, pairs bigint, bytes bigint, sse_share double")


def timed_sweep(spark: SparkSession, sf_dir: str, settings: dict, methods: tuple[str, ...], column: str) -> DataFrame:
    """`timed` at every setting."""
    out = None
    for x, s in settings.items():
        got = timed(spark, sf_dir, s, methods).select(F.lit(float(x)).alias(column), "*")
        out = got if out is None else out.unionByName(got)
    return out


# --- the same in SQL ------------------------------------------------------------------


def phases_sql(local: str, log2u: int, k: int, m: int, tight: bool = True, resend: bool = False, estimates: bool = False) -> str:
    """(phase, pairs, threshold, candidates) of the threshold rounds over local coefficients (site, coef_id, level, diff).

    estimates: instead of it the (coef_id, value, low, high) that are known after two rounds.
    """
    near = "(1 - 1e-9)"
    again, more = ("later", "TRUE") if resend else ("later AND NOT sent", "NOT sent AND NOT later")
    least, most = (f"least(hi, t1 / {m})", f"greatest(lo, -t1 / {m})") if tight else (f"t1 / {m}", f"-t1 / {m}")
    last = f"""SELECT CAST(1 AS INTEGER) AS phase, (SELECT count(*) FROM f WHERE sent) AS pairs, round((SELECT t1 FROM t), 6) AS threshold, CAST(0 AS BIGINT) AS candidates
UNION ALL SELECT 2, (SELECT count(*) FROM g WHERE {again}), round((SELECT t2 FROM t2), 6), (SELECT count(*) FROM w)
UNION ALL SELECT 3, (SELECT count(*) FROM g JOIN w USING (item) WHERE {more}), 0.0, CAST(0 AS BIGINT)"""
    if estimates:
        last = f"SELECT item AS coef_id, round((low + high) / 2, 6) AS value, round(low, 6) AS low, round(high, 6) AS high FROM w ORDER BY round(abs((low + high) / 2), 9) DESC, item LIMIT {k}"
    kth = f"coalesce((SELECT fl FROM (SELECT CASE WHEN low <= 0 AND high >= 0 THEN 0.0 ELSE least(abs(low), abs(high)) END AS fl FROM {{0}}) ORDER BY fl DESC LIMIT 1 OFFSET {k - 1}), 0.0)"
    t2 = f"greatest(t1, {kth.format('two')})" if tight else kth.format("two")
    return f"""WITH l AS MATERIALIZED (SELECT site, coef_id AS item, CAST(diff AS DOUBLE) * sqrt(pow(CAST(2 AS DOUBLE), greatest(level, 0) - {log2u})) AS v FROM ({local})),
f AS MATERIALIZED (SELECT *, d <= {k} OR u <= {k} AS sent FROM (SELECT *, row_number() OVER (PARTITION BY site ORDER BY v DESC, item) AS d, row_number() OVER (PARTITION BY site ORDER BY v, item) AS u FROM l)),
b AS MATERIALIZED (SELECT site, greatest(0.0, coalesce(max(CASE WHEN d = {k} THEN v END), 0.0)) AS hi, least(0.0, coalesce(max(CASE WHEN u = {k} THEN v END), 0.0)) AS lo FROM f GROUP BY site),
one AS (SELECT item, sum(v) + (SELECT sum(lo) FROM b) - sum(lo) AS low, sum(v) + (SELECT sum(hi) FROM b) - sum(hi) AS high FROM f JOIN b USING (site) WHERE sent GROUP BY item),
t AS MATERIALIZED (SELECT CAST({kth.format('one')} AS DOUBLE) AS t1),
g AS MATERIALIZED (SELECT f.*, t1 = 0 OR abs(v) >= t1 / {m} * {near} AS later FROM f, t),
c AS MATERIALIZED (SELECT site, {least} AS hi, {most} AS lo FROM b, t),
two AS MATERIALIZED (SELECT item, sum(v) + (SELECT sum(lo) FROM c) - sum(lo) AS low, sum(v) + (SELECT sum(hi) FROM c) - sum(hi) AS high FROM g JOIN c USING (site) WHERE sent OR later GROUP BY item),
t2 AS MATERIALIZED (SELECT {t2} AS t2 FROM t),
w AS MATERIALIZED (SELECT item, low, high FROM two, t2 WHERE greatest(abs(low), abs(high)) >= t2 * {near})
{last}"""


def exact_share(key: KeySpec, k: int) -> str:
    energy = f"(SELECT CAST(sum(cnt * cnt) AS DOUBLE) FROM ({duck.freq(key)}))"
    top = f"SELECT coef_id, CAST(diff AS DOUBLE) * sqrt(pow(CAST(2 AS DOUBLE), greatest(level, 0) - {key.log2u})) AS value FROM ({duck.coefs(duck.freq(key), key.log2u)}) ORDER BY {duck.ENERGY} DESC, coef_id LIMIT {k}"
    return f"round(({duck.sse(key, top)}) / {energy}, 6)"


def method_sql(name: str, s: Setting) -> str:
    """One row: method, pairs, bytes, sse_share."""
    key = s.sql_key()
    local = duck.local(key, s.m)
    if name in EXACT:
        if name == "ship_counts":
            pairs = f"SELECT count(*) AS pairs, count(*) * {WIDTHS['counts']} AS bytes FROM ({local})"
        elif name == "ship_coefs":
            pairs = f"SELECT count(*) AS pairs, count(*) * {WIDTHS['coefs']} AS bytes FROM ({duck.coefs(local, key.log2u, by='site')})"
        else:
            pairs = f"SELECT sum(pairs) AS pairs, sum(pairs) * {WIDTHS['marked']} + {8 * s.m} + {4 * s.m} * sum(candidates) AS bytes FROM ({phases_sql(duck.coefs(local, key.log2u, by='site'), key.log2u, s.k, s.m)})"
        return f"SELECT '{name}' AS method, CAST(pairs AS BIGINT) AS pairs, CAST(bytes AS BIGINT) AS bytes, {exact_share(key, s.k)} AS sse_share FROM ({pairs})"
    sent = duck.messages(name, key, s.m, s.eps)
    energy = f"(SELECT CAST(sum(cnt * cnt) AS DOUBLE) FROM ({duck.freq(key)}))"
    width = f"{WIDTHS['keys']}" if name == "uniform" else f"CASE WHEN cnt IS NULL THEN {WIDTHS['keys']} ELSE {WIDTHS['counts']} END"
    return f"SELECT '{name}' AS method, CAST(count(*) AS BIGINT) AS pairs, CAST(coalesce(sum({width}), 0) AS BIGINT) AS bytes, round(({duck.sse(key, duck.sampled_top(name, key, s.m, s.eps, s.k))}) / {energy}, 6) AS sse_share FROM ({sent})"


def sweep_sql(settings: dict, methods: tuple[str, ...], column: str) -> str:
    """settings: value of the varied parameter to Setting."""
    return " UNION ALL ".join(f"SELECT {x!r}::DOUBLE AS {column}, * FROM ({method_sql(name, s)})" for x, s in settings.items() for name in methods)


def sweep(spark: SparkSession, sf_dir: str, settings: dict, methods: tuple[str, ...], column: str) -> DataFrame:
    """Every method at every setting; settings that differ in k or eps only share their data."""
    out, runs = [], {}
    for x, s in settings.items():
        same = s.at(k=0, eps=0.0)
        if same not in runs:
            runs = {same: s.run(spark, sf_dir)}
        out += [(float(x), *runs[same].method(name, s.k, s.eps)) for name in methods]
    return spark.createDataFrame(out, f"{column} double, {SCHEMA}")
