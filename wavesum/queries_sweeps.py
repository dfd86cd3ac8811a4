"""The published experiments as queries: every method over every parameter, with costs and errors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavesum.functions.keys import KeySpec, spec
from wavesum.plans import experiments
from wavesum.plans.cost import LINK_BITS
from wavesum.plans.experiments import EXACT, SAMPLERS, Setting, method_sql, phases_sql, sweep, sweep_sql
from wavesum.queries import K, M, fitted, here, register

MAIN = ("ship_counts", "ship_coefs", "signed_topk", "floor", "two_stage")
ALL = (*EXACT, *SAMPLERS)

#: For each sweep: the column, the methods, and the settings by value, from the key of a folder and its records.
SWEEPS: dict = {}


def sweeping(name: str, key: str, column: str, methods: tuple[str, ...], settings, records: int = 0) -> None:
    """Registers a sweep: settings(key, n) gives {value: Setting}; `records` is n in the fixed folder of the SQL twin."""
    SWEEPS[name] = (key, column, methods, settings)

    @register(name, sweep_sql(settings(spec(key) if isinstance(key, str) else key(None, None), records), methods, column))
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = here(key, sf_dir, spark) if isinstance(key, str) else key(spark, sf_dir)
        n = spark.read.parquet(f"{sf_dir}/{found.table}.parquet").count() if found.table != "words" else 0  # from footers
        return sweep(spark, sf_dir, settings(found, n), methods, column)

    run.__doc__ = f"Pairs, bytes and error of {', '.join(methods)} over {column}."


# k and eps, on skewed keys (words) and flat ones
sweeping("sweep_k_methods_words", "words", "k", MAIN, lambda key, n: {k: Setting(key, M, k, 0.02) for k in (10, 20, 30, 40, 50)})
sweeping("sweep_k_methods_value", "value", "k", MAIN, lambda key, n: {k: Setting(key, M, k, 0.02) for k in (10, 30, 50)})
EPS_GRID = (0.01, 0.02, 0.05, 0.1)
for _key in ("words", "user"):
    sweeping(f"sweep_eps_methods_{_key}", _key, "eps", SAMPLERS, lambda key, n: {e: Setting(key, M, K, e) for e in EPS_GRID})

# records, with sites of one size
sweeping("sweep_n_methods", "partkey", "quarters", MAIN, lambda key, n: {x: Setting(key, M * x // 4, K, 0.02, f"SELECT * FROM {{table}} WHERE l_orderkey % 4 < {x}") for x in (1, 2, 4)})

# bytes of a record, n fixed: splits of 2^20 bytes, so the number of sites grows with the record
SPLIT_BYTES = 1 << 20
sweeping("sweep_record_size", "partkey", "record_bytes", ("ship_counts", "signed_topk", "floor", "two_stage"), lambda key, n: {r: Setting(key, max(1, -(-n * r // SPLIT_BYTES)), K, 0.02) for r in (4, 64, 256, 1024)}, 60_000)

# domain: one value column at finer and finer steps
STEPS = {9: 1.0, 13: 0.1, 16: 0.01, 19: 0.001}


def _steps(key: KeySpec, n: int) -> dict:
    return {log2u: Setting(key.at(position=f"cast(floor(value / cast('{step!r}' as double)) as bigint)", log2u=max(log2u, key.log2u + log2u - 9)), M, K, 0.02) for log2u, step in STEPS.items()}


sweeping("sweep_u_methods", "value", "log2u", MAIN, _steps)

# number of sites, and sites that are stretches or a mix of the key's order
sweeping("sweep_m_methods", "partkey", "m", MAIN, lambda key, n: {m: Setting(key, m, K, 0.02) for m in (4, 16, 64)})
sweeping("sweep_order_methods", "user", "contiguous", ("ship_counts", "signed_topk", "two_stage"), lambda key, n: {mixed: Setting(key.at(site=site), M, K, 0.02) for mixed, site in ((0, "event_id % {m}"), (1, f"cast(floor(event_id / {max(1, -(-n // M))}) as bigint)"))}, 10_000)

# skew
ZIPF_LOG2U = 14


def _zipf(key: KeySpec, n: int) -> dict:
    h = f"concat_ws(':', {key.row_id}, '7', '3')"
    from wavesum.sources.gen import permuted_sql, zipf_rank_sql

    def source(bits: str, alpha: float) -> str:
        # a step a column, so that none is computed twice
        return f"SELECT *, {permuted_sql('zipf_rank', ZIPF_LOG2U)} AS z FROM (SELECT *, {zipf_rank_sql('zipf_bits', alpha, ZIPF_LOG2U)} AS zipf_rank FROM (SELECT *, {bits} AS zipf_bits FROM {{table}}))"

    out = {}
    for alpha in (0.8, 1.1, 1.4):
        in_spark = source(f"CAST(conv(substring(md5({h}), 1, 8), 16, 10) AS BIGINT)", alpha)
        in_duck = source(f"CAST(('0x' || substr(md5({h}), 1, 8)) AS BIGINT)", alpha)
        out[alpha] = Setting(key.at(name="zipf", position="z", log2u=ZIPF_LOG2U), M, K, 0.02, in_spark, in_duck)
    return out


sweeping("sweep_skew_methods", "partkey", "alpha", MAIN, _zipf)


def _skew_comm_sql() -> str:
    parts = []
    for alpha, s in _zipf(spec("partkey"), 0).items():
        key = s.sql_key()
        parts.append(f"SELECT CAST({alpha} AS DOUBLE) AS alpha, CAST(count(*) AS BIGINT) AS count_pairs, {experiments.exact_share(key, K)} AS sse_share FROM ({experiments.duck.local(key, M)})")
    return " UNION ALL ".join(parts)


@register("sweep_skew_comm", _skew_comm_sql())
def sweep_skew_comm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Zipf keys of three exponents drawn by row hash: pairs of the baseline and error of the best terms."""
    out = []
    for alpha, s in _zipf(here("partkey", sf_dir, spark), 0).items():
        run = s.run(spark, sf_dir)
        _, pairs, _, share = run.method("ship_counts")
        out.append((alpha, pairs, share))
    return spark.createDataFrame(out, "alpha double, count_pairs bigint, sse_share double")


# composite keys of a log: (user, event type), and (supplier, part)
def user_type(spark: SparkSession | None, sf_dir: str | None) -> KeySpec:
    users = here("user", sf_dir, spark) if spark else spec("user")
    codes = " ".join(f"WHEN '{t}' THEN {i}" for i, t in enumerate(("click", "error", "purchase", "signup", "view")))
    return users.at(name="user_type", position=f"cast(user_id * 8 + CASE event_type {codes} ELSE 7 END as bigint)", log2u=users.log2u + 3)


sweeping("log_methods_user_type", user_type, "eps", MAIN, lambda key, n: {e: Setting(key, M, K, e) for e in (0.02, 0.05)})
sweeping("log_methods_pair", "pair", "eps", MAIN, lambda key, n: {e: Setting(key, M, K, e) for e in (0.02,)})
sweeping("log_eps_user_type", user_type, "eps", SAMPLERS, lambda key, n: {e: Setting(key, M, K, e) for e in EPS_GRID})

# cost at the same error: the cheapest setting of each method whose error is at most a share of the energy


def _cheapest(of: str, target: float) -> None:
    key, column, methods, settings = SWEEPS[of]
    fixed = spec(key) if isinstance(key, str) else key(None, None)
    sql = f"SELECT method, CAST(min(bytes) AS BIGINT) AS bytes, max({column}) AS {column} FROM ({sweep_sql(settings(fixed, 0), methods, column)}) WHERE sse_share <= {target} GROUP BY method"

    @register(of.replace("sweep_eps_methods", "cost_at_error").replace("log_eps", "cost_at_error_log"), sql)
    def cheapest(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Bytes of the cheapest setting of each sampler whose error is at most the target."""
        found = here(key, sf_dir, spark) if isinstance(key, str) else key(spark, sf_dir)
        got = sweep(spark, sf_dir, settings(found, 0), methods, column)
        return got.filter(F.col("sse_share") <= target).groupBy("method").agg(F.min("bytes").alias("bytes"), F.max(column).alias(column))


for _of, _target in (("sweep_eps_methods_words", 0.4), ("sweep_eps_methods_user", 0.62), ("log_eps_user_type", 0.999)):
    _cheapest(_of, _target)


# bandwidth: what moving the bytes takes over shares of the link
SHARES = (0.1, 0.2, 0.5, 1.0)
_default = lambda key: Setting(key, M, K, 0.02)


@register("bandwidth_methods", f"SELECT method, CAST(share AS DOUBLE) AS share, bytes, round(bytes * 8 / ({LINK_BITS} * share), 6) AS seconds FROM ({' UNION ALL '.join(method_sql(x, _default(spec('partkey'))) for x in MAIN)}), (SELECT CAST(unnest({list(SHARES)}) AS DOUBLE) AS share)")
def bandwidth_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds that moving each method's bytes takes over shares of the link, computing aside."""
    run = _default(here("partkey", sf_dir, spark)).run(spark, sf_dir)
    sizes = spark.createDataFrame([run.method(x) for x in MAIN], experiments.SCHEMA)
    return sizes.select("method", F.explode(F.array(*[F.lit(x) for x in SHARES])).alias("share"), "bytes").withColumn("seconds", F.round(F.col("bytes") * 8 / (F.lit(LINK_BITS) * F.col("share")), 6))


# the rounds of the exact method, in both engines
for _name in ("words", "value", "partkey"):
    _key = spec(_name)

    @register("signed_topk_phases_words" if _name == "words" else f"rounds_{_name}", phases_sql(experiments.duck.coefs(experiments.duck.local(_key, M), _key.log2u, by="site"), _key.log2u, K, M))
    def rounds(spark: SparkSession, sf_dir: str, name: str = _name) -> DataFrame:
        """What each round sends, its threshold, and how many candidates are left."""
        from wavesum.operators import exact
        from wavesum.operators.freq import rows

        key = here(name, sf_dir, spark)
        got = exact.signed_topk(rows(spark, sf_dir, key, M), key.log2u, K, M, by_id=True)
        return spark.createDataFrame([(p["phase"], int(p["pairs"]), round(float(p.get("t1", p.get("t2", 0.0))), 6), int(p.get("candidates", 0))) for p in got.phases], "phase int, pairs bigint, threshold double, candidates bigint")


@register("approx_topk_words", phases_sql(experiments.duck.coefs(experiments.duck.local(spec("words"), M), spec("words").log2u, by="site"), spec("words").log2u, K, M, estimates=True))
def approx_topk_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two rounds only: middles of the bounds."""
    from wavesum.operators import exact
    from wavesum.operators.freq import rows

    key = here("words", sf_dir, spark)
    got = exact.signed_topk(rows(spark, sf_dir, key, M), key.log2u, K, M, by_id=True, stop_after=2)
    return got.items.select("coef_id", *[F.round(c, 6).alias(c) for c in ("value", "low", "high")])


def _ablation_sql() -> str:
    key = spec("value")
    local = experiments.duck.coefs(experiments.duck.local(key, M), key.log2u, by="site")
    return " UNION ALL ".join(f"SELECT {resend} AS resend, {tight} AS tight, phase, pairs FROM ({phases_sql(local, key.log2u, K, M, tight, resend)})" for resend in (False, True) for tight in (False, True))


@register("ablation_resend_tight", _ablation_sql())
def ablation_resend_tight(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs by round with and without sending again, and with and without intersected bounds."""
    from wavesum.operators import exact
    from wavesum.operators.freq import rows

    key, out = here("value", sf_dir, spark), []
    df = rows(spark, sf_dir, key, M)
    for resend in (False, True):
        for tight in (False, True):
            got = exact.signed_topk(df, key.log2u, K, M, by_id=True, resend=resend, tight=tight)
            out += [(resend, tight, p["phase"], int(p["pairs"])) for p in got.phases]
    return spark.createDataFrame(out, "resend boolean, tight boolean, phase int, pairs bigint")


# seconds of every method by itself, and the sketch beside them: nothing that SQL could repeat
for _name in ("partkey", "price", "value"):

    @register(f"times_{_name}")
    def times(spark: SparkSession, sf_dir: str, name: str = _name) -> DataFrame:
        """Seconds, pairs, bytes and error of every method, each run by itself."""
        return experiments.timed(spark, sf_dir, _default(fitted(name, sf_dir, spark)), (*MAIN, "ship_counts_physical", "signed_topk_physical", "uniform", "sketch"))


@register("times_zipf")
def times_zipf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds, shuffled bytes, pairs, bytes and error of every method on Zipf keys of exponent 1.1."""
    s = _zipf(fitted("partkey", sf_dir, spark), 0)[1.1]
    return experiments.timed(spark, sf_dir, s, (*MAIN, "ship_counts_physical", "signed_topk_physical", "uniform"))


for _sweep in ("sweep_n_methods", "sweep_m_methods"):

    @register(_sweep.replace("methods", "times"))
    def sweep_times(spark: SparkSession, sf_dir: str, of: str = _sweep) -> DataFrame:
        """Seconds, shuffled bytes, pairs, bytes and error of the methods at each setting of a sweep."""
        key, column, methods, settings = SWEEPS[of]
        found = fitted(key, sf_dir, spark)
        n = spark.read.parquet(f"{sf_dir}/{found.table}.parquet").count()
        return experiments.timed_sweep(spark, sf_dir, settings(found, n), methods, column)


@register("sweep_skew_sketch")
def sweep_skew_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes and error of the sketch over the Zipf exponent."""
    out = []
    for alpha, s in _zipf(fitted("partkey", sf_dir, spark), 0).items():
        out.append((alpha, *s.run(spark, sf_dir).method("sketch", bytes_total=5 * 1024 * ZIPF_LOG2U)))
    return spark.createDataFrame(out, f"alpha double, {experiments.SCHEMA}")


@register("sweep_k_sketch_user")
def sweep_k_sketch_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes and error of the sketch over k."""
    run = _default(fitted("user", sf_dir, spark)).run(spark, sf_dir)
    return spark.createDataFrame([(k, *run.method("sketch", k)) for k in (10, 30, 50)], f"k int, {experiments.SCHEMA}")


@register("sweep_sketch_user")
def sweep_sketch_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes and error of the sketch over its size."""
    s = _default(fitted("user", sf_dir, spark))
    run = s.run(spark, sf_dir)
    out = [(kb, *run.method("sketch", bytes_total=kb * 1024 * s.key.log2u)) for kb in (2, 5, 20)]
    return spark.createDataFrame(out, f"kilobytes int, {experiments.SCHEMA}")
