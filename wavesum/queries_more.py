"""Experiment sweeps and the operators around the summaries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wavesum.functions import haar
from wavesum.functions.keys import spec
from wavesum.operators import exact, sample
from wavesum.operators.freq import global_freq, local_freq
from wavesum.plans import accuracy, duck
from wavesum.queries import EPS, K, M, ORACLES, _union, _with_log2u, fitted, here, keyed, register, sampling_plan, true_values

# --- sweeps, one row a setting --------------------------------------------------------

KS = (10, 20, 30, 40, 50)
_part = spec("partkey")
_ranked = f"SELECT row_number() OVER (ORDER BY {duck.ENERGY} DESC, coef_id) AS rank, CAST(diff AS DOUBLE) * diff * pow(CAST(2 AS DOUBLE), greatest(level, 0) - {{u}}) AS e FROM ({{c}})"


def _sweep_k_sql(name: str) -> str:
    key = spec(name)
    c = duck.coefs(duck.freq(key), key.log2u)
    return f"SELECT k, round((total - kept) / total, 6) AS sse_share FROM (SELECT k, (SELECT CAST(sum(cnt * cnt) AS DOUBLE) FROM ({duck.freq(key)})) AS total, sum(e) AS kept FROM ({_ranked.format(u=key.log2u, c=c)}), (SELECT CAST(unnest({list(KS)}) AS INTEGER) AS k) WHERE rank <= k GROUP BY k)"


for _name in ("partkey", "words"):

    @register(f"sweep_k_sse_{_name}", _sweep_k_sql(_name))
    def sweep_k_sse(spark: SparkSession, sf_dir: str, name: str = _name) -> DataFrame:
        """Squared error of the exact k best over energy, k = 10 .. 50: one transform, one ranking of 50 rows."""
        df, log2u = _with_log2u(spark, sf_dir, name)
        freq = global_freq(df)
        top = haar.best_k(haar.by_subtree(freq, log2u), max(KS), log2u)
        w = Window.orderBy(haar.energy_key(F.col("diff"), F.col("level")).desc(), "coef_id")  # 50 rows
        ranked = top.withColumn("rank", F.row_number().over(w)).withColumn("e", F.col("value") * F.col("value"))
        total = float(accuracy.energy(freq))
        ks = spark.createDataFrame([(k,) for k in KS], "k int")
        kept = ranked.join(F.broadcast(ks), F.col("rank") <= F.col("k")).groupBy("k").agg(F.sum("e").alias("kept"))
        return kept.select("k", F.round((F.lit(total) - F.col("kept")) / F.lit(total), 6).alias("sse_share"))


MS = (4, 8, 16, 32, 64)


@register("sweep_m_comm", " UNION ALL ".join(f"SELECT {m} AS m, (SELECT count(*) FROM ({duck.local(_part, m)})) AS count_pairs, (SELECT count(*) FROM ({duck.coefs(duck.local(_part, m), 11, by='site')})) AS coef_pairs" for m in MS))
def sweep_m_comm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of both baselines over the number of sites."""
    out = []
    for m in MS:
        df, key = keyed(spark, sf_dir, "partkey", m)
        local = local_freq(df)
        coefs = haar.local_sparse(local, key.log2u)
        out.append(local.agg(F.count("*").alias("count_pairs")).join(coefs.agg(F.count("*").alias("coef_pairs"))).select(F.lit(m).alias("m"), "count_pairs", "coef_pairs"))
    return _union(out)


STEPS = {9: 1.0, 13: 0.1, 16: 0.01, 19: 0.001}
_value_freq = "SELECT CAST(floor(value / CAST({s} AS DOUBLE)) AS BIGINT) AS pos, event_id % 16 AS site, CAST(count(*) AS BIGINT) AS cnt FROM events GROUP BY 1, 2"


@register("sweep_u_comm", " UNION ALL ".join(f"SELECT {u} AS log2u, (SELECT count(*) FROM ({_value_freq.format(s=s)})) AS count_pairs, (SELECT count(*) FROM ({duck.coefs(_value_freq.format(s=s), u, by='site')})) AS coef_pairs" for u, s in STEPS.items()))
def sweep_u_comm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of both baselines over the domain's size: one value column at finer and finer steps."""
    events, out = spark.read.parquet(f"{sf_dir}/events.parquet"), []
    for log2u, step in STEPS.items():
        local = events.select((F.col("event_id") % M).alias("site"), F.floor(F.col("value") / F.lit(step)).cast("long").alias("pos")).groupBy("site", "pos").agg(F.count("*").alias("cnt"))
        # values of a larger table need a larger domain than the least one listed
        need = int(local.agg(F.coalesce(F.max("pos"), F.lit(0))).first()[0]).bit_length()
        coefs = haar.local_sparse(local, max(log2u, need))
        out.append(local.agg(F.count("*").alias("count_pairs")).join(coefs.agg(F.count("*").alias("coef_pairs"))).select(F.lit(log2u).alias("log2u"), "count_pairs", "coef_pairs"))
    return _union(out)


EPSES = (0.01, 0.02, 0.05, 0.1)
_SAMPLERS = ("precombine", "floor", "two_stage")


def _sweep_eps_sql() -> str:
    return " UNION ALL ".join(f"SELECT '{x}' AS method, CAST({e} AS DOUBLE) AS eps, (SELECT count(*) FROM ({duck.messages(x, spec('value'), M, e)})) AS pairs, ({duck.sse(spec('value'), duck.sampled_top(x, spec('value'), M, e, K))}) AS sse" for x in _SAMPLERS for e in EPSES)


@register("sweep_eps_sse", _sweep_eps_sql())
def sweep_eps_sse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs sent and squared error of the samplers over eps."""
    df, key = keyed(spark, sf_dir, "value", row_id=True)
    total, true = accuracy.energy(global_freq(df)), true_values(df, key.log2u)
    out = []
    for x in _SAMPLERS:
        for e in EPSES:
            plan = sampling_plan(df, eps=e)
            sent = sample.messages(x, df, plan)
            top = sample.best_k(sample.coefficients(sample.totals(sent), plan, key.log2u), K)
            out.append(sent.agg(F.count("*").alias("pairs")).join(accuracy.sse(total, true, top)).select(F.lit(x).alias("method"), F.lit(e).alias("eps"), "pairs", F.round("sse", 3).alias("sse")))
    return _union(out)


@register("cost_vs_sse")
def cost_vs_sse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes sent and squared error of samplers over eps and of the sketch over its size."""
    from wavesum.operators.sketch import ship_sketch
    from wavesum.queries import local_values

    df, key = keyed(spark, sf_dir, "value", row_id=True, key=fitted("value", sf_dir, spark))
    total, true = accuracy.energy(global_freq(df)), true_values(df, key.log2u)
    out = [("two_stage" if x == "two_stage" else x, str(e), x, e) for x in _SAMPLERS for e in (0.02, 0.05)]
    rows = []
    for label, setting, x, e in out:
        plan = sampling_plan(df, eps=e)
        sent = sample.messages(x, df, plan)
        top = sample.best_k(sample.coefficients(sample.totals(sent), plan, key.log2u), K)
        size = sent.agg(F.sum(F.when(F.col("cnt").isNull(), 4).otherwise(8))).first()[0] or 0
        rows.append((label, setting, int(size), float(accuracy.sse(total, true, top).first()[0])))
    local, _ = local_values(spark, sf_dir, "value", key)
    for kb in (5, 20):
        top, cells = ship_sketch(local, key.log2u, K, bytes_total=kb * 1024 * key.log2u)
        est = spark.createDataFrame(top, "coef_id bigint, value double")
        rows.append(("sketch", f"{kb} kB", cells.count() * 12, float(accuracy.sse(total, true, est).first()[0])))
    return spark.createDataFrame(rows, "method string, setting string, bytes bigint, sse double")


# --- relational operators around the methods ------------------------------------------

_LINE, _ORD, _EV = "lineitem.parquet", "orders.parquet", "events.parquet"


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}")


@register("freq_after_join", "SELECT CAST(o_custkey AS BIGINT) AS pos, CAST(count(*) AS BIGINT) AS cnt FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def freq_after_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Key counts over a join: lines are counted by order first, so the join moves a row an order."""
    lines = read(spark, sf_dir, _LINE).groupBy("l_orderkey").agg(F.count("*").alias("n"))
    return read(spark, sf_dir, _ORD).join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_custkey").alias("pos")).agg(F.sum("n").alias("cnt"))


_top_sql = f"SELECT coef_id FROM ({duck.best_k(_part, K)})"


@register("cand_semi", f"SELECT site, coef_id, diff FROM ({duck.coefs(duck.local(_part, 4), 11, by='site')}) WHERE coef_id IN ({_top_sql})")
def cand_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Local coefficients of the candidates: the third round's filter."""
    df, key = keyed(spark, sf_dir, "partkey", 4)
    top = exact.ship_counts(df, key.log2u, K).select("coef_id")
    return exact.local_coefs(df, key.log2u).join(F.broadcast(top), "coef_id", "left_semi").select("site", "coef_id", "diff")


@register("unsent_anti", f"SELECT site, coef_id, diff FROM ({duck.coefs(duck.local(_part, 4), 11, by='site')}) WHERE coef_id NOT IN ({_top_sql})")
def unsent_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, key = keyed(spark, sf_dir, "partkey", 4)
    top = exact.ship_counts(df, key.log2u, K).select("coef_id")
    return exact.local_coefs(df, key.log2u).join(F.broadcast(top), "coef_id", "left_anti").select("site", "coef_id", "diff")


@register("support_range_join", f"SELECT coef_id, CAST(count(*) AS BIGINT) AS keys, CAST(sum(cnt) AS BIGINT) AS n FROM (SELECT coef_id, CASE WHEN coef_id = 1 THEN 0 ELSE CAST(floor(log2(coef_id - 1)) AS INTEGER) END AS l FROM ({_top_sql})) c JOIN ({duck.freq(_part)}) f ON (c.coef_id = 1 OR (f.pos >> (11 - l)) = c.coef_id - 1 - (CAST(1 AS BIGINT) << l)) GROUP BY coef_id")
def support_range_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys under each kept coefficient: the range join lo <= pos < hi, written as an equi-join on (level, block)."""
    df, key = keyed(spark, sf_dir, "partkey")
    freq = global_freq(df)
    top = exact.ship_counts(df, key.log2u, K)
    level = F.greatest(F.col("level"), F.lit(0))
    block = F.when(F.col("coef_id") == 1, F.lit(0).cast("long")).otherwise(F.col("coef_id") - 1 - F.call_function("shiftleft", F.lit(1).cast("long"), level))
    terms = top.select("coef_id", level.alias("l"), block.alias("b"))
    spots = freq.select("cnt", F.col("pos"), F.explode(F.sequence(F.lit(0), F.lit(key.log2u - 1))).alias("l")).withColumn("b", F.call_function("shiftright", F.col("pos"), F.lit(key.log2u) - F.col("l")))
    return spots.join(F.broadcast(terms), ["l", "b"]).groupBy("coef_id").agg(F.count("*").alias("keys"), F.sum("cnt").alias("n"))


@register("sse_join", f"SELECT pos, cnt, coalesce(other, 0) AS other FROM (SELECT coalesce(a.pos, b.pos) AS pos, coalesce(a.cnt, 0) AS cnt, b.cnt AS other FROM ({duck.freq(spec('custkey'))}) a FULL JOIN ({duck.freq(_part)}) b ON a.pos = b.pos)")
def sse_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two frequency vectors side by side, absent counts 0: the full outer join of a brute-force error."""
    a = global_freq(keyed(spark, sf_dir, "custkey")[0])
    b = global_freq(keyed(spark, sf_dir, "partkey")[0]).withColumnRenamed("cnt", "other")
    return a.join(b, "pos", "full").select("pos", F.coalesce("cnt", F.lit(0)).alias("cnt"), F.coalesce("other", F.lit(0)).alias("other"))


@register("prefix_freq", f"SELECT pos, CAST(sum(cnt) OVER (ORDER BY pos) AS BIGINT) AS upto FROM ({duck.freq(_part)})")
def prefix_freq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running counts in key order: sums of high-bit blocks first, so no window spans all keys."""
    df, key = keyed(spark, sf_dir, "partkey")
    shift = max(0, key.log2u - 8)
    freq = global_freq(df).withColumn("block", F.call_function("shiftright", F.col("pos"), F.lit(shift)))
    before = Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = freq.groupBy("block").agg(F.sum("cnt").alias("n")).select("block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))  # 256 rows at most
    inside = Window.partitionBy("block").orderBy("pos")
    return freq.join(F.broadcast(starts), "block").select("pos", (F.col("start") + F.sum("cnt").over(inside)).cast("long").alias("upto"))


@register("topk_per_site", f"SELECT site, pos, cnt FROM (SELECT *, row_number() OVER (PARTITION BY site ORDER BY cnt DESC, pos) AS rank FROM ({duck.local(_part, M)})) WHERE rank <= 5")
def topk_per_site(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("site").orderBy(F.desc("cnt"), "pos")
    return local_freq(keyed(spark, sf_dir, "partkey")[0]).withColumn("rank", F.row_number().over(w)).filter("rank <= 5").drop("rank")


@register("coef_overlap", f"({_top_sql}) INTERSECT (SELECT coef_id FROM ({duck.best_k(spec('shipday'), K)}))")
def coef_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = (exact.ship_counts(*_with_log2u(spark, sf_dir, n), K).select("coef_id") for n in ("partkey", "shipday"))
    return a.intersect(b)


@register("asof_snapshot", "SELECT event_id, snapshot FROM events e ASOF JOIN (SELECT DISTINCT date_trunc('day', ts) AS snapshot FROM events WHERE event_type = 'purchase') s ON e.ts >= s.snapshot UNION ALL SELECT event_id, NULL AS snapshot FROM events WHERE ts < (SELECT min(date_trunc('day', ts)) FROM events WHERE event_type = 'purchase') OR ts IS NULL")
def asof_snapshot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The latest day with a purchase at or before each event: both sides in one ordered stream by month, carried over months."""
    events = read(spark, sf_dir, _EV).select("event_id", "ts")
    snaps = read(spark, sf_dir, _EV).filter("event_type = 'purchase'").select(F.date_trunc("day", "ts").alias("at")).distinct()
    both = events.select("event_id", F.col("ts").alias("at"), F.lit(None).cast("timestamp").alias("snap")).unionByName(snaps.select(F.lit(None).cast("long").alias("event_id"), "at", F.col("at").alias("snap")))
    both = both.withColumn("month", F.date_trunc("month", "at"))
    last = both.groupBy("month").agg(F.max("snap").alias("last"))
    carry = last.select("month", F.max("last").over(Window.orderBy("month").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))  # a row a month
    w = Window.partitionBy("month").orderBy("at").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return both.join(F.broadcast(carry), "month").select("event_id", F.coalesce(F.max("snap").over(w), "carried").alias("snapshot")).filter("event_id is not null")


@register("interval_join", "SELECT w AS window_id, CAST(count(*) AS BIGINT) AS n FROM events JOIN (SELECT CAST(unnest(range(0, 10)) AS BIGINT) AS w) ON value >= w * 50 AND value < w * 50 + 80 GROUP BY w")
def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in overlapping value windows [50 w, 50 w + 80): each value names its windows, so it's an equi-join."""
    top = F.floor(F.col("value") / 50)
    spots = read(spark, sf_dir, _EV).select("value", F.explode(F.sequence(F.greatest(top - 1, F.lit(0)), top)).alias("window_id")).filter("value < window_id * 50 + 80 and window_id < 10")
    return spots.groupBy("window_id").agg(F.count("*").alias("n"))


@register("rollup_level_site", f"SELECT site, level, CAST(count(*) AS BIGINT) AS n, CAST(sum(abs(diff)) AS BIGINT) AS mass FROM ({duck.coefs(duck.local(_part, 4), 11, by='site')}) GROUP BY ROLLUP (site, level)")
def rollup_level_site(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, key = keyed(spark, sf_dir, "partkey", 4)
    return exact.local_coefs(df, key.log2u).rollup("site", "level").agg(F.count("*").alias("n"), F.sum(F.abs("diff")).alias("mass"))


@register("pivot_level_sign", f"SELECT level, CAST(count(*) FILTER (WHERE diff > 0) AS BIGINT) AS up, CAST(count(*) FILTER (WHERE diff < 0) AS BIGINT) AS down FROM ({duck.coefs(duck.freq(_part), 11)}) GROUP BY level")
def pivot_level_sign(spark: SparkSession, sf_dir: str) -> DataFrame:
    coefs = haar.by_basis(global_freq(keyed(spark, sf_dir, "partkey")[0]), here("partkey", sf_dir).log2u)
    return coefs.groupBy("level").agg(F.count_if(F.col("diff") > 0).alias("up"), F.count_if(F.col("diff") < 0).alias("down"))


@register("props_json_freq", "SELECT json_extract_string(props, '$.k') AS k, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
def props_json_freq(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, _EV).groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"))


@register("udtf_haar", duck.coefs(duck.freq(spec("quantity")), 6))
def udtf_haar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The transform as a table function over partitions of subtrees, from SQL."""
    from wavesum.functions.udtfs import register_all

    register_all(spark)
    global_freq(keyed(spark, sf_dir, "quantity")[0]).createOrReplaceTempView("quantity_freq")
    return spark.sql("SELECT coef_id, level, CAST(sum(diff) AS BIGINT) AS diff FROM quantity_freq, LATERAL haar_contributions(pos, cnt, 6) GROUP BY coef_id, level HAVING sum(diff) <> 0")


@register("sql_ship_counts", duck.best_k(_part, K))
def sql_ship_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The baseline as Spark SQL text."""
    from wavesum.plans.sqltext import sql_text

    rows = keyed(spark, sf_dir, "partkey")[0]
    rows.createOrReplaceTempView("partkey_rows")
    return spark.sql(sql_text("ship_counts", "partkey_rows", here("partkey", sf_dir).log2u, K))


@register("incremental_freq", f"SELECT coef_id, diff FROM ({duck.coefs(duck.freq(spec('user')), 8)})")
def incremental_freq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Coefficients of a stored state plus those of what came later: the transform is linear, so both are just added.

    The state is a table of epochs; the later part is one more epoch, so running it again
    replaces it and counts it once.
    """
    from wavesum.streaming.streams import coefficient_sink, coefficient_state

    df, log2u = _with_log2u(spark, sf_dir, "user")
    path = _scratch(spark, "coefficients")
    keep = coefficient_sink(log2u, path)
    keep(df.filter("site < 8"), 0)
    for _ in range(2):  # the second time changes nothing
        keep(df.filter("site >= 8"), 1)
    return coefficient_state(spark, path).select("coef_id", "diff")


# --- sources and streams --------------------------------------------------------------


def _scratch(spark: SparkSession, name: str) -> str:
    import uuid

    from wavesum.functions.tables import shared_folder

    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


@register("csv_json_orc_round_trip", "SELECT CAST(user_id AS BIGINT) AS pos, CAST(3 * count(*) AS BIGINT) AS cnt FROM events GROUP BY 1")
def csv_json_orc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys written and read again as CSV, JSON and ORC."""
    keys, out = read(spark, sf_dir, _EV).select("user_id"), []
    for form in ("csv", "json", "orc"):
        path = _scratch(spark, form)
        keys.write.format(form).save(path)
        out.append(spark.read.schema("user_id bigint").format(form).load(path))
    return _union(out).groupBy(F.col("user_id").alias("pos")).agg(F.count("*").alias("cnt"))


@register("stream_freq_user", duck.freq(spec("user")))
def stream_freq_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running counts of a file stream, after all of it: those of the batch."""
    from wavesum.streaming.streams import run_freq

    return run_freq(read(spark, sf_dir, _EV).select("event_id", "ts", F.col("user_id").alias("pos")), _scratch(spark, "stream"))


@register("stream_coefs_user", f"SELECT coef_id, diff FROM ({duck.coefs(duck.freq(spec('user')), 8)})")
def stream_coefs_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Coefficient state kept by micro-batches: each adds its delta once, whatever is retried."""
    from wavesum.streaming.streams import run_coefs

    return run_coefs(read(spark, sf_dir, _EV).select("event_id", "ts", F.col("user_id").alias("pos")), here("user", sf_dir).log2u, _scratch(spark, "stream"))


@register("stream_windows", "SELECT time_bucket(INTERVAL '1 day', ts, TIMESTAMP '1970-01-01') AS start, event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1, 2")
def stream_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tumbling one-day windows by type over a file stream with a watermark that drops nothing."""
    from wavesum.streaming.streams import run_windows

    return run_windows(read(spark, sf_dir, _EV).select("event_id", "ts", "event_type"), _scratch(spark, "stream"))


@register("stream_sliding", "SELECT start, event_type, CAST(count(*) AS BIGINT) AS n FROM (SELECT time_bucket(INTERVAL '12 hours', ts, TIMESTAMP '1970-01-01') - CAST(o AS INTEGER) * INTERVAL '12 hours' AS start, event_type FROM events, (SELECT unnest([0, 1]) AS o)) GROUP BY 1, 2")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One-day windows every twelve hours over a file stream."""
    from wavesum.streaming.streams import run_sliding

    return run_sliding(read(spark, sf_dir, _EV).select("event_id", "ts", "event_type"), _scratch(spark, "stream"))


@register("stream_sessions", "SELECT user_id, min(ts) AS start, CAST(count(*) AS BIGINT) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL '6 hours' THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, session")
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a user, closed by six hours without an event."""
    from wavesum.streaming.streams import run_sessions

    return run_sessions(read(spark, sf_dir, _EV).select("event_id", "ts", "user_id"), _scratch(spark, "stream"))


@register("stream_deduplicated", "SELECT event_id, user_id FROM events")
def stream_deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events that all come twice, once each."""
    from wavesum.streaming.streams import run_deduplicated

    events = read(spark, sf_dir, _EV).select("event_id", "ts", "user_id")
    return run_deduplicated(events.unionByName(events), _scratch(spark, "stream")).select("event_id", "user_id")


@register("stream_stateful_counts", duck.freq(spec("user")))
def stream_stateful_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts by key kept by a stateful operator."""
    from wavesum.streaming.streams import run_state

    return run_state(read(spark, sf_dir, _EV).select("event_id", "ts", F.col("user_id").alias("pos")), _scratch(spark, "stream"))


@register("stream_late_rows")
def stream_late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts with a watermark of a day: what later files bring for passed days is left out."""
    from wavesum.streaming.streams import run_late

    return run_late(read(spark, sf_dir, _EV).select("event_id", "ts", "event_type"), _scratch(spark, "stream"))


#: Bytes of a split of the fixture files, so that the given tables have several.
_FIXED_SPLIT, _TEXT_SPLIT = 32_768, 262_144


def _drawn_sql(numbered: str, site: str, ordinal: str, p: str) -> str:
    """The drawn records of a relation with its site and the record's number in it."""
    from wavesum.sources.readers import mix_sql

    return f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY {site} ORDER BY {mix_sql(ordinal, site, 42)}, {ordinal}) AS drawn, floor({p} * count(*) OVER (PARTITION BY {site}) + 0.5) AS take FROM ({numbered})) WHERE drawn <= take"


_lines_sql = "SELECT CAST((o - o % 8192) / 8192 AS BIGINT) AS site, o, o % 8192 AS i, l_partkey AS pos FROM (SELECT row_number() OVER () - 1 AS o, l_partkey FROM lineitem)"


@register("seek_sample_fixed", f"SELECT site, o AS ordinal, CAST(pos AS BIGINT) AS pos FROM ({_drawn_sql(_lines_sql, 'site', 'i', '0.05')})")
def seek_sample_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A share of the records of a fixed-length file by seeking: exact sizes, no scan."""
    return _fixed_records(spark, sf_dir, 0.05)


def _fixed_records(spark: SparkSession, sf_dir: str, p: float) -> DataFrame:
    from wavesum.sources.gen import fixed_file
    from wavesum.sources.readers import register_sources

    register_sources(spark)
    path = fixed_file(read(spark, sf_dir, _LINE).select("l_partkey"), 4)
    return spark.read.format("fixed_sample").option("path", path).option("record", 4).option("p", p).option("split", _FIXED_SPLIT).load()


_text_sql = "SELECT row_number() OVER () - 1 AS r, octet_length(encode(replace(coalesce(text, ''), chr(10), ' '))) AS n FROM documents"
_text_sql = f"SELECT start, start + n + 5 AS stop, n, CAST((start - start % {_TEXT_SPLIT}) / {_TEXT_SPLIT} AS BIGINT) AS site FROM (SELECT *, CAST(sum(n + 5) OVER (ORDER BY r) - n - 5 AS BIGINT) AS start FROM ({_text_sql}))"
_WANTED = 5


def _hits_sql() -> str:
    from wavesum.sources.readers import mix_sql

    whole = f"SELECT *, (SELECT max(stop) FROM ({_text_sql})) AS total FROM (SELECT DISTINCT site FROM ({_text_sql}))"
    span = f"least({_TEXT_SPLIT}, total - site * {_TEXT_SPLIT})"
    tries = f"SELECT site, t, CAST(site * {_TEXT_SPLIT} + ({mix_sql('t', 'site', 42)} * CAST({span} AS UBIGINT) >> 32) AS BIGINT) AS byte FROM ({whole}), (SELECT unnest(range(0, 300)) AS t)"
    first = f"SELECT d.site, d.start, any_value(d.n) AS n, min(t) AS t FROM ({tries}) x JOIN ({_text_sql}) d ON d.site = x.site AND x.byte >= d.start AND x.byte < d.stop GROUP BY d.site, d.start"
    return f"SELECT CAST(start AS BIGINT) AS \"offset\", CAST(n AS BIGINT) AS length FROM (SELECT *, row_number() OVER (PARTITION BY site ORDER BY t) AS hit FROM ({first})) WHERE hit <= {_WANTED}"


@register("seek_sample_delimited", _hits_sql())
def seek_sample_delimited(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records of varying length found from random bytes by their trailing length: five of each split."""
    from wavesum.sources.gen import delimited_file
    from wavesum.sources.readers import register_sources

    register_sources(spark)
    path = delimited_file(read(spark, sf_dir, "documents.parquet").select("text"))
    return spark.read.format("delimited_sample").option("path", path).option("p", 0.1).option("n_records", 10 * _WANTED).option("split", _TEXT_SPLIT).load().select("offset", "length")


_rows_sql = "SELECT 0 AS site, row_number() OVER () - 1 AS o, l_partkey AS pos FROM lineitem"


@register("parquet_ordinal_sample", f"SELECT CAST(site AS BIGINT) AS site, o AS ordinal, CAST(pos AS BIGINT) AS pos FROM ({_drawn_sql(_rows_sql, 'site', 'o', '0.05')})")
def parquet_ordinal_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of a Parquet file by ordinal, row groups without one left out, the key column only."""
    return _parquet_records(spark, sf_dir, 0.05)


def _parquet_records(spark: SparkSession, sf_dir: str, p: float) -> DataFrame:
    from wavesum.sources.readers import register_sources

    register_sources(spark)
    return spark.read.format("parquet_ordinal_sample").option("path", f"{sf_dir}/{_LINE}").option("column", "l_partkey").option("p", p).load()


def _seek_top_sql(method: str, numbered: str, ordinal: str, m: int) -> str:
    p = f"(SELECT p FROM ({duck.plan(_part, m, 0.02)}))"
    drawn = f"SELECT CAST(site AS BIGINT) AS site, CAST(pos AS BIGINT) AS pos FROM ({_drawn_sql(numbered, 'site', ordinal, p)})"
    return f"SELECT coef_id, level, round(value, 6) AS value FROM ({duck.sampled_top(method, _part, m, 0.02, K, drawn=drawn)})"


for _method in ("precombine", "two_stage"):

    @register(f"{_method}_hist_seek_fixed", _seek_top_sql(_method, _lines_sql, "i", 8))
    def seek_fixed_hist(spark: SparkSession, sf_dir: str, method: str = _method) -> DataFrame:
        """A summary from a fixed-length file: n follows from its length, and only drawn records are fetched."""
        n = read(spark, sf_dir, _LINE).count()  # as the file's length over the record's
        plan = sample.Plan(n, -(-n * 4 // _FIXED_SPLIT), 0.02)
        return _seek_hist(method, _fixed_records(spark, sf_dir, plan.p), plan, here("partkey", sf_dir).log2u)

    @register(f"{_method}_hist_seek_parquet", _seek_top_sql(_method, _rows_sql, "o", 1))
    def seek_parquet_hist(spark: SparkSession, sf_dir: str, method: str = _method) -> DataFrame:
        """A summary from Parquet ordinals: n and the row groups' sizes come from the footers."""
        from wavesum.sources.readers import ParquetOrdinalReader

        parts = ParquetOrdinalReader({"path": f"{sf_dir}/{_LINE}", "column": "l_partkey"}).partitions()
        plan = sample.Plan(sum(x.hi for x in parts), len(parts), 0.02)
        return _seek_hist(method, _parquet_records(spark, sf_dir, plan.p), plan, here("partkey", sf_dir).log2u)


def _seek_hist(method: str, drawn: DataFrame, plan: sample.Plan, log2u: int) -> DataFrame:
    counts = sample.sample_freq(drawn)
    sent = sample.two_stage_messages(counts, plan) if method == "two_stage" else counts.withColumnRenamed("scnt", "cnt")
    return sample.best_k(sample.coefficients(sample.totals(sent), plan, log2u), K).select("coef_id", "level", F.round("value", 6).alias("value"))


@register("bounds_worked_sizes", "SELECT quantity, round(bytes, 3) AS bytes FROM (SELECT unnest(['uniform', 'floor', 'two_stage', 'two_stage_pairs']) AS quantity, unnest([4 / (eps * eps), 4 * m / eps, 8 * sqrt(m) / eps, 2 * sqrt(m) / eps]) AS bytes FROM (SELECT CAST(0.0001 AS DOUBLE) AS eps, CAST(count(DISTINCT l_orderkey % 1000) AS DOUBLE) AS m FROM lineitem))")
def bounds_worked_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes at eps 1e-4 and the sites that the lines have, by orders, 1,000 at most: what each sampler may send."""
    from wavesum.plans.cost import worked_sizes

    m = read(spark, sf_dir, _LINE).agg(F.count_distinct(F.col("l_orderkey") % 1000)).first()[0]
    return spark.createDataFrame([(k, round(float(v), 3)) for k, v in worked_sizes(m, 1e-4).items()], "quantity string, bytes double")


def _trials_sql(seeds: int) -> str:
    key = spec("user")
    runs = " UNION ALL ".join(f"SELECT pos, (rho + bare / weight) / p AS v FROM ({duck.totals('two_stage', key, M, 0.02, s)}), ({duck.plan(key, M, 0.02)})" for s in range(seeds))
    return f"SELECT f.pos, f.cnt, round(coalesce(s, 0) / {seeds} - f.cnt, 6) AS bias, round(sqrt(greatest(0, coalesce(q, 0) / {seeds} - pow(coalesce(s, 0) / {seeds}, 2))), 6) AS sd FROM ({duck.freq(key)}) f LEFT JOIN (SELECT pos, sum(v) AS s, sum(v * v) AS q FROM ({runs}) GROUP BY pos) t ON f.pos = t.pos"


@register("sampler_trials_user", _trials_sql(10))
def sampler_trials_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bias and deviation of two-stage count estimates over ten seeds."""
    df, _ = keyed(spark, sf_dir, "user", row_id=True)
    plan = sampling_plan(df, eps=0.02)
    runs = [sample.estimates(sample.totals(sample.messages("two_stage", df, plan, seed=s)), plan) for s in range(10)]
    return accuracy.trials(global_freq(df), runs).select("pos", "cnt", F.round("bias", 6).alias("bias"), F.round("sd", 6).alias("sd"))


@register("sketch_cells_keywise_user", ORACLES["sketch_cells_user"])
def sketch_cells_keywise_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same cells from updates by distinct key instead of by coefficient."""
    from wavesum.operators.sketch import GroupSketch, key_updates

    df, key = keyed(spark, sf_dir, "user")
    g = GroupSketch(key.log2u)
    cells = g.merge(g.cells(key_updates(local_freq(df), key.log2u), "diff", by=("site",)))
    return cells.select("lvl", "row", F.col("bucket").cast("long").alias("bucket"), F.col("sub").cast("long").alias("sub"), F.col("val").cast("long").alias("val")).filter("val <> 0")


@register("ship_coefs_physical", duck.best_k(_part, K))
def ship_coefs_physical(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Coefficients shipped by file pieces, transformed inside the scan."""
    log2u = here("partkey", sf_dir).log2u
    local = exact.local_coefs_physical(read(spark, sf_dir, _LINE), "l_partkey", log2u)
    sums = local.groupBy("coef_id", "level").agg(F.sum("diff").cast("long").alias("diff")).filter("diff <> 0")
    return haar.best_k(sums, K, log2u).select("coef_id", "diff", F.round("value", 6).alias("value"))


for _name in ("partkey", "price"):

    @register(f"signed_topk_physical_{_name}", duck.best_k(spec(_name), K))
    def signed_topk_physical(spark: SparkSession, sf_dir: str, name: str = _name) -> DataFrame:
        """The threshold rounds with file pieces as sites: only messages are shuffled."""
        key = here(name, sf_dir)
        got = exact.signed_topk_physical(read(spark, sf_dir, _LINE), key.position, key.log2u, K).items
        return got.select("coef_id", "diff", F.round("value", 6).alias("value"))


_SHARES = (1, 2, 4)


def _sweep_n_sql() -> str:
    parts = []
    for x in _SHARES:
        key = _part.at(table=f"(SELECT * FROM lineitem WHERE l_orderkey % 4 < {x})")
        m = M * x // 4
        parts.append(f"SELECT {x} AS quarters, {m} AS m, (SELECT count(*) FROM ({duck.local(key, m)})) AS count_pairs, (SELECT count(*) FROM ({duck.messages('two_stage', key, m, 0.02)})) AS two_stage_pairs")
    return " UNION ALL ".join(parts)


@register("sweep_n_comm", _sweep_n_sql())
def sweep_n_comm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs over the number of records, with sites of one size."""
    from wavesum.functions.keys import project

    key, out = here("partkey", sf_dir), []
    for x in _SHARES:
        m = M * x // 4
        df = project(read(spark, sf_dir, _LINE).filter(F.col("l_orderkey") % 4 < x), key, m, row_id=True)
        sent = sample.messages("two_stage", df, sampling_plan(df, m, 0.02))
        out.append(local_freq(df).agg(F.count("*").alias("count_pairs")).join(sent.agg(F.count("*").alias("two_stage_pairs"))).select(F.lit(x).alias("quarters"), F.lit(m).alias("m"), "count_pairs", "two_stage_pairs"))
    return _union(out)


@register("coef_variance_user")
def coef_variance_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variance of estimated coefficients over ten second-level seeds, beside the bound in the sample's counts."""
    from wavesum.plans.accuracy import coef_variance, coefficient_variance_bound

    df, key = keyed(spark, sf_dir, "user", row_id=True, key=fitted("user", sf_dir, spark))
    plan = sampling_plan(df, eps=0.02)
    counts = sample.sample_freq(sample.level1(df, plan))
    runs = [sample.coefficients(sample.totals(sample.two_stage_messages(counts, plan, seed=s)), plan, key.log2u) for s in range(10)]
    # each coefficient's own support in the sample
    inside = counts.groupBy("pos").agg(F.sum("scnt").alias("cnt")).select(*haar.contributions(key.log2u, F.col("pos"), F.col("cnt"))).groupBy(F.col("c.coef_id").alias("coef_id"), F.greatest(F.col("c.level"), F.lit(0)).alias("level")).agg(F.sum("cnt").alias("inside"))
    unit = coefficient_variance_bound(1, plan.n, plan.m, plan.eps, 0, key.log2u)
    return coef_variance(runs).join(inside, "coef_id").select("coef_id", "variance", (F.lit(float(unit)) * F.col("inside") * F.pow(F.lit(2.0), F.col("level"))).alias("bound"))


# --- one of each kind of relational operator ------------------------------------------


@register("window_ranks", "SELECT event_id, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS n, CAST(rank() OVER (PARTITION BY user_id ORDER BY date_trunc('day', ts)) AS BIGINT) AS r, CAST(dense_rank() OVER (PARTITION BY user_id ORDER BY date_trunc('day', ts)) AS BIGINT) AS d, CAST(ntile(4) OVER (PARTITION BY user_id ORDER BY event_id) AS BIGINT) AS q, lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS before, first_value(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS first FROM events")
def window_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ranks, tiles and neighbours of each user's events: two sorts of one partitioning."""
    w = Window.partitionBy("user_id").orderBy("event_id")
    day = Window.partitionBy("user_id").orderBy(F.date_trunc("day", "ts"))
    return read(spark, sf_dir, _EV).select("event_id", F.row_number().over(w).cast("long").alias("n"), F.rank().over(day).cast("long").alias("r"), F.dense_rank().over(day).cast("long").alias("d"), F.ntile(4).over(w).cast("long").alias("q"), F.lag("event_id").over(w).alias("before"), F.first("event_id").over(w).alias("first"))


@register("moving_counts", "SELECT pos, CAST(sum(cnt) OVER (PARTITION BY pos >> 4 ORDER BY pos ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS around FROM (" + duck.freq(spec("shipday")) + ")")
def moving_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy(F.call_function("shiftright", F.col("pos"), F.lit(4))).orderBy("pos").rowsBetween(-2, 2)
    return global_freq(keyed(spark, sf_dir, "shipday")[0]).select("pos", F.sum("cnt").over(w).alias("around"))


@register("set_operations", "SELECT 'both' AS kind, CAST(count(*) AS BIGINT) AS n FROM (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A') UNION ALL SELECT 'only' AS kind, CAST(count(*) AS BIGINT) AS n FROM (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R' EXCEPT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A') UNION ALL SELECT 'any' AS kind, CAST(count(*) AS BIGINT) AS n FROM (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R' UNION SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A')")
def set_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys common to, only in, and in either of two parts of a table."""
    lines = read(spark, sf_dir, _LINE)
    r, a = (lines.filter(F.col("l_returnflag") == x).select("l_partkey") for x in "RA")
    made = {"both": r.intersect(a), "only": r.subtract(a), "any": r.union(a).distinct()}
    return _union([df.agg(F.count("*").alias("n")).select(F.lit(k).alias("kind"), "n") for k, df in made.items()])


@register("cube_orders", "SELECT o_orderstatus, o_orderpriority, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def cube_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, _ORD).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@register("quantiles_by_type", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(min(value), 6) AS low, round(max(value), 6) AS high FROM events GROUP BY 1")
def quantiles_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, _EV).groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.min("value"), 6).alias("low"), F.round(F.max("value"), 6).alias("high"))


@register("max_by_site", "SELECT site, CAST(arg_max(pos, cnt * 100000 - pos) AS BIGINT) AS pos FROM (" + duck.local(_part, M) + ") GROUP BY site")
def max_by_site(spark: SparkSession, sf_dir: str) -> DataFrame:
    return local_freq(keyed(spark, sf_dir, "partkey")[0]).groupBy("site").agg(F.max_by("pos", F.col("cnt") * 100000 - F.col("pos")).alias("pos"))


@register("coin_hash", "SELECT o_orderkey, CAST(" + duck.h32("o_orderkey", "42", "1") + " AS BIGINT) AS h FROM orders")
def coin_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The samplers' coins."""
    return read(spark, sf_dir, _ORD).select("o_orderkey", sample.h32(F.col("o_orderkey"), 42, 1).alias("h"))


@register("date_parts", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(count(*) AS BIGINT) AS n, CAST(sum(datediff('day', timestamp '1992-01-01', o_orderdate)) AS BIGINT) AS days FROM orders GROUP BY 1, 2")
def date_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    days = F.expr("datediff(o_orderdate, timestamp'1992-01-01')")
    return read(spark, sf_dir, _ORD).groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(F.count("*").alias("n"), F.sum(days).alias("days"))


@register("left_join_counts", "SELECT n_name, CAST(count(DISTINCT c_custkey) AS BIGINT) AS customers, CAST(count(o_orderkey) AS BIGINT) AS orders FROM nation LEFT JOIN customer ON n_nationkey = c_nationkey LEFT JOIN orders ON c_custkey = o_custkey GROUP BY n_name")
def left_join_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders counted by customer before the joins, so each join moves a row a customer."""
    orders = read(spark, sf_dir, _ORD).groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("k"))
    customers = read(spark, sf_dir, "customer.parquet").join(orders, "c_custkey", "left").groupBy("c_nationkey").agg(F.count("*").alias("customers"), F.sum("k").alias("k"))
    nation = read(spark, sf_dir, "nation.parquet")
    return nation.join(customers, nation["n_nationkey"] == customers["c_nationkey"], "left").select("n_name", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("k", F.lit(0)).cast("long").alias("orders"))


@register("embedding_dims", "SELECT CAST(i - 1 AS BIGINT) AS dim, CAST(sum(CAST(round(CAST(embedding[i] AS DOUBLE) * 1000000) AS BIGINT)) AS BIGINT) AS total FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY 1")
def embedding_dims(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "embeddings.parquet").select(F.posexplode("embedding").alias("dim", "x"))
    return e.groupBy(F.col("dim").cast("long").alias("dim")).agg(F.sum(F.round(F.col("x").cast("double") * 1000000).cast("long")).alias("total"))


@register("url_hosts", "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, CAST(count(*) AS BIGINT) AS n, CAST(sum(length(html)) AS BIGINT) AS chars FROM pages GROUP BY 1")
def url_hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages.parquet").groupBy(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host")).agg(F.count("*").alias("n"), F.sum(F.length("html")).alias("chars"))


@register("distinct_counts", "SELECT event_type, CAST(count(DISTINCT user_id) AS BIGINT) AS users FROM events GROUP BY 1")
def distinct_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, _EV).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@register("exact_distinct", f"SELECT CAST(count(DISTINCT pos) AS BIGINT) AS keys, CAST(min(pos) AS BIGINT) AS lo, CAST(max(pos) AS BIGINT) AS hi FROM ({duck.rows(_part, 1)})")
def exact_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(spark, sf_dir, "partkey")[0].agg(F.count_distinct("pos").alias("keys"), F.min("pos").alias("lo"), F.max("pos").alias("hi"))


@register("map_functions", "SELECT k, CAST(sum(v) AS BIGINT) AS n FROM (SELECT event_type AS k, count(*) AS v FROM events GROUP BY 1) GROUP BY 1")
def map_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts by type as one map a day, merged from its entries; to JSON and back on the way."""
    days = read(spark, sf_dir, _EV).groupBy(F.date_trunc("day", "ts").alias("day"), "event_type").agg(F.count("*").alias("n"))
    maps = days.groupBy("day").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("counts"))
    back = maps.select(F.from_json(F.to_json("counts"), "map<string,bigint>").alias("counts")).select(F.transform_values("counts", lambda k, v: v).alias("counts"))
    return back.select(F.explode("counts").alias("k", "v")).groupBy("k").agg(F.sum("v").alias("n"))


@register("approximate_distinct")
def approximate_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct keys and a built-in histogram beside the exact ones: fixed-size state whatever the input."""
    return keyed(spark, sf_dir, "partkey")[0].agg(F.approx_count_distinct("pos", 0.02).alias("about"), F.count_distinct("pos").alias("exact"), F.histogram_numeric("pos", F.lit(8)).alias("bins"))


@register("case_filters", "SELECT CAST(count(*) FILTER (WHERE l_quantity BETWEEN 10 AND 20) AS BIGINT) AS mid, CAST(count(*) FILTER (WHERE l_returnflag IN ('R', 'A')) AS BIGINT) AS back, CAST(count(*) FILTER (WHERE l_linestatus LIKE 'O%') AS BIGINT) AS open, CAST(count(*) FILTER (WHERE l_shipdate IS NULL) AS BIGINT) AS unknown FROM lineitem")
def case_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.count_if
    return read(spark, sf_dir, _LINE).agg(c(F.col("l_quantity").between(10, 20)).alias("mid"), c(F.col("l_returnflag").isin("R", "A")).alias("back"), c(F.col("l_linestatus").like("O%")).alias("open"), c(F.col("l_shipdate").isNull()).alias("unknown"))
