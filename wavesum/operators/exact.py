"""Exact best-k summaries: ship counts, ship coefficients, and the threshold rounds."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.functions import haar
from wavesum.functions.tables import materialize
from wavesum.operators import topk
from wavesum.operators.freq import global_freq, local_freq


def ship_counts(keyed: DataFrame, log2u: int, k: int = 30) -> DataFrame:
    """Local counts (the partial aggregate), their sum by key, the transform by subtrees, the best k.

    keyed: (site, pos) records without null keys, or (site, pos, cnt).  Ties go to the lower
    id; without records there are no coefficients; with fewer than k nonzero ones, these.
    """
    return haar.best_k(haar.by_subtree(global_freq(keyed), log2u), k, log2u)


def local_coefs(keyed: DataFrame, log2u: int, k: int = 0) -> DataFrame:
    # records are counted before they move; what comes counted is added up where it meets
    return haar.local_sparse(keyed if "cnt" in keyed.columns else local_freq(keyed), log2u, k)


def ship_coefs(keyed: DataFrame, log2u: int, k: int = 30) -> DataFrame:
    """Nonzero local coefficients, summed by id: right because the transform is linear.  Cases as in `ship_counts`."""
    sums = local_coefs(keyed, log2u).groupBy("coef_id", "level").agg(F.sum("diff").cast("long").alias("diff")).filter("diff <> 0")
    return haar.best_k(sums, k, log2u)


#: Bits of an item that hold a coefficient's level, plus one.
LEVEL_BITS = 6


def scores_of(local: DataFrame, log2u: int, by_id: bool = False) -> DataFrame:
    """Local coefficients as scores: item, the integer behind it, and its value.

    An item is an id and its level, which is more than the id only for positions past the
    domain; by_id: it is the id alone, and the level is a part of it.
    """
    item = F.col("coef_id") if by_id else F.col("coef_id") * (1 << LEVEL_BITS) + F.col("level") + 1
    more = [*([F.col("level").alias("part")] if by_id else []), *(["cand"] if "cand" in local.columns else [])]
    return local.select("site", item.alias("item"), F.col("diff").alias("score"), haar.value_of(F.col("diff"), F.col("level"), log2u).alias("value"), *more)


def level_expr(item):
    return F.when(item == 1, F.lit(0)).otherwise(F.length(F.regexp_replace(F.bin(item - 1), "^0*", "")) - 1).cast("int")


def signed_topk(keyed: DataFrame, log2u: int, k: int = 30, m: int | None = None, **options) -> topk.TopkResult:
    """The best k coefficients by three threshold rounds; items are (coef_id, diff, value).

    Null keys are not among the records; a tie goes to the lower id; no records, no items.
    """
    send = max(k, options.get("fanout") or k)
    return signed_topk_of(local_coefs(keyed, log2u, send), log2u, k, m, **options)


def signed_topk_of(local: DataFrame, log2u: int, k: int = 30, m: int | None = None, by_id: bool = False, **options) -> topk.TopkResult:
    """`signed_topk` from the sites' coefficients (site, coef_id, level, diff[, cand]).

    by_id: messages and candidates name ids without levels.  The same within a domain; past
    it, levels that share an id share its bounds, so a coefficient may be missed.
    """
    coef_id = F.col("item") if by_id else F.call_function("shiftright", F.col("item"), F.lit(LEVEL_BITS))
    level = F.col("part") if by_id else (F.col("item").bitwiseAND(F.lit((1 << LEVEL_BITS) - 1)) - 1).cast("int")
    ready = options.pop("ready", log2u > haar.SUBTREE)
    got = topk.signed(scores_of(local, log2u, by_id), k, m, order=[haar.energy_key(F.col("score"), level).desc()], ready=ready, **options)
    if options.get("stop_after", 3) == 2:
        got.items = got.items.select(coef_id.alias("coef_id"), "value", "low", "high")
    else:
        got.items = got.items.select(coef_id.alias("coef_id"), F.col("score").alias("diff"), haar.value_of(F.col("score"), level, log2u).alias("value"))
    return got


def planned(keyed: DataFrame, log2u: int, k: int = 30, m: int | None = None) -> tuple[str, DataFrame]:
    """signed_topk unless its first round gives no threshold and counts are fewer than coefficients; then ship_counts.

    Both go on from the same local state.
    """
    local = materialize(local_freq(keyed), "local-freq")
    coefs = materialize(haar.local_sparse(local, log2u, k), "local-coefs")
    first = topk.first_round(scores_of(coefs, log2u), k, m, ready=True)
    if first.t1 == 0 and local.count() < coefs.count():
        freq = local.groupBy("pos").agg(F.sum("cnt").cast("long").alias("cnt"))
        return "ship_counts", haar.best_k(haar.by_subtree(freq, log2u), k, log2u)
    return "signed_topk", signed_topk_of(coefs, log2u, k, m, first=first).items


def ship_counts_2d(cells: DataFrame, log2us: list[int], k: int = 30) -> DataFrame:
    """cells: (site, pos_1, .., pos_d) rows."""
    names = [f"pos_{a}" for a in range(1, len(log2us) + 1)]
    freq = cells.groupBy(*names).agg(F.count("*").alias("cnt"))
    return haar.best_k_nd(haar.by_basis_nd(freq, log2us), k, log2us)


def signed_topk_2d(cells: DataFrame, log2us: list[int], k: int = 30, m: int | None = None, **options) -> topk.TopkResult:
    """The rounds over d-dimensional coefficients, an item being the ids folded into one long."""
    d = len(log2us)
    names = [f"pos_{a}" for a in range(1, d + 1)]
    freq = cells.groupBy("site", *names).agg(F.count("*").alias("cnt"))
    sites = freq.withColumnRenamed("site", "s")
    # the site rides along as one more measure-free axis
    state = sites.select("s", *names, "cnt")
    local = _by_site_nd(state, log2us)
    item, weight, bits = F.lit(0).cast("long"), F.lit(0), 0
    for a in range(d, 0, -1):
        item = item + F.col(f"c_{a}") * (1 << bits)
        bits += log2us[a - 1] + 1
        weight = weight + F.greatest(F.col(f"l_{a}"), F.lit(0))
    value = F.col("cnt").cast("double") * F.sqrt(F.pow(F.lit(2.0), weight - F.lit(sum(log2us))))
    scores = materialize(local.select(F.col("s").alias("site"), item.alias("item"), F.col("cnt").alias("score"), value.alias("value")), "scores-nd")

    def part(a: int):
        below = sum(log2us[b - 1] + 1 for b in range(a + 1, d + 1))
        return F.call_function("shiftright", F.col("item"), F.lit(below)).bitwiseAND(F.lit((1 << (log2us[a - 1] + 1)) - 1))

    levels = F.lit(0)
    for a in range(1, d + 1):
        levels = levels + level_expr(part(a))
    got = topk.signed(scores, k, m, order=[haar.energy_key(F.col("score"), levels).desc()], **options)
    exact_value = F.col("score").cast("double") * F.sqrt(F.pow(F.lit(2.0), levels - F.lit(sum(log2us))))
    got.items = got.items.select(*[part(a).alias(f"c_{a}") for a in range(1, d + 1)], F.col("score").alias("diff"), exact_value.alias("value"))
    return got


def _by_site_nd(state: DataFrame, log2us: list[int]) -> DataFrame:
    done = ["s"]
    names = [f"pos_{a}" for a in range(1, len(log2us) + 1)]
    for a, log2u in enumerate(log2us, 1):
        rest = names[a:]
        parts = state.select(*done, *rest, *haar.contributions(log2u, F.col(f"pos_{a}"), F.col("cnt")))
        state = parts.groupBy(*done, F.col("c.coef_id").alias(f"c_{a}"), F.col("c.level").alias(f"l_{a}"), *rest).agg(F.sum(F.col("cnt") * F.col("c.sign")).cast("long").alias("cnt")).filter("cnt <> 0")
        done += [f"c_{a}", f"l_{a}"]
    return state


def centralized(keyed: DataFrame, log2u: int, k: int = 30) -> list[tuple[int, float]]:
    """The whole vector on the driver, for tests and small domains only."""
    if log2u > 20:
        raise ValueError("centralized is for domains of at most 2^20")
    v = np.zeros(1 << log2u)
    for r in global_freq(keyed).collect():
        v[r.pos] = r.cnt
    w = haar.dense(v)
    order = sorted(range(len(w)), key=lambda i: (-round(abs(w[i]), 9), i))[:k]
    return [(i + 1, float(w[i])) for i in order if w[i]]


def local_coefs_physical(df: DataFrame, key: str, log2u: int, sites: int | None = None, k: int = 0) -> DataFrame:
    """Local coefficients where a site is a piece of a file: made inside the scan's tasks, without a shuffle.

    df: a file scan; key: SQL for the position; sites: if given, pieces are merged into at
    most so many super-sites, whose parts are then added up by one shuffle of coefficients.
    A piece is read by one task, so its counts are complete there; a task holds the distinct
    keys of its pieces.  With k, and without super-sites, there is the mark `cand` of
    `haar.local_sparse`.
    """
    import pyarrow as pa

    from wavesum.functions.keys import physical_sites, super_site

    site = physical_sites(df)
    rows = df.select(site, F.expr(key).cast("long").alias("pos")).filter("pos is not null")
    if sites:
        rows = rows.select(super_site(F.col("site"), sites), "pos")

    def run(batches):
        counts: dict[int, list] = {}
        for b in batches:
            s, p = (b.column(c).to_numpy() for c in ("site", "pos"))
            for one in np.unique(s).tolist():
                u, n = np.unique(p[s == one], return_counts=True)
                have = counts.setdefault(one, [])
                have.append((u, n))
                if len(have) > 16:
                    counts[one] = [_added(have)]
        for one, have in counts.items():
            u, n = _added(have)
            ids, levels, diffs, _, total = haar.sparse(u, n, log2u)
            ids, levels, diffs = np.append(ids, 1), np.append(levels, np.int32(haar.AVERAGE)), np.append(diffs, total.sum())
            cols = {"site": pa.array(np.full(len(ids), one)), "coef_id": pa.array(ids), "level": pa.array(levels, pa.int32()), "diff": pa.array(diffs)}
            if k:
                cols["cand"] = pa.array(haar.extreme(diffs * np.sqrt(2.0 ** (np.maximum(levels, 0) - log2u)), ids, k))
            yield pa.RecordBatch.from_pydict(cols)

    k = 0 if sites else k
    local = rows.mapInArrow(run, f"site bigint, {haar.COEF}{', cand boolean' if k else ''}")
    if not sites:
        return local
    return local.groupBy("site", "coef_id", "level").agg(F.sum("diff").cast("long").alias("diff")).filter("diff <> 0")


def signed_topk_physical(df: DataFrame, key: str, log2u: int, k: int = 30, **options) -> topk.TopkResult:
    """`signed_topk` with the pieces of files as sites: only what the rounds send is shuffled.

    The coefficients of each piece are made and written by the task that reads it.  Many
    pieces make the method dear; above some thousands use `local_coefs_physical` with
    super-sites.
    """
    local = materialize(local_coefs_physical(df, key, log2u, k=max(k, options.get("fanout") or k)), "piece-coefs")
    return signed_topk_of(local, log2u, k, ready=True, **options)


def _added(parts: list) -> tuple[np.ndarray, np.ndarray]:
    keys, counts = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    u, where = np.unique(keys, return_inverse=True)
    return u, np.bincount(where, counts, len(u)).astype(np.int64)
