"""Haar transforms of count vectors.

Coefficient 1 is the average, coefficient 2^j + b + 1 the detail of block b at level j
(level 0 is the whole domain).  `diff` is the exact integer behind a coefficient: right half
less left half, or the total for the average; its value is diff * sqrt(2^j / u).  Ranking
uses the integer diff^2 * 2^j, so no order depends on rounding.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

COEF = "coef_id bigint, level int, diff bigint"
#: Level of the average; it weighs like level 0.
AVERAGE = -1
#: Subtrees have 2^SUBTREE positions at most.
SUBTREE = 16


def dense(v: np.ndarray) -> np.ndarray:
    """All u coefficients of a vector, the average first: pairwise sums and differences, bottom up."""
    u = len(v)
    if u & (u - 1) or not u:
        raise ValueError("the length must be a power of two")
    out, s = np.zeros(u), np.asarray(v, float)
    while len(s) > 1:
        left, right = s[0::2], s[1::2]
        out[len(left) : 2 * len(left)] = (right - left) * math.sqrt(len(left) / u)
        s = left + right
    out[0] = s[0] / math.sqrt(u)
    return out


def inverse(w: np.ndarray) -> np.ndarray:
    """The vector behind all its coefficients."""
    u = len(w)
    s = np.array([w[0] * math.sqrt(u)])
    while len(s) < u:
        d = w[len(s) : 2 * len(s)] / math.sqrt(len(s) / u)
        s = np.stack([(s - d) / 2, (s + d) / 2], axis=1).ravel()
    return s


def unnormalised(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The average and difference form, and the level scales that turn it into `dense`."""
    u = len(v)
    out, scale, a = np.zeros(u), np.zeros(u), np.asarray(v, float)
    while len(a) > 1:
        left, right = a[0::2], a[1::2]
        n = len(left)
        out[n : 2 * n], scale[n : 2 * n] = (right - left) / 2, math.sqrt(u / n)
        a = (left + right) / 2
    out[0], scale[0] = a[0], math.sqrt(u)
    return out, scale


def sparse(pos: np.ndarray, cnt: np.ndarray, log2u: int, top: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Nonzero details of ascending positions, from the leaves up to level `top`: ids, levels, diffs; and the blocks of level `top` with their sums.

    Every level works on the blocks that have counts, so the work is |v| log u at most.
    """
    ids, levels, diffs = [], [], []
    for level in range(log2u - 1, top - 1, -1):
        sign = np.where(pos & 1, cnt, -cnt)
        pos = pos >> 1
        first = np.flatnonzero(np.concatenate([[True], pos[1:] != pos[:-1]])) if len(pos) else np.zeros(0, np.int64)
        if len(first):
            diff, cnt, pos = np.add.reduceat(sign, first), np.add.reduceat(cnt, first), pos[first]
            keep = diff != 0
            ids.append((1 << level) + pos[keep] + 1)
            levels.append(np.full(int(keep.sum()), level, np.int32))
            diffs.append(diff[keep])
    join = lambda x, t: np.concatenate(x).astype(t) if x else np.zeros(0, t)
    return join(ids, np.int64), join(levels, np.int32), join(diffs, np.int64), pos, cnt


def contributions(log2u: int, pos: Column, *weights: Column) -> list[Column]:
    """Column expressions of one position's coefficients: `c` (struct of coef_id, level, sign) to be exploded."""
    levels = F.sequence(F.lit(AVERAGE), F.lit(log2u - 1))

    def one(j: Column) -> Column:
        shift = F.lit(log2u) - F.greatest(j, F.lit(0))
        block = F.call_function("shiftright", pos, shift)
        right = F.call_function("shiftright", pos, F.greatest(shift - 1, F.lit(0))).bitwiseAND(F.lit(1)) == 1
        detail = F.call_function("shiftleft", F.lit(1).cast("long"), F.greatest(j, F.lit(0))) + block + 1
        return F.struct(F.when(j < 0, F.lit(1).cast("long")).otherwise(detail).alias("coef_id"), j.alias("level"), F.when((j < 0) | right, F.lit(1)).otherwise(F.lit(-1)).alias("sign"))

    return [F.explode(F.transform(levels, one)).alias("c"), *weights]


def by_basis(freq: DataFrame, log2u: int, measures: tuple[str, ...] = ("cnt",), by: tuple[str, ...] = (), out: tuple[str, ...] = ("diff",)) -> DataFrame:
    """Nonzero coefficients as a grouped sum over each position's log2u + 1 signed contributions."""
    parts = freq.select(*by, *contributions(log2u, F.col("pos"), *[F.col(m) for m in measures]))
    sums = [F.sum(F.col(m) * F.col("c.sign")).cast("long").alias(o) for m, o in zip(measures, out, strict=True)]
    some = F.lit(False)
    for o in out:
        some = some | (F.col(o) != 0)
    return parts.groupBy(*by, F.col("c.coef_id").alias("coef_id"), F.col("c.level").alias("level")).agg(*sums).filter(some)


def with_root(ids: np.ndarray, levels: np.ndarray, diffs: np.ndarray, root: np.ndarray, total: np.ndarray, **more) -> pa.Table:
    """A subtree's details and its sum, which is marked by a null coefficient, with its block as level."""
    none = np.zeros(len(ids) + 1, bool)
    none[-1] = True
    cols = {"coef_id": pa.array(np.append(ids, 0), pa.int64(), mask=none), "level": pa.array(np.append(levels, np.int32(root[0])), pa.int32()), "diff": pa.array(np.append(diffs, total[0]), pa.int64())}
    return pa.table(cols | more)


def by_subtree(freq: DataFrame, log2u: int, subtree_log2: int | None = None) -> DataFrame:
    """Nonzero coefficients by aligned subtrees of 2^subtree_log2 positions, one shuffle of freq.

    A subtree's task sorts its positions and takes its own details; its sum goes, as one
    row, to the tree above the subtrees, which is transformed the same way by `by_basis`.
    """
    low = min(SUBTREE, max(log2u - 4, 0)) if subtree_log2 is None else min(subtree_log2, log2u)
    if low == 0:
        return by_basis(freq, log2u)
    top = log2u - low

    def subtree(key: tuple, table: pa.Table) -> pa.Table:
        pos, cnt = (table.column(c).to_numpy().astype(np.int64) for c in ("pos", "cnt"))
        order = np.argsort(pos)
        ids, levels, diffs, root, total = sparse(pos[order], cnt[order], log2u, top)
        return with_root(ids, levels, diffs, root, total)

    from wavesum.functions.tables import materialize

    parts = materialize(freq.groupBy(F.call_function("shiftright", F.col("pos"), F.lit(low)).alias("subtree")).applyInArrow(subtree, COEF), "subtrees")
    sums = parts.filter("coef_id is null").select(F.col("level").cast("long").alias("pos"), F.col("diff").alias("cnt"))
    return parts.filter("coef_id is not null").unionByName(by_basis(sums, top))


def extreme(values: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Mask of the k highest and the k lowest values, the lower ids first among equal ones."""
    out = np.zeros(len(values), bool)
    if len(values) <= 2 * k:
        out[:] = True
        return out
    for v in (values, -values):
        edge = np.partition(v, len(v) - k)[len(v) - k]
        over, on = v > edge, np.flatnonzero(v == edge)
        out |= over
        out[on[np.argsort(ids[on])[: k - int(over.sum())]]] = True
    return out


def local_sparse(local: DataFrame, log2u: int, k: int = 0, subtree_log2: int | None = None) -> DataFrame:
    """(site, coef_id, level, diff): each site's own nonzero coefficients, by subtrees of a site, so no task holds a whole one.

    local may have a position more than once.  With k there is a column `cand`: whether a
    coefficient may be among the k highest or lowest values of its site.  A domain of more
    than one subtree gives a materialized result.
    """
    low = min(SUBTREE if subtree_log2 is None else subtree_log2, log2u)
    top = log2u - low
    more = ", cand boolean" if k else ""

    def one(key: tuple, table: pa.Table) -> pa.Table:
        pos, cnt = (table.column(c).to_numpy().astype(np.int64) for c in ("pos", "cnt"))
        order = np.argsort(pos)
        ids, levels, diffs, root, total = sparse(pos[order], cnt[order], log2u, top)
        if not top and int(total.sum()):
            ids, levels, diffs = np.append(ids, 1), np.append(levels, np.int32(AVERAGE)), np.append(diffs, int(total.sum()))
        cand = extreme(diffs * np.sqrt(2.0 ** (np.maximum(levels, 0) - log2u)), ids, k) if k else np.zeros(0, bool)
        if top:
            out = with_root(ids, levels, diffs, root, total, **({"cand": pa.array(np.append(cand, True))} if k else {}))
        else:
            out = pa.table({"coef_id": pa.array(ids, pa.int64()), "level": pa.array(levels, pa.int32()), "diff": pa.array(diffs, pa.int64())} | ({"cand": pa.array(cand)} if k else {}))
        return out.add_column(0, "site", pa.array(np.full(len(out), key[0].as_py()), pa.int64()))

    if not top:
        return local.groupBy("site").applyInArrow(one, f"site bigint, {COEF}{more}")
    from wavesum.functions.tables import materialize

    parts = materialize(local.groupBy("site", F.call_function("shiftright", F.col("pos"), F.lit(low)).alias("subtree")).applyInArrow(one, f"site bigint, {COEF}{more}"), "site-subtrees")
    sums = parts.filter("coef_id is null").select("site", F.col("level").cast("long").alias("pos"), F.col("diff").alias("cnt"))
    above = by_basis(sums, top, by=("site",))
    above = materialize(above.withColumn("cand", F.lit(True)) if k else above, "site-tops")
    return parts.filter("coef_id is not null").unionByName(above)


def value_of(diff: Column, level: Column, log2u: int) -> Column:
    return diff.cast("double") * F.sqrt(F.pow(F.lit(2.0), F.greatest(level, F.lit(0)) - F.lit(log2u)))


def energy_key(diff: Column, level: Column) -> Column:
    """diff^2 * 2^level, exact: u times the squared value."""
    d = diff.cast("decimal(19,0)")
    return ((d * d).cast("decimal(38,0)") * F.call_function("shiftleft", F.lit(1).cast("long"), F.greatest(level, F.lit(0))).cast("decimal(10,0)")).cast("decimal(38,0)")


def best_k(coefs: DataFrame, k: int, log2u: int) -> DataFrame:
    """The k coefficients of largest magnitude, lower ids first among equals: coef_id, level, diff, value."""
    return coefs.orderBy(energy_key(F.col("diff"), F.col("level")).desc(), F.col("coef_id")).limit(k).withColumn("value", value_of(F.col("diff"), F.col("level"), log2u))


def support(coef_id: Column, log2u: int) -> dict[str, Column]:
    """lo, mid, hi of a coefficient's support and its scale, as expressions of the id."""
    level = F.when(coef_id == 1, F.lit(0)).otherwise(F.length(F.regexp_replace(F.bin(coef_id - 1), "^0*", "")) - 1).cast("int")
    block = F.when(coef_id == 1, F.lit(0).cast("long")).otherwise(coef_id - 1 - F.call_function("shiftleft", F.lit(1).cast("long"), level))
    width = F.call_function("shiftright", F.lit(1 << log2u).cast("long"), level)
    lo = block * width
    return {"lo": lo, "mid": F.when(coef_id == 1, lo).otherwise(lo + F.call_function("shiftright", width, F.lit(1))), "hi": lo + width, "scale": F.sqrt(F.pow(F.lit(2.0), level - F.lit(log2u)))}


def by_basis_nd(cells: DataFrame, log2us: list[int], measures: tuple[str, ...] = ("cnt",)) -> DataFrame:
    """The standard transform of cells (pos_1 .. pos_d, measures): (c_1, l_1, .., c_d, l_d, diffs), an axis at a time.

    Each axis explodes only what the axes before it have summed up.
    """
    state, names = cells, [f"pos_{a}" for a in range(1, len(log2us) + 1)]
    done: list[str] = []
    for a, log2u in enumerate(log2us, 1):
        rest = names[a:]
        parts = state.select(*done, *rest, *contributions(log2u, F.col(f"pos_{a}"), *[F.col(m) for m in measures]))
        done += [f"c_{a}", f"l_{a}"]
        keep = [c for c in done if c not in (f"c_{a}", f"l_{a}")]
        sums = [F.sum(F.col(m) * F.col("c.sign")).cast("long").alias(m) for m in measures]
        state = parts.groupBy(*keep, F.col("c.coef_id").alias(f"c_{a}"), F.col("c.level").alias(f"l_{a}"), *rest).agg(*sums)
        some = F.lit(False)
        for m in measures:
            some = some | (F.col(m) != 0)
        state = state.filter(some)
    return state


def dense_2d(v: np.ndarray) -> np.ndarray:
    """Rows, then columns."""
    return np.apply_along_axis(dense, 0, np.apply_along_axis(dense, 1, v))


def best_k_nd(coefs: DataFrame, k: int, log2us: list[int]) -> DataFrame:
    weight = F.lit(0)
    for a in range(1, len(log2us) + 1):
        weight = weight + F.greatest(F.col(f"l_{a}"), F.lit(0))
    ids = [F.col(f"c_{a}") for a in range(1, len(log2us) + 1)]
    value = F.col("cnt").cast("double") * F.sqrt(F.pow(F.lit(2.0), weight - F.lit(sum(log2us))))
    return coefs.orderBy(energy_key(F.col("cnt"), weight).desc(), *ids).limit(k).select(*[c.alias(f"c_{a}") for a, c in enumerate(ids, 1)], F.col("cnt").alias("diff"), value.alias("value"))
