"""The methods as SQL text for an independent engine: the oracles, and a readable definition."""

from __future__ import annotations

from wavesum.functions.keys import KeySpec, duck_text

_SPLIT = "regexp_split_to_array(trim(text), '\\s+')"
WORDS = f"(SELECT t.doc_id, t.ord, r.pos FROM (SELECT doc_id, unnest({_SPLIT}) AS word, unnest(range(0, len({_SPLIT}))) AS ord FROM documents) t JOIN (SELECT word, row_number() OVER (ORDER BY word) - 1 AS pos FROM (SELECT DISTINCT unnest({_SPLIT}) AS word FROM documents) WHERE word <> '') r ON t.word = r.word)"


def rows(key: KeySpec, m: int, row_id: bool = False) -> str:
    source = WORDS if key.table == "words" else key.table
    more = f", {key.row_id} AS row_id" if row_id else ""
    return f"SELECT CAST({key.site.format(m=m)} AS BIGINT) AS site, CAST({duck_text(key.position)} AS BIGINT) AS pos{more} FROM {source}"


def freq(key: KeySpec) -> str:
    return f"SELECT pos, CAST(count(*) AS BIGINT) AS cnt FROM ({rows(key, 1)}) GROUP BY pos"


def local(key: KeySpec, m: int) -> str:
    return f"SELECT site, pos, CAST(count(*) AS BIGINT) AS cnt FROM ({rows(key, m)}) GROUP BY site, pos"


def coefs(of: str, log2u: int, measures: tuple[str, ...] = ("cnt",), out: tuple[str, ...] = ("diff",), by: str = "") -> str:
    """Nonzero coefficients of a relation with pos and the measures."""
    sums = ", ".join(f"CAST(sum(CASE WHEN j < 0 OR ((pos >> greatest({log2u} - j - 1, 0)) & 1) = 1 THEN {x} ELSE -{x} END) AS BIGINT) AS {o}" for x, o in zip(measures, out, strict=True))
    some = " OR ".join(f"{o} <> 0" for o in out)
    group = "1, 2, 3" if by else "1, 2"
    lead = f"{by}, " if by else ""
    return f"SELECT * FROM (SELECT {lead}CASE WHEN j < 0 THEN 1 ELSE (CAST(1 AS BIGINT) << greatest(j, 0)) + (pos >> ({log2u} - greatest(j, 0))) + 1 END AS coef_id, CAST(j AS INTEGER) AS level, {sums} FROM ({of}), (SELECT unnest(range(-1, {log2u})) AS j) GROUP BY {group}) WHERE {some}"


def value(log2u: int) -> str:
    return f"round(CAST(diff AS DOUBLE) * sqrt(pow(CAST(2 AS DOUBLE), greatest(level, 0) - {log2u})), 6)"


ENERGY = "CAST(diff AS HUGEINT) * diff * (CAST(1 AS HUGEINT) << greatest(level, 0))"


def top(of: str, log2u: int, k: int) -> str:
    return f"SELECT coef_id, diff, {value(log2u)} AS value FROM ({of}) ORDER BY {ENERGY} DESC, coef_id LIMIT {k}"


def best_k(key: KeySpec, k: int) -> str:
    return top(coefs(freq(key), key.log2u), key.log2u, k)


def h32(*parts: str) -> str:
    return f"CAST(('0x' || substr(md5(concat_ws(':', {', '.join(parts)})), 1, 8)) AS UBIGINT)"


def plan(key: KeySpec, m: int, eps: float) -> str:
    """One row: n, p, coin, weight, weight_coin."""
    e = f"CAST({eps!r} AS DOUBLE)"
    w = f"{e} * sqrt(CAST({m} AS DOUBLE))"
    return f"SELECT n, p, CAST(floor(p * 4294967296) AS BIGINT) AS coin, {w} AS weight, CAST(floor(least(1.0, {w}) * 4294967296) AS BIGINT) AS weight_coin FROM (SELECT count(*) AS n, least(CAST(1 AS DOUBLE), CAST(1 AS DOUBLE) / ({e} * {e} * count(*))) AS p FROM ({rows(key, m)}))"


def sampled(key: KeySpec, m: int, eps: float, seed: int, design: str = "coin") -> str:
    if design == "coin":
        return f"SELECT site, pos FROM ({rows(key, m, True)}), ({plan(key, m, eps)}) WHERE p >= 1 OR {h32('row_id', str(seed), '1')} < coin"
    return f"SELECT site, pos FROM (SELECT *, row_number() OVER (PARTITION BY site ORDER BY {h32('row_id', str(seed), '1')}, CAST(row_id AS VARCHAR)) AS rank, round(p * count(*) OVER (PARTITION BY site)) AS take FROM ({rows(key, m, True)}), ({plan(key, m, eps)})) WHERE p >= 1 OR rank <= take"


def messages(method: str, key: KeySpec, m: int, eps: float, seed: int = 42, design: str = "coin", drawn: str | None = None) -> str:
    """drawn: SQL of the sampled (site, pos) records, if they come from elsewhere."""
    s = drawn or sampled(key, m, eps, seed, design)
    if method == "uniform":
        return f"SELECT site, pos, CAST(1 AS BIGINT) AS cnt FROM ({s})"
    counts = f"SELECT site, pos, CAST(count(*) AS BIGINT) AS scnt FROM ({s}) GROUP BY site, pos"
    if method == "precombine":
        return f"SELECT site, pos, scnt AS cnt FROM ({counts})"
    if method == "floor":
        return f"SELECT site, pos, scnt AS cnt FROM (SELECT *, sum(scnt) OVER (PARTITION BY site) AS t FROM ({counts})) WHERE scnt >= CAST({eps!r} AS DOUBLE) * t"
    return f"SELECT site, pos, CASE WHEN scnt * weight >= 1 THEN scnt END AS cnt FROM ({counts}), ({plan(key, m, eps)}) WHERE scnt * weight >= 1 OR {h32('site', 'pos', str(seed), '2')} < scnt * weight_coin"


def totals(method: str, key: KeySpec, m: int, eps: float, seed: int = 42, design: str = "coin", drawn: str | None = None) -> str:
    return f"SELECT pos, CAST(coalesce(sum(cnt), 0) AS BIGINT) AS rho, CAST(sum(CASE WHEN cnt IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS bare FROM ({messages(method, key, m, eps, seed, design, drawn)}) GROUP BY pos"


def estimated(method: str, key: KeySpec, m: int, eps: float, seed: int = 42, design: str = "coin", drawn: str | None = None) -> str:
    """(coef_id, level, value) estimates, unrounded."""
    parts = coefs(totals(method, key, m, eps, seed, design, drawn), key.log2u, ("rho", "bare"), ("rho", "bare"))
    return f"SELECT coef_id, level, (rho + bare / weight) / p * sqrt(pow(CAST(2 AS DOUBLE), greatest(level, 0) - {key.log2u})) AS value FROM ({parts}), ({plan(key, m, eps)})"


def sampled_top(method: str, key: KeySpec, m: int, eps: float, k: int, seed: int = 42, design: str = "coin", drawn: str | None = None) -> str:
    return f"SELECT coef_id, level, value FROM ({estimated(method, key, m, eps, seed, design, drawn)}) WHERE round(value, 9) <> 0 ORDER BY round(abs(value), 9) DESC, coef_id LIMIT {k}"


def sse(key: KeySpec, top_sql: str) -> str:
    """Squared error of kept estimates (coef_id, value) by the orthonormal basis."""
    true = f"SELECT coef_id, CAST(diff AS DOUBLE) * sqrt(pow(CAST(2 AS DOUBLE), greatest(level, 0) - {key.log2u})) AS w FROM ({coefs(freq(key), key.log2u)})"
    return f"SELECT round((SELECT sum(cnt * cnt) FROM ({freq(key)})) + coalesce(sum((value - coalesce(w, 0)) * (value - coalesce(w, 0)) - coalesce(w, 0) * coalesce(w, 0)), 0), 3) AS sse FROM ({top_sql}) e LEFT JOIN ({true}) t ON e.coef_id = t.coef_id"


def coefs_2d(of: str, a: int, b: int, measures: tuple[str, ...] = ("cnt",)) -> str:
    def axis(source: str, pos: str, log2u: int, c: str, l: str, keep: str) -> str:
        sums = ", ".join(f"CAST(sum(CASE WHEN j < 0 OR (({pos} >> greatest({log2u} - j - 1, 0)) & 1) = 1 THEN {x} ELSE -{x} END) AS BIGINT) AS {x}" for x in measures)
        return f"SELECT {keep}, CASE WHEN j < 0 THEN 1 ELSE (CAST(1 AS BIGINT) << greatest(j, 0)) + ({pos} >> ({log2u} - greatest(j, 0))) + 1 END AS {c}, j AS {l}, {sums} FROM ({source}), (SELECT unnest(range(-1, {log2u})) AS j) GROUP BY ALL"

    one = axis(of, "pos_1", a, "c_1", "l_1", "pos_2")
    two = axis(one, "pos_2", b, "c_2", "l_2", "c_1, l_1")
    return f"SELECT * FROM ({two}) WHERE {' OR '.join(f'{x} <> 0' for x in measures)}"


def top_2d(of: str, a: int, b: int, k: int) -> str:
    weight = "(greatest(l_1, 0) + greatest(l_2, 0))"
    return f"SELECT c_1, c_2, cnt AS diff, round(CAST(cnt AS DOUBLE) * sqrt(pow(CAST(2 AS DOUBLE), {weight} - {a + b})), 6) AS value FROM ({coefs_2d(of, a, b)}) ORDER BY CAST(cnt AS HUGEINT) * cnt * (CAST(1 AS HUGEINT) << {weight}) DESC, c_1, c_2 LIMIT {k}"


def coefs_nd(of: str, log2us: list[int], measures: tuple[str, ...] = ("cnt",)) -> str:
    """The transform of cells (pos_1 .., measures), an axis at a time."""
    done: list[str] = []
    for a, log2u in enumerate(log2us, 1):
        rest = [f"pos_{b}" for b in range(a + 1, len(log2us) + 1)]
        sums = ", ".join(f"CAST(sum(CASE WHEN j < 0 OR ((pos_{a} >> greatest({log2u} - j - 1, 0)) & 1) = 1 THEN {x} ELSE -{x} END) AS BIGINT) AS {x}" for x in measures)
        keep = ", ".join([*done, *rest])
        of = f"SELECT {keep}{', ' if keep else ''}CASE WHEN j < 0 THEN 1 ELSE (CAST(1 AS BIGINT) << greatest(j, 0)) + (pos_{a} >> ({log2u} - greatest(j, 0))) + 1 END AS c_{a}, j AS l_{a}, {sums} FROM ({of}), (SELECT unnest(range(-1, {log2u})) AS j) GROUP BY ALL"
        done += [f"c_{a}", f"l_{a}"]
    return f"SELECT * FROM ({of}) WHERE {' OR '.join(f'{x} <> 0' for x in measures)}"


def top_nd(of: str, log2us: list[int], k: int) -> str:
    axes = range(1, len(log2us) + 1)
    weight = "(" + " + ".join(f"greatest(l_{a}, 0)" for a in axes) + ")"
    ids = ", ".join(f"c_{a}" for a in axes)
    return f"SELECT {ids}, cnt AS diff, round(CAST(cnt AS DOUBLE) * sqrt(pow(CAST(2 AS DOUBLE), {weight} - {sum(log2us)})), 6) AS value FROM ({coefs_nd(of, log2us)}) ORDER BY CAST(cnt AS HUGEINT) * cnt * (CAST(1 AS HUGEINT) << {weight}) DESC, {ids} LIMIT {k}"
