"""The methods as Spark SQL over a view of (site, pos) rows."""

from __future__ import annotations


def _coefs(freq: str, log2u: int) -> str:
    shift = f"{log2u} - greatest(j, 0)"
    sign = f"CASE WHEN j < 0 OR (shiftright(pos, greatest({log2u} - j - 1, 0)) & 1) = 1 THEN cnt ELSE -cnt END"
    return f"SELECT CASE WHEN j < 0 THEN 1L ELSE shiftleft(1L, greatest(j, 0)) + shiftright(pos, {shift}) + 1 END AS coef_id, j AS level, CAST(sum({sign}) AS BIGINT) AS diff FROM ({freq}) LATERAL VIEW explode(sequence(-1, {log2u - 1})) l AS j GROUP BY 1, 2 HAVING sum({sign}) <> 0"


def sql_text(method: str, view: str, log2u: int, k: int = 30, coin: int = 1 << 32, weight: float = 1.0, p: float = 1.0) -> str:
    """haar, ship_counts, ship_coefs, uniform or two_stage; the samplers' view has row_id too."""
    freq = f"SELECT pos, count(*) AS cnt FROM {view} GROUP BY pos"
    top = "ORDER BY CAST(diff AS DECIMAL(19,0)) * CAST(diff AS DECIMAL(19,0)) * CAST(shiftleft(1L, greatest(level, 0)) AS DECIMAL(10,0)) DESC, coef_id"
    value = f"CAST(diff AS DOUBLE) * sqrt(pow(2.0D, greatest(level, 0) - {log2u}))"
    if method == "haar":
        return _coefs(freq, log2u)
    if method == "ship_counts":
        return f"SELECT coef_id, diff, round({value}, 6) AS value FROM ({_coefs(freq, log2u)}) {top} LIMIT {k}"
    if method == "ship_coefs":
        local = f"SELECT site, pos, count(*) AS cnt FROM {view} GROUP BY site, pos"
        per_site = _coefs(local, log2u).replace("SELECT CASE", "SELECT site, CASE", 1).replace("GROUP BY 1, 2", "GROUP BY 1, 2, 3")
        return f"SELECT coef_id, diff, round({value}, 6) AS value FROM (SELECT coef_id, level, CAST(sum(diff) AS BIGINT) AS diff FROM ({per_site}) GROUP BY coef_id, level HAVING sum(diff) <> 0) {top} LIMIT {k}"
    sampled = f"SELECT site, pos, count(*) AS scnt FROM {view} WHERE CAST(conv(substring(md5(concat_ws(':', row_id, '42', '1')), 1, 8), 16, 10) AS BIGINT) < {coin} GROUP BY site, pos"
    if method == "uniform":
        return f"SELECT pos, sum(scnt) / {p!r}D AS v_hat FROM ({sampled}) GROUP BY pos"
    if method == "two_stage":
        h = "CAST(conv(substring(md5(concat_ws(':', site, pos, '42', '2')), 1, 8), 16, 10) AS BIGINT)"
        sent = f"SELECT pos, CASE WHEN scnt * {weight!r}D >= 1 THEN scnt END AS cnt FROM ({sampled}) WHERE scnt * {weight!r}D >= 1 OR {h} < scnt * {int(min(1.0, weight) * (1 << 32))}L"
        return f"SELECT pos, (coalesce(sum(cnt), 0) + count_if(cnt IS NULL) / {weight!r}D) / {p!r}D AS v_hat FROM ({sent}) GROUP BY pos"
    raise ValueError(method)
