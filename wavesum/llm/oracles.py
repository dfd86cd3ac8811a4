"""DuckDB SQL of the text operators that SQL can express."""

from __future__ import annotations

from wavesum.llm.quality import GROWTH, LEAST, LEAST_SPREAD, SPREAD

WORD = r"'[^\x20\x09-\x0D]+'"

SUBSTRING_DEDUP = f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(coalesce(text, ''), {WORD}) AS w FROM documents),
g AS (SELECT r, doc_id, i, array_to_string(w[i:i + 19], ' ') AS k FROM (SELECT r, doc_id, w, unnest(range(1, len(w) - 18)) AS i FROM d)),
f AS (SELECT r, i FROM (SELECT *, min((doc_id, i)) OVER (PARTITION BY k) AS first FROM g) WHERE (doc_id, i) > first),
gone AS (SELECT DISTINCT r, i + o AS p FROM f, (SELECT unnest(range(0, 20)) AS o)),
kept AS (SELECT x.r, string_agg(word, ' ' ORDER BY x.p) FILTER (WHERE gone.p IS NULL) AS t, count(gone.p) AS n_removed
  FROM (SELECT r, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS p FROM d) x LEFT JOIN gone ON gone.r = x.r AND gone.p = x.p GROUP BY x.r)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM d LEFT JOIN kept ON kept.r = d.r
"""


def quality() -> str:
    """The counts, the base rules, and the cutoffs from the same bucket counts."""
    values = {
        "symbols": "n_symbols / greatest(n_words, 1)::DOUBLE",
        "dup_lines": "n_dup_lines / greatest(n_lines, 1)::DOUBLE",
        "repeats": "n_repeat_words / greatest(n_words, 1)::DOUBLE",
        "long_words": "greatest(word_chars, 1)::DOUBLE / greatest(n_words, 1)",
        "short_words": "greatest(n_words, 1)::DOUBLE / greatest(word_chars, 1)",
    }
    rules = " UNION ALL ".join(f"SELECT r, lang, source, '{k}' AS rule, {v} AS x FROM c WHERE NOT base_failed" for k, v in values.items())
    groups = {"own": "lang, source, rule", "l": "lang, rule", "a": "rule"}
    level = "".join(
        f", {n}_m AS (SELECT {by}, bucket, sum(n) AS n FROM k GROUP BY ALL), {n} AS (SELECT {by}, max(total) AS size, min(CASE WHEN upto >= total * 0.25 THEN v END) AS q25, min(CASE WHEN upto >= total * 0.75 THEN v END) AS q75 FROM (SELECT *, sum(n) OVER (PARTITION BY {by}) AS total, sum(n) OVER (PARTITION BY {by} ORDER BY bucket) AS upto, CASE WHEN bucket = 0 THEN 0.0::DOUBLE ELSE pow({GROWTH}::DOUBLE, bucket - 0.5) * 1e-4 END AS v FROM {n}_m) GROUP BY {by})"
        for n, by in groups.items()
    )
    least = "CASE own.rule " + " ".join(f"WHEN '{k}' THEN {g}::DOUBLE" for k, g in LEAST_SPREAD.items()) + " END"
    cut = lambda t: f"{t}.q75 + {SPREAD} * greatest({t}.q75 - {t}.q25, {least})"
    verdict = " UNION ALL ".join(f"SELECT r, lang, source, '{k}' AS rule, {v} AS x FROM c" for k, v in values.items())
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, source, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, regexp_extract_all(t, {WORD}) AS w FROM d),
lines AS (SELECT r, count(*) AS n_lines, count(DISTINCT line) AS n_distinct FROM (SELECT r, unnest(string_split(t, chr(10))) AS line FROM d) WHERE regexp_matches(line, {WORD}) GROUP BY r),
tri AS (SELECT r, i, count(*) OVER (PARTITION BY r, w[i:i + 2]) AS n FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM w)),
rep AS (SELECT r, count(DISTINCT i + o) AS n_repeat_words FROM tri, (SELECT unnest([0, 1, 2]) AS o) WHERE n > 1 GROUP BY r),
c AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM (
  SELECT d.r, doc_id, lang, source, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars,
    CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(n_lines - n_distinct, 0) AS BIGINT) AS n_dup_lines,
    CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines
  FROM d JOIN w USING (r) LEFT JOIN lines USING (r) LEFT JOIN rep USING (r))),
k AS (SELECT lang, source, rule, greatest(0, ceil(ln(greatest(x, 1e-9) / 1e-4) / ln({GROWTH}::DOUBLE)))::INTEGER AS bucket, count(*) AS n FROM ({rules}) GROUP BY ALL){level},
cuts AS (SELECT own.lang, own.source, own.rule, CASE WHEN own.size >= {LEAST} THEN {cut("own")} WHEN l.size >= {LEAST} THEN {cut("l")} ELSE {cut("a")} END AS cut
  FROM own LEFT JOIN l ON own.lang IS NOT DISTINCT FROM l.lang AND own.rule = l.rule LEFT JOIN a ON own.rule = a.rule),
bad AS (SELECT DISTINCT r FROM ({verdict}) v JOIN cuts ON v.lang IS NOT DISTINCT FROM cuts.lang AND v.source IS NOT DISTINCT FROM cuts.source AND v.rule = cuts.rule WHERE x > cut)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND bad.r IS NULL AS kept FROM c LEFT JOIN bad USING (r)
"""

SUFFIX_DEDUP = """
WITH d AS (SELECT row_number() OVER () AS r, doc_id, encode(coalesce(text, '')) AS b, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
g AS (SELECT r, doc_id, i, array_slice(b, i, i + 49) AS k FROM (SELECT r, doc_id, b, unnest(range(1, n - 48)) AS i FROM d)),
firsts AS (SELECT k, min(doc_id) AS first FROM g GROUP BY k HAVING count(DISTINCT doc_id) > 1),
f AS (SELECT r, i FROM g JOIN firsts USING (k) WHERE doc_id > first),
marked AS (SELECT r, i, CASE WHEN i > lag(i) OVER (PARTITION BY r ORDER BY i) + 50 THEN 1 ELSE 0 END AS fresh FROM f),
runs AS (SELECT r, min(i) AS lo, max(i) + 49 AS hi FROM (SELECT r, i, sum(fresh) OVER (PARTITION BY r ORDER BY i) AS run FROM marked) GROUP BY r, run),
cut AS (SELECT r, sum(hi - lo + 1) AS n_removed, count(*) AS n_spans FROM runs GROUP BY r),
pieces AS (
  SELECT d.r, 1 AS s, coalesce(min(lo) - 1, any_value(n)) AS e FROM d LEFT JOIN runs ON runs.r = d.r GROUP BY d.r
  UNION ALL SELECT runs.r, hi + 1, coalesce(lead(lo) OVER (PARTITION BY runs.r ORDER BY lo) - 1, n) FROM runs JOIN d ON runs.r = d.r),
kept AS (SELECT p.r, string_agg(hex(array_slice(b, s, e)), '' ORDER BY s) AS t FROM pieces p JOIN d ON d.r = p.r WHERE e >= s GROUP BY p.r)
SELECT doc_id, CAST(n AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(n_spans, 0) AS BIGINT) AS n_spans, sha256(unhex(coalesce(t, ''))) AS kept_sha256
FROM d LEFT JOIN cut USING (r) LEFT JOIN kept USING (r)
"""
