"""Quality rules whose cutoffs come from mergeable quantile sketches by language and source.

The sketch is a relative-error histogram: a value x goes to the bucket ceil(log_g x), and a
sketch is the counts by bucket, so two sketches merge by adding counts and a quantile is
within (g - 1) / (g + 1) of the true one, whatever the order of merging.  As rows
(lang, source, rule, bucket, n) it needs one partially aggregated groupBy.

A rule rejects a document whose value is over q75 + SPREAD * (q75 - q25) of its group, up or
down with the group; where the quartiles lie closer than the rule's LEAST_SPREAD (in a group
in which three quarters have no symbol they coincide), that stands for their distance.
Groups of under `least` documents take their language's merged sketch, and those of too
small languages the one of all documents.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavesum.llm.common import SPACE, blocks, flat, fresh, strings, sums, word_spans, written

GROWTH = 1.02
SPREAD = 5.0
LEAST = 30
#: Rule: the least distance of quartiles that is believed.
LEAST_SPREAD = {"symbols": 0.03, "dup_lines": 0.07, "repeats": 0.06, "long_words": 0.1, "short_words": 0.004}
#: Fixed: the symbols counted in n_symbols.
SYMBOLS = np.zeros(256, dtype=bool)
SYMBOLS[list(b"#*$%&|<>")] = True
FEATURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines"]


def measure(texts: pa.Array) -> dict[str, np.ndarray]:
    """The counts of FEATURES for each text of a block (null: none); n_lines counts lines with a word."""
    data, docs = flat(texts)
    n = len(docs) - 1
    starts, lengths, by_doc, inside = word_spans(data, docs)
    out = {"n_words": np.diff(by_doc), "word_chars": sums(inside & ((data & 0xC0) != 0x80), docs), "n_symbols": sums(SYMBOLS[data], docs)}

    newline = data == 0x0A
    # lines: cut at each newline and at each document's end
    cuts = np.union1d(np.flatnonzero(newline) + 1, docs)
    cuts = cuts[cuts <= len(data)]
    ends = cuts[1:].copy()
    ends -= newline[ends - 1] if len(ends) else 0
    begin = cuts[:-1]
    doc_of = np.searchsorted(docs, begin, side="right") - 1
    filled = np.searchsorted(starts, ends) > np.searchsorted(starts, begin)
    # the newline bytes fall out of the buffer; every other byte belongs to one line
    lines = strings(data[~newline], np.concatenate([[0], np.cumsum(ends - begin)]) if len(begin) else np.zeros(1))
    code = pc.dictionary_encode(lines).indices.to_numpy().astype(np.int64)
    key = np.unique((code * n + doc_of)[filled])
    out["n_lines"] = np.bincount(doc_of[filled], minlength=n)
    out["n_dup_lines"] = out["n_lines"] - np.bincount(key % n if len(key) else key, minlength=n)

    words = strings(data[inside], np.concatenate([[0], np.cumsum(lengths)]))
    c = pc.dictionary_encode(words).indices.to_numpy().astype(np.int64)
    out["n_repeat_words"] = np.zeros(n, np.int64)
    if len(c) >= 3:
        m = int(c.max()) + 1
        pair = np.unique(c[:-1] * m + c[1:], return_inverse=True)[1]
        doc_of = np.repeat(np.arange(n), np.diff(by_doc))
        valid = doc_of[:-2] == doc_of[2:]
        tri = np.unique(pair[:-1] * m + c[2:], return_inverse=True)[1]
        _, where, count = np.unique((tri * n + doc_of[:-2])[valid], return_inverse=True, return_counts=True)
        again = np.zeros(len(c), bool)
        at = np.flatnonzero(valid)[count[where] > 1]
        for k in range(3):
            again[at + k] = True
        out["n_repeat_words"] = sums(again, by_doc)
    return out


def measured(docs: DataFrame, keep: list[str], text: str = "text") -> tuple[DataFrame, list[str]]:
    """The columns `keep` and the counts of each text; also the names the counts got."""
    names = fresh(keep, *FEATURES)
    need = list(dict.fromkeys([*keep, text]))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keep).schema), *(f"`{n}` bigint" for n in names)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches, text):
            got = measure(block.column(text))
            yield pa.RecordBatch.from_arrays([*(block.column(k) for k in keep), *(pa.array(got[f], pa.int64()) for f in FEATURES)], names=[*keep, *names])

    return docs.select(*need).mapInArrow(run, schema), names


def base_failed(n: dict[str, str]) -> Column:
    return (F.col(n["n_words"]) < 50) | (100 * F.col(n["n_repeat_words"]) > 50 * F.col(n["n_words"]))


def values(n: dict[str, str]) -> dict[str, Column]:
    """The value of each rule; all are zero or more, and larger is worse."""
    words, chars = F.greatest(F.col(n["n_words"]), F.lit(1)).cast("double"), F.greatest(F.col(n["word_chars"]), F.lit(1)).cast("double")
    return {
        "symbols": F.col(n["n_symbols"]) / words,
        "dup_lines": F.col(n["n_dup_lines"]) / F.greatest(F.col(n["n_lines"]), F.lit(1)).cast("double"),
        "repeats": F.col(n["n_repeat_words"]) / words,
        "long_words": chars / words,
        "short_words": words / chars,
    }


def bucket_of(value: Column) -> Column:
    """0 for values of 1e-4 and less, else a positive logarithmic bucket."""
    return F.greatest(F.lit(0), F.ceil(F.log(F.greatest(value, F.lit(1e-9)) / 1e-4) / math.log(GROWTH)).cast("int"))


def sketches(features: DataFrame, n: dict[str, str], lang: str = "lang", source: str = "source") -> DataFrame:
    """(lang, source, rule, bucket, n) over the documents that pass the base rules."""
    rules = F.array(*[F.struct(F.lit(k).alias("rule"), bucket_of(v).alias("bucket")) for k, v in values(n).items()])
    return features.filter(~base_failed(n)).select(F.col(lang).alias("lang"), F.col(source).alias("source"), F.explode(rules).alias("r")).groupBy("lang", "source", "r.rule", "r.bucket").agg(F.count("*").alias("n"))


def quantiles(sketch: DataFrame, by: list[str]) -> DataFrame:
    """Merged sketches of the groups `by`: size, q25 and q75 of each rule."""
    merged = sketch.groupBy(*by, "rule", "bucket").agg(F.sum("n").alias("n"))
    w = Window.partitionBy(*by, "rule")
    run = merged.withColumns({"all": F.sum("n").over(w), "upto": F.sum("n").over(w.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0))})
    at = lambda q: F.min(F.when(F.col("upto") >= F.col("all") * q, F.when(F.col("bucket") == 0, 0.0).otherwise(F.pow(F.lit(GROWTH), F.col("bucket") - 0.5) * 1e-4)))
    return run.groupBy(*by, "rule").agg(F.max("all").alias("size"), at(0.25).alias("q25"), at(0.75).alias("q75"))


def thresholds(sketch: DataFrame, spread: float = SPREAD, least: int = LEAST) -> DataFrame:
    """One row for each (lang, source): a cutoff for each rule, from the smallest group that is large enough."""
    believed = F.create_map(*[F.lit(x) for pair in LEAST_SPREAD.items() for x in pair])[F.col("rule")]
    cut = lambda d: d.withColumn("cut", F.col("q75") + spread * F.greatest(F.col("q75") - F.col("q25"), believed)).drop("q25", "q75")
    own = cut(quantiles(sketch, ["lang", "source"]))
    lang = cut(quantiles(sketch, ["lang"])).select(F.col("lang").alias("l_lang"), F.col("rule").alias("l_rule"), F.col("size").alias("l_size"), F.col("cut").alias("l_cut"))
    every = cut(quantiles(sketch, [])).select(F.col("rule").alias("a_rule"), F.col("cut").alias("a_cut"))
    both = own.join(lang, F.col("lang").eqNullSafe(F.col("l_lang")) & (F.col("rule") == F.col("l_rule")), "left").join(every, F.col("rule") == F.col("a_rule"), "left")
    chosen = F.when(F.col("size") >= least, F.col("cut")).when(F.col("l_size") >= least, F.col("l_cut")).otherwise(F.col("a_cut"))
    return both.groupBy(F.col("lang").alias("t_lang"), F.col("source").alias("t_source")).agg(*[F.max(F.when(F.col("rule") == k, chosen)).alias(f"cut_{k}") for k in LEAST_SPREAD])


def judged(features: DataFrame, cuts: DataFrame, n: dict[str, str], lang: str = "lang", source: str = "source", most_groups: int = 100_000) -> DataFrame:
    """features with `base_failed` and `kept`.

    The cutoffs are broadcast while there are at most `most_groups` groups; beyond that the
    join is left to the optimizer, which splits hot groups.
    """
    names = fresh([*features.columns, lang, source], *cuts.columns)
    cuts = cuts.toDF(*names)
    limit = dict(zip(LEAST_SPREAD, names[2:], strict=True))
    verdict = F.lit(False)
    for k, v in values(n).items():
        verdict |= v > F.col(limit[k])
    cuts = F.broadcast(cuts) if cuts.limit(most_groups + 1).count() <= most_groups else cuts
    bad = base_failed(n)
    joined = features.join(cuts, F.col(lang).eqNullSafe(F.col(names[0])) & F.col(source).eqNullSafe(F.col(names[1])), "left")
    flag, kept = fresh(joined.columns, "base_failed", "kept")
    return joined.withColumns({flag: bad, kept: ~bad & ~F.coalesce(verdict, F.lit(False))}).select(*[F.col(f"`{c}`") for c in features.columns], flag, kept)


def quality_digest(docs: DataFrame) -> DataFrame:
    """Counts and verdict of every document.

    Null texts have no words and fail the base rules; null language or source is a group
    of its own; repeated rows are judged alike; an empty table gives an empty result.
    """
    features, names = measured(docs.select("doc_id", "lang", "source", "text"), ["doc_id", "lang", "source"])
    n = dict(zip(FEATURES, names, strict=True))
    features = written(features, "quality-features")
    cuts = written(thresholds(sketches(features, n)), "quality-cuts")
    return judged(features, cuts, n).select("doc_id", *[n[k] for k in FEATURES[:5]], "base_failed", "kept")


def quality_filter(docs: DataFrame) -> DataFrame:
    """The documents that the rules keep, with all their columns; two scans, no shuffle of texts.

    Cases as in `quality_digest`: null, empty and short texts go; columns of any other name
    are carried along; repeated rows stay or go together.
    """
    narrow, names = measured(docs, ["lang", "source"])
    n = dict(zip(FEATURES, names, strict=True))
    cuts = written(thresholds(sketches(narrow, n)), "quality-cuts")
    wide, names = measured(docs, docs.columns)
    n = dict(zip(FEATURES, names, strict=True))
    out = judged(wide, cuts, n)
    return out.filter(F.col(out.columns[-1])).select(*[F.col(f"`{c}`") for c in docs.columns])
