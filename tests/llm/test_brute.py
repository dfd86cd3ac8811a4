"""Decontamination, larger radii and the whole pipeline against plain versions of their definitions."""

import collections
import hashlib
import math
import random
import re

import numpy as np
import pyarrow as pa
import pytest
import xxhash

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


def plain(t):
    return re.sub(r"[!-/:-@\[-`{-~]", " ", lower(t or "")).split()


def within(item, words):
    """Whether some part of words is within floor(0.3 n) edits of item."""
    k, row = int(0.3 * len(item)), [0] * (len(words) + 1)
    for i, w in enumerate(item, 1):
        new = [i]
        for j, v in enumerate(words, 1):
            new.append(min(row[j - 1] + (v != w), row[j] + 1, new[-1] + 1))
        row = new
    return min(row) <= k


def test_decontamination_finds_what_exhaustive_search_finds(spark):
    from wavesum.llm.decontaminate import contaminated, decontaminate

    rng = random.Random(11)
    vocab = [f"w{i}" for i in range(400)]
    items = [(i, " ".join(rng.choice(vocab) for _ in range(n))) for i, n in enumerate([1, 2, 3, 4, 5, 6, 7, 9, 12, 16, 25, 40] * 2)]
    items += [(50, "?!"), (51, ""), (52, items[9][1])]
    docs = []
    for d in range(150):
        w = [rng.choice(vocab) for _ in range(rng.randrange(40))]
        if d % 3:
            part = plain(rng.choice(items)[1])
            for _ in range(rng.randrange(int(0.3 * len(part)) + 2)):
                if part:
                    at = rng.randrange(len(part))
                    part[at : at + rng.randrange(2)] = rng.choice([[], [rng.choice(vocab)]])
            at = rng.randrange(len(w) + 1)
            w[at:at] = part
        docs.append((d, rng.choice([" ", ", ", "\n"]).join(w)))
    docs += [(300, None), (301, ""), (302, "...")]
    want = {(d, i) for d, t in docs for i, x in items if plain(x) and within(plain(x), plain(t))}
    table, bench = spark.createDataFrame(docs, "doc_id bigint, text string").repartition(3), spark.createDataFrame(items, "item_id bigint, text string")
    got = {(r.doc_id, r.item_id) for r in contaminated(table, bench).collect()}
    assert got <= want and len(got) >= 0.99 * len(want) > 100
    short = {i for i, x in items if 1 <= len(plain(x)) <= 4}
    assert {p for p in want if p[1] in short} <= got
    telling = {d for d, i in got if i not in short}
    assert {r.doc_id for r in decontaminate(table, bench).collect()} == {d for d, _ in docs} - telling


@pytest.mark.parametrize("radius", [0, 1, 2, 3, 5])
def test_fingerprint_links_of_any_radius(spark, radius):
    from wavesum.llm.simhash import fingerprint_links

    rng = np.random.default_rng(radius)
    base = rng.integers(0, 1 << 63, 25, dtype=np.uint64)
    values = {int(b) for b in base}
    for b in base:
        for _ in range(6):
            for bit in rng.integers(0, 64, rng.integers(1, 8)):
                b = b ^ np.uint64(1 << int(bit))
            values.add(int(b))
    values = sorted(values)
    group = {v: v for v in values}

    def root(v):
        while group[v] != v:
            v = group[v]
        return v

    for i, a in enumerate(values):
        for b in values[:i]:
            if (a ^ b).bit_count() <= radius:
                group[root(a)] = root(b)
    want = {frozenset(w for w in values if root(w) == root(v)) for v in values}
    df = spark.createDataFrame([(int(np.uint64(v).view(np.int64)),) for v in values], "fp bigint")
    links = [(int(np.int64(r.x).view(np.uint64)), int(np.int64(r.y).view(np.uint64))) for r in fingerprint_links(df, radius).collect()]
    group = {v: v for v in values}
    for a, b in links:
        group[root(a)] = root(b)
    assert {frozenset(w for w in values if root(w) == root(v)) for v in values} == want


# --- the pipeline ---------------------------------------------------------------------


def features(t):
    w = WORD.findall(t)
    c, cover = collections.Counter(zip(w, w[1:], w[2:])), set()
    for i in range(len(w) - 2):
        if c[tuple(w[i : i + 3])] > 1:
            cover |= {i, i + 1, i + 2}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    n, chars = len(w), max(1, sum(map(len, w)))
    bad = n < 50 or 100 * len(cover) > 50 * n
    return bad, {"symbols": sum(ch in "#*$%&|<>" for ch in t) / max(n, 1), "dup_lines": (len(lines) - len(set(lines))) / max(len(lines), 1), "repeats": len(cover) / max(n, 1), "long_words": chars / max(n, 1), "short_words": max(n, 1) / chars}


def kept_by_quality(rows):
    from wavesum.llm.quality import GROWTH, LEAST, LEAST_SPREAD, SPREAD

    got = [(r, *features(r[1] or "")) for r in rows]
    groups = collections.defaultdict(lambda: collections.defaultdict(list))
    for r, bad, v in got:
        if not bad:
            for k, x in v.items():
                b = max(0, math.ceil(math.log(max(x, 1e-9) / 1e-4) / math.log(GROWTH)))
                for g in ((r[2], r[3]), (r[2],), ()):
                    groups[g][k].append(b)

    def cut(g, k):
        b = sorted(groups[g][k])
        at = lambda q: b[math.ceil(q * len(b)) - 1]
        value = lambda x: 0.0 if x == 0 else GROWTH ** (x - 0.5) * 1e-4
        lo, hi = value(at(0.25)), value(at(0.75))
        return hi + SPREAD * max(hi - lo, LEAST_SPREAD[k])

    out = []
    for r, bad, v in got:
        if bad:
            continue
        g = (r[2], r[3])
        if len(groups[g]["repeats"]) < LEAST:
            g = g[:1] if len(groups[g[:1]]["repeats"]) >= LEAST else ()
        if all(x <= cut(g, k) for k, x in v.items()):
            out.append(r)
    return out


def shingles(t):
    w = WORD.findall(lower(t or ""))
    return [" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))] if w else []


def print_of(t):
    h = [xxhash.xxh64_intdigest(s, 42) for s in shingles(t)]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def firsts_of_groups(rows):
    sets, prints, group = [set(shingles(r[1])) for r in rows], [print_of(r[1]) for r in rows], list(range(len(rows)))

    def root(i):
        while group[i] != i:
            i = group[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            union = len(sets[i] | sets[j])
            if (prints[i] ^ prints[j]).bit_count() <= 2 or union and 5 * len(sets[i] & sets[j]) >= 4 * union:
                group[root(i)] = root(j)
    best = {}
    for i, r in enumerate(rows):
        best[root(i)] = min(best.get(root(i), r[0]), r[0])
    return [r for i, r in enumerate(rows) if r[0] == best[root(i)]]


def cut_repeats(rows, length=50):
    first, out = {}, []
    for r in sorted(rows):
        raw = r[1].encode()
        for i in range(len(raw) - length + 1):
            first.setdefault(raw[i : i + length], r[0])
    for r in rows:
        raw = r[1].encode()
        gone = np.zeros(len(raw), bool)
        for i in range(len(raw) - length + 1):
            if first[raw[i : i + length]] < r[0]:
                gone[i : i + length] = True
        left = bytes(np.frombuffer(raw, np.uint8)[~gone])
        if left:
            out.append((r[0], left.decode("utf-8", "ignore"), *r[2:]))
    return out


def corpus(seed=5):
    rng = random.Random(seed)
    vocab = ["".join(rng.choice("abcdefghilmnorstuéß") for _ in range(rng.randrange(2, 9))) for _ in range(1500)]
    text = lambda n: " ".join(rng.choice(vocab) + rng.choice(["", "", "", ",", ".\n"]) for _ in range(n))
    items = [(i, text(rng.choice([16, 24, 40]))) for i in range(12)]
    shared, rows = text(60), []
    for d in range(110):
        t = text(rng.randrange(40, 220))
        if d % 9 == 1:
            t += " " + shared + " " + text(8)
        if d % 10 == 2:
            part = rng.choice(items)[1].split()
            part[rng.randrange(len(part))] = rng.choice(vocab)
            t = t + " " + " ".join(part) + " " + text(10)
        if d % 8 == 3:  # near and exact copies
            w = rng.choice(rows)[1].split(" ")
            for _ in range(rng.choice([0, 1, 2])):
                w[rng.randrange(len(w))] = rng.choice(vocab)
            t = " ".join(w)
        if d % 17 == 4:
            t = "### $$$ " * 20 + t
        if d % 19 == 5:
            t = text(6) * 12
        rows.append((d * 2, t, rng.choice(["en", "fr"]), rng.choice(["a", "b"]), len(t)))
    return rows + [(500, None, "en", "a", None), (501, "", "en", "b", 0), (502, "short " * 10, "fr", "a", 60)], items


def test_pipeline_gives_the_rows_of_a_plain_version(spark, tmp_path, vocabulary):
    import sentencepiece

    import corpus_pipeline
    from wavesum.llm.common import cleanup, written

    rows, items = corpus()
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(items, "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))

    stages = [kept_by_quality(rows)]
    stages.append(firsts_of_groups(stages[-1]))
    stages.append(cut_repeats(stages[-1]))
    stages.append([r for r in stages[-1] if not any(within(plain(x), plain(r[1])) for _, x in items)])
    sizes = [len(rows), *map(len, stages)]
    assert all(a > b for a, b in zip(sizes[:2], sizes[1:3])) and sizes[3] > sizes[4] > 40, sizes
    assert sum(len(r[1]) for r in stages[2]) < sum(len(r[1]) for r in stages[1]) - 300

    table = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for (name, stage), want in zip(corpus_pipeline.STAGES[:-1], stages):
        table = written(stage(spark, table, str(tmp_path)), "stage")
        got = sorted((r.doc_id, r.text) for r in table.collect())
        assert got == sorted((r[0], r[1]) for r in want), name

    model = sentencepiece.SentencePieceProcessor(model_file=vocabulary("piece_bpe_32k.model"))
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    want = set()
    for r in stages[-1]:
        ids = model.encode(r[1])
        want.add((r[0], len(ids) + 1, sha(" ".join(map(str, [*ids, 2]))), sha(model.decode(ids))))
    got = {(r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert got == want
    assert cleanup(spark) > 0


def test_a_very_long_text_beside_short_ones(spark, vocabulary):
    """Over 16 MB in one row: whole results from every operator that reads texts."""
    from wavesum.llm import quality, scoring, seed_dedup, sentencepieces, sharding, simhash, suffix_dedup, token_files

    rng = np.random.default_rng(3)
    words = rng.integers(0, 10**5, 2_900_000).astype("U")
    long, tail = " ".join(words.tolist()), " ".join(f"tail{i}" for i in range(80))
    assert len(long) > 16 << 20
    texts = [(1, f"{long} {tail}"), (2, f"head {tail} end"), (3, "the cat sat"), (4, None)]
    df = spark.createDataFrame([(*r, "en", "s") for r in texts], "doc_id bigint, text string, lang string, source string").repartition(2).cache()
    n = len(words) + 80
    by = lambda d: {r.doc_id: r for r in d.collect()}
    got = by(seed_dedup.seed_dedup_digest(df))
    assert (got[1].n_words, got[1].n_removed, got[2].n_removed) == (n, 0, 80)
    got = by(suffix_dedup.suffix_dedup_digest(df))
    assert got[1].n_removed == 0 and got[2].n_removed == len(tail) + 1 and got[1].n_bytes == len(long) + 1 + len(tail)
    got = by(scoring.scored(df, vocabulary("byte_bpe_50k.json"), folds=1000))
    assert got[1].n_tokens == n + 1 and got[1].n_known == n + 1 and math.isfinite(got[1].score)
    assert by(quality.quality_digest(df))[1].n_words == n
    got = by(token_files.token_file_digest(df, vocabulary("word_bpe_49k.json")))
    assert got[2].start == got[1].n_tokens > n
    assert by(sentencepieces.sentencepiece_digest(df, vocabulary("piece_bpe_32k.model")))[1].n_tokens > n
    assert len({r.fingerprint for r in simhash.near_components(df).collect()}) == 4
    assert sorted(r["size"] for r in sharding.shard_documents(df, 3).collect())[-1] == len(long) + len(tail) + 9
    df.unpersist()
