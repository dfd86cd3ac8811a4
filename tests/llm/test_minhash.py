"""Near copies of the pipeline stage against all pairs of five-word shingle sets."""

import random
import re

import numpy as np

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingles(t, k=5):
    w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} or ({tuple(w)} if w else set())


def similar(a, b):
    return a and b and 5 * len(a & b) >= 4 * len(a | b)


def edited(seed=4):
    """Texts of 60 to 300 words, each followed by copies of 1 to 12 changed words."""
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(3000)]
    rows = []
    for i in range(60):
        w = [rng.choice(vocab) for _ in range(rng.randrange(60, 300))]
        rows.append((10 * i, " ".join(w)))
        for j in range(1, 4):
            c = list(w)
            for _ in range(rng.randrange(1, 13)):
                c[rng.randrange(len(c))] = rng.choice(vocab)
            rows.append((10 * i + j, " ".join(c).title()))
    return rows


def test_pipeline_stage_drops_similar_copies(spark):
    import corpus_pipeline

    rows = edited()
    sets = {d: shingles(t) for d, t in rows}
    group = {d: d for d in sets}

    def root(x):
        while group[x] != x:
            x = group[x]
        return x

    for x in sets:
        for y in sets:
            if x < y and similar(sets[x], sets[y]):
                a, b = root(x), root(y)
                group[max(a, b)] = min(a, b)
    want = {x for x in sets if root(x) == x}
    assert 60 < len(want) < 200
    df = spark.createDataFrame([*rows, (None, rows[0][1]), (5000, None)], "doc_id bigint, text string")
    got = [r.doc_id for r in corpus_pipeline.simhash_near_dedup(spark, df, "").collect()]
    assert sorted(d for d in got if d is not None) == sorted([*want, 5000]) and got.count(None) == 1


def test_joined_sets_follow_chains():
    from wavesum.llm.minhash import joined_sets

    rng = np.random.default_rng(3)
    base = rng.choice(10_000, 400, replace=False).astype(np.uint64)
    # windows of 100 that move by 8: neighbours have similarity 92 / 108, next ones 84 / 116
    sets = [np.sort(base[8 * i : 8 * i + 100]) for i in rng.permutation(30)] + [np.arange(20_000, 20_100, dtype=np.uint64)]
    links = joined_sets(sets, 0.8)
    assert len(links) == 29 and {i for p in links for i in p} == set(range(30))
    edge = [np.arange(10, dtype=np.uint64), np.arange(8, dtype=np.uint64), np.arange(12, dtype=np.uint64)]
    assert sorted(map(sorted, joined_sets(edge[:2], 0.8))) == [[0, 1]] and joined_sets(edge[1:], 0.8) == []
