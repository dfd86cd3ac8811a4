"""Each text operator against a plain version of its definition, on awkward rows."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


def sha(x):
    return hashlib.sha256(x if isinstance(x, bytes) else x.encode()).hexdigest()


def multiset(df, *cols):
    return collections.Counter(tuple(r[c] for c in cols) for r in df.collect())


def test_words_and_blocks(rows):
    from wavesum.llm.common import blocks, words_of

    texts = [r[1] for r in rows]
    words, by = words_of(pa.array(texts, pa.string()))
    got = [words.to_pylist()[a:b] for a, b in zip(by[:-1], by[1:])]
    assert got == [WORD.findall(t or "") for t in texts]
    batch = pa.RecordBatch.from_arrays([pa.array(texts, pa.string())], names=["text"])
    parts = list(blocks([batch], limit=500))
    assert sum(p.num_rows for p in parts) == len(texts)
    assert all(p.num_rows == 1 or sum(len((t or "").encode()) for t in p.column("text").to_pylist()) <= 500 for p in parts)


def test_sharding(spark, docs, rows, empty, tmp_path):
    from wavesum.llm.sharding import shard_documents, write_shards

    got = shard_documents(docs, 5, bucket_rows=4).collect()
    want = collections.Counter((r[0], len((r[1] or "").encode()) + 8, zlib.crc32((r[1] or "").encode())) for r in rows)
    assert collections.Counter((r.doc_id, r["size"], r.text_crc32) for r in got) == want
    slots = collections.defaultdict(list)
    for r in got:
        slots[r.shard].append(r.slot)
        assert r.law == "key" and r.grown_shard in (r.shard, 5)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert len({(r.doc_id, r.shard) for r in got}) == len({r[0] for r in rows})
    again = {r.doc_id: r.shard for r in shard_documents(docs.repartition(2), 5).collect()}
    assert again == {r.doc_id: r.shard for r in got}
    six = {r.doc_id: r.shard for r in shard_documents(docs, 6).collect()}
    assert six == {r.doc_id: r.grown_shard for r in got}
    assert shard_documents(empty).count() == 0
    write_shards(docs, str(tmp_path / "out"), 3)
    assert multiset(spark.read.parquet(str(tmp_path / "out")), "doc_id", "text") == collections.Counter((r[0], r[1]) for r in rows)


def test_sentencepiece(docs, rows, empty, vocabulary):
    import sentencepiece

    from wavesum.llm.sentencepieces import sentencepiece_digest, sentencepiece_ids

    path = vocabulary("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    want = collections.Counter()
    for r in rows:
        ids = [*sp.encode(r[1] or ""), 2]
        want[r[0], len(ids), sha(" ".join(map(str, ids))), sha(sp.decode(ids))] += 1
    assert multiset(sentencepiece_digest(docs, path), "doc_id", "n_tokens", "ids_sha256", "decoded_sha256") == want
    assert sentencepiece_digest(empty, path).count() == 0
    full = sentencepiece_ids(docs, path).collect()
    assert collections.Counter((r.doc_id, tuple(r.piece_ids), r.decoded) for r in full) == collections.Counter((r[0], (*sp.encode(r[1] or ""), 2), sp.decode(sp.encode(r[1] or ""))) for r in rows)


def test_sentencepiece_random_strings(vocabulary):
    import sentencepiece

    from wavesum.llm.sentencepieces import encoded

    path = vocabulary("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    rng = random.Random(2)
    texts = ["".join(rng.choice(["a", "b", " ", " ", "▁", "\n", "\t", "é", "日", "😀", " ", "the", "<s>", "\x00"]) for _ in range(rng.randrange(30))) for _ in range(400)]
    n, ids, text = encoded(pa.array(texts, pa.string()), path)
    for t, a, b, c in zip(texts, n, ids.to_pylist(), text.to_pylist()):
        e = sp.encode(t)
        assert (a, b, c) == (len(e), " ".join(map(str, e)), sp.decode(e)), t


def test_token_files(spark, docs, rows, empty, vocabulary):
    from tokenizers import Tokenizer

    from wavesum.llm.token_files import EliasFano, Segment, pack, token_file_digest

    path = vocabulary("word_bpe_49k.json")
    t = Tokenizer.from_file(path)
    want = collections.Counter()
    for r in rows:
        ids = [*t.encode(r[1] or "", add_special_tokens=False).ids, 1]
        want[r[0], len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())] += 1
    got = token_file_digest(docs, path)
    assert multiset(got, "doc_id", "n_tokens", "ids_crc32") == want
    got = sorted(got.collect(), key=lambda r: r.start)
    assert [r.start for r in got] == [0, *np.cumsum([r.n_tokens for r in got])[:-1].tolist()]
    ids = [r.doc_id for r in got if r.doc_id is not None]
    assert ids == sorted(ids) and got[0].doc_id is None
    assert token_file_digest(empty, path).count() == 0
    rng = np.random.default_rng(1)
    for n in (1, 2, 63, 64, 65, 1000):
        v = np.sort(rng.integers(0, 10 ** int(rng.integers(1, 9)), n))
        e, _ = EliasFano.load(b"xx" + EliasFano.of(v).dump(), 2)
        assert e.all().tolist() == v.tolist() == [e.select(i) for i in range(n)] == e.select_many(np.arange(n)).tolist()
        some = np.sort(rng.integers(0, n, 9))
        assert e.select_many(some).tolist() == v[some].tolist()
        assert len(EliasFano.of(v).dump()) <= n * (3 + max(1, int(v[-1]) // n).bit_length()) / 8 + n / 16 + 80
    s = Segment(pack(np.array([-5, 7, 7]), 1, np.array([2, 0, 3, 1]), np.arange(6), 2))
    assert s.doc_ids() == [None, -5, 7, 7] and s.document(2).tolist() == [2, 3, 4] and s.document(1).tolist() == []


def test_word_ids_are_the_library_s(vocabulary):
    from tokenizers import Tokenizer

    from wavesum.llm.token_files import word_ids

    path, rng = vocabulary("word_bpe_49k.json"), random.Random(4)
    t = Tokenizer.from_file(path)
    atoms = ["The", "ing", "don't", "I'LL", "'s", ",", "...", "&&&", "###", "é", "É", "İ", "ẞ", "e\u0301", "A\u030a", "3", "12.5", "<|endoftext|>", "<|STARTOFTEXT|>", "<|", "|>", "a<b", "_", "\x7f", "\x00", "日本", "ﬁ", "Σ", "\u200b", "\xa0", "-", "X", " ", "  ", "\n", "\t "]
    texts = ["".join(rng.choice(atoms) for _ in range(rng.randrange(0, 40))) for _ in range(3_000)] + ["", "<|endoftext|>", "x" * 70_000]
    ids, offs = word_ids(pa.array(texts), path, 1)
    for i, text in enumerate(texts):
        assert ids[offs[i] : offs[i + 1]].tolist() == [*t.encode(text, add_special_tokens=False).ids, 1], text


def test_quality(docs, rows, empty):
    from wavesum.llm.quality import quality_digest, quality_filter

    want = collections.Counter()
    for r in rows:
        t = r[1] or ""
        w = WORD.findall(t)
        c, cover = collections.Counter(zip(w, w[1:], w[2:])), set()
        for i in range(len(w) - 2):
            if c[tuple(w[i : i + 3])] > 1:
                cover |= {i, i + 1, i + 2}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        want[r[0], len(w), sum(map(len, w)), sum(ch in "#*$%&|<>" for ch in t), len(lines) - len(set(lines)), len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)] += 1
    got = quality_digest(docs)
    assert multiset(got, "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed") == want
    assert got.filter("base_failed and kept").count() == 0
    kept = quality_filter(docs)
    assert kept.columns == docs.columns and kept.count() == got.filter("kept").count()
    assert quality_digest(empty).count() == 0 and quality_filter(empty).count() == 0


def test_quality_sketch_error(spark):
    from pyspark.sql import functions as F

    from wavesum.llm.quality import GROWTH, bucket_of, quantiles

    rng = np.random.default_rng(4)
    x = rng.lognormal(0, 1, 3000)
    df = spark.createDataFrame([(float(v),) for v in x], "v double").select(F.lit("r").alias("rule"), bucket_of(F.col("v")).alias("bucket")).groupBy("rule", "bucket").agg(F.count("*").alias("n"))
    q = quantiles(df, []).first()
    for got, p in ((q.q25, 25), (q.q75, 75)):
        assert abs(got / np.percentile(x, p, method="inverted_cdf") - 1) <= GROWTH - 1


def brute_bytes(rows, length=50):
    first = {}
    for d, t in rows:
        b = (t or "").encode()
        if d is not None:
            for i in range(len(b) - length + 1):
                k = b[i : i + length]
                first[k] = min(first.get(k, d), d)
    out = collections.Counter()
    for d, t in rows:
        b = (t or "").encode()
        gone = bytearray(len(b))
        if d is not None:
            for i in range(len(b) - length + 1):
                if first[b[i : i + length]] < d:
                    gone[i : i + length] = b"\1" * length
        out[d, len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), sha(bytes(x for x, g in zip(b, gone) if not g))] += 1
    return out


def brute_words(rows, n=20):
    first = {}
    for d, t in rows:
        w = WORD.findall(t or "")
        if d is not None:
            for i in range(len(w) - n + 1):
                k = tuple(w[i : i + n])
                first[k] = min(first.get(k, (d, i)), (d, i))
    out = collections.Counter()
    for d, t in rows:
        w = WORD.findall(t or "")
        gone = [0] * len(w)
        if d is not None:
            for i in range(len(w) - n + 1):
                if first[tuple(w[i : i + n])] < (d, i):
                    gone[i : i + n] = [1] * n
        out[d, len(w), sum(gone), sha(" ".join(x for x, g in zip(w, gone) if not g))] += 1
    return out


@pytest.mark.parametrize("hot", [1, 4096])
def test_repeats(docs, rows, empty, monkeypatch, hot):
    import functools

    from wavesum.llm import repeats, seed_dedup, suffix_dedup

    pairs = [(r[0], r[1]) for r in rows]
    for module in (seed_dedup, suffix_dedup):
        monkeypatch.setattr(module, "TEXT_BYTES", 3000)
        monkeypatch.setattr(module, "pipeline", functools.partial(repeats.pipeline, hot=hot))
    got = suffix_dedup.suffix_dedup_digest(docs)
    assert multiset(got, "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == brute_bytes(pairs)
    got = seed_dedup.seed_dedup_digest(docs)
    assert multiset(got, "doc_id", "n_words", "n_removed", "kept_sha256") == brute_words(pairs)
    assert suffix_dedup.suffix_dedup_digest(empty).count() == 0 and seed_dedup.seed_dedup_digest(empty).count() == 0
    cut = suffix_dedup.suffix_dedup(docs)
    assert cut.columns == docs.columns and seed_dedup.seed_dedup(docs).count() == docs.count()
    assert cut.filter("text is null").count() == 1


def test_suffix_array():
    from wavesum.llm.suffixes import PERIOD, difference_cover, suffix_array

    rng = random.Random(5)
    for _ in range(150):
        s = bytes(rng.choice(b"ab\0") for _ in range(rng.randrange(90))) + b"\0" * rng.randrange(5)
        assert suffix_array(s).tolist() == sorted(range(len(s)), key=lambda i: s[i:])
    s = b"abc" * 400
    assert suffix_array(s).tolist() == sorted(range(len(s)), key=lambda i: s[i:])
    cover = difference_cover(PERIOD)
    assert {(a - b) % PERIOD for a in cover for b in cover} == set(range(PERIOD)) and len(cover) == 3


def fingerprint(t, k=3):
    import xxhash

    w = WORD.findall(lower(t or ""))
    s = [" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] or ([" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def test_simhash(spark, docs, rows, empty):
    from wavesum.llm import simhash

    masks = simhash.covering_masks(2)
    assert len(masks) == 7 and all(any(not m >> i & 1 and not m >> j & 1 for m in masks) for i in range(64) for j in range(i))
    f = [(r[0], fingerprint(r[1])) for r in rows]
    best = {}
    for d, x in f:
        best[x] = min(best.get(x, math.inf), math.inf if d is None else d)
    group = {x: x for x in best}

    def root(x):
        while group[x] != x:
            x = group[x]
        return x

    for x in best:
        for y in best:
            if (x ^ y).bit_count() <= 2:
                group[root(x)] = root(y)
    least = collections.defaultdict(lambda: math.inf)
    for x in best:
        least[root(x)] = min(least[root(x)], best[x])
    want = collections.Counter((d, f"{x:016x}", None if d is None else least[root(x)]) for d, x in f)
    assert multiset(simhash.near_components(docs), "doc_id", "fingerprint", "component_id") == want
    assert simhash.near_components(empty).count() == 0
    kept = simhash.near_dedup(docs, 3)
    assert kept.columns == docs.columns
    assert {r.doc_id for r in kept.collect() if r.doc_id is not None} == {c for _, _, c in want if c is not None}


def test_components(spark):
    from wavesum.llm.graph import components

    rng = random.Random(8)
    for n, m in ((40, 30), (200, 190), (60, 300)):
        links = [(rng.randrange(n), rng.randrange(n)) for _ in range(m)] + [(i, i + 1) for i in range(1000, 1040)]
        got = {r.a: r.b for r in components(spark.createDataFrame(links, "a bigint, b bigint")).collect()}
        group = {x: x for pair in links for x in pair}

        def root(x):
            while group[x] != x:
                x = group[x]
            return x

        for a, b in links:
            a, b = root(a), root(b)
            group[max(a, b)] = min(a, b)
        assert got == {x: root(x) for x in group if root(x) != x}
    assert components(spark.createDataFrame([(None, 1), (2, 2)], "a bigint, b bigint")).count() == 0


def test_decontamination(spark, docs, empty):
    from wavesum.llm.decontaminate import Items, allowed, best_part, contaminated, decontaminate, plain_words

    rng = random.Random(3)
    vocab = ["".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(2000)]
    items = [(i, " ".join(rng.choice(vocab) for _ in range(rng.choice([8, 20, 45])))) for i in range(30)]
    made, planted = [], set()
    for d in range(200):
        w = [rng.choice(vocab) for _ in range(rng.randrange(60))]
        if d % 2:
            i = rng.randrange(30)
            part = items[i][1].split()
            for _ in range(rng.randrange(allowed(len(part)) + 1)):
                at = rng.randrange(len(part))
                kind = rng.randrange(3)
                part[at : at + (kind != 1)] = [rng.choice(vocab)] if kind < 2 else []
            at = rng.randrange(len(w) + 1)
            w[at:at] = part
            planted.add((d, i))
        made.append((d, " ".join(w).title() + " !"))
    made += [(900, None), (901, ""), (902, items[0][1]), (902, items[0][1])]
    table, bench = spark.createDataFrame(made, "doc_id bigint, text string"), spark.createDataFrame([*items, (99, None), (98, "too short")], "item_id bigint, text string")
    got = collections.Counter((r.doc_id, r.item_id) for r in contaminated(table, bench).collect())
    found = len(planted & set(got)) / len(planted)
    assert found >= 0.98 and set(got) - planted <= {(902, 0)} and got[902, 0] == 2
    left = {r.doc_id for r in decontaminate(table, bench).collect()}
    assert left == {d for d, _ in made} - {d for d, _ in got}
    assert contaminated(empty, bench).count() == 0 and contaminated(docs, bench.filter("false")).count() == 0
    assert decontaminate(docs, bench).columns == docs.columns
    a, _ = plain_words(pa.array(["q b c d"]))
    b, _ = plain_words(pa.array(["x B, c! y d z"]))
    assert best_part(a[1:], b) == (1, 1, 3)  # of equal parts the one that ends first
    assert set(Items([1, 2, 3], ["a b", "!!", "c"]).classes) == {1, 2}


def test_language(spark, empty):
    from wavesum.llm.language import codewords, identify

    rng = random.Random(6)
    sound = {"en": "the and ing with", "de": "der und sch ich", "fr": "le est que dans", "es": "los que una por"}
    rows = [(i, " ".join(rng.choice(sound[g].split()) + rng.choice("aeiou") for _ in range(30)), g) for i in range(400) for g in [rng.choice(list(sound))]]
    rows += [(500, None, "en"), (501, "123 !", "en"), (502, "der und sch ich und der", None), (None, "los que una", "es"), (503, "", "fr")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    got = identify(df).collect()
    truth = {r[0]: r[2] for r in rows}
    held = [r for r in got if r.held_out and r.doc_id is not None and r.lang_pred != "und"]
    assert held and sum(r.lang_pred == truth[r.doc_id] for r in held) / len(held) > 0.95
    assert {r.doc_id: r.held_out for r in got if r.doc_id is not None} == {i: zlib.crc32(str(i).encode()) % 5 == 0 for i in truth if i is not None}
    by = {r.doc_id: r for r in got}
    assert by[500].lang_pred == by[501].lang_pred == by[503].lang_pred == "und" and by[500].score == 0 and by[502].lang_pred == "de"
    assert all(0 <= r.score <= 1 for r in got) and len(got) == len(rows)
    assert identify(empty).count() == 0
    assert {r.lang_pred for r in identify(df.withColumn("lang", df.lang.substr(9, 0))).collect()} <= {"und", ""}
    for n in (2, 4, 9):
        c = codewords(n)
        assert min((c[i] != c[j]).sum() for i in range(n) for j in range(i)) >= (1 if n == 2 else 3)


def test_scoring(spark, docs, rows, empty, vocabulary):
    from wavesum.llm import scoring

    path = vocabulary("byte_bpe_50k.json")
    got = scoring.scored(docs, path).collect()
    tokens = [(r[0], [*WORD.findall(lower(r[1] or "")), None]) for r in rows]
    held = lambda d: zlib.crc32(("" if d is None else str(d)).encode()) % 10 == 0
    c = collections.Counter(w for d, ws in tokens if not held(d) for w in ws)
    n, v = sum(c.values()), len(c)
    want = collections.Counter((d, held(d), len(ws), sum(c[w] > 0 for w in ws), n, round(sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws), 6)) for d, ws in tokens)
    assert collections.Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == want
    assert all(r.score < 0 and math.isfinite(r.score) for r in got)
    assert scoring.scored(empty, path).count() == 0


def test_attention_gradient_and_order():
    from wavesum.llm.attention import SMALL, Adam, Attention, Words

    rng = np.random.default_rng(0)
    n = 40
    length = rng.integers(1, 4, n)
    words = Words(rng.integers(0, 30, int(length.sum())).astype(np.uint32), np.cumsum(length) - length, length)
    tokens, offs = rng.integers(1, n, 300).astype(np.int64), np.array([0, 125, 125, 300])
    a = Attention(31, np.append(np.ones(30), 0))

    def score(tokens, offs, **k):
        x, logs, out = a.vectors(words, np.arange(n)), a.log_classes(words, np.arange(n)), np.full(len(tokens), np.nan)
        for at, mix in a.mixtures(x, tokens, offs, 0, **k):
            assert np.isnan(out[at]).all()  # every token once
            out[at] = np.log((mix * np.exp(logs[tokens[at]])).sum(1))
        return out

    before = score(tokens, offs)
    # causal: a later token doesn't change an earlier score; batches and neighbouring documents don't matter
    changed = tokens.copy()
    changed[100] = changed[100] % (n - 1) + 1
    assert np.allclose(score(changed, offs)[:100], before[:100]) and not np.allclose(score(changed, offs)[101:125], before[101:125])
    assert np.allclose(score(tokens, offs, batch=2), before, atol=1e-5)
    assert np.allclose(np.concatenate([score(tokens[:125], offs[:2]), score(tokens[125:], np.array([0, 175]))]), before, atol=1e-5)

    # the small parameters' gradients against differences
    from wavesum.llm.attention import windowed

    x, logs = a.vectors(words, np.arange(n)), a.log_classes(words, np.arange(n))
    inputs, targets, first, place = windowed(tokens, offs, 0)
    real = np.zeros(targets.size, np.float32)
    real[place] = 1
    weight = real.reshape(targets.shape) / real.sum()
    prior = np.maximum(np.arange(len(inputs)) - 1, 0)

    def loss():
        s = a.state(x, inputs, inputs[prior], first)
        joint = s["mix"] * np.exp(logs[targets] - logs[targets].max(-1, keepdims=True)).astype(np.float32)
        return s, joint, -(weight * np.log(joint.sum(-1))).sum(dtype=np.float64)

    s, joint, _ = loss()
    g = a.gradients(s, joint, weight)[0]
    for name in SMALL:
        at = np.unravel_index(np.abs(g[name]).argmax(), g[name].shape)
        old, sides = a.p[name][at], []
        for step in (0.02, -0.02):
            a.p[name][at] = old + np.float32(step)
            sides.append(loss()[2])
        a.p[name][at] = old
        assert abs((sides[0] - sides[1]) / 0.04 - g[name][at]) < 0.1 * abs(g[name][at]) + 2e-5, name
    a.train(words, tokens, offs, 0, steps=60)
    assert score(tokens, offs).mean() > before.mean() + 0.2
    trained = score(tokens, offs).mean()
    assert a.refine(words, tokens, offs, 0, Adam(a.p, SMALL), 1) == 300
    assert score(tokens, offs).mean() > trained - 0.05


def test_pipeline(spark, docs, tmp_path, vocabulary):
    import corpus_pipeline

    from wavesum.llm.common import written

    names = ["doc_id", "text", "lang", "source", "n_chars"]
    docs.select(*names).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, "the " * 3)], "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert len(corpus_pipeline.STAGES) == 5
    table = spark.read.parquet(str(tmp_path / "documents.parquet"))
    ids = {r.doc_id for r in table.collect()}
    for _, stage in corpus_pipeline.STAGES[:-1]:
        table = written(stage(spark, table, str(tmp_path)), "t")
        assert table.columns == names
        left = {r.doc_id for r in table.collect()}
        assert left <= ids
        ids = left
    assert ids
    assert {r.doc_id for r in corpus_pipeline.run(spark, str(tmp_path)).collect()} == ids
