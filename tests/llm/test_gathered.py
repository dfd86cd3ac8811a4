"""What the language model gathers from all training documents, and what its scores are worth."""

import os

import numpy as np
import pyarrow as pa
import pytest


def test_long_text_does_not_end_the_sample():
    from wavesum.llm.scoring import chosen_within

    assert chosen_within([(1, 9), (2, 50), (3, 9), (4, 9)], 30) == [1, 3, 4]
    assert chosen_within([(2, 50), (3, 9), (3, 9), (None, 1)], 30) == [3, None]
    assert chosen_within([(2, 50), (5, 60)], 30) == [2] and chosen_within([], 30) == []


def test_statistics_cover_all_training_documents(spark, vocabulary):
    from wavesum.llm import scoring

    path = vocabulary("byte_bpe_50k.json")
    table = scoring.subwords(path, scoring.CAP)
    size = table.merges.size
    texts = [f"common words here {'zebra' if i >= 40 else 'apple'}" for i in range(80)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(3)
    model, words = scoring.fit(df, path, 2, most_docs=5)
    assert model.n == 5 * 80 and model.v == 6
    at, offs, _ = scoring.token_rows(pa.array(texts), path)
    ids, by = scoring.table_words(table).spelled(at)
    seen, last = np.bincount(ids, minlength=size), np.bincount(ids[by[1:] - 1], minlength=size)
    assert np.allclose(model.ends, (last + 0.5) / (seen + 1.0))
    assert np.isclose(model.of_class.sum(), model.n, atol=0.1)
    got = {r.kind: (r.tokens, r["words"]) for r in scoring.gathered(df, model.attention, path, 2).groupBy("kind").agg({"tokens": "sum", "words": "sum"}).toDF("kind", *("tokens", "words")).collect()}
    assert sorted(got[scoring.WORD]) == [6, 400] and scoring.WEIGHTS in got
    # every task's training moves the weights from where the sample left them
    start, _ = scoring.started(scoring.sample_texts(df, 5, 1 << 20), path)
    assert any(not np.array_equal(start.p[n], model.attention.p[n]) for n in ("q", "g", "b"))


def test_one_word_probabilities_sum_to_one_at_most(spark, vocabulary):
    from wavesum.llm import scoring

    path = vocabulary("byte_bpe_50k.json")
    table = scoring.subwords(path, scoring.CAP)
    texts = ["alpha beta gamma " * 9, "uno dos tres " * 9, "alpha dos " * 5]
    df = spark.createDataFrame(list(enumerate(texts * 4)), "doc_id bigint, text string")
    model, words = scoring.fit(df, path, 1)
    vocab = ["alpha", "beta", "gamma", "uno", "dos", "tres", "", "unseen", "zzz"]
    total = 0.0
    for w in vocab:
        at, offs, end = scoring.token_rows(pa.array([f"alpha beta {w}"]), path)
        rows = scoring.Rows(model).grow(table)
        known, spelled = rows.parts(at, offs, end)
        _, c = scoring.lookup(model.hashes, model.counts, rows.h[at])
        total += 10 ** model.mixed(c, known.astype(float), spelled.astype(float))[2]
    assert 0.9 < total <= 1 + 1e-4


def test_scores_of_two_tables_in_one_session_are_their_own(spark, vocabulary):
    from wavesum.llm.scoring import scored

    path = vocabulary("byte_bpe_50k.json")

    def table(w):
        return spark.createDataFrame([(i, f"{w} the cat {i % 7} sat on a {w} mat") for i in range(60)], "doc_id bigint, text string")

    def plain(df):
        return sorted((r.doc_id, r.n_known, round(r.base_score, 6), round(r.score, 4)) for r in scored(df, path).collect())

    a, b = table("black"), table("white").unionByName(table("red"))
    one, two = plain(a), plain(b)
    assert plain(a) == one and plain(b) == two and one != two


@pytest.mark.parametrize("scale", ["0.01", "0.1"])
def test_model_beats_its_base_on_held_out_documents(spark, vocabulary, scale):
    from pyspark.sql import functions as F

    from wavesum.llm.queries import op1_lm_scoring

    folder = f"/root/testdata/sf{scale}"
    if not os.path.isdir(folder):
        pytest.skip("no given tables here")
    r = op1_lm_scoring(spark, folder).filter("held_out").agg(F.sum("score").alias("score"), F.sum("base_score").alias("base"), F.sum("n_tokens").alias("n")).first()
    assert r.score / r.n > r.base / r.n + 0.05


def test_merges_give_the_library_s_ids(vocabulary):
    import random

    from tokenizers import Tokenizer

    from wavesum.llm import subwords

    path, rng = vocabulary("byte_bpe_50k.json"), random.Random(2)
    t, table = Tokenizer.from_file(path), subwords.SubwordTable(subwords.Merges(path), 500)
    vocab = ["the", "aaaaaaaaa", "tionthing", "é", "日本語", "", "x", "!!!!!!!!", "2024", *("".join(rng.choice("abcdefghinorst") for _ in range(rng.randrange(1, 31))) for _ in range(2_000))]
    vocab = [w for w in vocab if len(w.encode()) < subwords.PART]
    for _ in range(3):  # the table is emptied in between
        words = [rng.choice(vocab) for _ in range(900)]
        at = table.index(pa.array(words, pa.large_string()))
        for w, r in zip(words, at.tolist(), strict=True):
            assert table.ids[table.begin[r] : table.begin[r] + table.length[r]].tolist() == t.encode(f" {w}", add_special_tokens=False).ids, w
    long = "abc" * 100_000
    (r,) = table.index(pa.array([long], pa.large_string())).tolist()
    ids = table.ids[table.begin[r] : table.begin[r] + table.length[r]].tolist()
    assert t.decode(ids) == f" {long}"


def test_work_of_a_home_does_not_follow_the_number_of_buckets():
    """op5 at large sizes: rows of homes x buckets are made and read at once, not by a loop in Python."""
    import sys

    import numpy as np
    import pyarrow as pa

    from wavesum.llm import repeats, suffix_dedup

    rng = np.random.default_rng(5)
    texts = ["".join(map(chr, rng.integers(97, 123, 4000))) for _ in range(8)]
    docs = pa.table({"doc_id": pa.array(range(16)), "home": pa.array([0] * 16, pa.int32()), "text": texts + texts})

    def steps(buckets: int):
        calls = 0

        def count(frame, event, arg):
            nonlocal calls
            calls += event in ("call", "c_call")

        sys.setprofile(count)
        try:
            first = pa.Table.from_batches(repeats.anchor_rows(suffix_dedup.byte_symbols, 50, 20, buckets, False, 1 << 20)(iter(docs.to_batches())))
            places, anchor = repeats.anchor_places(*suffix_dedup.byte_symbols(docs.column("text").combine_chunks()), 50, 20)
            keys = np.unique(repeats.bucket_of(anchor, buckets).astype(np.uint64) << np.uint64(32) | repeats.low(anchor).astype(np.uint64))
            sent = suffix_dedup.send(50)(0, docs, keys, np.zeros(len(keys), bool), buckets)
            one = sent.filter(pa.compute.equal(sent.column("kind"), 0))
            back = suffix_dedup.compare(50)(0, pa.concat_tables([one.slice(0, 1)] * buckets))
        finally:
            sys.setprofile(None)
        return calls, first, sent, back

    few, some, many = steps(2), steps(50), steps(2000)
    assert many[0] < 1.5 * few[0]
    assert many[1].num_rows > 1000 and some[1].num_rows == 50
    # what is sent is the same, however it is dealt out: all texts occur twice, and one of the two is settled at home
    assert len({sum(map(len, t[2].column("bytes").to_pylist())) for t in (few, some, many)}) == 1
    settled = {tuple(np.frombuffer(b"".join(r["numbers"] for r in t[2].to_pylist() if r["kind"] == 1), np.uint32).tolist()) for t in (few, some, many)}
    assert len(settled) == 1 and len(settled.pop()) > 0


def test_rows_of_numbers_come_back_as_they_were_woven():
    import numpy as np
    import pyarrow as pa

    from wavesum.llm.repeats import binaries, packed_bits, unpacked_bits, unwoven, woven

    a, b = np.arange(7, dtype=np.uint32), np.arange(100, 104, dtype=np.uint32)
    numbers, offs = woven((a, np.array([3, 0, 4])), (b, np.array([1, 2, 1])))
    assert numbers.tolist() == [0, 1, 2, 100, 101, 102, 3, 4, 5, 6, 103] and offs.tolist() == [0, 4, 6, 11]
    back, at = unwoven(pa.chunked_array([binaries(numbers, offs)]).slice(1))
    assert back.tolist() == numbers[4:].tolist() and at.tolist() == [0, 2, 7]
    flags, edge = np.arange(20) % 3 == 0, np.array([0, 9, 9, 20])
    assert (unpacked_bits(pa.chunked_array([packed_bits(flags, edge)]), np.diff(edge)) == flags).all()
    assert not len(unwoven(pa.chunked_array([], pa.binary()))[0])


@pytest.mark.parametrize("small", [4, 0])  # every round over all documents, or documents dealt out among rounds
def test_every_training_document_trains_every_parameter(spark, vocabulary, monkeypatch, small):
    from wavesum.llm import scoring

    def sampled(*args):
        raise AssertionError("the model comes from a sample")

    sums, average = [], scoring.averaged

    def averaged(attention, weights, classes, seen):
        parts = [(r.bucket, np.frombuffer(r.counts, np.float64)) for r in weights]
        last = max(b for b, _ in parts)
        sums.append((sum(c.reshape(-1, scoring.CLASSES + scoring.WIDTH + 1)[:, -1].sum() for b, c in parts if b < last), sum(c[-1] for b, c in parts if b == last)))
        average(attention, weights, classes, seen)

    monkeypatch.setattr(scoring, "SMALL_BUCKETS", small)
    monkeypatch.setattr(scoring, "sample_texts", sampled)
    monkeypatch.setattr(scoring, "averaged", averaged)
    path = vocabulary("byte_bpe_50k.json")
    texts = [f"number{i} is the {['red', 'green', 'blue'][i % 3]} one" for i in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(3)
    model, words = scoring.fit(df, path, 2)
    assert (model.n, model.v) == (60 * 6, 60 + 7) and 0.01 < model.share < 0.999
    at, offs, _ = scoring.token_rows(pa.array(texts), path)
    ids, _ = scoring.table_words(scoring.subwords(path, scoring.CAP)).spelled(at)
    # a round over all, or all rounds together, take each token and each of its ids once
    for id_sum, tokens in sums if small else [tuple(map(sum, zip(*sums, strict=True)))]:
        assert (id_sum, tokens) == (len(ids), len(at))
    own = np.abs(model.attention.p["e"][:-1]).sum(1) > 0
    assert own[np.unique(ids)].all() and own.sum() == len(np.unique(ids))


def test_windows_in_a_row_have_the_states_and_gradients_of_single_ones():
    from wavesum.llm.attention import CLASSES, HALF, WIDTH, Attention

    rng = np.random.default_rng(1)
    a, n = Attention(20, np.ones(20)), 5
    a.p["r"] = rng.normal(size=a.p["r"].shape).astype(np.float32)
    x, inputs = rng.normal(size=(20, WIDTH)).astype(np.float32), rng.integers(0, 20, (n, HALF))
    before, first = np.concatenate([inputs[:1], inputs[:-1]]), np.array([True, False, False, True, False])
    one, row = a.state(x, inputs, before, first), a.forward(x[np.concatenate([before[:1], inputs])], first)
    assert np.allclose(one["mix"].reshape(-1, CLASSES), row["mix"], atol=1e-5)
    joint, weight = (one["mix"] * rng.random(one["mix"].shape)).astype(np.float32), rng.random((n, HALF)).astype(np.float32)
    g, dx, share = a.gradients(one, joint, weight)
    got, by_row = a.backward(row, share / weight.reshape(-1, 1), weight.ravel())
    assert all(np.allclose(g[k], got[k], atol=1e-4) for k in g)
    dx = dx.reshape(n, 2 * HALF, WIDTH)
    want = np.concatenate([dx[:1, :HALF], dx[:, HALF:]])
    want[1:-1] += dx[1:, :HALF]
    assert np.allclose(want.reshape(-1, WIDTH), by_row, atol=1e-4)
