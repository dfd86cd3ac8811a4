import random

import pytest

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, extra string, Bucket int, held_out int"


def passages(seed: int = 1, n: int = 60) -> list[tuple]:
    """Documents with exact and near copies, shared passages, junk, nulls, empty texts and repeated rows."""
    rng = random.Random(seed)
    vocab = ["".join(rng.choice("abcdeéßñ") for _ in range(rng.randrange(2, 8))) for _ in range(300)]
    vocab += ["The", "of", "<|endoftext|>", "▁", "x" * 60, "don't", "1,234", "日本語"]
    text = lambda k: " ".join(rng.choice(vocab) for _ in range(k))
    shared, rows = text(40), []
    for i in range(n):
        t = text(rng.choice([0, 1, 2, 5, 30, 90, 200]))
        if i % 7 == 0:
            t += "\n" + shared + "\n" + text(5)
        if i % 11 == 0 and rows and rows[-1][1]:
            t = rows[-1][1]
        if i % 13 == 0 and rows and rows[-2][1]:
            t = rows[-2][1].replace(" ", "  ", 1) + " z"
        if i % 17 == 0:
            t = "Spam " * 70
        rows.append((i * 3 - 20, t, rng.choice(["en", "fr", None]), rng.choice(["s0", "s0", "s1", None]), len(t), "x", 1, None))
    rows += [(5, None, "en", "s0", None, None, None, None), (6, "", None, None, 0, None, None, 1), (7, " \n\t ", "en", "s0", 4, None, None, None), (None, text(80), "en", "s0", 9, None, None, None), rows[3], rows[3], (1000, "\n".join([text(9)] * 4 + [shared]), "fr", "s1", 3, None, None, None), (1001, "  lead  and trail  ", "en", "s1", 3, None, None, None), (1002, "a " * 4000 + shared, "en", "s1", 8, None, None, None)]
    return rows


@pytest.fixture(scope="session")
def rows():
    return passages()


@pytest.fixture(scope="session")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def vocabulary():
    from wavesum.llm.queries import vocabulary

    return vocabulary
