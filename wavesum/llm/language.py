"""Language identification by error-correcting output codes.

Each language has a codeword; one binary classifier per bit predicts that bit from hashed
byte n-grams of the letters of the whole text.  A text's language is the codeword with the
least logistic loss over the bit margins, each bit weighted by what it was worth in
training (1 less twice its error), and a result whose two best codewords are close is
flagged as ambiguous.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.llm.common import LOWER, blocks, flat, remainder

WIDTH = 1 << 12
#: About so many training documents in all, and twice as many at most; an equal share for each language.
TRAIN_DOCS = 2_400
AMBIGUOUS = 0.2

#: Bytes that aren't of letters count as a blank; those over 127 are parts of letters here.
LETTERS = LOWER.copy()
LETTERS[[b for b in range(128) if not chr(b).isalpha()]] = 0x20


def codewords(classes: int, seed: int = 7) -> np.ndarray:
    """classes x bits of -1 and 1: every split of the classes up to 5 of them, else random columns, the best of many draws."""
    if classes <= 1:
        return np.ones((classes, 1))
    if classes <= 5:
        return np.array([[1 if c == classes - 1 or split >> c & 1 else -1 for split in range(2 ** (classes - 1) - 1)] for c in range(classes)], float)
    rng, bits = np.random.default_rng(seed), 4 * int(np.ceil(np.log2(classes))) + 7
    least = lambda m: min((m[i] != m[j]).sum() for i in range(classes) for j in range(i))
    return max((rng.choice([-1.0, 1.0], (classes, bits)) for _ in range(50)), key=least)


def grams(texts: pa.Array) -> Iterator[np.ndarray]:
    """The feature vector of each text: roots of the shares of hashed 1- to 4-byte grams, of length one."""
    data, docs = flat(texts)
    b = LETTERS[data].astype(np.uint32)
    for lo, hi in zip(docs[:-1].tolist(), docs[1:].tolist(), strict=True):
        x = b[lo:hi]
        got = np.zeros(WIDTH)
        h = np.zeros(len(x), np.uint32)
        for k in range(1, 5):
            if len(x) < k:
                break
            h = h[: len(x) - k + 1] * np.uint32(0x01000193) ^ x[k - 1 :] * np.uint32(0x9E3779B1)
            if k > 1:
                got += np.bincount((h * np.uint32(0x85EBCA6B)) >> np.uint32(20), minlength=WIDTH)
        got = np.sqrt(got)
        yield got / (np.linalg.norm(got) or 1.0)


def has_letter(texts: pa.Array) -> np.ndarray:
    return pc.fill_null(pc.match_substring_regex(pc.fill_null(texts, ""), r"\p{L}"), False).to_numpy(zero_copy_only=False)


def training_rows(docs: DataFrame, folds: int, most: int) -> tuple[list[str], np.ndarray, list[str]]:
    """Languages, vectors and labels of about `most` training documents: those of each language whose hash is under its share.

    The shares follow from the languages' counts, so no task ranks or gathers a language.
    """
    train = docs.filter((remainder(F.col("doc_id"), folds) != 0) & F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = {r["lang"]: r["count"] for r in train.groupBy("lang").count().collect()}
    langs = sorted(counts)
    if not langs:
        return [], np.zeros((0, WIDTH)), []
    share = max(20, most // len(langs))
    reach = F.create_map(*[F.lit(x) for g in langs for x in (g, min(1 << 31, -(-share * (1 << 31) // counts[g])))])
    sample = train.filter(F.xxhash64("doc_id").bitwiseAND(F.lit((1 << 31) - 1)) < F.element_at(reach, F.col("lang"))).select("lang", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches):
            vectors = [v.astype(np.float16).tobytes() for v in grams(block.column("text"))]
            yield pa.RecordBatch.from_arrays([block.column("lang"), pa.array(vectors, pa.binary())], names=["lang", "vector"])

    # a repeated doc_id may come with many rows, so the sample itself is bounded again, by the vectors' hashes
    got = sample.mapInArrow(run, "lang string, vector binary").orderBy(F.xxhash64("vector"), "lang").limit(2 * most).collect()
    return langs, np.stack([np.frombuffer(r.vector, np.float16) for r in got]).astype(np.float64), [r.lang for r in got]


def fit(langs: list[str], x: np.ndarray, labels: list[str], steps: int = 300) -> dict:
    """All binary classifiers at once, by gradient descent with momentum on the logistic loss."""
    code = codewords(len(langs))
    order = np.lexsort([x[:, k] for k in range(0, WIDTH, 97)])  # rows come in any order
    x, y = x[order], code[[langs.index(labels[i]) for i in order]]
    w, b = np.zeros((WIDTH, code.shape[1])), np.zeros(code.shape[1])
    dw, db = np.zeros_like(w), np.zeros_like(b)
    for _ in range(steps):
        g = -y / (1 + np.exp(y * (x @ w + b))) / len(x)
        dw, db = 0.9 * dw - 4.0 * (x.T @ g + 1e-6 * w), 0.9 * db - 4.0 * g.sum(0)
        w, b = w + dw, b + db
    worth = np.clip(1 - 2 * ((x @ w + b) * y <= 0).mean(0), 0.05, 1)
    return {"langs": langs, "code": code, "w": w.astype(np.float32), "b": b, "worth": worth / worth.sum()}


def decode(model: dict, margins: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Losses (rows x languages) and the share of each language."""
    m = margins[:, None, :] * model["code"][None]
    loss = (np.logaddexp(0, -m) * model["worth"]).sum(2)
    share = np.exp(-(loss - loss.min(1, keepdims=True)) * 4)
    return loss, share / share.sum(1, keepdims=True)


def identify(docs: DataFrame, folds: int = 5, most: int = TRAIN_DOCS) -> DataFrame:
    """doc_id, held_out, lang_pred, score, ambiguous for every document.

    A text that is null or without a letter is `und` with score 0, and so is every text if
    there's nothing to learn from.  Null ids are held out; repeated rows get equal results.
    """
    langs, x, labels = training_rows(docs, folds, most)
    model = fit(langs, x, labels) if len(labels) else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches):
            text = block.column("text")
            known = has_letter(text)
            names, scores, near = ["und"] * len(known), np.zeros(len(known)), np.zeros(len(known), bool)
            if model and known.any():
                rows = np.flatnonzero(known)
                margins = np.stack([v.astype(np.float32) @ model["w"] for v in grams(text.take(pa.array(rows)))]) + model["b"]
                _, share = decode(model, margins)
                top = np.sort(share, 1)
                scores[rows] = top[:, -1]
                near[rows] = (top[:, -1] - top[:, -2] < AMBIGUOUS) if share.shape[1] > 1 else False
                for r, k in zip(rows.tolist(), share.argmax(1).tolist(), strict=True):
                    names[r] = model["langs"][k]
            yield pa.RecordBatch.from_arrays([block.column("doc_id").cast(pa.int64()), block.column("held_out"), pa.array(names), pa.array(scores), pa.array(near)], names=["doc_id", "held_out", "lang_pred", "score", "ambiguous"])

    held = (remainder(F.col("doc_id"), folds) == 0).alias("held_out")
    return docs.select("doc_id", held, "text").mapInArrow(run, "doc_id bigint, held_out boolean, lang_pred string, score double, ambiguous boolean")
