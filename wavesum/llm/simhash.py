"""SimHash near-dedup with covering locality-sensitive hashing.

Covering masks: bit i of 64 gets a non-zero vector of r + 1 bits, and for each of the
2^(r+1) - 1 non-zero vectors v a mask has the bits whose vector has an odd overlap with v.
Any r differing bits have vectors in a proper subspace, so some v is orthogonal to all of
them: that mask sees none of the differing bits and the pair collides there, for certain.

Buckets of two or more different fingerprints are resolved without pairs: with radius 2,
two fingerprints are linked exactly if they, or copies of them with one bit flipped,
coincide, so each fingerprint of a bucket is sent with its flips outside the mask, and
what coincides is at most 65 fingerprints, linked to the least of them.  Then the links'
components are taken (`graph`).  Work is by fingerprint, so copies count once.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.llm.common import LOWER, blocks, flat, fresh, word_spans, written
from wavesum.llm.graph import components

WORDS, RADIUS, SEED = 3, 2, 42


def shingle_hashes(texts: pa.Array, words: int = WORDS) -> Iterator[tuple[int, Iterator[np.ndarray]]]:
    """Each text's number and the big-endian 64-bit hashes of its shingles, in parts; texts under `words` words are one shingle."""
    import xxhash

    one = xxhash.xxh64_intdigest
    data, docs = flat(texts)
    data = LOWER[data]
    _, lengths, by_doc, inside = word_spans(data, docs)
    body = data[inside]
    # words with a blank behind each
    ends = np.cumsum(lengths)
    line = np.full(len(body) + len(lengths), 0x20, np.uint8)
    line[np.arange(len(body)) + np.repeat(np.arange(len(lengths)), lengths)] = body
    stop = ends + np.arange(len(lengths))
    begin = stop - lengths
    view = memoryview(line.tobytes())

    def parts(lo: int, hi: int) -> Iterator[np.ndarray]:
        k = min(words, hi - lo)
        n = hi - lo - k + 1 if k else 0
        for at in range(lo, lo + n, 1 << 16):
            upto = min(at + (1 << 16), lo + n)
            yield np.array([one(view[a:b], SEED) for a, b in zip(begin[at:upto].tolist(), stop[at + k - 1 : upto + k - 1].tolist(), strict=True)], dtype=">u8")

    for d, (lo, hi) in enumerate(zip(by_doc[:-1].tolist(), by_doc[1:].tolist(), strict=True)):
        yield d, parts(lo, hi)


def majority(parts: Iterable[np.ndarray]) -> np.uint64:
    """The fingerprint of the hashes: bits set in more than half of them; 0 without any."""
    count, n = np.zeros(64, np.int64), 0
    for h in parts:
        count += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
        n += len(h)
    return np.packbits(2 * count > n).view(">u8")[0]


def fingerprints_of(texts: pa.Array, words: int = WORDS) -> np.ndarray:
    """The 64-bit fingerprint of each text of a block."""
    return np.array([majority(parts) for _, parts in shingle_hashes(texts, words)], np.uint64)


def fingerprints(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches):
            fp = fingerprints_of(block.column("text"), words).view(np.int64)
            yield pa.RecordBatch.from_arrays([block.column("doc_id").cast(pa.int64()), pa.array(fp)], names=["doc_id", "fp"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, fp bigint")


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def covering_masks(radius: int) -> list[int]:
    """One mask for each non-zero vector of radius + 1 bits."""
    vectors = [i % (2 ** (radius + 1) - 1) + 1 for i in range(64)]
    return [sum(1 << i for i, m in enumerate(vectors) if (m & v).bit_count() & 1) for v in range(1, 2 ** (radius + 1))]


def fingerprint_links(distinct: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(x, y): pairs of fingerprints whose components are those of all pairs within the radius.

    distinct: (fp), each value once.  Up to radius 2 nothing is compared pairwise; beyond it a
    bucket is searched by one task, from fingerprint to fingerprint, and what is linked isn't
    compared again.
    """
    masks = covering_masks(radius)
    keyed = distinct.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(signed(m)).cast("long")) for m in masks])).alias("mask", "key"))
    shared = keyed.groupBy("mask", "key").agg(F.count("*").alias("n")).filter("n > 1").select("mask", "key")
    inside = keyed.join(shared, ["mask", "key"]).select("mask", "fp")
    if radius > 2:
        linked = inside.groupBy("mask", F.col("fp").bitwiseAND(F.element_at(F.array(*[F.lit(signed(m)).cast("long") for m in masks]), F.col("mask") + 1)).alias("key"))
        return linked.applyInArrow(lambda t: near_chains(t, radius), "x bigint, y bigint").distinct()
    outside = F.array(*[F.array(*[F.lit(signed(1 << b)).cast("long") for b in range(64) if radius == 2 and not m >> b & 1] or [F.lit(0).cast("long")]) for m in masks])
    one = F.lit(0).cast("long")
    if radius == 1:  # one flip on one side is enough: each with its flips, but only originals receive
        outside = F.array(*[F.array(*[F.lit(signed(1 << b)).cast("long") for b in range(64) if not m >> b & 1]) for m in masks])
        flips = inside.select("fp", F.explode(F.element_at(outside, F.col("mask") + 1)).alias("bit")).select("fp", F.col("fp").bitwiseXOR(F.col("bit")).alias("at")).distinct()
        return flips.join(distinct.select(F.col("fp").alias("at")), "at", "left_semi").select(F.col("fp").alias("x"), F.col("at").alias("y"))
    flips = inside.select("fp", F.explode(F.concat(F.array(one), F.element_at(outside, F.col("mask") + 1))).alias("bit")).select("fp", F.col("fp").bitwiseXOR(F.col("bit")).alias("at"))
    meet = flips.groupBy("at").agg(F.collect_set("fp").alias("all")).filter(F.size("all") > 1)
    return meet.select(F.explode("all").alias("x"), F.array_min("all").alias("y")).filter("x <> y").distinct()


def near_chains(bucket: pa.Table, radius: int) -> pa.Table:
    """Links of a bucket's fingerprints under which those within the radius of each other are together."""
    left = np.sort(bucket.column("fp").to_numpy().view(np.uint64))
    x, y = [np.zeros(0, np.uint64)], [np.zeros(0, np.uint64)]
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            one = queue.pop()
            near = np.bitwise_count(left ^ one) <= radius
            x.append(left[near])
            y.append(np.full(int(near.sum()), one))
            queue += list(left[near])
            left = left[~near]
    return pa.table([pa.array(np.concatenate(z).view(np.int64)) for z in (x, y)], names=["x", "y"])


def near_components(docs: DataFrame, words: int = WORDS, radius: int = RADIUS) -> DataFrame:
    """doc_id, fingerprint, component_id of every document.

    A null or wordless text has fingerprint zero and links like any other; repeated rows
    link to each other; rows without doc_id get a null component but still link others; an
    empty table gives an empty result.
    """
    prints = written(fingerprints(docs, words), "fingerprints")
    nodes = written(prints.groupBy("fp").agg(F.min("doc_id").alias("node"), F.count("*").alias("n")).withColumn("node", F.coalesce("node", F.lit((1 << 63) - 1))), "nodes")
    name = lambda c: nodes.select(F.col("fp").alias(c), F.col("node").alias(f"n{c}"))
    links = fingerprint_links(nodes.select("fp"), radius).join(name("x"), "x").join(name("y"), "y").select(F.col("nx").alias("a"), F.col("ny").alias("b"))
    roots = components(links)
    rooted = nodes.join(roots, nodes["node"] == roots["a"], "left").select("fp", F.coalesce("b", "node").alias("component_id"))
    hexed = F.lpad(F.lower(F.hex("fp")), 16, "0")
    return prints.join(rooted, "fp").select("doc_id", hexed.alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def near_dedup(docs: DataFrame, words: int = 5, radius: int = RADIUS) -> DataFrame:
    """The documents whose doc_id is the smallest of its component, all columns kept.

    Repeated rows of one doc_id keep one row; rows without doc_id stay.
    """
    return firsts_only(docs, near_components(docs, words, radius))


def firsts_only(docs: DataFrame, classes: DataFrame) -> DataFrame:
    """One row of each doc_id that is its class's (classes: doc_id, component_id); rows without doc_id stay."""
    (name,) = fresh(docs.columns, "kept_id")
    first = classes.filter("doc_id = component_id").select(F.col("doc_id").alias(name)).distinct()
    kept = docs.join(first, docs["doc_id"] == F.col(name), "left_semi").dropDuplicates(["doc_id"])
    return kept.unionByName(docs.filter("doc_id is null"))
