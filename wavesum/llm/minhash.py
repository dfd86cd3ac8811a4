"""Near-dedup by the Jaccard similarity of word-shingle sets, for the corpus pipeline.

A document's set has the 64-bit hashes of its shingles (`simhash`), each once.  Every set
gets BANDS keys of ROWS least values each under multiplied hashes; sets that agree in a key
meet in a bucket: two sets of similarity s meet with probability 1 - (1 - s^ROWS)^BANDS,
0.99993 at 0.8.  Buckets with the same members are kept once.  Inside a bucket similarities
are counted exactly, and a search from set to set links all that pairs of at least the
similarity hold together; what is linked isn't compared again, so a bucket of near copies
of one text costs one pass.  These links and those of the fingerprints within the radius
(`simhash.fingerprint_links`) go into one graph.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wavesum.llm.common import blocks, written
from wavesum.llm.graph import components
from wavesum.llm.simhash import RADIUS, fingerprint_links, firsts_only, majority, shingle_hashes

BANDS, ROWS, SIMILARITY = 24, 5, 0.8
_rng = np.random.default_rng(17)
FACTORS = _rng.integers(0, 1 << 64, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)
MIXERS = _rng.integers(0, 1 << 64, (BANDS, ROWS + 1), dtype=np.uint64) | np.uint64(1)
#: Shingles for which the least values are taken at once.
CHUNK = 1 << 15
#: Text bytes of a block; a block's sets and keys take some 30 times that.
BLOCK = 1 << 20


def least_values(flat: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """(sets, BANDS * ROWS) least multiplied hashes of non-empty sets that lie after each other."""
    out = np.empty((len(begin), len(FACTORS)), np.uint64)
    # whole sets up to CHUNK hashes; a longer set is one of its own
    lo = 0
    while lo < len(begin):
        hi = max(lo + 1, int(np.searchsorted(begin, begin[lo] + CHUNK)))
        part = flat[begin[lo] : begin[hi] if hi < len(begin) else len(flat)]
        for j, a in enumerate(FACTORS):
            out[lo:hi, j] = np.minimum.reduceat(part * a, begin[lo:hi] - begin[lo])
        lo = hi
    return out


def band_keys(least: np.ndarray) -> np.ndarray:
    """(sets, BANDS) keys, each of the ROWS least values of its band."""
    v = least.reshape(len(least), BANDS, ROWS)
    v = v ^ (v >> np.uint64(31))
    key = (v * MIXERS[:, :ROWS]).sum(2, dtype=np.uint64)
    return (key ^ (key >> np.uint64(29))) * MIXERS[:, ROWS]


def sets_of(texts: pa.Array, words: int) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """Fingerprint, set of shingle hashes (ascending) and signature of the set of each text; 0 is the empty set's."""
    import xxhash

    fp, sig, sets = np.zeros(len(texts), np.uint64), np.zeros(len(texts), np.uint64), []
    for d, parts in shingle_hashes(texts, words):
        parts = list(parts)
        sets.append(np.unique(np.concatenate([np.zeros(0, np.uint64), *(h.astype(np.uint64) for h in parts)])))
        fp[d] = majority(parts)
        sig[d] = xxhash.xxh64_intdigest(sets[-1].tobytes(), 7) | 1 if len(sets[-1]) else 0
    return fp, sets, sig


def prints_and_bands(docs: DataFrame, words: int) -> DataFrame:
    """(doc_id, fp, sig, bands) of every document; an empty set has no bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches, limit=BLOCK):
            fp, sets, sig = sets_of(block.column("text"), words)
            size = np.array([len(s) for s in sets])
            some = np.flatnonzero(size)
            keys = band_keys(least_values(np.concatenate([np.zeros(0, np.uint64), *sets]), (np.cumsum(size) - size)[some])).view(np.int64)
            offs = np.concatenate([[0], np.cumsum(np.where(size > 0, BANDS, 0))]).astype(np.int32)
            bands = pa.ListArray.from_arrays(pa.array(offs, pa.int32()), pa.array(keys.ravel()))
            yield pa.RecordBatch.from_arrays([block.column("doc_id").cast(pa.int64()), pa.array(fp.view(np.int64)), pa.array(sig.view(np.int64)), bands], names=["doc_id", "fp", "sig", "bands"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, fp bigint, sig bigint, bands array<bigint>")


def shingle_sets(docs: DataFrame, words: int) -> DataFrame:
    """(sig, hashes): the set of every document, packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches, limit=BLOCK):
            _, sets, sig = sets_of(block.column("text"), words)
            yield pa.RecordBatch.from_arrays([pa.array(sig.view(np.int64)), pa.array([s.tobytes() for s in sets], pa.binary())], names=["sig", "hashes"])

    return docs.select("doc_id", "text").mapInArrow(run, "sig bigint, hashes binary")


def joined_sets(sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """(i, j): links under which sets i and j are together exactly if pairs of at least the similarity join them."""
    ratio = Fraction(str(similarity))
    size = np.array([len(s) for s in sets])
    _, flat = np.unique(np.concatenate(sets), return_inverse=True)
    begin = np.cumsum(size) - size
    parts = [flat[b : b + n] for b, n in zip(begin.tolist(), size.tolist(), strict=True)]
    mark, links = np.zeros(int(flat.max()) + 1, bool), []
    left = np.arange(len(sets))
    while len(left):
        queue, left = [int(left[0])], left[1:]
        rest = np.concatenate([parts[i] for i in left]) if len(left) else flat[:0]
        while queue and len(left):
            x = queue.pop()
            mark[parts[x]] = True
            inter = np.add.reduceat(mark[rest], np.cumsum(size[left]) - size[left], dtype=np.int64)
            mark[parts[x]] = False
            near = ratio.denominator * inter >= ratio.numerator * (size[x] + size[left] - inter)
            if near.any():
                links += [(int(i), x) for i in left[near]]
                queue += left[near].tolist()
                rest = rest[np.repeat(~near, size[left])]
                left = left[~near]
    return links


def similar_links(prints: DataFrame, docs: DataFrame, words: int, similarity: float) -> DataFrame:
    """(x, y): linked signatures; prints: (doc_id, fp, sig, bands) of docs."""
    distinct = prints.filter("sig <> 0").groupBy("sig").agg(F.min("doc_id").alias("doc_id"), F.first("bands").alias("bands"))
    keyed = distinct.select("sig", F.explode("bands").alias("key"))
    members = keyed.groupBy("key").agg(F.array_sort(F.collect_set("sig")).alias("all")).filter(F.size("all") > 1).select("all").distinct()
    buckets = written(members.select(F.xxhash64("all", F.size("all")).alias("bucket"), F.explode("all").alias("sig")), "bands")
    # one document of each set in a bucket; a null doc_id names no document, so those are all read
    wanted = prints.groupBy("sig").agg(F.min("doc_id").alias("doc_id")).join(buckets.select("sig").distinct(), "sig", "left_semi").select("doc_id").distinct()
    texts = docs.select("doc_id", "text")
    texts = texts.join(wanted, "doc_id", "left_semi").unionByName(texts.filter("doc_id is null"))
    sets = written(shingle_sets(texts, words).dropDuplicates(["sig"]), "shingle-sets")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by bucket."""
        bucket, sigs, sets = None, [], []

        def linked() -> pa.RecordBatch:
            pairs = joined_sets(sets, similarity)
            return pa.RecordBatch.from_arrays([pa.array([sigs[p[k]] for p in pairs], pa.int64()) for k in (0, 1)], names=["x", "y"])

        for batch in batches:
            for b, s, raw in zip(*(batch.column(c) for c in ("bucket", "sig", "hashes")), strict=True):
                if b.as_py() != bucket:
                    if sets:
                        yield linked()
                    bucket, sigs, sets = b.as_py(), [], []
                sigs.append(s.as_py())
                sets.append(np.frombuffer(raw.as_py(), np.uint64))
        if sets:
            yield linked()

    met = buckets.join(sets, "sig").select("bucket", "sig", "hashes").repartition("bucket").sortWithinPartitions("bucket")
    return met.mapInArrow(run, "x bigint, y bigint").distinct()


def node_of(sig: Column, least_id: Column) -> Column:
    """The set's least doc_id; a set of no doc_id gets a number of its own above all ids."""
    return F.coalesce(least_id, F.lit(1 << 62).bitwiseOR(sig.bitwiseAND(F.lit((1 << 62) - 1))))


def near_copies(docs: DataFrame, words: int = 5, similarity: float = SIMILARITY, radius: int = RADIUS) -> DataFrame:
    """doc_id, component_id of every document.

    Documents are linked if their shingle sets have at least the similarity, or if their
    fingerprints differ in at most `radius` bits; rows without doc_id get a null component
    but still link others.
    """
    prints = written(prints_and_bands(docs, words), "prints")
    sets = written(prints.groupBy("fp", "sig").agg(F.min("doc_id").alias("least")), "sets")
    by_sig = written(sets.groupBy("sig").agg(F.min("least").alias("least")).select("sig", node_of(F.col("sig"), F.col("least")).alias("node")), "set-nodes")
    by_fp = written(sets.join(by_sig, "sig").groupBy("fp").agg(F.min("node").alias("fp_node")), "fp-nodes")
    same = sets.join(by_sig, "sig").join(by_fp, "fp").select(F.col("node").alias("a"), F.col("fp_node").alias("b"))

    def named(links: DataFrame, nodes: DataFrame, key: str, node: str) -> DataFrame:
        at = lambda c, n: nodes.select(F.col(key).alias(c), F.col(node).alias(n))
        return links.join(at("x", "a"), "x").join(at("y", "b"), "y").select("a", "b")

    close = named(fingerprint_links(by_fp.select("fp"), radius), by_fp, "fp", "fp_node")
    alike = named(similar_links(prints, docs, words, similarity), by_sig, "sig", "node")
    roots = components(same.unionByName(close).unionByName(alike))
    rooted = by_sig.join(roots, by_sig["node"] == roots["a"], "left").select("sig", F.coalesce("b", "node").alias("component_id"))
    return prints.select("doc_id", "sig").join(rooted, "sig").select("doc_id", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def similar_dedup(docs: DataFrame, words: int = 5, similarity: float = SIMILARITY, radius: int = RADIUS) -> DataFrame:
    """The documents whose doc_id is the smallest of its component in `near_copies`, all columns kept.

    Repeated rows of one doc_id keep one row; rows without doc_id stay.
    """
    return firsts_only(docs, near_copies(docs, words, similarity, radius))
