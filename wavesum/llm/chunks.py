"""A bounded table of distinct chunks and their token ids, kept as flat arrays.

Tokenizers whose pieces cannot cross a chunk border need to segment each distinct chunk
once; the ids of a text follow by position.  The table lives as long as the Python worker
and is emptied when it would pass `cap` chunks (one block's may), which changes nothing but
the time.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CAP = 500_000
CHUNK_BLOCK = 4 << 20
SLICE = 20_000


def listed(lists: list[list[int]]) -> tuple[np.ndarray, np.ndarray]:
    """Id lists as (lengths, ids)."""
    length = np.fromiter(map(len, lists), np.int64, len(lists))
    return length, np.fromiter(itertools.chain.from_iterable(lists), np.uint32, int(length.sum()))


def apart(tokenizer, lead: str = "", literal: bool = False) -> Callable:
    """An encoder of lists of texts, each by itself with `lead` before it, as (lengths, ids).

    The library's cost for a short text is mostly that of the call, so texts go to it in
    long lines with a special token between them, at which it cuts before all else; texts
    that hold the spelling of an added token go alone, as ordinary text if `literal`.
    """
    added = {t.content: i for i, t in tokenizer.get_added_tokens_decoder().items()}
    cut = next((t.content for t in tokenizer.get_added_tokens_decoder().values() if t.special and not (t.lstrip or t.rstrip or t.single_word)), None)
    marks = {x[:2] for x in added}

    def lines(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        if not texts:
            return np.zeros(0, np.int64), np.zeros(0, np.uint32)
        joined = [cut.join([lead + t for t in texts[k : k + 1000]]) + cut for k in range(0, len(texts), 1000)]
        ids = np.concatenate([np.array(x.ids, np.uint32) for x in tokenizer.encode_batch_fast(joined, add_special_tokens=False)])
        ends = np.flatnonzero(ids == added[cut])
        return np.diff(np.concatenate([[-1], ends])) - 1, np.delete(ids, ends)

    def alone(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        tokenizer.encode_special_tokens = literal
        got = listed([x.ids for x in tokenizer.encode_batch_fast([lead + t for t in texts], add_special_tokens=False)])
        tokenizer.encode_special_tokens = False
        return got

    def encode(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        whole = "\n".join(texts)
        if cut is None:
            return alone(texts)
        if not any(m in whole for m in marks):
            return lines(texts)
        odd = np.array([any(m in t for m in marks) for t in texts])
        parts = lines([t for t, o in zip(texts, odd, strict=True) if not o]), alone([t for t, o in zip(texts, odd, strict=True) if o])
        length = np.empty(len(texts), np.int64)
        length[~odd], length[odd] = parts[0][0], parts[1][0]
        begin = np.cumsum(length) - length
        ids = np.empty(int(length.sum()), np.uint32)
        for (n, x), b in zip(parts, (begin[~odd], begin[odd]), strict=True):
            ids[np.arange(len(x)) + np.repeat(b - (np.cumsum(n) - n), n)] = x
        return length, ids

    return encode


class ChunkTable:
    """`encode`: list of texts to (lengths, ids); `extra`: names to functions from (texts, lengths, ids) to strings."""

    def __init__(self, encode: Callable, extra: dict[str, Callable] | None = None, cap: int = CAP):
        self.encode, self.extra, self.cap = encode, extra or {}, cap
        self.generation = 0
        self.clear()

    def clear(self) -> None:
        self.generation += 1
        self.row: dict[str, int] = {}
        self.ids = np.zeros(0, np.uint32)
        self.begin, self.length = np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.more = {k: pa.array([], pa.large_string()) for k in self.extra}

    def __len__(self) -> int:
        return len(self.row)

    def words(self, have: int) -> pa.Array:
        """The chunks from row `have` on."""
        return pa.array(itertools.islice(self.row, have, None), pa.large_string())

    def index(self, chunks: pa.Array) -> np.ndarray:
        """The row of each chunk in the table, unseen ones added.

        A block's chunks are found in a hash table that only grows between clearings, so a
        block costs what it has, whatever the table's size.
        """
        coded = pc.dictionary_encode(chunks)
        keys = coded.dictionary.to_pylist()
        at = np.fromiter(map(self.row.get, keys, itertools.repeat(-1)), np.int64, len(keys))
        if len(self.row) + int((at < 0).sum()) > self.cap and len(self.row):
            self.clear()
            at[:] = -1
        new = np.flatnonzero(at < 0).tolist()
        if new:
            missing = [keys[i] for i in new]
            at[new] = len(self.row) + np.arange(len(new))
            self.row.update(zip(missing, at[new].tolist(), strict=True))
            lengths, ids, more = [], [], {k: [] for k in self.extra}
            for lo in range(0, len(missing), SLICE):  # a tokenizer's own results are many times their text
                texts = missing[lo : lo + SLICE]
                n, x = self.encode(texts)
                lengths.append(n)
                ids.append(x)
                for k, f in self.extra.items():
                    got = f(texts, n, x)
                    more[k].append(got if isinstance(got, pa.Array) else pa.array(got, pa.large_string()))
            length = np.concatenate(lengths)
            self.begin = np.concatenate([self.begin, len(self.ids) + np.cumsum(length) - length])
            self.ids, self.length = np.concatenate([self.ids, *ids]), np.concatenate([self.length, length])
            for k in self.extra:
                self.more[k] = pa.concat_arrays([self.more[k], *more[k]])
        return at[coded.indices.to_numpy()]
