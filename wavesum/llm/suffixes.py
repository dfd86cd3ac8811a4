"""Blockwise suffix sorting with a difference cover.

A difference cover of period v is a set D of residues such that for any two positions i, j
some shift d < v puts both i + d and j + d on residues in D.  The suffixes at D's residues,
the cover sample, are ranked first, by doubling with stride v (i + v has i's residue, so the
sample is closed under it).  The other suffixes are then sorted one prefix bucket at a time:
by their first bytes, and where those tie by the sample's ranks at the shift that belongs to
the two residues.  A tie costs the same however long it is, and only a bucket's suffixes are
in work at once, next to the text and the sample's ranks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Fixed: period of the cover; one 8-byte word orders more than a period.
PERIOD = 7
BUCKET = 1 << 20


def difference_cover(v: int) -> list[int]:
    """A small cover of period v, by exhaustive deepening from the residues 0 and 1."""
    from itertools import combinations

    for size in range(1, v + 1):
        for rest in combinations(range(2, v), max(0, size - 2)):
            cover = [0, 1, *rest][:size]
            if {(a - b) % v for a in cover for b in cover} == set(range(v)):
                return cover
    return list(range(v))


def words8(text: np.ndarray) -> np.ndarray:
    """The 8 bytes from each position as a big-endian number, zero bytes past the end."""
    padded = np.concatenate([text, np.zeros(8, np.uint8)])
    view = np.lib.stride_tricks.as_strided(padded, (len(text), 8), (1, 1))
    return np.ascontiguousarray(view).view(np.uint64).ravel().byteswap(inplace=True) if len(text) else np.zeros(0, np.uint64)


def dense(keys: np.ndarray) -> np.ndarray:
    """Ranks of keys from 1, equal keys alike."""
    order = np.argsort(keys)
    k = keys[order]
    rank = np.empty(len(keys), np.int64)
    rank[order] = np.cumsum(np.concatenate([[1], k[1:] != k[:-1]])) if len(keys) else 0
    return rank


class CoverSuffixes:
    """Suffix order of a byte array, compared up to `depth` bytes at least (None: to the end)."""

    def __init__(self, text: np.ndarray, depth: int | None = None):
        v = PERIOD
        self.text, self.v, n = text, v, len(text)
        self.first = words8(text)
        cover = difference_cover(v)
        self.shift = np.array([[next(d for d in range(v) if (a + d) % v in cover and (b + d) % v in cover) for b in range(v)] for a in range(v)])
        sample = np.flatnonzero(np.isin(np.arange(v), cover)[np.arange(n) % v]) if n else np.zeros(0, np.int64)
        # ranks by position; past the end 0, below every rank
        self.rank = np.zeros(n + 2 * v + 1, np.int32 if n < 1 << 30 else np.int64)
        # 7 bytes and how many of them are text: of two equal ones the one that ends early is less
        names = dense(self.first[sample] & ~np.uint64(0xFF) | np.minimum(n - sample, v).astype(np.uint64))
        done, goal = v, n if depth is None else min(depth, n)
        while len(sample):
            self.rank[sample] = names
            if done >= goal or names.max() == len(sample):
                break
            # an end of the text inside the compared bytes sorts first, as rank 0
            names = dense(names * (len(sample) + 1) + self.rank[np.minimum(sample + done, n)])
            done *= 2

    def buckets(self, positions: np.ndarray, limit: int = BUCKET) -> Iterator[np.ndarray]:
        """The positions in suffix order, a bucket of first two bytes at a time; small neighbours go together."""
        lead = (self.first[positions] >> np.uint64(48)).astype(np.int64)
        size = np.bincount(lead, minlength=1 << 16)
        where = np.flatnonzero(size)
        turn = np.cumsum(size[where]) // limit
        for t in np.unique(turn):
            keys = where[turn == t]
            yield self.order(positions[(lead >= keys[0]) & (lead <= keys[-1])])

    def order(self, at: np.ndarray) -> np.ndarray:
        """These positions in suffix order."""
        at = at[np.argsort(self.first[at])]
        key = self.first[at]
        n = len(self.text)
        change = np.concatenate([[True], key[1:] != key[:-1]]) if len(at) else np.zeros(0, bool)
        group = np.cumsum(change)
        size = np.bincount(group)
        tied = np.flatnonzero(size[group] > 1)
        if not len(tied):
            return at
        pos, grp = at[tied], group[tied]
        residue = pos % self.v
        less = np.zeros(len(pos), np.int64)
        span = len(self.rank) + 1
        of = [np.flatnonzero(residue == r) for r in range(self.v)]
        for a in range(self.v):
            for b in range(self.v):
                if len(of[a]) and len(of[b]):
                    d = int(self.shift[a, b])
                    mine, theirs = (grp[of[x]] * span + self.rank[pos[of[x]] + d] for x in (a, b))
                    theirs = np.sort(theirs)
                    # rows of earlier groups count too, alike for all of a group
                    less[of[a]] += np.searchsorted(theirs, mine)
        at = at.copy()
        at[tied] = pos[np.lexsort((-pos, less, grp))]  # equal only if both end within the shift: the shorter is less
        return at


def suffix_array(text: bytes) -> np.ndarray:
    """The whole suffix array of a text, for tests and small uses."""
    raw = np.frombuffer(text, np.uint8)
    s = CoverSuffixes(raw)
    parts = list(s.buckets(np.arange(len(raw), dtype=np.int64)))
    return np.concatenate(parts) if parts else np.zeros(0, np.int64)


def same_prefix(w: np.ndarray, ordered: np.ndarray, length: int) -> np.ndarray:
    """Whether each suffix starts with the same `length` bytes as the one before it in the order; all have that many.

    w: words8 of the text.
    """
    out = np.zeros(len(ordered), bool)
    if len(ordered) > 1:
        a, b, eq = ordered[1:], ordered[:-1], np.ones(len(ordered) - 1, bool)
        for k in [*range(0, length - 7, 8), *([length - 8] if length % 8 and length > 8 else [])]:
            eq &= w[a + k] == w[b + k]
        if length < 8:
            eq = (w[a] ^ w[b]) >> np.uint64(64 - 8 * length) == 0
        out[1:] = eq
    return out
