"""Linear sketches of the coefficient vector, and the best k read from them.

Group-count sketch: ids are arranged in a tree of degree 8.  At each tree level an id's
group (id >> 3 * level) is hashed to one of `buckets` in each row, the id inside it to one
of `subs` cells, and its value is added there with a random sign; a group's energy is the
median over the rows of its cells' sum of squares, and a search goes down from the root into
the groups with the most energy.  Tug-of-war: signed sums over all ids; a coefficient is the
median over rows of the mean over columns of sign times cell.

Hashes are (a x + b) mod (2^31 - 1) mod B, with another factor for what of x is over the
prime, so ids of any 62 bits are told apart and cells are the same in any engine; cells of
sites or parts add up, which is all that merging is.  Without coefficients a sketch has no
cells and no best; values are not null; ties go to the lower id.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed: the Mersenne prime of the hashes.
PRIME = (1 << 31) - 1
ROWS, SUBS = 5, 8


def coefficients_of(seed: int, count: int) -> list[tuple[int, int]]:
    rng = np.random.default_rng(seed)
    return [(int(a), int(b)) for a, b in zip(rng.integers(1, PRIME, count), rng.integers(0, PRIME, count), strict=True)]


def high(a: int, b: int) -> int:
    """The factor of the part of an id that is over the prime."""
    return (a * 48_271 + b) % PRIME or 1


def hashed(x, ab: tuple[int, int]):
    """The hash of numbers (Python or NumPy integers)."""
    a, b = ab
    return (x % PRIME * a % PRIME + x // PRIME % PRIME * high(a, b) + b) % PRIME


def hash_column(x: Column, ab: tuple[int, int]) -> Column:
    a, b = ab
    p = F.lit(PRIME)
    over = ((x - x % p) / p).cast("long")  # exact: a multiple of the prime under 2^62
    return (x % p * F.lit(a) % p + over % p * F.lit(high(a, b)) + F.lit(b)) % p


class GroupSketch:
    """Shape and hashes of a sketch of a domain of 2^log2u coefficients."""

    def __init__(self, log2u: int, bytes_total: int | None = None, degree_log2: int = 3, seed: int = 11):
        self.log2u, self.d = log2u, degree_log2
        self.levels = -(-(log2u + 1) // degree_log2)
        cells = (bytes_total or 20 * 1024 * log2u) // 8
        self.buckets = max(1, cells // (self.levels * ROWS * SUBS))
        self.hash = coefficients_of(seed, 3 * self.levels * ROWS)

    def params(self, level: int, row: int) -> list[tuple[int, int]]:
        at = 3 * (level * ROWS + row)
        return self.hash[at : at + 3]

    def cells(self, coefs: DataFrame, value: str = "value", by: tuple[str, ...] = ()) -> DataFrame:
        """(lvl, row, bucket, sub, val) summed over the coefficients (coef_id, value): nonzero cells only."""
        mod = hash_column
        spots = []
        for level in range(self.levels):
            group = F.call_function("shiftright", F.col("coef_id"), F.lit(self.d * level))
            for row in range(ROWS):
                g, s, t = self.params(level, row)
                # inside a group of one id there's nothing to tell apart, so leaves use the id too
                spots.append(F.struct(F.lit(level).alias("lvl"), F.lit(row).alias("row"), (mod(group, g) % F.lit(self.buckets)).alias("bucket"), (mod(F.col("coef_id"), s) % F.lit(SUBS)).alias("sub"), (F.lit(1) - 2 * (mod(F.col("coef_id"), t) % 2)).alias("sign")))
        parts = coefs.select(*by, F.col(value).alias("v"), F.explode(F.array(*spots)).alias("c"))
        return parts.groupBy(*by, "c.lvl", "c.row", "c.bucket", "c.sub").agg(F.sum(F.col("v") * F.col("c.sign")).alias("val")).filter("val <> 0")

    @staticmethod
    def merge(cells: DataFrame) -> DataFrame:
        return cells.groupBy("lvl", "row", "bucket", "sub").agg(F.sum("val").alias("val"))

    def load(self, cells: DataFrame) -> np.ndarray:
        """The merged sketch on the driver: its size is fixed by bytes_total, not by the data."""
        out = np.zeros((self.levels, ROWS, self.buckets, SUBS))
        for r in cells.collect():
            out[r.lvl, r.row, r.bucket, r.sub] = r.val
        return out

    def energy(self, grid: np.ndarray, level: int, group: int) -> float:
        return float(np.median([(grid[level, row, hashed(group, self.params(level, row)[0]) % self.buckets] ** 2).sum() for row in range(ROWS)]))

    def point(self, grid: np.ndarray, coef_id: int) -> float:
        est = []
        for row in range(ROWS):
            g, s, t = self.params(0, row)
            cell = grid[0, row, hashed(coef_id, g) % self.buckets, hashed(coef_id, s) % SUBS]
            est.append((1 - 2 * (hashed(coef_id, t) % 2)) * cell)
        return float(np.median(est))

    def top_k(self, grid: np.ndarray, k: int) -> list[tuple[int, float]]:
        """Best first from the root: a group is opened in the order of its energy, until k ids are out."""
        top = self.levels - 1
        heap = [(-self.energy(grid, top, g), top, g) for g in range(-(-((1 << self.log2u) + 1) // (1 << (self.d * top))))]
        heapq.heapify(heap)
        found: list[tuple[int, float]] = []
        while heap and len(found) < 4 * k:
            e, level, g = heapq.heappop(heap)
            if e == 0:
                break
            if level == 0:
                if 1 <= g <= 1 << self.log2u:
                    found.append((g, self.point(grid, g)))
                continue
            for child in range(g << self.d, (g + 1) << self.d):
                if child <= (1 << self.log2u) >> (self.d * (level - 1)):
                    heapq.heappush(heap, (-self.energy(grid, level - 1, child), level - 1, child))
        found = [f for f in found if f[1]]
        return sorted(found, key=lambda f: (-abs(f[1]), f[0]))[:k]


class TugOfWar:
    """rows x columns signed sums over all coefficients."""

    def __init__(self, log2u: int, bytes_total: int | None = None, seed: int = 13):
        self.log2u = log2u
        self.columns = max(1, (bytes_total or 20 * 1024 * log2u) // 8 // ROWS)
        self.hash = coefficients_of(seed, 2 * ROWS)

    def signs(self, ids: np.ndarray, row: int) -> np.ndarray:
        """(ids, columns) of +1 and -1."""
        ab, (c, e) = self.hash[2 * row : 2 * row + 2]
        x, cols = hashed(ids.astype(np.int64)[:, None], ab), np.arange(self.columns, dtype=np.int64)
        return 1 - 2 * (((x + cols * c + e) % PRIME * ((x + cols) % 65_521 + 1)) % PRIME % 2)

    def cells(self, coefs: DataFrame, value: str = "value") -> DataFrame:
        """(site, row, column, val): every coefficient touches every cell, which is why it is the slow one.

        Tasks add up their rows' signs in blocks, so what moves is cells, not contributions.
        """
        columns = self.columns

        def flush(sums: dict) -> Iterator[pa.RecordBatch]:
            for site, grid in sums.items():
                r, c = np.nonzero(grid)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), site)), pa.array(r.astype(np.int32)), pa.array(c), pa.array(grid[r, c])], names=["site", "row", "column", "val"])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for b in batches:
                sites, ids, v = (b.column(c).to_numpy(zero_copy_only=False) for c in ("site", "coef_id", "v"))
                for site in np.unique(sites).tolist():
                    mine = np.flatnonzero(sites == site)
                    grid = sums.setdefault(site, np.zeros((ROWS, columns)))
                    for at in np.array_split(mine, -(-len(mine) // 512)):
                        for row in range(ROWS):
                            grid[row] += v[at] @ self.signs(ids[at], row)
                if len(sums) * ROWS * columns > 1 << 22:
                    yield from flush(sums)
                    sums = {}
            yield from flush(sums)

        parts = coefs.select("site", "coef_id", F.col(value).cast("double").alias("v")).mapInArrow(run, "site bigint, row int, column bigint, val double")
        return parts.groupBy("site", "row", "column").agg(F.sum("val").alias("val"))

    @staticmethod
    def merge(cells: DataFrame) -> DataFrame:
        return cells.groupBy("row", "column").agg(F.sum("val").alias("val"))

    def estimate(self, grid: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Estimates for the given ids; finding the best k means asking for all of them."""
        return np.median([(self.signs(ids, row) * grid[row]).mean(1) for row in range(ROWS)], axis=0)

    def load(self, cells: DataFrame) -> np.ndarray:
        out = np.zeros((ROWS, self.columns))
        for r in cells.collect():
            out[r.row, r.column] = r.val
        return out

    def top_k(self, spark: SparkSession, grid: np.ndarray, k: int) -> list[tuple[int, float]]:
        """All ids of the domain asked by tasks, each sending its best k."""
        shared = spark.sparkContext.broadcast(grid)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                ids = b.column("id").to_numpy()
                est = np.concatenate([self.estimate(shared.value, part) for part in np.array_split(ids, max(1, len(ids) // 512))]) if len(ids) else np.zeros(0)
                order = np.lexsort((ids, -np.abs(est)))[:k]
                yield pa.RecordBatch.from_arrays([pa.array(ids[order]), pa.array(est[order])], names=["coef_id", "est"])

        best = spark.range(1, (1 << self.log2u) + 1).mapInArrow(run, "coef_id bigint, est double").orderBy(F.abs("est").desc(), "coef_id").limit(k)
        return [(r.coef_id, r.est) for r in best.collect()]


def ship_sketch(local: DataFrame, log2u: int, k: int = 30, kind: str = "group", bytes_total: int | None = None) -> tuple[list[tuple[int, float]], DataFrame]:
    """local: (site, coef_id, value).  The best k estimates, and the cells that the sites send."""
    if kind == "group":
        s = GroupSketch(log2u, bytes_total)
        sent = s.cells(local, by=("site",))
        return s.top_k(s.load(s.merge(sent)), k), sent
    s = TugOfWar(log2u, bytes_total)
    sent = s.cells(local)
    return s.top_k(local.sparkSession, s.load(s.merge(sent)), k), sent


def key_updates(local: DataFrame, log2u: int) -> DataFrame:
    """(site, coef_id, diff) of every distinct local key's contributions, not summed: the sketch's other way of updating.

    By linearity the cells are those of the summed coefficients; the cost is log2u + 1
    updates for each distinct key, whatever cancels.
    """
    from wavesum.functions.haar import contributions

    return local.select("site", *contributions(log2u, F.col("pos"), F.col("cnt"))).select("site", F.col("c.coef_id").alias("coef_id"), (F.col("cnt") * F.col("c.sign")).alias("diff"))
