"""The summary itself and what it's used for."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wavesum.functions.haar import AVERAGE


def _terms(ids: np.ndarray, log2u: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """lo, mid, hi of each coefficient; the average has mid = lo, so it adds everywhere."""
    level = np.array([0 if i == 1 else (int(i) - 1).bit_length() - 1 for i in ids], np.int64)
    block = np.where(ids == 1, 0, ids - 1 - (1 << level))
    width = (1 << log2u) >> level
    lo = block * width
    return lo, np.where(ids == 1, lo, lo + width // 2), lo + width


@dataclass
class WaveletHistogram:
    """k coefficients (id, value) of a domain of 2^log2u positions.  k rows, so it lives on the driver."""

    log2u: int
    ids: np.ndarray
    values: np.ndarray
    method: str = ""
    meta: dict = field(default_factory=dict)

    @classmethod
    def of(cls, coefs: DataFrame, log2u: int, method: str = "", **meta) -> WaveletHistogram:
        """From a DataFrame with coef_id and value, of k rows."""
        got = coefs.select("coef_id", "value").collect()
        return cls(log2u, np.array([r[0] for r in got], np.int64), np.array([r[1] for r in got], float), method, meta)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(int(i), float(v)) for i, v in zip(self.ids, self.values, strict=True)], "coef_id bigint, value double")

    def pieces(self) -> list[tuple[int, int, float]]:
        """The reconstruction as constant pieces (lo, hi, value): at most 3k + 1 of them, never u rows."""
        lo, mid, hi = _terms(self.ids, self.log2u)
        height = self.values / np.sqrt(np.maximum(hi - lo, 1))
        steps: dict[int, float] = {0: 0.0, 1 << self.log2u: 0.0}
        for at, by in ((lo, np.where(mid == lo, height, -height)), (mid, np.where(mid == lo, 0, 2 * height)), (hi, -height)):
            for x, y in zip(at.tolist(), by.tolist(), strict=True):
                steps[x] = steps.get(x, 0.0) + y
        edges = sorted(steps)
        level = np.cumsum([steps[x] for x in edges])
        return [(a, b, float(h)) for a, b, h in zip(edges[:-1], edges[1:], level, strict=False)]

    def point(self, x: int) -> float:
        """Estimated count at a position, from the k terms."""
        lo, mid, hi = _terms(self.ids, self.log2u)
        sign = np.where((x < lo) | (x >= hi), 0, np.where(x >= mid, 1, -1))
        return float((sign * self.values / np.sqrt(hi - lo)).sum())

    def range_count(self, lo: int, hi: int) -> float:
        """Estimated count in [lo, hi): each term's overlap with its two halves."""
        a, mid, b = _terms(self.ids, self.log2u)
        over = lambda p, q: np.clip(np.minimum(q, hi) - np.maximum(p, lo), 0, None)
        return float(((over(mid, b) - over(a, mid)) * self.values / np.sqrt(b - a)).sum())

    def total(self) -> float:
        return self.range_count(0, 1 << self.log2u)

    def selectivity(self, lo: int, hi: int) -> float:
        n = self.total()
        return min(1.0, max(0.0, self.range_count(lo, hi) / n)) if n else 0.0

    def quantile(self, q: float) -> int:
        """The first position whose running count reaches the share q; negative pieces count as empty."""
        parts = [(a, b, max(h, 0.0)) for a, b, h in self.pieces()]
        goal, run = q * sum((b - a) * h for a, b, h in parts), 0.0
        for a, b, h in parts:
            if h and run + (b - a) * h >= goal:
                return a + min(b - a - 1, max(0, int(np.ceil((goal - run) / h)) - 1))
            run += (b - a) * h
        return (1 << self.log2u) - 1

    def balanced_boundaries(self, parts: int) -> list[int]:
        """First positions of `parts` key ranges with about equal counts, for range partitioning."""
        return [0, *(self.quantile(i / parts) + 1 for i in range(1, parts))]

    def inner_product(self, other: WaveletHistogram) -> float:
        """Estimated size of the equi-join of two keys on one domain: the basis is orthonormal.  Terms of one id are added up."""
        mine: dict[int, float] = {}
        for i, v in zip(self.ids.tolist(), self.values.tolist(), strict=True):
            mine[i] = mine.get(i, 0.0) + v
        return sum(v * mine.get(i, 0.0) for i, v in zip(other.ids.tolist(), other.values.tolist(), strict=True))

    def merge(self, other: WaveletHistogram, k: int) -> WaveletHistogram:
        """The k largest of the added coefficients: exact only if none that matters was dropped before."""
        both: dict[int, float] = {}
        for h in (self, other):
            for i, v in zip(h.ids.tolist(), h.values.tolist(), strict=True):
                both[i] = both.get(i, 0.0) + v
        top = sorted(both.items(), key=lambda x: (-abs(x[1]), x[0]))[:k]
        return WaveletHistogram(self.log2u, np.array([i for i, _ in top], np.int64), np.array([v for _, v in top]), "merge", {})

    def reconstruct(self, spark: SparkSession, positions: DataFrame | None = None) -> DataFrame:
        """(lo, hi, estimate) pieces, or (pos, estimate) for the given positions."""
        pieces = spark.createDataFrame(self.pieces(), "lo bigint, hi bigint, estimate double")
        if positions is None:
            return pieces
        return positions.join(F.broadcast(pieces), (F.col("pos") >= F.col("lo")) & (F.col("pos") < F.col("hi"))).select("pos", "estimate")

    def save(self, spark: SparkSession, path: str, name: str, form: str = "parquet") -> None:
        """A row (name, method, log2u, coefficients as a map) in a table partitioned by name."""
        row = [(name, self.method, self.log2u, {int(i): float(v) for i, v in zip(self.ids, self.values, strict=True)})]
        spark.createDataFrame(row, "name string, method string, log2u int, coefficients map<bigint,double>").write.mode("append").partitionBy("name").format(form).save(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str, name: str, form: str = "parquet") -> WaveletHistogram:
        schema = "method string, log2u int, coefficients map<bigint,double>, name string"
        r = spark.read.schema(schema).format(form).load(path).filter(F.col("name") == name).first()
        items = sorted(r.coefficients.items())
        return cls(r.log2u, np.array([i for i, _ in items], np.int64), np.array([v for _, v in items]), r.method, {})


def level_of(coef_id: int) -> int:
    return AVERAGE if coef_id == 1 else (coef_id - 1).bit_length() - 1
