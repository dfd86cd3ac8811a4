"""SQL surface: the transform and the reconstruction as table functions, range counts as an Arrow function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


class HaarContributions:
    """One position's signed contributions to its coefficients."""

    def eval(self, pos: int, cnt: int, log2u: int):
        yield 1, -1, cnt
        for j in range(log2u):
            yield (1 << j) + (pos >> (log2u - j)) + 1, j, cnt if pos >> (log2u - j - 1) & 1 else -cnt


class ReconstructPieces:
    """Constant pieces of a summary given as arrays of ids and values."""

    def eval(self, ids: list, values: list, log2u: int):
        import numpy as np

        from wavesum.operators.hist import WaveletHistogram

        yield from WaveletHistogram(log2u, np.array(ids, np.int64), np.array(values, float)).pieces()


def register_all(spark: SparkSession, hist=None) -> None:
    """haar_contributions(pos, cnt, log2u), reconstruct_pieces(ids, values, log2u) and, with a histogram, range_count(lo, hi)."""
    spark.udtf.register("haar_contributions", F.udtf(HaarContributions, returnType="coef_id: bigint, level: int, diff: bigint"))
    spark.udtf.register("reconstruct_pieces", F.udtf(ReconstructPieces, returnType="lo: bigint, hi: bigint, estimate: double"))
    if hist is not None:

        @F.pandas_udf("double")
        def range_count(lo: pd.Series, hi: pd.Series) -> pd.Series:
            return pd.Series([hist.range_count(int(a), int(b)) for a, b in zip(lo, hi, strict=True)], dtype=float)

        spark.udf.register("range_count", range_count)
