"""Files and keys made from the given tables, for tests and experiments."""

from __future__ import annotations

import struct
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.operators.sample import h32


def zipf_rank_sql(h: str, alpha: float, log2u: int) -> str:
    """A Zipf rank under 2^log2u as SQL that both engines read; h: 32 hash bits of the row.

    It is the inverse of the continuous law's distribution function.
    """
    u = 1 << log2u
    number = lambda x: f"CAST('{x!r}' AS DOUBLE)"
    x = f"(CAST({h} AS DOUBLE) + {number(0.5)}) / {number(4294967296.0)}"
    if abs(alpha - 1) < 1e-9:
        rank = f"pow({number(float(u + 1))}, {x})"
    else:
        rank = f"pow({number(float(u + 1) ** (1 - alpha) - 1)} * {x} + {number(1.0)}, {number(1 / (1 - alpha))})"
    return f"least(greatest(CAST(floor({rank}) AS BIGINT) - 1, 0), {u - 1})"


def permuted_sql(rank: str, log2u: int) -> str:
    """A rank moved over the domain (up to 2^32) by an odd multiplier, in halves so that no product overflows."""
    u, half = 1 << log2u, 65536
    odd = 2654435761 % u
    return f"((CAST(({rank} - {rank} % {half}) / {half} AS BIGINT) * {odd} % {u}) * {half} % {u} + {rank} % {half} * {odd} + 12345) % {u}"


def zipf_positions(rows: DataFrame, alpha: float, log2u: int, seed: int = 7) -> DataFrame:
    """(site, pos): keys of a Zipf law over 2^log2u values, drawn for each row by a hash of row_id."""
    drawn = rows.select("site", h32(F.col("row_id"), seed, 3).alias("h"))
    ranked = drawn.select("site", F.expr(zipf_rank_sql("h", alpha, log2u)).alias("r"))
    return ranked.select("site", F.expr(permuted_sql("r", log2u)).cast("long").alias("pos"))


def _written(df: DataFrame, path: str | None, kind: str, pack) -> str:
    """A folder of files, one from each partition in order, through any file system that Arrow can open; a retried task overwrites its own."""
    from wavesum.functions.tables import shared_folder
    from wavesum.sources.readers import file_system

    path = path or f"{shared_folder(df.sparkSession)}/{kind}-{uuid.uuid4().hex}"
    store, inner = file_system(path)
    store.create_dir(inner, recursive=True)

    def run(batches):
        from pyspark import TaskContext

        store, inner = file_system(path)
        n = 0
        with store.open_output_stream(f"{inner}/part-{TaskContext.get().partitionId():08d}.{kind}") as f:
            for b in batches:
                f.write(pack(b.column(0)))
                n += b.num_rows
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    df.mapInArrow(run, "n bigint").agg(F.sum("n")).collect()
    return path


def fixed_file(keys: DataFrame, record: int = 4, path: str | None = None) -> str:
    """Records of `record` bytes in a folder, the key as 4 bytes and the rest zeros."""

    def pack(column: pa.Array) -> bytes:
        out = np.zeros((len(column), record), np.uint8)
        out[:, :4] = column.to_numpy(zero_copy_only=False).astype("<i4").view(np.uint8).reshape(-1, 4)
        return out.tobytes()

    return _written(keys, path, "bin", pack)


def delimited_file(texts: DataFrame, path: str | None = None) -> str:
    """Each text (newlines as blanks, null as nothing), its length in 4 bytes and a newline, in a folder."""

    def pack(column: pa.Array) -> bytes:
        raw = [(t or "").replace("\n", " ").encode() for t in column.to_pylist()]
        return b"".join(r + struct.pack("<i", len(r)) + b"\n" for r in raw)

    return _written(texts, path, "txt", pack)


def splits_parquet(df: DataFrame, path: str, files: int = 16, rows_per_group: int = 1_000) -> str:
    """The table in many files with small row groups, for physical splits."""
    df.repartition(files).write.mode("overwrite").option("parquet.block.row.count.limit", rows_per_group).parquet(path)
    return path


def stream_files(events: DataFrame, folder: str, files: int = 5) -> str:
    """Events by event_id range, a file each, in arrival order."""
    n = events.agg(F.max("event_id")).first()[0] or 0
    step = n // files + 1
    for i in range(files):
        events.filter((F.col("event_id") >= i * step) & (F.col("event_id") < (i + 1) * step)).coalesce(1).write.mode("append").parquet(folder)
    return folder
