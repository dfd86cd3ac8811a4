"""Sampling data sources: records found by seeking, so what isn't sampled isn't read.

Paths are URIs of any file system that Arrow can open (file, hdfs, s3, ..), or plain paths of
mounted ones; a folder stands for its files in the order of their names.  The parallel unit
is a split, a byte range or a row group, and the sample of a split depends on the seed and
the split only: record i of split s has the number mix(i, s, seed), and the records with the
least numbers are drawn.  `mix_sql` is the same in SQL.
"""

from __future__ import annotations

import bisect
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: Odd multipliers of the mix.
ODD = (2654435761, 2246822519, 3266489917)


def mix(i: np.ndarray, site: int, seed: int) -> np.ndarray:
    """32 bits for each number i."""
    x = (np.asarray(i, np.uint64) * np.uint64(ODD[0]) + np.uint64(site * 40503 + seed * 97)) & np.uint64(0xFFFFFFFF)
    for shift, odd in ((15, ODD[1]), (13, ODD[2])):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(odd) & np.uint64(0xFFFFFFFF)
    return x ^ (x >> np.uint64(16))


def mix_sql(i: str, site: str, seed: int) -> str:
    """`mix` as DuckDB SQL of two integer expressions."""
    u = lambda x: f"CAST({x} AS UBIGINT)"
    x = f"(({u(i)} % 4294967296 * {ODD[0]} % 4294967296 + {u(site)} * 40503 + {seed * 97}) % 4294967296)"
    for shift, odd in ((15, ODD[1]), (13, ODD[2])):
        x = f"(xor({x}, {x} >> {shift}) * {u(odd)} % 4294967296)"
    return f"xor({x}, {x} >> 16)"


def drawn(n: int, p: float, site: int, seed: int) -> np.ndarray:
    """floor(p n + 1/2) different numbers under n, ascending."""
    take = min(n, int(np.floor(p * n + 0.5)))
    if take <= 0:
        return np.zeros(0, np.int64)
    h = mix(np.arange(n), site, seed)
    near = np.flatnonzero(h <= np.partition(h, take - 1)[take - 1])
    return np.sort(near[np.argsort(h[near], kind="stable")[:take]])


def file_system(path: str) -> tuple:
    """The file system of a path and the path in it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


def files(path: str) -> list[tuple[str, int]]:
    """(path in its file system, bytes) of a file or of a folder's files."""
    from pyarrow import fs

    store, inner = file_system(path)
    info = store.get_file_info(inner)
    if info.type == fs.FileType.File:
        return [(inner, info.size)]
    found = store.get_file_info(fs.FileSelector(inner, recursive=True))
    return sorted((f.path, f.size) for f in found if f.type == fs.FileType.File and not f.base_name.startswith(("_", ".")))


class Range(InputPartition):
    """Bytes lo to hi of a file (or a row group lo); number: among all splits; before: bytes (or rows) of the files before."""

    def __init__(self, path: str, lo: int, hi: int, number: int, before: int):
        self.path, self.lo, self.hi, self.number, self.before = path, lo, hi, number, before


def byte_ranges(path: str, size: int, unit: int = 1) -> list[Range]:
    size, out, before = max(unit, size // unit * unit), [], 0
    for name, total in files(path):
        for lo in range(0, total, size):
            out.append(Range(name, lo, min(lo + size, total), len(out), before))
        before += total
    return out


class FixedSample(DataSource):
    """fixed_sample: path, record (bytes), p, seed, split, gap.

    Rows (site, ordinal, pos): a 4-byte little-endian key leads a record.  Drawn records
    that lie within `gap` bytes of each other are fetched together.
    """

    @classmethod
    def name(cls) -> str:
        return "fixed_sample"

    def schema(self) -> str:
        return "site bigint, ordinal bigint, pos bigint"

    def reader(self, schema):
        return FixedReader(dict(self.options))


class FixedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.record = options["path"], int(options.get("record", 4))
        self.p, self.seed = float(options.get("p", 1)), int(options.get("seed", 42))
        self.split, self.gap = int(options.get("split", 64 << 20)), int(options.get("gap", 1 << 16))
        self.bytes_read = 0

    def partitions(self):
        return byte_ranges(self.path, self.split, self.record)

    def read(self, part: Range) -> Iterator[pa.RecordBatch]:
        # n_j follows from the split's length
        take = drawn((part.hi - part.lo) // self.record, self.p, part.number, self.seed)
        if not len(take):
            return
        keys = np.empty(len(take), np.int64)
        cut = np.flatnonzero(np.diff(take) * self.record - 4 > self.gap) + 1
        with file_system(self.path)[0].open_input_file(part.path) as f:
            for lo, hi in zip([0, *cut.tolist()], [*cut.tolist(), len(take)], strict=True):
                first, last = int(take[lo]), int(take[hi - 1])
                raw = f.read_at((last - first) * self.record + 4, part.lo + first * self.record)
                self.bytes_read += len(raw)
                at = (take[lo:hi] - first) * self.record
                keys[lo:hi] = np.frombuffer(raw, np.uint8)[at[:, None] + np.arange(4)].copy().view("<i4").ravel()
        ordinal = (part.before + part.lo) // self.record + take
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(take), part.number)), pa.array(ordinal), pa.array(keys)], names=["site", "ordinal", "pos"])


class DelimitedSample(DataSource):
    """delimited_sample: path, p, seed, split, n_records (of a split; else from stat = avg, median or min of a probe), min_gap, unbias.

    Rows (site, offset, length, record).  A record is its bytes, their number in 4 bytes,
    and a newline.  Random bytes hit long records more often; unbias=true keeps a record
    with probability (least length of the probe / its length), so all are as likely.  Draws
    end when the wanted number of different records is found; where too many draws fail, the
    split is read through and the records with the least numbers make up the rest, so a
    sample is short only if its split has no more records.
    """

    @classmethod
    def name(cls) -> str:
        return "delimited_sample"

    def schema(self) -> str:
        return "site bigint, offset bigint, length bigint, record string"

    def reader(self, schema):
        return DelimitedReader(dict(self.options))


class DelimitedReader(DataSourceReader):
    PROBE = 64

    def __init__(self, options: dict):
        self.path, self.p, self.seed = options["path"], float(options.get("p", 1)), int(options.get("seed", 42))
        self.split, self.gap = int(options.get("split", 64 << 20)), int(options.get("min_gap", 0))
        self.n, self.stat = options.get("n_records"), options.get("stat", "avg")
        self.unbias = str(options.get("unbias", "false")).lower() == "true"

    def partitions(self):
        return byte_ranges(self.path, self.split)

    @staticmethod
    def end_of(f, at: int, size: int) -> tuple[int, int] | None:
        """(start, end) of the record around byte `at`: the first newline whose 4 bytes before it lead back to a record's start."""
        base, step = at, 1 << 12
        while base < size:
            window = f.read_at(min(step, size - base), base)
            cut = window.find(b"\n")
            while cut >= 0:
                end = base + cut + 1
                if end >= 5:
                    (length,) = struct.unpack("<i", f.read_at(4, end - 5))
                    start = end - 5 - length
                    if 0 <= length and 0 <= start <= at and (start == 0 or f.read_at(1, start - 1) == b"\n"):
                        return start, end
                cut = window.find(b"\n", cut + 1)
            base, step = base + len(window), min(step * 4, 1 << 20)
        return None

    def probe(self, f, part: Range, size: int, most: int | None) -> list[tuple[int, int]]:
        """The split's first records, or all of them."""
        out, at = [], part.lo
        while at < part.hi and (most is None or len(out) < most):
            got = self.end_of(f, at, size)
            if not got:
                break
            at = got[1]
            if part.lo <= got[0] < part.hi:
                out.append(got)
        return out

    def estimated(self, lengths: list[int], size: int) -> int:
        """Records of a split of `size` bytes, from the lengths of some."""
        if self.n:
            return int(self.n)
        of = {"avg": np.mean, "median": np.median, "min": np.min}[self.stat](lengths) if lengths else 1
        return max(1, int(size / of))

    def read(self, part: Range) -> Iterator[pa.RecordBatch]:
        store = file_system(self.path)[0]
        with store.open_input_file(part.path) as f:
            size = f.size()
            some = self.probe(f, part, size, self.PROBE) if self.unbias or not self.n else []
            lengths = [b - a for a, b in some]
            wanted = int(np.floor(self.p * self.estimated(lengths, part.hi - part.lo) + 0.5))
            least, starts, taken, tries = min(lengths, default=1), [], [], 0
            while len(taken) < wanted and tries < 50 * wanted + 50:
                at = part.lo + (int(mix(np.array([tries]), part.number, self.seed)[0]) * (part.hi - part.lo) >> 32)
                tries += 1
                i = bisect.bisect_right(starts, at) - 1
                if i >= 0 and at < taken[i][1] + self.gap:
                    continue  # inside a record that's taken: drawn again
                got = self.end_of(f, at, size)
                # a record belongs to the split it starts in; its tail in the next split leads to that one's head
                if not got or not part.lo <= got[0] < part.hi or got in taken:
                    continue
                if self.unbias and int(mix(np.array([tries]), part.number, self.seed + 1)[0]) * (got[1] - got[0]) >= least << 32:
                    continue
                j = bisect.bisect_left(starts, got[0])
                starts.insert(j, got[0])
                taken.insert(j, got)
            if len(taken) < wanted:
                rest = [r for r in self.probe(f, part, size, None) if r not in set(taken)]
                order = np.argsort(mix(np.array([r[0] for r in rest], np.int64), part.number, self.seed + 2), kind="stable")
                taken = sorted(taken + [rest[k] for k in order[: wanted - len(taken)].tolist()])
            if taken:
                texts = [f.read_at(b - a - 5, a).decode("utf-8", "replace") for a, b in taken]
                yield pa.RecordBatch.from_arrays([pa.array([part.number] * len(taken), pa.int64()), pa.array([part.before + a for a, _ in taken], pa.int64()), pa.array([b - a - 5 for a, b in taken], pa.int64()), pa.array(texts, pa.string())], names=["site", "offset", "length", "record"])


class ParquetOrdinalSample(DataSource):
    """parquet_ordinal_sample: path (a file or folder), column, p, seed.  Rows (site, ordinal, pos); site is the row group's number."""

    @classmethod
    def name(cls) -> str:
        return "parquet_ordinal_sample"

    def schema(self) -> str:
        return "site bigint, ordinal bigint, pos bigint"

    def reader(self, schema):
        return ParquetOrdinalReader(dict(self.options))


class ParquetOrdinalReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.column = options["path"], options["column"]
        self.p, self.seed = float(options.get("p", 1)), int(options.get("seed", 42))

    def opened(self, name: str):
        import pyarrow.parquet as pq

        return pq.ParquetFile(file_system(self.path)[0].open_input_file(name))

    def partitions(self):
        out, before = [], 0
        for name, _ in files(self.path):
            if not name.endswith(".parquet"):
                continue
            meta = self.opened(name).metadata
            for g in range(meta.num_row_groups):
                out.append(Range(name, g, meta.row_group(g).num_rows, len(out), before))
                before += meta.row_group(g).num_rows
        return out

    def read(self, part: Range) -> Iterator[pa.RecordBatch]:
        take = drawn(part.hi, self.p, part.number, self.seed)
        if not len(take):
            return  # nothing of this group is read
        values = self.opened(part.path).read_row_group(part.lo, columns=[self.column]).column(0).take(pa.array(take)).combine_chunks().cast(pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(take), part.number)), pa.array(part.before + take), values], names=["site", "ordinal", "pos"])


def register_sources(spark: SparkSession) -> None:
    for source in (FixedSample, DelimitedSample, ParquetOrdinalSample):
        spark.dataSource.register(source)
