"""Helpers the operators share: table access, lineage cuts and byte views of Arrow text columns."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: UTF-8 bytes that vectorised kernels look at together; a longer text forms a block of its own.
BLOCK_BYTES = 1 << 19
#: The temporary folder of a local session without a shared one.
LOCAL: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, by a path that any Hadoop file system may serve."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names. A local session without one (tests) gets a temporary folder, a cluster an error."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not LOCAL:
        LOCAL.append(tempfile.mkdtemp(prefix="cuts-"))
        atexit.register(shutil.rmtree, LOCAL[0], ignore_errors=True)
    return LOCAL[0]


def cut(df: DataFrame, path: str | None = None) -> DataFrame:
    """Lineage cut: a written table in the shared folder."""
    spark = df.sparkSession
    path = path or f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Cuts:
    """Lineage cuts of one operator call. A table that nothing reads any more is deleted with ``drop``; what the lazy result reads stays."""

    def __init__(self) -> None:
        self.held: dict[int, tuple[DataFrame, str]] = {}

    def __call__(self, df: DataFrame) -> DataFrame:
        out = cut(df, path := f"{shared_folder(df.sparkSession)}/cut-{uuid.uuid4().hex}")
        self.held[id(out)] = out, path
        return out

    def drop(self, *tables: DataFrame) -> None:
        for table in tables:
            df, path = self.held.pop(id(table))
            at = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(at, True)


def free_name(name: str, taken: Iterable[str]) -> str:
    """``name`` with as many underscores before it as make it differ from all ``taken`` (Spark compares without case)."""
    lower = {x.lower() for x in taken}
    while name.lower() in lower:
        name = f"_{name}"
    return name


def word_count(text):
    """Words ``[^\\x20\\x09-\\x0D]+`` of a column, null as 0."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def text_blocks(batch: pa.RecordBatch, column: str, most: int = BLOCK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of rows (first, end, bytes, row offsets into bytes) of a string column; a null row has no bytes."""
    array = batch.column(batch.schema.get_field_index(column))
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    array = array.cast(pa.large_string()).fill_null("")
    n = len(array)
    if not n:
        return
    _, offsets, data = array.buffers()
    off = np.frombuffer(offsets, np.int64, n + 1, array.offset * 8)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    first = 0
    while first < n:
        end = int(np.searchsorted(off, off[first] + most, side="right")) - 1
        end = min(n, max(end, first + 1))
        yield first, end, raw[off[first] : off[end]], off[first : end + 1] - off[first]
        first = end


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scramble of 64-bit values (multiply and xor-shift rounds)."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return x


class Powers:
    """Powers of an odd base and of its inverse modulo 2^64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            m = max(n, 1 << 16)

            def run(b):
                steps = np.full(m, b, np.uint64)
                steps[0] = 1
                return np.cumprod(steps)

            self.up, self.down = run(self.base), run(self.inverse)
        return self.up, self.down


class PrefixHash:
    """Prefix polynomial hashes of a byte array modulo 2^64; ``of(i, n)`` does not depend on where a string stands."""

    powers = Powers(0x5851F42D4C957F2D)
    symbol = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))

    def __init__(self, data: np.ndarray):
        up, self.down = self.powers.upto(len(data) + 1)
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self.symbol[data] * up[: len(data)], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return (self.sums[end] - self.sums[start]) * self.down[start]
