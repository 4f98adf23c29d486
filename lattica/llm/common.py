"""What the corpus operators share: tables, scratch space, text hashing in numpy."""

from __future__ import annotations

import uuid
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Text bytes that are worked on at a time: the arrays of eight bytes and more a byte stay small.
PIECE = 1 << 18
DOC_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh folder in the shared checkpoint folder; only a session on one machine may do without that setting."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        base = "/tmp/checkpoints/lattica"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


#: Runtime settings of writes: Spark drops an execution's shuffle files when it has ended, and a batch that goes to
#: Python is bounded by its bytes and not by its rows alone.
WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxBytesPerBatch": str(4 << 20)}


@contextmanager
def writing(spark: SparkSession):
    """Writes inside leave no shuffle files behind (what they made is on shared storage) and move bounded batches."""
    before = {k: spark.conf.get(k, None) for k in WRITING}
    for k, v in WRITING.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df to scratch space and read it back: lineage ends here and lost executors cost nothing."""
    path = scratch(df.sparkSession, name)
    with writing(df.sparkSession):
        df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def release(*frames: DataFrame) -> None:
    """Delete the scratch folders of frames that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_scratch", None)
        if path:
            sc = df.sparkSession.sparkContext
            p = sc._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)


def plus(schema: T.StructType, **columns: str) -> T.StructType:
    """The schema with further columns (DataFrame.schema itself must not be changed)."""
    return T.StructType([*schema.fields, *(T.StructField(k, T._parse_datatype_string(v)) for k, v in columns.items())])


def crc_mod(column, n: int):
    """crc32 of a number's decimal text modulo n; null ids fall in class 0."""
    return F.coalesce(F.pmod(F.crc32(F.coalesce(column.cast("string"), F.lit("")).cast("binary")), F.lit(n)), F.lit(0))


# ---------------------------------------------------------------- numpy text hashing

BASE = 0x9E3779B97F4A7C15
INV = pow(BASE, -1, 1 << 64)


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser with full avalanche (shift-multiply rounds on uint64)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class PrefixHash:
    """Polynomial prefix sums modulo 2^64 over randomised bytes: the hash of any byte range in O(1)."""

    def __init__(self):
        with np.errstate(over="ignore"):
            self.byte = mix64((np.arange(256, dtype=np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93))
        self.up = self.down = np.ones(1, np.uint64)

    def sums(self, data: np.ndarray) -> np.ndarray:
        n = len(data) + 1
        if len(self.up) < n:
            size = max(n, PIECE + (PIECE >> 2))
            for name, base in (("up", BASE), ("down", INV)):
                p = np.full(size, base, np.uint64)
                p[0] = 1
                setattr(self, name, np.multiply.accumulate(p))
        out = np.zeros(n, np.uint64)
        np.cumsum(self.byte[data] * self.up[: n - 1], out=out[1:])
        return out

    def ranges(self, sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix64((sums[end] - sums[start]) * self.down[start])

    def grams(self, sums: np.ndarray, k: int) -> np.ndarray:
        n = len(sums) - k
        return mix64((sums[k:] - sums[:n]) * self.down[:n])


SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True


def padded(column: pa.Array, lower: bool) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts, each followed by one space, and the start offset of each (one more at the end)."""
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if lower:
        column = pc.utf8_lower(column)
    column = pc.binary_join_element_wise(column, pa.scalar("", pa.large_string()), pa.scalar(" ", pa.large_string()))
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    _, off, data = column.buffers()
    off = np.frombuffer(off, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if off[-1] > off[0] else np.zeros(0, np.uint8)
    return data, off - off[0]


#: Bytes that are neither ASCII letters or digits nor part of a longer UTF-8 sequence.
NOT_WORD = np.array([not (chr(c).isalnum() or c > 127) for c in range(256)])


def words(data: np.ndarray, gap: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of bytes outside gap (ASCII white space)."""
    inside = np.empty(len(data) + 2, np.int8)
    inside[0] = inside[-1] = 0
    inside[1:-1] = ~gap[data]
    edge = np.diff(inside)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def slices(batch: pa.RecordBatch, text: str, most: int = PIECE):
    """Cuts of a batch of at most `most` text bytes each (one long text stays whole)."""
    sizes = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(text))), 0).to_numpy(zero_copy_only=False)
    ends, start, total = [], 0, 0
    for i, n in enumerate(sizes):
        if i > start and total + n > most:
            ends.append((start, i))
            start, total = i, 0
        total += int(n)
    if len(sizes) > start:
        ends.append((start, len(sizes)))
    for a, b in ends:
        yield batch.slice(a, b - a)
