"""Readers, writers and scratch space."""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGE = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("w", T.LongType())])


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> DataFrame:
    """(src, dst, w) from parquet, orc, csv, tsv, json lines or coordinate text (two or three columns, % comments, a size line)."""
    if fmt == "coordinate":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.trim("value").rlike("^%") & (F.trim("value") != ""))
        # files with a banner have a size line first
        banner = spark.read.text(path).where(F.col("value").rlike("^%%MatrixMarket")).limit(1).collect()
        rows = lines.select(F.get(parts, F.lit(0)).cast("long").alias("src"), F.get(parts, F.lit(1)).cast("long").alias("dst"), F.coalesce(F.get(parts, F.lit(2)).try_cast("double").cast("long"), F.lit(1).cast("long")).alias("w"))
        if banner:
            size = lines.limit(1).select(*[F.get(parts, F.lit(i)).cast("long").alias(c) for i, c in enumerate(("src", "dst", "w"))]).collect()
            rows = rows.where(~((F.col("src") == size[0][0]) & (F.col("dst") == size[0][1]) & (F.col("w") == size[0][2])))
        return rows.select("src", "dst", "w")
    if fmt == "tsv":
        fmt, options = "csv", {"sep": "\t", **options}
    reader = spark.read.format(fmt).options(**options)
    df = (reader if fmt in ("parquet", "orc") else reader.schema(EDGE)).load(path)
    return df.select(F.col("src").cast("long"), F.col("dst").cast("long"), (F.coalesce(F.col("w"), F.lit(1)) if "w" in df.columns else F.lit(1)).cast("long").alias("w"))


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", buckets: int | None = None, table: str | None = None) -> None:
    """Bucketed and sorted by src as a table, or files of a format."""
    writer = edges.select("src", "dst", "w").write.mode("overwrite")
    if buckets:
        writer.option("path", path).bucketBy(buckets, "src").sortBy("src").saveAsTable(table or f"edges_{uuid.uuid4().hex}")
    elif fmt == "tsv":
        writer.option("sep", "\t").csv(path)
    else:
        writer.format(fmt).save(path)


def write_levels(levels: DataFrame, path: str) -> None:
    """The maps between levels, partitioned so that one level reads alone."""
    levels.write.mode("overwrite").partitionBy("level").parquet(path)


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh folder in the shared checkpoint folder; only a session on one machine may do without that setting."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        base = "/tmp/checkpoints/lattica"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


#: Runtime setting under which Spark drops an execution's shuffle files when it has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def settle(df: DataFrame, name: str = "step") -> DataFrame:
    """Write df to shared scratch space and read it back: lineage ends, sizes are known to the planner, shuffle files go."""
    spark = df.sparkSession
    path, before = scratch(spark, name), spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    for made in _scopes[-1:]:
        made.append(out)
    return out


def bucketed(df: DataFrame, key: str, name: str = "buckets") -> DataFrame:
    """Like settle, but dealt into sorted buckets by a key: joins and groups by it move only the other side."""
    spark = df.sparkSession
    path, before = scratch(spark, name), spark.conf.get(CLEANUP, None)
    table = "t_" + path.rpartition("-")[2]
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    spark.conf.set(CLEANUP, "true")
    try:
        df.repartition(parts, key).write.option("path", path).bucketBy(parts, key).sortBy(key).saveAsTable(table)
    except Exception:
        spark.sql(f"drop table if exists {table}")
        raise
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
    out = spark.table(table)
    out._scratch, out._table = path, table
    for made in _scopes[-1:]:
        made.append(out)
    return out


_scopes: list[list[DataFrame]] = []


@contextmanager
def scratch_scope():
    """The frames that are settled inside, for the caller to drop."""
    _scopes.append([])
    try:
        yield _scopes[-1]
    finally:
        _scopes.pop()


def drop(*frames: DataFrame) -> None:
    """Delete the scratch folders (and tables, and what is held in memory) of frames that nothing reads any more; others are left alone."""
    for df in frames:
        if held := getattr(df, "_held", None):
            held.unpersist()
        if name := getattr(df, "_table", None):
            df.sparkSession.sql(f"drop table if exists {name}")
        if path := getattr(df, "_scratch", None):
            sc = df.sparkSession.sparkContext
            p = sc._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)
