"""Shared plumbing: tables, the shared work folder, staged tables and global running offsets."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """The named columns of one table; other columns never reach a plan, so clashing names can't occur."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def shared_dir(spark: SparkSession) -> str:
    """Folder every executor can reach: the session's checkpoint folder; only where none is set, a new one (tests)."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="kgfold-"))
    return sc._jsc.sc().getCheckpointDir().get()


def staged(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts the lineage and outlives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._kgfold_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete staged tables that nothing reads any more."""
    for df in frames:
        sc = df.sparkSession.sparkContext
        path = sc._jvm.org.apache.hadoop.fs.Path(df._kgfold_path)
        path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def n_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def ordered_ids(df: DataFrame, key: str = "doc_id", *tie: str) -> DataFrame:
    """``df`` range-partitioned by its key and staged, with ``_part`` (ascending with the key) naming the partition.

    Meant for narrow rows (ids and sizes).  Equal keys share a partition; null keys come first.
    """
    n = n_partitions(df.sparkSession)
    return staged(df.repartitionByRange(n, F.col(key).asc_nulls_first()).withColumn("_part", F.spark_partition_id()), "order")


def running_start(df: DataFrame, size: str, key: str = "doc_id", tie: tuple[str, ...] = ()) -> DataFrame:
    """Adds ``start``: the sum of ``size`` over all rows before this one in ascending key order.

    No window spans the table: sums run inside range partitions, and only one total per partition reaches the driver.
    """
    spark = df.sparkSession
    rows = ordered_ids(df, key)
    totals = sorted(rows.groupBy("_part").agg(F.sum(size).alias("n")).collect(), key=lambda r: r["_part"])
    base, at = [], 0
    for r in totals:
        base.append((r["_part"], at))
        at += int(r["n"] or 0)
    schema = T.StructType([T.StructField("_part", T.IntegerType()), T.StructField("_base", T.LongType())])
    bases = spark.createDataFrame(base, schema)
    order = [F.col(key).asc_nulls_first(), *[F.col(t).asc_nulls_first() for t in tie]]
    w = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    out = rows.withColumn("_before", F.coalesce(F.sum(size).over(w), F.lit(0)))
    # one row per range partition: at most spark.sql.shuffle.partitions rows
    return out.join(F.broadcast(bases), "_part").withColumn("start", (F.col("_base") + F.col("_before")).cast("long")).drop("_part", "_base", "_before")


def next_lower(df: DataFrame, key: str = "doc_id") -> DataFrame:
    """Adds ``next_id``: the row's successor in descending key order; after the last (smallest) comes the first (largest).

    Keys must be unique.  Partition boundaries are patched from one row per range partition.
    """
    spark = df.sparkSession
    rows = ordered_ids(df, key)
    edges = sorted(rows.groupBy("_part").agg(F.max(key).alias("top")).collect(), key=lambda r: r["_part"])
    tops = [(r["_part"], edges[i - 1]["top"]) for i, r in enumerate(edges)]  # i = 0 wraps to the largest key of all
    bounds = spark.createDataFrame(tops, T.StructType([T.StructField("_part", T.IntegerType()), T.StructField("_wrap", T.LongType())]))
    w = Window.partitionBy("_part").orderBy(F.col(key).desc())
    out = rows.withColumn("_lead", F.lead(key).over(w)).join(F.broadcast(bounds), "_part")
    return out.withColumn("next_id", F.coalesce("_lead", "_wrap")).drop("_part", "_lead", "_wrap")
