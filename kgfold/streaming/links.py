"""A stream of links from ``events``: purchases are equivalences, clicks and views references, errors deprecations.

Every query drains its files with availableNow into a written table, so the result is that of a finished stream and
can be compared with the batch answer.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfold.work import work_dir



def relation():
    e = F.col("event_type")
    return F.when(e == "purchase", "exactMatch").when(e == "error", "deprecates").when(e == "signup", "declares").otherwise("xref")


def stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, ts, user_id, src, relation, dst of every event, as it arrives."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    # a file source reads folders; the glob names the table's file or the files of its folder
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", True).parquet(_folder(spark, sf_dir))
    # timestamps without zone can't carry a watermark
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", F.concat(F.lit("U:"), "user_id").alias("src"), relation().alias("relation"), F.concat(F.lit("K:"), F.get_json_object("props", "$.k")).alias("dst"))


def _folder(spark: SparkSession, sf_dir: str) -> str:
    """A folder that holds the events only (the given table may be a single file among others)."""
    path = f"{work_dir(spark)}/events-{uuid.uuid4().hex}"
    spark.read.parquet(f"{sf_dir}/events.parquet").write.parquet(path)
    return path


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a streaming frame to the end of its input and return what it wrote."""
    spark = df.sparkSession
    base = f"{work_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = df.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    if mode == "append":
        writer.outputMode("append").format("parquet").option("path", f"{base}/out").start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/out")
    # complete or update: every batch replaces the table
    writer.outputMode("complete").foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{base}/out")).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{base}/out")


def _ntz(col: str):
    return F.col(col).cast("timestamp_ntz")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day"), "relation").agg(F.count("*").alias("n"))
    out = drained(rows.select(F.col("window.start").alias("start"), "relation", "n"), "complete")
    return out.select(_ntz("start").alias("start"), "relation", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return drained(rows.select(F.col("window.start").alias("start"), "n"), "complete").select(_ntz("start").alias("start"), "n")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, sessions (gaps of a day end one), events."""
    rows = stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "1 day"), "user_id").agg(F.count("*").alias("n"))
    return drained(rows.select("user_id", F.col("session_window.start").alias("start"), "n"), "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(stream(spark, sf_dir).select("src", "relation", "dst").dropDuplicates(["src", "relation", "dst"]))


def late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Appended day counts: a day is out once the watermark (1 hour) has passed it; the last days wait for more input."""
    rows = stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return drained(rows.select(F.col("window.start").alias("start"), "n")).select(_ntz("start").alias("start"), "n")


def with_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return drained(stream(spark, sf_dir).join(customers, "user_id").groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


def interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases with an error of the same user within a day after them (stream-stream join)."""
    events = stream(spark, sf_dir)
    p = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("ts").alias("pt"), F.col("user_id").alias("pu")).withWatermark("pt", "2 days")
    e = stream(spark, sf_dir).filter("event_type = 'error'").select(F.col("event_id").alias("error"), F.col("ts").alias("et"), F.col("user_id").alias("eu")).withWatermark("et", "2 days")
    cond = (F.col("pu") == F.col("eu")) & (F.col("et") >= F.col("pt")) & (F.col("et") <= F.col("pt") + F.expr("INTERVAL 1 DAY"))
    return drained(p.join(e, cond).select("purchase", "error"))


def first_target(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, settled: the election of one target per name, kept as two values (least and greatest target) a name."""
    rows = stream(spark, sf_dir).filter("relation = 'exactMatch'").groupBy("src").agg(F.min("dst").alias("lo"), F.max("dst").alias("hi"))
    same = F.col("lo") == F.col("hi")
    return drained(rows.select("src", F.when(same, F.col("lo")).alias("dst"), same.alias("settled")), "complete")


def upsert(batch: DataFrame, path: str, merge: Callable[[DataFrame, DataFrame], DataFrame]) -> None:
    """foreachBatch helper: merge a micro-batch into a candidate table, written beside it and then put in its place."""
    spark = batch.sparkSession
    try:
        known = spark.read.parquet(path)
    except Exception:  # the first batch: no table yet
        batch.write.parquet(path)
        return
    merge(known, batch).write.mode("overwrite").parquet(f"{path}.next")
    spark.read.parquet(f"{path}.next").write.mode("overwrite").parquet(path)
