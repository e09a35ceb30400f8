"""Continuous leaderboard and windowed streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from querygrade.sources.tables import shared_folder

def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1000) -> DataFrame:
    """Run-log events as a file stream with event time and a family."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/[e]vents.parquet")  # a pattern: the table may be one file
    return raw.withColumns({"ts": F.col("ts").cast("timestamp"), "model_id": (F.col("user_id") % 25).cast("int")})


def drained(stream: DataFrame, mode: str, label: str) -> DataFrame:
    """Run a stream over what is there now and return its result as a table.

    Update and complete results are written for each trigger and the newest trigger's row of a key wins;
    append results are plain rows.
    """
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    out = f"{base}/out"
    if mode == "append":
        query = stream.writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def put(batch: DataFrame, number: int) -> None:
        batch.withColumn("trigger", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{out}/n={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema.add("trigger", "long")).parquet(f"{out}/*")


def newest(table: DataFrame, keys: list[str]) -> DataFrame:
    rest = [c for c in table.columns if c not in (*keys, "trigger")]
    return table.groupBy(*keys).agg(F.max_by(F.struct(*rest), "trigger").alias("x")).select(*keys, "x.*")


def live_leaderboard(stream: DataFrame, late: str | None = None) -> DataFrame:
    """Mergeable sums by contestant and day, kept up to date; means and ranks follow from them at reading.

    With ``late`` a day's state is dropped once events that much after its end have been read, and rows later still
    are left out; without it every row counts and the state holds all days.
    """
    if late is not None:
        stream = stream.withWatermark("ts", late)
    day = F.window("ts", "1 day")
    sums = stream.groupBy(day.alias("w"), "model_id").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("event_type") == "error").alias("errors"), F.sum("value").alias("seconds"))
    board = sums.select(F.col("w.start").cast("date").alias("day"), "model_id", "n", "errors", "seconds")
    return newest(drained(board, "update", "board"), ["day", "model_id"])


def board_ranks(board: DataFrame) -> DataFrame:
    """Measures, rank and its reason for each contestant, from the board's sums: fewest errors first, then the fastest."""
    total = board.groupBy("model_id").agg(F.sum("n").alias("n"), F.sum("errors").alias("errors"), F.sum("seconds").alias("seconds"))
    rates = total.select("model_id", "n", "errors", F.round(F.col("errors") / F.col("n"), 6).alias("error_rate"), F.round(F.col("seconds") / F.col("n"), 4).alias("mean_seconds"))
    reason = F.concat(F.col("errors").cast("string"), F.lit(" errors in "), F.col("n").cast("string"), F.lit(" answers"))
    return rates.withColumn("rank", F.rank().over(Window.orderBy("error_rate", "mean_seconds"))).withColumn("reason", reason)
