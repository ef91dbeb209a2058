"""Class histograms of event streams: sums that a stream keeps up to date, and what is derived from them.

A histogram by window, attribute and cell is a sum, so late rows are added until the watermark passes;
cut-points are derived again from the sums, and rows meet the version of their time.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from contrast.operators.cuts import grid_cell, merged_cuts
from contrast.schema import HybridSchema, as_number

EVENT_FIELDS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_rows(events: DataFrame, purchase: str = "purchase") -> DataFrame:
    """event_id, ts, user_id, value, hour, k, pos."""
    return events.select("event_id", "ts", "user_id", "value", F.hour("ts").alias("hour"), F.get_json_object("props", "$.k").cast("int").alias("k"), (F.col("event_type") == purchase).cast("long").alias("pos"))


def read_events(spark: SparkSession, path: str, files_each: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENT_FIELDS).option("maxFilesPerTrigger", files_each).parquet(path)


def distinct_events(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Each event once, as long as its copies come within the lateness."""
    return events.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def window_histogram(rows: DataFrame, schema: HybridSchema, window: Column) -> DataFrame:
    """begin, end, attr, cell, n_pos, n_neg of each window; rows of a stream need a watermark."""
    values = F.array(*(F.struct(F.lit(i).alias("attr"), grid_cell(as_number(rows, a.name), a.delta).alias("cell")) for i, a in schema.numbers()))
    each = rows.select("ts", "pos", F.explode(values).alias("x")).select("ts", "pos", "x.*").where("cell is not null")
    sums = each.groupBy(window.alias("w"), "attr", "cell").agg(F.sum("pos").alias("n_pos"), F.sum(1 - F.col("pos")).alias("n_neg"))
    return sums.select(F.col("w.start").alias("begin"), F.col("w.end").alias("end"), "attr", "cell", "n_pos", "n_neg")


def tumbling(size: str = "1 day") -> Column:
    return F.window("ts", size)


def sliding(size: str = "2 days", step: str = "1 day") -> Column:
    return F.window("ts", size, step)


def sessions(rows: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """user_id, begin, end, n, n_pos of each user's sessions."""
    sums = rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"), F.sum("pos").alias("n_pos"))
    return sums.select("user_id", F.col("w.start").alias("begin"), F.col("w.end").alias("end"), "n", "n_pos")


def merge_into(path: str):
    """For foreachBatch: adds a batch's sums (attr, cell, vmin, vmax, n_pos, n_neg) to the table of its number; readers sum all.

    A batch that is run again writes the same folder again, so nothing counts twice.
    """

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def current_cuts(spark: SparkSession, path: str) -> DataFrame:
    """Cut-points of all batches written so far."""
    sums = spark.read.parquet(path).groupBy("attr", "cell").agg(F.min("vmin").alias("vmin"), F.max("vmax").alias("vmax"), F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"))
    return merged_cuts(sums)


def latest_version(rows: DataFrame, versions: DataFrame) -> DataFrame:
    """rows (ts, ...) with the `version` (version, since) that was in force: the last one not after ts, or null.

    Versions are few: they come as one sorted array, and rows don't move.
    """
    array = versions.agg(F.array_sort(F.collect_list(F.struct("since", "version"))).alias("v"))
    before = F.filter("__v", lambda x: x["since"] <= F.col("ts"))
    return rows.withColumn("__v", array.scalar()).withColumn("version", F.get(before, F.size(before) - 1)["version"]).drop("__v")
