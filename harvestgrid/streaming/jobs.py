"""The same samples as a stream of uploaded files: windows of mass, sessions as tray candidates, stateful trays per cart.

Uploads come after the shift, so the watermark allows hours of lateness. Rows and conflicts of a day need the whole
day: those steps run as batches per closed day.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.shared import keep, shared_folder

LATENESS = "2 days"


def source(spark: SparkSession, sf_dir: str, files_a_batch: int | None = None) -> DataFrame:
    """events as a file stream; zone-less times are cast, as watermarks need timestamps with a zone."""
    path = f"{sf_dir}/events.parquet"
    reader = spark.readStream.schema(spark.read.parquet(path).schema).option("pathGlobFilter", "events.parquet")
    if files_a_batch:
        reader = reader.option("maxFilesPerTrigger", files_a_batch)
    return reader.parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def deduplicated(events: DataFrame) -> DataFrame:
    """Repeated uploads of a sample count once."""
    return events.withWatermark("ts", LATENESS).dropDuplicatesWithinWatermark(["user_id", "event_id"])


def window_mass(events: DataFrame, width: str = "1 day") -> DataFrame:
    """Mass per cart group and tumbling window."""
    w = F.window("ts", width)
    out = events.withWatermark("ts", LATENESS).groupBy(w.alias("win"), (F.col("user_id") % 2).cast("int").alias("field_id"))
    return out.agg(F.sum(0.05 * F.col("value")).alias("mass"), F.count(F.lit(1)).alias("n")).select(F.date_format("win.start", "yyyy-MM-dd").alias("day"), "field_id", "mass", "n")


def session_trays(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    """Sessions of a cart without a longer pause: candidates for trays."""
    w = F.session_window("ts", gap)
    out = events.withWatermark("ts", LATENESS).groupBy(w.alias("win"), "user_id").agg(F.sum(0.05 * F.col("value")).alias("mass"), F.count(F.lit(1)).alias("n"))
    return out.select(F.col("user_id").alias("cart_id"), F.unix_micros("win.start").alias("t_start"), "mass", "n")


def run_to_table(spark: SparkSession, sf_dir: str, job, name: str) -> DataFrame:
    """Run what is available once in complete mode and return the result: a table of files that every batch writes anew, with its checkpoint beside it."""
    folder = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    result = job(source(spark, sf_dir))

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/table")

    q = result.writeStream.outputMode("complete").foreachBatch(write).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(result.schema).parquet(f"{folder}/table")


def upsert_daily_map(path: str):
    """foreachBatch sink: adds a batch's cells to the day partitions it touches, which are overwritten as a whole."""

    def run(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        days = [r.day for r in batch.select("day").distinct().collect()]  # days of one batch: few
        try:
            old = spark.read.parquet(path).where(F.col("day").isin(days)).where(F.col("batch_id") != batch_id)
        except Exception as e:  # the first batch finds no table
            if "PATH_NOT_FOUND" not in str(e) and "UNABLE_TO_INFER" not in str(e):
                raise
            old = None
        new = batch.select("field_id", "day", "j", "k", "mass").withColumn("batch_id", F.lit(batch_id))
        both = new if old is None else new.unionByName(old.select(*new.columns))
        keep(both).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("day").parquet(path)

    return run


CLOSED = "cart_id long, tray_no long, t_first long, t_last long, n long, mass double"
_OPEN = "tray_no long, t_first long, t_last long, n long, mass double, last_w double"


def stateful_trays(events: DataFrame, drop_kg: float = 1.0, idle: str = "1 day") -> DataFrame:
    """Closed trays per cart, from a stream: a tray closes when the load falls by more than ``drop_kg`` or the cart stays silent.

    State per cart is one open tray (a few numbers), however long the stream. Samples of
    one batch are taken in order of time; samples behind the watermark are dropped by Spark and
    belong to the batch re-run of their day.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def run(key, batches, state: GroupState):
        import pandas as pd

        closed = []
        tray = list(state.get) if state.exists else None
        if state.hasTimedOut:
            if tray:
                closed.append((key[0], *tray[:5]))
            state.remove()
        else:
            rows = pd.concat(list(batches)).sort_values(["t_us", "src_id"])
            for t, w in zip(rows["t_us"], rows["w"]):
                t, w = int(t), float(w)
                if tray is None:
                    tray = [0, t, t, 0, 0.0, w]
                elif tray[5] - w > drop_kg:
                    closed.append((key[0], *tray[:5]))
                    tray = [tray[0] + 1, t, t, 0, 0.0, w]
                tray[2], tray[3], tray[4], tray[5] = t, tray[3] + 1, tray[4] + w, w
            state.update(tuple(tray))
            until = max(state.getCurrentWatermarkMs(), tray[2] // 1000) + int(pd.Timedelta(idle).total_seconds() * 1000)
            state.setTimeoutTimestamp(until)
        yield pd.DataFrame(closed, columns=["cart_id", "tray_no", "t_first", "t_last", "n", "mass"])

    samples = events.withWatermark("ts", LATENESS).select(
        F.col("user_id").alias("cart_id"), F.unix_micros("ts").alias("t_us"), (0.05 * F.col("value")).alias("w"), F.col("event_id").alias("src_id"), "ts"
    )
    return samples.groupBy("cart_id").applyInPandasWithState(run, CLOSED, _OPEN, "append", GroupStateTimeout.EventTimeTimeout)


def late_days(batch: DataFrame, closed_until_us: int, t: str = "t_us", keys=("field_id", "session")) -> DataFrame:
    """Keys of the days that late samples touch: these days are run again as batches and their partitions overwritten."""
    return batch.where(F.col(t) < closed_until_us).select(*keys).distinct()
