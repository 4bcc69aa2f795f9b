"""The given tables in the canonical shapes (trace, segments, yield points, truth pairs)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import table

SPACING = (1.63, 1.22)


def micros(ts):
    """Microseconds of a zone-less timestamp, independent of the session's time zone."""
    return F.datediff(F.to_date(ts), F.lit("1970-01-01")).cast("long") * 86_400_000_000 + _of_day(ts)


def _of_day(ts):
    second = F.hour(ts) * 3600 + F.minute(ts) * 60
    return second.cast("long") * 1_000_000 + F.round(F.date_format(ts, "ss.SSSSSS").cast("decimal(18,6)") * 1_000_000).cast("long")


def trace_from_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cart samples: one user is a cart, its parity the field, ten days a session."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    field = (F.col("user_id") % 2).cast("int")
    spacing = F.when(field == 0, SPACING[0]).otherwise(SPACING[1])
    wobble = (((37 * F.col("event_id")) % 101 - 50).cast("double") / 100.0) * 1.2 * spacing
    shake = lambda k: (((k * F.col("event_id")) % 41 - 20).cast("double")) / 10.0
    kind = F.col("event_type")
    state = F.when(kind.isin("view", "click"), "picking").when(kind == "purchase", "transport").when(kind == "signup", "setup").otherwise("idle")
    return e.select(
        field.alias("field_id"), ((F.dayofmonth("ts") - 1) / 10).cast("int").alias("session"), F.col("user_id").alias("cart_id"), micros(F.col("ts")).alias("t_us"),
        (((7 * F.col("user_id")) % 40).cast("double") * spacing + wobble).alias("x"), (0.5 * F.get_json_object("props", "$.k").cast("double")).alias("y"),
        (0.05 * F.col("value")).alias("w"), shake(13).alias("ax"), shake(17).alias("ay"), shake(19).alias("az"), state.alias("state"), F.col("event_id").alias("src_id"), spacing.alias("spacing"),
        ((7 * F.col("user_id")) % 40).cast("int").alias("row_base"), kind.alias("event_type"),
    )


def suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """cart -> field, site, region: small dimension tables, joined once."""
    s, n, r = (table(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
    return s.join(n, s.s_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).select(F.col("s_suppkey").alias("cart_id"), F.col("s_nationkey").alias("field_id"), "n_name", "r_name")


def yield_from_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Yield points: each line is some mass of a tray (order) at a place of a row."""
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    part = F.col("l_partkey")
    points = li.select(
        F.col("l_suppkey").alias("cart_id"), F.to_date("l_shipdate").alias("day"), (part % 50).cast("int").alias("row_idx"),
        ((F.floor(part / 50).cast("long") % 40).cast("double") * 0.3048).alias("y_int"), (0.1 * F.col("l_quantity")).alias("dmass"),
        F.col("l_orderkey").alias("tray_id"), F.col("l_linenumber").alias("segment"), part.alias("part_id"), F.col("l_quantity").alias("quantity"), "l_returnflag",
    )
    return points.join(suppliers(spark, sf_dir), "cart_id").withColumn("row_x", (F.col("row_idx") + 0.5) * SPACING[0])


def traces_from_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Traces at volume: seven neighbouring rows per cart, three of them shared with each neighbour."""
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    day = F.datediff(F.to_date("l_shipdate"), F.lit("1970-01-01")).cast("long")
    t = day * 86400 + (7 * F.col("l_orderkey") + F.col("l_linenumber")) % 86400
    return li.select(
        F.col("l_suppkey").alias("cart_id"), (F.year("l_shipdate") * 4 + F.quarter("l_shipdate")).alias("session"), F.year("l_shipdate").alias("year"),
        (4 * F.col("l_suppkey") + F.col("l_linenumber")).cast("int").alias("row_idx"), (0.5 * (F.col("l_partkey") % 100)).cast("double").alias("y"),
        (0.1 * F.col("l_quantity")).alias("m"), t.alias("t"), F.col("l_orderkey").alias("ok"), F.col("l_linenumber").alias("ln"), F.col("l_partkey").alias("pk"), F.col("l_quantity").alias("quantity"),
    )


#: Order of samples with equal times.
ORDER = ("t", "ok", "ln", "pk")


def count_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tray counts per cart and month: true, and estimated from mass."""
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    month = F.trunc(F.to_date("l_shipdate"), "month")
    return li.groupBy(F.col("l_suppkey").alias("cart_id"), month.alias("month")).agg(F.count(F.lit(1)).cast("double").alias("gt"), (F.sum("l_quantity") / 25.5).alias("est"))


def segment_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Masses per tray and row segment: true, and estimated."""
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    est = F.col("l_quantity") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))
    return li.groupBy(F.col("l_orderkey").alias("tray_id"), F.col("l_linenumber").alias("segment")).agg(F.sum("l_quantity").alias("gt"), F.sum(est).alias("est"))
