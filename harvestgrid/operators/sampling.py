"""Reproducible samples: a row is in or out by a digest of its key, whatever the partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def key_share(*keys: str) -> Column:
    """A number in [0, 1) from the first eight hex digits of an md5 of the keys."""
    text = F.concat_ws("|", *[F.coalesce(F.col(k).cast("string"), F.lit("")) for k in keys])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))


def sample_keys(df: DataFrame, share: float, *keys: str) -> DataFrame:
    """All rows of about ``share`` of the keys: traces of whole cart-days stay unbroken. A filter, no shuffle."""
    return df.where(key_share(*keys) < share)


def sample_per_group(df: DataFrame, n: int, by, *keys: str) -> DataFrame:
    """``n`` rows of each group (all, if fewer), those of smallest digest; ties by the keys. Each task drops what can't be among them before the shuffle."""
    w = Window.partitionBy(*by).orderBy("_share", *keys)
    return df.withColumn("_share", key_share(*keys)).withColumn("_rank", F.row_number().over(w)).where(F.col("_rank") <= n).drop("_share", "_rank")
