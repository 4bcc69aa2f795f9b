"""What a plan does: counts of its nodes, and checks that tests assert."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    """The physical plan, formatted."""
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def nodes(df: DataFrame) -> Counter:
    plan = text(df).split("\n\n")[0]
    return Counter(m[1] for m in re.finditer(r"^[\s:|+*\-]*(?:\* )?([A-Z]\w+)[^\n]*\(\d+\)\s*$", plan, re.M))


def exchanges(df: DataFrame) -> int:
    return nodes(df)["Exchange"]


def has_pair_join(df: DataFrame) -> bool:
    """Whether some join compares all pairs of two tables that aren't one-row results."""
    found = nodes(df)
    return bool(found["CartesianProduct"] or found["BroadcastNestedLoopJoin"])


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[(.*?)\]", text(df))


def read_schemas(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<(.*?)>\s*$", text(df), re.M)
