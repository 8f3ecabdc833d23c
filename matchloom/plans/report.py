"""What a physical plan will do: exchanges, joins, whole-stage spans, pushed filters."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def operators(df: DataFrame) -> Counter:
    """Physical operators and how often they occur."""
    tree = plan_text(df).split("\n\n")[0]
    return Counter(re.findall(r"(?:^|[-+*:| ]+)\*? ?([A-Z][A-Za-z]+)(?= \(|\b)", tree, re.M))


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"(?<!Broadcast)Exchange \(", plan_text(df).split("\n\n")[0]))
