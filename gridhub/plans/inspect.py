"""What a plan does, read from its text: exchanges, joins, Python nodes, pushed filters."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

#: Plan nodes that no operator on points may have.
FORBIDDEN = ("BroadcastNestedLoopJoin", "CartesianProduct")
PYTHON = ("PythonUDF", "ArrowEvalPython", "BatchEvalPython", "MapInArrow", "MapInPandas", "FlatMapGroupsInArrow", "FlatMapGroupsInPandas")


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def nodes(df: DataFrame) -> list[str]:
    """Physical operators in the order of the plan's tree."""
    tree = plan_text(df).split("\n\n\n")[0]
    return re.findall(r"([A-Z]\w+)(?: \w+)* \(\d+\)", tree)


def exchanges(df: DataFrame) -> int:
    return sum(n == "Exchange" for n in nodes(df))


def has_python(df: DataFrame) -> bool:
    text = plan_text(df)
    return any(p in text for p in PYTHON)


def has_pair_join(df: DataFrame) -> bool:
    text = plan_text(df)
    return any(f in text for f in FORBIDDEN)


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\n]*)\]", plan_text(df))


def read_columns(df: DataFrame) -> list[set[str]]:
    """Columns that each scan reads."""
    return [set(re.findall(r"(\w+):", s)) for s in re.findall(r"ReadSchema: struct<([^\n]*)>", plan_text(df))]
