"""Assertions on plans: what a plan of this engine must not hold."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def plan_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def python_nodes(df: DataFrame) -> list[str]:
    return sorted(set(re.findall(r"\b(\w*(?:EvalPython|InPandas|InArrow|PythonUDTF)\w*)", plan_of(df))))


def read_schemas(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: (\S+)", plan_of(df))


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[(.*?)\]", plan_of(df))


def has_cartesian(df: DataFrame) -> bool:
    return "CartesianProduct" in plan_of(df)


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"^\(\d+\) Exchange\b", plan_of(df), re.M))


def single_partition_windows(df: DataFrame) -> int:
    """Windows whose rows were all sent to one task."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return len(re.findall(r"Window [^\n]*\n[^\n]*Sort[^\n]*\n[^\n]*Exchange SinglePartition", text))
