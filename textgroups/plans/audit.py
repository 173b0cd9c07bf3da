"""Looking at plans."""

from __future__ import annotations

from pyspark.sql import DataFrame


def explain(df: DataFrame, mode: str = "formatted") -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString(mode))


def plan_uses(df: DataFrame, operator: str) -> bool:
    return operator in df._jdf.queryExecution().executedPlan().toString()
