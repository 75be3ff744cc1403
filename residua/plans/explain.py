"""Plan checks used in tests: what a plan must and must not hold."""

from __future__ import annotations

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    """The physical plan as a tree, a line for each operator, as planned before the run."""
    return df._jdf.queryExecution().sparkPlan().toString()


def plan_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def has_python(df: DataFrame) -> bool:
    return any(k in plan_of(df) for k in ("Python", "Pandas", "MapInArrow"))


def has_product(df: DataFrame) -> bool:
    return "CartesianProduct" in plan_of(df)
