"""Scalar expressions and the UDF surface: each UDF has a built-in twin that plans prefer."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf


def host(url: Column) -> Column:
    return F.regexp_extract(url, r"://([^/]+)", 1)


def bounded(x: Column, low: int, high: int, base: int) -> Column:
    """A capacity from a measure: modulo ``base``, clamped."""
    return F.greatest(F.lit(low), F.least(F.lit(high), F.pmod(F.floor(x), F.lit(base)))).cast("long")


def bounded_udf(low: int, high: int, base: int):
    @pandas_udf("long")
    def run(x: pd.Series) -> pd.Series:
        return (x // 1 % base).clip(low, high).astype("int64")

    return run


def state_label(excess: Column) -> Column:
    return F.when(excess > 0, "overflow").when(excess < 0, "deficit").otherwise("balanced")
