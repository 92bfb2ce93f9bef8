"""Correctness of answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def difference(got: DataFrame, want: DataFrame) -> DataFrame:
    """One row: rows only in one of two bags."""
    want = want.select(*got.columns)
    extra = got.exceptAll(want).agg(F.count("*").alias("extra"))
    return extra.crossJoin(want.exceptAll(got).agg(F.count("*").alias("missing")))
