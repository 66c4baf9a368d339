"""Functions for SQL users: comparison limit, NPMI, mapping lookup, and a table function that makes ordered column pairs."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, StringType, StructField, StructType


@udtf(returnType=StructType([StructField(c, StringType()) for c in ("l_header", "r_header", "l", "r")]), useArrow=True)
class ColumnPairs:
    """All ordered pairs of a row's columns, given as parallel arrays of headers and values; nulls are left out."""

    def eval(self, headers: list, values: list) -> Iterator[tuple]:
        cells = [(h, v) for h, v in zip(headers or [], values or []) if v is not None]
        for h, v in cells:
            for g, w in cells:
                if g != h:
                    yield h, g, v, w


@pandas_udf(DoubleType())
def theta_of(l: pd.Series, r: pd.Series) -> float:
    """The functional share of a relation (as a set) of one group: for groups that fit a task; ``fd_ratio`` has no such bound."""
    pairs = pd.DataFrame({"l": l, "r": r}).drop_duplicates()
    return float(pairs["l"].nunique() / len(pairs)) if len(pairs) else 1.0


def register(spark: SparkSession, mapping: DataFrame | None = None) -> None:
    """Temporary SQL functions edit_limit(a, b), npmi(nu, nv, nuv, n), theta_of(l, r), column_pairs_of(headers, values) and, with a
    ``mapping`` (l, r), the table function mapping_lookup(value)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edit_limit(a STRING, b STRING) RETURNS INT RETURN least(length(a) div 5, length(b) div 5, 10)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION npmi(nu DOUBLE, nv DOUBLE, nuv DOUBLE, n DOUBLE) RETURNS DOUBLE RETURN CASE WHEN nuv = 0 THEN -1D WHEN nuv = n THEN 1D ELSE log10(nuv * n / (nu * nv)) / -log10(nuv / n) END")
    spark.udf.register("theta_of", theta_of)
    spark.udtf.register("column_pairs_of", ColumnPairs)
    if mapping is not None:
        mapping.groupBy("l").agg(F.min("r").alias("r")).createOrReplaceTempView("mapping_rows")
        spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mapping_lookup(value STRING) RETURNS TABLE (r STRING) RETURN SELECT r FROM mapping_rows WHERE l = value")
