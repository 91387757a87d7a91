"""SQL functions of the methods, table functions and vectorised functions, for use from SQL text."""


import pandas as pd

from pyspark.sql import SparkSession

BODIES = (
    "CREATE OR REPLACE TEMPORARY FUNCTION friend_jaccard(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE RETURN try_divide(size(array_intersect(a, b)), size(array_union(a, b)))",
    "CREATE OR REPLACE TEMPORARY FUNCTION friend_cosine(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE RETURN try_divide(size(array_intersect(a, b)), sqrt(CAST(size(array_distinct(a)) AS DOUBLE) * size(array_distinct(b))))",
    "CREATE OR REPLACE TEMPORARY FUNCTION months_back(ts TIMESTAMP_NTZ, base DATE) RETURNS INT RETURN year(base) * 12 + month(base) - year(ts) * 12 - month(ts)",
)


def register(spark: SparkSession) -> None:
    """friend_jaccard, friend_cosine and months_back inline into plans; period_keys is a table function; rank_auc an aggregate."""
    from pyspark.sql.functions import pandas_udf, udtf

    for body in BODIES:
        spark.sql(body)

    @udtf(returnType="unit STRING, period INT")
    class PeriodKeys:
        """The day, week and month periods of a number of days before the baseline."""

        def eval(self, days: int):
            if days is not None and days >= 1:
                for unit, length in (("day", 1), ("week", 7), ("month", 30)):
                    yield unit, (days - 1) // length + 1

    spark.udtf.register("period_keys", PeriodKeys)

    @pandas_udf("double")
    def rank_auc(label: pd.Series, score: pd.Series) -> float:  # a reference for tests: one group in one task
        n1, n0 = int((label == 1).sum()), int((label == 0).sum())
        if not n1 or not n0:
            return float("nan")
        return float((score.rank()[label == 1].sum() - n1 * (n1 + 1) / 2) / (n1 * n0))

    spark.udf.register("rank_auc", rank_auc)
