"""Exploration: what a wide table's columns hold. One pass for each block of columns, so plans stay inside generated code."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 50
NUMBERS = ("tinyint", "smallint", "int", "bigint", "float", "double")


def is_number(kind: str) -> bool:
    return kind in NUMBERS or kind.startswith("decimal")


def _missing(c: str, kind: str):
    return F.col(c).isNull() | F.isnan(c) if kind in ("float", "double") else F.col(c).isNull()


def profile(df: DataFrame, columns: list[str] | None = None, exact: bool = True, block: int = BLOCK) -> DataFrame:
    """(column, kind, n, nulls, zeros, zero_or_null_share, distinct, top_share, low, high, mean, stddev) for each column.

    NaN counts as missing. exact=False counts distinct values by sketches and leaves top_share null, so nothing is
    expanded. Each block is one aggregate of one row, then turned on its side."""
    kinds = dict(df.dtypes)
    out = []
    columns = [c for c in (columns or df.columns)]
    for at in range(0, len(columns), block):
        part = columns[at : at + block]
        aggs = [F.count("*").alias("_n")]
        for c in part:
            number, gone = is_number(kinds[c]), _missing(c, kinds[c])
            value = F.when(~gone, F.col(c))
            real = value.cast("double") if number else F.lit(None).cast("double")
            aggs += [
                F.struct(
                    F.count_if(gone).alias("nulls"), (F.count_if(real == 0) if number else F.lit(0).cast("long")).alias("zeros"),
                    (F.lit(0).cast("long") if exact else F.approx_count_distinct(value)).alias("distinct"),  # the exact number comes with the values
                    F.min(real).alias("low"), F.max(real).alias("high"), F.avg(real).alias("mean"), F.stddev(real).alias("stddev"),
                ).alias(c)
            ]
        row = df.select(*part).agg(*aggs)
        entries = F.array(*[F.struct(F.lit(c).alias("column"), F.lit("number" if is_number(kinds[c]) else "category").alias("kind"), F.col("_n").alias("n"), F.col(f"`{c}`").alias("s")) for c in part])
        out.append(row.select(F.explode(entries).alias("e")).select("e.column", "e.kind", "e.n", "e.s.*"))
    flat = reduce(DataFrame.union, out)
    share = F.try_divide(F.col("nulls") + F.col("zeros"), F.col("n"))
    flat = flat.withColumn("zero_or_null_share", share)
    if exact:
        flat = flat.drop("distinct").join(top_values(df, columns), "column", "left")
    else:
        flat = flat.withColumn("top_share", F.lit(None).cast("double"))
    return flat.select("column", "kind", "n", "nulls", "zeros", "zero_or_null_share", "distinct", "top_share", "low", "high", "mean", "stddev")


def value_counts(df: DataFrame, columns: list[str]) -> dict[str, tuple[int, int, int]]:
    """{column: (rows, missing, known values)}: the few numbers that refining decides by, from one pass over all columns."""
    if not columns:
        return {}
    kinds = dict(df.dtypes)
    known = [F.when(~_missing(c, kinds[c]), F.col(c)).cast("string").alias(c) for c in columns]
    counts = df.select(*known).unpivot([], columns, "column", "value").groupBy("column", "value").agg(F.count("*").alias("c"))
    rows = counts.groupBy("column").agg(F.sum("c").alias("n"), F.coalesce(F.sum(F.when(F.col("value").isNull(), F.col("c"))), F.lit(0)).alias("nulls"), F.count("value").alias("d")).collect()
    found = {r["column"]: (r["n"], r["nulls"], r["d"]) for r in rows}
    return {c: found.get(c, (0, 0, 0)) for c in columns}


def top_values(df: DataFrame, columns: list[str]) -> DataFrame:
    """(column, top_share, distinct): share of the commonest known value among all rows, and how many known values there are.
    Values are summed in each task first; no row is repeated for each of many distinct counts."""
    kinds = dict(df.dtypes)
    known = [F.when(~_missing(c, kinds[c]), F.col(c)).cast("string").alias(c) for c in columns]
    long = df.select(*known).unpivot([], columns, "column", "value")
    counts = long.groupBy("column", "value").agg(F.count("*").alias("c"))
    return counts.groupBy("column").agg((F.coalesce(F.max(F.when(F.col("value").isNotNull(), F.col("c"))), F.lit(0)) / F.sum("c")).alias("top_share"), F.count("value").alias("distinct"))


def profile_summary(p: DataFrame) -> DataFrame:
    """(measure, share): of columns with few values, one value, mostly zeros or nulls, mostly missing."""
    number, category = F.col("kind") == "number", F.col("kind") == "category"
    share = lambda among, what: F.try_divide(F.count_if(among & what), F.count_if(among))
    measures = {
        "numbers with one or two values": share(number, F.col("distinct") <= 2),
        "categories with fewer than ten values": share(category, F.col("distinct") < 10),
        "numbers with one value": share(number, F.col("distinct") <= 1),
        "categories with one value": share(category, F.col("distinct") <= 1),
        "numbers over 97% zero or null": share(number, F.col("zero_or_null_share") > 0.97),
        "columns over 98% missing": share(F.lit(True), F.try_divide(F.col("nulls"), F.col("n")) > 0.98),
    }
    row = p.agg(*[v.alias(k) for k, v in measures.items()])
    return row.unpivot([], list(measures), "measure", "share")


def class_share(df: DataFrame, label: str = "label") -> DataFrame:
    """(label, rows, share, unbalanced): unbalanced where the smallest class is at most a tenth of the largest."""
    counts = df.groupBy(label).agg(F.count("*").alias("rows"))
    whole = counts.agg(F.sum("rows").alias("_all"), F.min("rows").alias("_least"), F.max("rows").alias("_most"))
    return counts.crossJoin(F.broadcast(whole)).select(label, "rows", (F.col("rows") / F.col("_all")).alias("share"), (F.col("_least") / F.col("_most") <= 0.1).alias("unbalanced"))


def all_null_columns(df: DataFrame) -> DataFrame:
    """(column) of those without any value."""
    row = df.agg(*[F.count(c).alias(c) for c in df.columns])
    return row.unpivot([], df.columns, "column", "known").where("known = 0").select("column")


def class_categories(df: DataFrame, column: str, label: str = "label") -> DataFrame:
    """(label, value, rows, share): the distribution of a category in each class."""
    counts = df.groupBy(label, F.col(column).alias("value")).agg(F.count("*").alias("rows"))
    whole = df.groupBy(label).agg(F.count("*").alias("_all"))
    return counts.join(F.broadcast(whole), label).select(label, "value", "rows", (F.col("rows") / F.col("_all")).alias("share"))


def class_histogram(df: DataFrame, column: str, label: str = "label", bins: int = 10) -> DataFrame:
    """(label, bin, rows): the distribution of a number in each class over even bins of its range; nulls are bin -1."""
    ends = df.agg(F.min(column).cast("double").alias("_lo"), F.max(column).cast("double").alias("_hi"))
    place = F.floor(F.try_divide(F.col(column) - F.col("_lo"), F.col("_hi") - F.col("_lo")) * bins)
    number = F.when(F.col(column).isNull(), -1).otherwise(F.least(F.coalesce(place, F.lit(0)), F.lit(bins - 1))).cast("int")
    return df.crossJoin(F.broadcast(ends)).groupBy(label, number.alias("bin")).agg(F.count("*").alias("rows"))
