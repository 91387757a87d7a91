"""Splits, folds and balancing: by hash of the id, so any engine repeats them, and without moving rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import draw


#: Cells of the range of draws in which rows are counted.
CELLS = 65_536


def split(df: DataFrame, share: float = 0.7, key: str = "sub_id", seed: str = "split") -> DataFrame:
    """Adds part: "train" or "test"."""
    return df.withColumn("part", F.when(draw(F.col(key), seed) < share, "train").otherwise("test"))


def folds(df: DataFrame, k: int = 10, key: str = "sub_id", seed: str = "fold") -> DataFrame:
    return df.withColumn("fold", F.floor(draw(F.col(key), seed) * k).cast("int"))


def _counted(df: DataFrame, label: str) -> DataFrame:
    sizes = df.groupBy(label).agg(F.count("*").alias("_n"))  # one row a class
    most = sizes.agg(F.max("_n").alias("_most"), F.min("_n").alias("_least"))
    return df.join(F.broadcast(sizes.crossJoin(most)), label)


def _least(rows: DataFrame, label: str, key: str, seed: str, wanted, out: str) -> DataFrame:
    """rows with a boolean column `out`: whether a row is among its class's `wanted` ones of least draw, ties by key.

    Draws are counted by class and cell of their range; only the rows of the cell where a class's number is reached are
    put in order, a few in a million, so no task sees a class."""
    spread = rows.withColumn("_draw", draw(F.col(key), seed)).withColumn("_cell", F.floor(F.col("_draw") * CELLS).cast("int"))
    cells = spread.groupBy(label, "_cell").agg(F.count("*").alias("_c"), F.max(wanted).alias("_wanted"))
    upto = Window.partitionBy(label).orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)  # CELLS rows a class at most
    edge = cells.withColumn("_before", F.coalesce(F.sum("_c").over(upto), F.lit(0))).where("_before < _wanted AND _before + _c >= _wanted")
    met = spread.join(F.broadcast(edge.select(F.col(label).alias("_of"), F.col("_cell").alias("_edge"), (F.col("_wanted") - F.col("_before")).alias("_left"))), F.col(label) == F.col("_of"), "left")
    at_edge = F.col("_cell") == F.col("_edge")
    place = F.row_number().over(Window.partitionBy(label, "_cell").orderBy("_draw", key))
    inside = met.where(at_edge).withColumn("_in", place <= F.col("_left"))
    sure = met.where(~F.coalesce(at_edge, F.lit(False))).withColumn("_in", F.coalesce(F.col("_cell") < F.col("_edge"), wanted > 0))
    return sure.union(inside).withColumn(out, F.col("_in")).select(*rows.columns, out)


def oversample(df: DataFrame, label: str = "label", key: str = "sub_id", seed: str = "over", exact: bool = True) -> DataFrame:
    """df with rows of smaller classes repeated until classes are even; copy numbers the repeats.

    exact makes classes even to the row; otherwise the remainder is drawn by hash, without another pass."""
    rows = _counted(df, label)
    whole = F.floor(F.col("_most") / F.col("_n"))
    if exact:
        rows = _least(rows, label, key, seed, F.col("_most") % F.col("_n"), "_more").withColumn("_extra", F.col("_more").cast("int"))
    else:
        rows = rows.withColumn("_extra", (draw(F.col(key), seed) < F.col("_most") / F.col("_n") - whole).cast("int"))
    copies = F.when(F.col("_n") == F.col("_most"), F.lit(1)).otherwise((whole + F.col("_extra")).cast("int"))
    return rows.where(copies > 0).withColumn("copy", F.explode(F.sequence(F.lit(1), copies))).select(*df.columns, "copy")


def undersample(df: DataFrame, label: str = "label", key: str = "sub_id", seed: str = "under", exact: bool = True) -> DataFrame:
    """df with larger classes cut to the size of the smallest; by hash threshold where exact is false."""
    rows = _counted(df, label)
    if exact:
        return _least(rows, label, key, seed, F.col("_least"), "_taken").where("_taken").select(*df.columns)
    return rows.where(draw(F.col(key), seed) < F.col("_least") / F.col("_n")).select(*df.columns)


def weighted(df: DataFrame, label: str = "label") -> DataFrame:
    """Adds weight: classes weigh the same in total."""
    return _counted(df, label).withColumn("weight", F.col("_most") / F.col("_n")).select(*df.columns, "weight")


def balance_report(df: DataFrame, label: str = "label") -> DataFrame:
    return df.groupBy(label).agg(F.count("*").alias("rows"))


BALANCINGS = {"none": lambda df: df, "oversample": lambda df: oversample(df, exact=False).drop("copy"), "undersample": lambda df: undersample(df, exact=False)}
