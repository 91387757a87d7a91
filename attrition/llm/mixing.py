"""Mixing sources to target weights: repetition rates, whole copies and one hash-seeded coin.

Sizes are summed per source (with a partial sum in every task, so a source that holds a
third of the rows costs nothing extra); targets share a budget by weight, none above a
multiple of what its source has; a source's rate is target over size. Each document is
emitted floor(rate) times, and once more if a hash of its id falls below the rest.

Source null is a source of its own, ranked last. A null or empty text has size 0. Rows that
repeat an id repeat its coin. A source whose size is 0 has target 0 and rate 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import saved, spare


def word_count(text: str = "text") -> Column:
    """Maximal runs of characters other than space and 0x09-0x0D; null: 0."""
    return F.coalesce(F.regexp_count(F.col(text), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def coin(key: str, seed: str) -> Column:
    """Uniform in [0, 1) from an id: the first 32 bits of an MD5, the same in any SQL engine."""
    digest = F.md5(F.concat(F.coalesce(F.col(key).cast("string"), F.lit("")), F.lit(f"|{seed}")))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def ranked(sources: DataFrame) -> DataFrame:
    """Adds place, 1 for the first source by code point, null last.

    Sources are dealt out by range, numbered inside each range and moved up by the rows of the ranges before,
    so no task sees them all."""
    dealt = sources.repartitionByRange(F.col("source").isNull(), F.col("source")).withColumn("_range", F.spark_partition_id())
    dealt = saved(dealt)
    before = {r["_range"]: r["n"] for r in dealt.groupBy("_range").agg(F.count("*").alias("n")).collect()}
    offset, total = {}, 0
    for k in sorted(before):
        offset[k], total = total, total + before[k]
    if not offset:
        return dealt.withColumn("place", F.lit(1).cast("long")).drop("_range")  # no rows
    moved = F.create_map(*[F.lit(x) for k, v in offset.items() for x in (k, v)])
    inside = F.row_number().over(Window.partitionBy("_range").orderBy(F.col("source").asc_nulls_last()))
    return dealt.withColumn("place", inside + F.element_at(moved, F.col("_range"))).drop("_range")


def source_targets(sizes: DataFrame, weights: tuple[float, ...], share: float, most: float) -> DataFrame:
    """(source, source_size, target, rate) from (source, source_size).

    Water filling: a level times weight for each source, cut at most times its size. The level is found by
    passes that return three scalars each; a source that is cut stays cut, so passes end."""
    cycle = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (((F.col("place") - 1) % len(weights)) + 1).cast("int"))
    table = saved(ranked(sizes).withColumn("weight", cycle).withColumn("cap", F.col("source_size") * F.lit(float(most))))
    budget = (table.agg(F.sum("source_size")).first()[0] or 0) * share
    level = 0.0
    while True:
        is_cut = F.col("cap") <= F.lit(level) * F.col("weight")
        cut, free, n_cut = table.agg(
            F.coalesce(F.sum(F.when(is_cut, F.col("cap"))), F.lit(0.0)),
            F.coalesce(F.sum(F.when(~is_cut, F.col("weight"))), F.lit(0.0)),
            F.count_if(is_cut),
        ).first()
        higher = (budget - cut) / free if free else level
        if higher <= level * (1 + 1e-12) or not free:
            break
        level = higher
    target = F.least(F.col("cap"), F.lit(level) * F.col("weight"))
    rate = F.when(F.col("source_size") > 0, target / F.col("source_size")).otherwise(F.lit(0.0))
    return table.select("source", "source_size", target.alias("target"), rate.alias("rate"))


def mix(
    docs: DataFrame, weights=(5.0, 2.0, 1.0), share: float = 1.5, most: float = 2.0, seed: str = "mix",
    key: str = "doc_id", text: str = "text", source: str = "source",
) -> DataFrame:
    """(key, source, size, source_size, target, copies): what the mix takes of every row."""
    rows = docs.select(F.col(key), F.col(source).alias("source"), word_count(text).alias("size"))
    sizes = rows.groupBy("source").agg(F.sum("size").alias("source_size"))
    targets = source_targets(sizes, weights, share, most)
    whole = F.floor(F.col("rate"))
    copies = whole + F.when(coin(key, seed) < F.col("rate") - whole, F.lit(1)).otherwise(F.lit(0))
    return with_source(rows, targets).withColumn("copies", copies.cast("long"))


def with_source(rows: DataFrame, targets: DataFrame) -> DataFrame:
    """Rows joined to their source, null to null. Spark sends the few sources to all tasks or, where they are
    many, splits the hot ones."""
    other, = spare(rows, "other_source")
    t = targets.withColumnRenamed("source", other)
    return rows.join(t, F.col("source").eqNullSafe(F.col(other))).drop(other)


def emitted(docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus: each row of docs as often as its rate asks, all columns kept.

    The rate is attached to the row itself, so texts are never joined by id."""
    source, text, key = options.get("source", "source"), options.get("text", "text"), options.get("key", "doc_id")
    own, rate, copies, copy = spare(docs, "own_source", "rate", "copies", "copy")
    rows = docs.select(F.col(source).alias("source"), word_count(text).alias("size"))
    targets = source_targets(
        rows.groupBy("source").agg(F.sum("size").alias("source_size")),
        options.get("weights", (5.0, 2.0, 1.0)), options.get("share", 1.5), options.get("most", 2.0),
    ).select(F.col("source").alias(own), F.col("rate").alias(rate))
    whole = F.floor(F.col(rate))
    times = (whole + F.when(coin(key, options.get("seed", "mix")) < F.col(rate) - whole, 1).otherwise(0)).cast("int")
    joined = docs.join(targets, F.col(source).eqNullSafe(F.col(own))).withColumn(copies, times)
    return joined.where(F.col(copies) > 0).withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(copies)))).select(*docs.columns)
