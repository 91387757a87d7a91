"""The directed, weighted contact graph: arcs, their three weightings, nodes and sizes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.periods import BASELINE, before, in_last

KINDS = ("call", "sms", "mms")


def build_arcs(contact: DataFrame, baseline: str = BASELINE, months: int | None = 4, kinds: tuple[str, ...] = KINDS) -> DataFrame:
    """(src, dst, n_events, talk): every two numbers' interactions of the window in one directed arc. One shuffle, with a
    partial sum before it."""
    window = before(F.col("ts"), baseline) if months is None else in_last(F.col("ts"), baseline, months)
    rows = contact.where(window & F.col("kind").isin(*kinds))
    return rows.groupBy("src", "dst").agg(F.count("*").alias("n_events"), F.sum("duration").alias("talk"))


def _normalised(value: str, norm: str) -> Column:
    by = {"source_share": Window.partitionBy("src"), "target_share": Window.partitionBy("dst")}.get(norm)
    if by is not None:
        return F.coalesce(F.try_divide(F.col(value), F.sum(value).over(by)), F.lit(0.0))
    return F.coalesce(F.try_divide(F.col(value), F.col(f"_{value}")), F.lit(0.0))


def weigh(arcs: DataFrame, norm: str = "graph_max") -> DataFrame:
    """Adds w_time, w_count and their mean w_mean.

    norm: "graph_max", "graph_total" (one scalar row goes to all tasks), "source_share" or "target_share"."""
    if norm.startswith("graph"):
        total = F.max if norm == "graph_max" else F.sum
        scale = arcs.agg(total("talk").alias("_talk"), total(F.col("n_events").cast("double")).alias("_n_events"))
        arcs = arcs.crossJoin(F.broadcast(scale))  # one row
    out = arcs.withColumns({"w_time": _normalised("talk", norm), "w_count": _normalised("n_events", norm)})
    return out.withColumn("w_mean", (F.col("w_time") + F.col("w_count")) / 2).drop("_talk", "_n_events")


def build_nodes(arcs: DataFrame, subscribers: DataFrame | None = None) -> DataFrame:
    """(id, operator) of all numbers that send or receive; operator null where the number is unknown."""
    ids = arcs.select(F.col("src").alias("id")).union(arcs.select(F.col("dst").alias("id"))).distinct()
    if subscribers is None:
        return ids
    return ids.join(subscribers.select(F.col("sub_id").alias("id"), "operator"), "id", "left")


def graph_size(arcs: DataFrame) -> DataFrame:
    nodes = build_nodes(arcs).agg(F.count("*").alias("nodes"))
    return nodes.crossJoin(arcs.agg(F.count("*").alias("arcs")))  # one row by one row


def ego_sample(arcs: DataFrame, nodes: DataFrame, centre: int, hops: int = 1) -> DataFrame:
    """Arcs within `hops` of a number, with both ends' operators, for viewing."""
    near = nodes.where(F.col("id") == centre).select("id")
    for _ in range(hops):
        out = arcs.join(near, F.col("src") == F.col("id"), "left_semi").select(F.col("dst").alias("id"))
        back = arcs.join(near, F.col("dst") == F.col("id"), "left_semi").select(F.col("src").alias("id"))
        near = near.union(out).union(back).distinct()
    kept = arcs.join(near, F.col("src") == F.col("id"), "left_semi").join(near, F.col("dst") == F.col("id"), "left_semi")
    ends = lambda side: nodes.select(F.col("id").alias(side), F.col("operator").alias(f"{side}_operator"))
    return kept.select("src", "dst", "n_events").join(ends("src"), "src", "left").join(ends("dst"), "dst", "left").select("src", "src_operator", "dst", "dst_operator", "n_events")
