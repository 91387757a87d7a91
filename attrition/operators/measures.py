"""Accuracy and business measures of scored rows: (label, score).

Everything starts from counts by distinct score (or by score bins for very many rows); running
sums over them go range by range.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scratch import kept


def by_score(scored: DataFrame, bins: int | None = None) -> DataFrame:
    score = F.col("score") if bins is None else F.floor(F.col("score") * bins) / bins
    return scored.groupBy(score.alias("score")).agg(F.sum("label").alias("pos"), F.sum(1 - F.col("label")).alias("neg"))


def running(counts: DataFrame, order: str, *columns: str, falling: bool = False) -> DataFrame:
    """counts with, for each column c, `_c`: its sum over all rows before this one in the order, this one left out.

    Rows are dealt out by ranges of the order, summed inside each range, and moved on by the sums of the ranges before:
    one row a range, so no task sees all rows."""
    by = F.col(order).desc() if falling else F.col(order)
    ranged = kept(counts.repartitionByRange(by).withColumn("_range", F.spark_partition_id()), "ranged")
    whole = ranged.groupBy("_range").agg(*[F.sum(c).alias(f"_{c}") for c in columns])
    ahead = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    moved = whole.select("_range", *[F.coalesce(F.sum(f"_{c}").over(ahead), F.lit(0)).alias(f"_{c}") for c in columns])
    inside = Window.partitionBy("_range").orderBy(by).rowsBetween(Window.unboundedPreceding, -1)
    met = ranged.join(F.broadcast(moved), "_range")
    return met.select(*counts.columns, *[(F.col(f"_{c}") + F.coalesce(F.sum(c).over(inside), F.lit(0))).alias(f"_{c}") for c in columns])


def auc(scored: DataFrame, bins: int | None = None) -> DataFrame:
    """(auc): chance that a positive scores above a negative, ties half. bins: scores are rounded down to so many steps."""
    wins = running(by_score(scored, bins), "score", "neg").withColumn("_w", F.col("pos") * (F.col("_neg") + F.col("neg") / 2))
    return wins.agg(F.try_divide(F.sum("_w"), F.sum("pos").cast("double") * F.sum("neg")).alias("auc"))


def auc_value(scored: DataFrame, bins: int | None = None) -> float:
    """The number of `auc`; with bins, from the counts by bin on the driver: bins + 1 rows of 24 bytes at most."""
    if bins is None:
        return float(auc(scored).first()[0] or 0.5)
    counts = by_score(scored, bins).toArrow()
    score, pos, neg = (counts[c].combine_chunks() for c in ("score", "pos", "neg"))
    order = np.argsort(score.fill_null(-math.inf).to_numpy(zero_copy_only=False), kind="stable")
    pos, neg = (c.fill_null(0).to_numpy(zero_copy_only=False).astype(float)[order] for c in (pos, neg))
    pairs = pos.sum() * neg.sum()
    return float((pos * (np.cumsum(neg) - neg / 2)).sum() / pairs) or 0.5 if pairs else 0.5


def roc(scored: DataFrame, bins: int | None = None) -> DataFrame:
    """(cut, tpr, fpr): one point for each distinct score, and the origin (cut null)."""
    counts = by_score(scored, bins)
    whole = counts.agg(F.sum("pos").alias("_p"), F.sum("neg").alias("_n"))
    points = running(counts, "score", "pos", "neg", falling=True).crossJoin(F.broadcast(whole)).select(
        F.col("score").alias("cut"), F.try_divide(F.col("_pos") + F.col("pos"), F.col("_p")).alias("tpr"), F.try_divide(F.col("_neg") + F.col("neg"), F.col("_n")).alias("fpr")
    )
    return points.union(whole.select(F.lit(None).cast("double"), F.lit(0.0), F.lit(0.0)))


def confusion(scored: DataFrame, cut: float = 0.5) -> DataFrame:
    """(tp, fp, fn, tn, precision, recall) at a cut."""
    yes, pos = F.col("score") >= cut, F.col("label") == 1
    c = scored.agg(F.count_if(yes & pos).alias("tp"), F.count_if(yes & ~pos).alias("fp"), F.count_if(~yes & pos).alias("fn"), F.count_if(~yes & ~pos).alias("tn"))
    return c.withColumns({"precision": F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")), "recall": F.try_divide(F.col("tp"), F.col("tp") + F.col("fn"))})


def top_lift(scored: DataFrame, k: int, key: str = "sub_id") -> DataFrame:
    """(k, positives, share, lift) among the k best scores; ties by key."""
    best = scored.orderBy(F.desc("score"), key).limit(k).agg(F.sum("label").alias("positives"), F.avg("label").alias("share"))
    return best.crossJoin(F.broadcast(scored.agg(F.avg("label").alias("_base")))).select(F.lit(k).alias("k"), "positives", "share", F.try_divide(F.col("share"), F.col("_base")).alias("lift"))


def stability_index(old: DataFrame, new: DataFrame, column: str, bins: int = 10) -> DataFrame:
    """(column, psi): drift of a number between two populations, over even bins of the old one's range."""
    ends = old.agg(F.min(column).cast("double").alias("_lo"), F.max(column).cast("double").alias("_hi"))
    place = F.floor(F.try_divide(F.col(column) - F.col("_lo"), F.col("_hi") - F.col("_lo")) * bins)
    number = F.greatest(F.lit(0), F.least(F.coalesce(place, F.lit(0)), F.lit(bins - 1)))
    both = old.select(column, F.lit(0).alias("which")).union(new.select(column, F.lit(1))).crossJoin(F.broadcast(ends))
    counts = both.groupBy(number.alias("bin")).agg(F.count_if(F.col("which") == 0).alias("a"), F.count_if(F.col("which") == 1).alias("b"))
    whole = counts.agg(F.sum("a").alias("_a"), F.sum("b").alias("_b"))
    # half a row is added to each bin, so that an empty one has a finite logarithm
    share = lambda x: (F.col(x) + 0.5) / (F.col(f"_{x}") + 0.5 * bins)
    return counts.crossJoin(F.broadcast(whole)).agg(F.sum((share("a") - share("b")) * F.ln(share("a") / share("b"))).alias("psi")).select(F.lit(column).alias("column"), "psi")


def campaign_outcome(scored: DataFrame, offered: DataFrame, outcome: DataFrame, cut: float = 0.5, key: str = "sub_id") -> DataFrame:
    """(offered, predicted, n_left, retained_share) of those predicted to leave, and in `change` how far the share that left
    differs from that of those who got no offer. offered: (key); outcome: (key, left 0/1)."""
    rows = scored.where(F.col("score") >= cut).select(key).join(outcome, key).join(offered.select(key, F.lit(True).alias("_o")), key, "left")
    groups = rows.groupBy(F.coalesce("_o", F.lit(False)).alias("offered")).agg(F.count("*").alias("predicted"), F.sum("left").alias("n_left"), (1 - F.avg("left")).alias("retained_share"))
    base = groups.where("NOT offered").agg(F.max(1 - F.col("retained_share")).alias("_base"))
    return groups.crossJoin(F.broadcast(base)).select("offered", "predicted", "n_left", "retained_share", (F.col("_base") - (1 - F.col("retained_share"))).alias("change"))


def campaign_value(outcome: DataFrame, unit_cost: float = 1.0, ratio: float = 6.0) -> DataFrame:
    """Adds saved: keeping a customer costs unit_cost an offer, winning a new one ratio times as much."""
    kept = F.col("predicted") - F.col("n_left")
    return outcome.withColumn("saved", F.when(F.col("offered"), kept * ratio * unit_cost - F.col("predicted") * unit_cost).otherwise(F.lit(0.0)))


def internet_churners(labelled: DataFrame, session: DataFrame, low: float = 2.5, key: str = "sub_id") -> DataFrame:
    """(churners, internet_share, low_share): of those who left, who used the internet; of these, whose radio level is low."""
    code = F.when(F.col("rat") == "2G", 2.0).when(F.col("rat") == "3G", 3.0)
    level = session.groupBy(key).agg(F.avg(code).alias("level"), F.count_if(F.col("bytes_down") + F.col("bytes_up") > 0).alias("n"))
    rows = labelled.where("label = 1").join(level, key, "left")
    used = F.coalesce(F.col("n") > 0, F.lit(False))
    return rows.agg(F.count("*").alias("churners"), F.avg(used.cast("double")).alias("internet_share"), F.avg(F.when(used, (F.col("level") < low).cast("double"))).alias("low_share"))


def needs_retrain(psi: float, auc_before: float, auc_now: float, drift: float = 0.2, loss: float = 0.03) -> bool:
    """Whether drift or the loss of accuracy passed its limit."""
    return psi > drift or auc_before - auc_now > loss


def importance_shift(parts: dict[str, DataFrame]) -> DataFrame:
    """(feature, one place for each named importance table (feature, gain)): how ranks move when families merge."""
    out = None
    for name, table in parts.items():
        ranked = table.select("feature", F.row_number().over(Window.orderBy(F.desc("gain"), "feature")).alias(name))  # one row a feature
        out = ranked if out is None else out.join(ranked, "feature", "full")
    return out


def lift_table(results: DataFrame) -> DataFrame:
    """(learner, one AUC for each family, gain of both over usage) from (learner, family, auc)."""
    wide = results.groupBy("learner").pivot("family", ["usage", "graph", "both"]).agg(F.max("auc"))
    return wide.withColumn("gain", F.col("both") - F.col("usage"))
