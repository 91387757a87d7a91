"""Labels and populations: who is idle after the baseline, who is too new to tell."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import draw
from ..functions.periods import BASELINE, at, months_before


def population(subscribers: DataFrame, segment: str | None = None) -> DataFrame:
    return subscribers if segment is None else subscribers.where(F.col("segment") == segment)


def idle_label(activity: DataFrame, people: DataFrame, baseline: str, horizon: int, gap: int = 0) -> DataFrame:
    """(sub_id, label): 1 for those without activity in the `horizon` months that start `gap` months after the baseline.

    activity: (sub_id, ts). One filtered scan, a partial maximum, one left join."""
    start, end = months_before(baseline, -gap), months_before(baseline, -gap - horizon)
    seen = activity.where((F.col("ts") >= at(start)) & (F.col("ts") < at(end))).groupBy("sub_id").agg(F.lit(1).alias("seen"))
    return people.select("sub_id").join(seen, "sub_id", "left").select("sub_id", F.when(F.col("seen").isNull(), 1).otherwise(0).alias("label"))


def exclude_new(people: DataFrame, contact: DataFrame, baseline: str = BASELINE, months: int = 4) -> DataFrame:
    """people without those whose first outgoing record before the baseline falls in its last months."""
    first = contact.where(F.col("ts") < at(baseline)).groupBy(F.col("src").alias("sub_id")).agg(F.min("ts").alias("first"))
    new = first.where(F.col("first") >= at(months_before(baseline, months))).select("sub_id")
    return people.join(new, "sub_id", "left_anti")


def planted_label(features: DataFrame, share: float = 0.05) -> DataFrame:
    """Adds label: a declared synthetic rule over home numbers, for comparing learners and feature families only.

    features: (sub_id, idle_days, balance, out_rival_share, max_cos_rival). Percent ranks come from approximate
    quantiles of 1000 steps, so no task sees all rows."""
    filled = features.na.fill({"idle_days": 9999, "out_rival_share": 0.0, "max_cos_rival": 0.0})
    names = ["idle_days", "balance", "out_rival_share", "max_cos_rival"]
    steps = [i / 1000 for i in range(1, 1000)]
    cuts = filled.agg(*[F.percentile_approx(F.col(c).cast("double"), steps, 10000).alias(c) for c in names]).first()
    rank = lambda c: F.size(F.filter(F.array(*[F.lit(float(x)) for x in sorted(set(cuts[c]))]), lambda x: x < F.col(c))) / float(max(1, len(set(cuts[c]))))
    score = 1.6 * rank("idle_days") - 1.4 * rank("balance") + 0.8 * rank("out_rival_share") + 1.2 * rank("max_cos_rival") + 1.2 * draw(F.col("sub_id"), "noise")
    scored = filled.withColumn("_score", score)
    cut = scored.agg(F.percentile_approx("_score", 1 - share, 10000)).first()[0]
    return scored.withColumn("label", (F.col("_score") > F.lit(cut)).cast("int")).drop("_score")
