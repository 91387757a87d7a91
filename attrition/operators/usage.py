"""Statistical usage features. Rows at or after the baseline never contribute; ratios over nothing are null."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.periods import BASELINE, EVENT_BASELINE, before, days_back, in_last, period_index


def share_of(condition: Column) -> Column:
    """Share of rows where a condition holds; null conditions count as false."""
    return F.avg(F.when(condition, 1.0).otherwise(0.0))


def period_rollup(contact: DataFrame, unit: str, baseline: str = BASELINE, months: int = 9) -> DataFrame:
    """(sub_id, period, kind, n, total, mean, low, high) of charges: one scan, one shuffle of partial sums."""
    rows = contact.where(in_last(F.col("ts"), baseline, months)).withColumn("period", period_index(F.col("ts"), baseline, unit))
    return rows.groupBy(F.col("src").alias("sub_id"), "period", "kind").agg(
        F.count("*").alias("n"), F.sum("charge").alias("total"), F.avg("charge").alias("mean"), F.min("charge").alias("low"), F.max("charge").alias("high")
    )


def multi_unit_rollup(contact: DataFrame, units: tuple[str, ...] = ("day", "week", "month"), baseline: str = BASELINE, months: int = 9) -> DataFrame:
    """(sub_id, unit, period, kind, n, total, low, high): raw rows are read once and summed by day; longer units are
    summed from the days."""
    rows = contact.where(in_last(F.col("ts"), baseline, months)).withColumn("day", F.col("ts").cast("date"))
    days = rows.groupBy(F.col("src").alias("sub_id"), "day", "kind").agg(
        F.count("*").alias("n"), F.sum("charge").alias("total"), F.min("charge").alias("low"), F.max("charge").alias("high")
    )
    keys = F.array(*[F.struct(F.lit(u).alias("unit"), period_index(F.col("day").cast("timestamp_ntz"), baseline, u).cast("int").alias("period")) for u in units])
    return days.withColumn("key", F.explode(keys)).groupBy("sub_id", F.col("key.unit").alias("unit"), F.col("key.period").alias("period"), "kind").agg(
        F.sum("n").alias("n"), F.sum("total").alias("total"), F.min("low").alias("low"), F.max("high").alias("high")
    )


def category_counts(contact: DataFrame, exact: bool = True, baseline: str = BASELINE, months: int = 9) -> DataFrame:
    """(sub_id, devices, packages, peers): distinct values; mergeable sketches where exact is false."""
    count = F.count_distinct if exact else F.approx_count_distinct
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    return rows.groupBy(F.col("src").alias("sub_id")).agg(count("device").alias("devices"), count("package").alias("packages"), count("dst").alias("peers"))


def rate_per_month(contact: DataFrame, kind: str = "call", baseline: str = BASELINE, months: int = 6) -> DataFrame:
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    return rows.groupBy(F.col("src").alias("sub_id")).agg((F.count_if(F.col("kind") == kind) / months).alias("rate"))


def traffic_mean(session: DataFrame, baseline: str = EVENT_BASELINE) -> DataFrame:
    """(sub_id, mean_up, mean_down) over sessions that carried anything that way."""
    carried = lambda c: F.avg(F.when(F.col(c) > 0, F.col(c)))
    return session.where(before(F.col("ts"), baseline)).groupBy("sub_id").agg(carried("bytes_up").alias("mean_up"), carried("bytes_down").alias("mean_down"))


def package_count(contact: DataFrame, baseline: str = BASELINE, months: int = 9) -> DataFrame:
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    return rows.groupBy(F.col("src").alias("sub_id")).agg(F.count_distinct("package").alias("packages"))


def rat_share_by_site(session: DataFrame, unit: str = "3 day", baseline: str = EVENT_BASELINE) -> DataFrame:
    """(site, period, rat, share): of each radio type among a site's sessions of a period. The window runs on counts."""
    rows = session.where(before(F.col("ts"), baseline)).withColumn("period", period_index(F.col("ts"), baseline, unit))
    counts = rows.groupBy("site", "period", "rat").agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("site", "period"))).drop("n")


def kind_ratio(contact: DataFrame, over: str = "call", under: str = "sms", baseline: str = BASELINE, months: int = 6) -> DataFrame:
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    return rows.groupBy(F.col("src").alias("sub_id")).agg(F.try_divide(F.count_if(F.col("kind") == over), F.count_if(F.col("kind") == under)).alias("ratio"))


def ticket_features(ticket: DataFrame, baseline: str = EVENT_BASELINE) -> DataFrame:
    """(sub_id, complaints, coverage_share, mean_hours, last_result)."""
    return ticket.where(before(F.col("opened"), baseline)).groupBy("sub_id").agg(
        F.count("*").alias("complaints"), share_of(F.col("coverage")).alias("coverage_share"), F.avg("hours_to_close").alias("mean_hours"),
        F.max_by("result", "opened").alias("last_result"),
    )


def ticket_gap(ticket: DataFrame, baseline: str = EVENT_BASELINE) -> DataFrame:
    """(sub_id, mean_gap_hours) between consecutive complaints; null with one complaint."""
    rows = ticket.where(before(F.col("opened"), baseline))
    ago = F.lag("opened").over(Window.partitionBy("sub_id").orderBy("opened"))
    gap = F.timestamp_diff("MICROSECOND", ago, F.col("opened"))
    return rows.withColumn("gap", gap).groupBy("sub_id").agg((F.avg("gap") / 3.6e9).alias("mean_gap_hours"))


def handset_latest(contact: DataFrame, handset: DataFrame, baseline: str = BASELINE) -> DataFrame:
    """(sub_id, brand, type, dual) of the device last used; ties by the larger device number."""
    last = contact.where(before(F.col("ts"), baseline)).groupBy(F.col("src").alias("sub_id")).agg(F.max_by("device", F.struct("ts", "device")).alias("device"))
    return last.join(handset, "device", "left").select("sub_id", "brand", "type", "dual")


def handset_changes(contact: DataFrame, baseline: str = BASELINE, months: int = 9) -> DataFrame:
    """(sub_id, changes, per_month): times the device differs from the one before, and devices a month of use."""
    rows = contact.where(in_last(F.col("ts"), baseline, months)).select(F.col("src").alias("sub_id"), "ts", "device", "dst", "charge").withColumn("period", period_index(F.col("ts"), baseline, "month"))
    ago = F.lag("device").over(Window.partitionBy("sub_id").orderBy("ts", "device", "dst", "charge"))
    changes = rows.withColumn("changed", (F.col("device") != ago).cast("long")).groupBy("sub_id").agg(F.coalesce(F.sum("changed"), F.lit(0)).cast("long").alias("changes"))
    monthly = rows.groupBy("sub_id", "period").agg(F.count_distinct("device").alias("d")).groupBy("sub_id").agg(F.avg("d").alias("per_month"))
    return changes.join(monthly, "sub_id")


def both_directions(contact: DataFrame) -> DataFrame:
    """(sub_id, peer, direction, kind, ts) of each contact from both ends."""
    out = contact.select(F.col("src").alias("sub_id"), F.col("dst").alias("peer"), F.lit("out").alias("direction"), "kind", "ts")
    return out.union(contact.select("dst", "src", F.lit("in"), "kind", "ts"))


def peer_operator_share(contact: DataFrame, subscribers: DataFrame, baseline: str = BASELINE, months: int = 6) -> DataFrame:
    """(sub_id, direction, kind, rival_share, landline_share). Contacts are counted by couple before the operator is
    looked up, so the lookup sees couples, not raw rows."""
    rows = both_directions(contact.where(in_last(F.col("ts"), baseline, months)))
    counted = rows.groupBy("sub_id", "peer", "direction", "kind").agg(F.count("*").alias("n"))
    met = counted.join(subscribers.select(F.col("sub_id").alias("peer"), "operator"), "peer", "left")
    part = lambda op: F.sum(F.when(F.col("operator") == op, F.col("n")).otherwise(F.lit(0))) / F.sum("n")
    return met.groupBy("sub_id", "direction", "kind").agg(part("rival").alias("rival_share"), part("landline").alias("landline_share"))


def service_flags(contact: DataFrame, groups: int = 5, baseline: str = BASELINE, months: int = 9) -> DataFrame:
    """(sub_id, service_0 .. service_{groups-1}): 1 if any package of the group was used."""
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    return rows.groupBy(F.col("src").alias("sub_id")).agg(*[F.max((F.col("package") % groups == g).cast("int")).alias(f"service_{g}") for g in range(groups)])


def rat_share(session: DataFrame, baseline: str = EVENT_BASELINE) -> DataFrame:
    rows = session.where(before(F.col("ts"), baseline))
    return rows.groupBy("sub_id").agg(*[share_of(F.col("rat") == r).alias(f"share_{r.lower()}") for r in ("2G", "3G", "4G")])


def rat_level(session: DataFrame, baseline: str = EVENT_BASELINE) -> DataFrame:
    """(sub_id, level): mean of 2 and 3 over 2G and 3G sessions; low is mostly 2G."""
    code = F.when(F.col("rat") == "2G", 2.0).when(F.col("rat") == "3G", 3.0)
    return session.where(before(F.col("ts"), baseline)).groupBy("sub_id").agg(F.avg(code).alias("level"))


def silent_days(contact: DataFrame, subscribers: DataFrame, days: int = 60, baseline: str = BASELINE) -> DataFrame:
    """(sub_id, silent): days of the window without an outgoing record: the window less the active days, so no
    calendar is multiplied by the subscribers."""
    back = days_back(F.col("ts"), baseline)
    active = contact.where(before(F.col("ts"), baseline) & (F.col("ts") >= F.date_sub(F.lit(baseline).cast("date"), days).cast("timestamp_ntz")) & (back >= 1) & (back <= days))
    counts = active.groupBy(F.col("src").alias("sub_id")).agg(F.count_distinct(F.col("ts").cast("date")).alias("n"))
    return subscribers.select("sub_id").join(counts, "sub_id", "left").select("sub_id", (F.lit(days) - F.coalesce("n", F.lit(0))).cast("long").alias("silent"))


def friend_rival_share(pairs: DataFrame, subscribers: DataFrame) -> DataFrame:
    """(id, share): of friends who are on the rival operator."""
    return pairs.join(subscribers.select(F.col("sub_id").alias("friend"), "operator"), "friend", "left").groupBy("id").agg(share_of(F.col("operator") == "rival").alias("share"))


def idle_days(contact: DataFrame, baseline: str = BASELINE) -> DataFrame:
    return contact.where(before(F.col("ts"), baseline)).groupBy(F.col("src").alias("sub_id")).agg(days_back(F.max("ts"), baseline).cast("long").alias("idle_days"))


def line_age(contact: DataFrame, baseline: str = BASELINE) -> DataFrame:
    return contact.where(before(F.col("ts"), baseline)).groupBy(F.col("src").alias("sub_id")).agg(days_back(F.min("ts"), baseline).cast("long").alias("line_age"))


def other_operator_share(contact: DataFrame, subscribers: DataFrame, baseline: str = BASELINE, months: int = 6) -> DataFrame:
    """(sub_id, share): of contacts in both directions whose peer is not on the subscriber's own operator."""
    counted = both_directions(contact.where(in_last(F.col("ts"), baseline, months))).groupBy("sub_id", "peer").agg(F.count("*").alias("n"))
    own, theirs = subscribers.select("sub_id", "operator"), subscribers.select(F.col("sub_id").alias("peer"), F.col("operator").alias("peer_operator"))
    met = counted.join(own, "sub_id").join(theirs, "peer")
    return met.groupBy("sub_id").agg((F.sum(F.when(F.col("operator") != F.col("peer_operator"), F.col("n")).otherwise(F.lit(0))) / F.sum("n")).alias("share"))


def drop_share(session: DataFrame, baseline: str = EVENT_BASELINE) -> DataFrame:
    return session.where(before(F.col("ts"), baseline)).groupBy("sub_id").agg(share_of(F.col("dropped")).alias("share"))


def age_band(subscribers: DataFrame) -> DataFrame:
    band = F.when(F.col("age_years") < 32, "under 32").when(F.col("age_years") < 50, "32 to 49").otherwise("50 and over")
    return subscribers.select("sub_id", "age_years", band.alias("band"), (F.col("age_years") < 32).cast("int").alias("young"))


def history(contact: DataFrame, months: int, baseline: str = BASELINE) -> DataFrame:
    """(sub_id, n, total) over the last `months` months together."""
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    return rows.groupBy(F.col("src").alias("sub_id")).agg(F.count("*").alias("n"), F.sum("charge").alias("total"))


def history_windows(contact: DataFrame, windows: tuple[int, ...] = (1, 4, 6, 9), baseline: str = BASELINE) -> DataFrame:
    return reduce(DataFrame.union, [history(contact, m, baseline).withColumn("months", F.lit(m)) for m in windows])


def history_all(contact: DataFrame, months: int = 9, baseline: str = BASELINE) -> DataFrame:
    """(sub_id, months, n, total) for each window 1..months from one pass: sums by month, then running sums."""
    rows = contact.where(in_last(F.col("ts"), baseline, months)).withColumn("period", period_index(F.col("ts"), baseline, "month"))
    monthly = rows.groupBy(F.col("src").alias("sub_id"), "period").agg(F.count("*").alias("n"), F.sum("charge").alias("total"))
    grid = monthly.select("sub_id").distinct().withColumn("period", F.explode(F.sequence(F.lit(1), F.lit(months))))
    full = grid.join(monthly, ["sub_id", "period"], "left").na.fill(0)
    running = Window.partitionBy("sub_id").orderBy("period").rowsBetween(Window.unboundedPreceding, 0)
    return full.select("sub_id", F.col("period").alias("months"), F.sum("n").over(running).alias("n"), F.sum("total").over(running).alias("total"))


#: Blocks of the reduced subset that a warehouse would hold: billing, calls and messages, complaints.
WAREHOUSE = ("contacts", "tickets", "balance")


def blocks(contact: DataFrame, session: DataFrame, ticket: DataFrame, subscribers: DataFrame, baseline: str = BASELINE, months: int = 6) -> dict[str, DataFrame]:
    """The usage blocks by name, each one row a subscriber; blocks over one source share one aggregate."""
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    contacts = rows.groupBy(F.col("src").alias("sub_id")).agg(
        F.count("*").alias("n_out"), F.sum("charge").alias("charge_sum"), F.avg("charge").alias("charge_mean"), F.max("charge").alias("charge_max"),
        F.count_if(F.col("kind") == "call").alias("calls"), F.count_if(F.col("kind") == "sms").alias("sms"), F.count_if(F.col("kind") == "mms").alias("mms"),
        F.sum("duration").alias("talk"), F.count_distinct("package").alias("packages"),
    )
    return {
        "contacts": contacts,
        "idle": idle_days(contact, baseline).join(line_age(contact, baseline), "sub_id"),
        "others": other_operator_share(contact, subscribers, baseline, months).withColumnRenamed("share", "other_share"),
        "tickets": ticket_features(ticket).drop("last_result"),
        "session": rat_share(session).join(drop_share(session).withColumnRenamed("share", "drop_share"), "sub_id"),
        "balance": subscribers.select("sub_id", "balance", "age_years"),
    }


def period_columns(contact: DataFrame, baseline: str = BASELINE, months: int = 6, weeks: int = 4, days: int = 7) -> DataFrame:
    """(sub_id, n and total of each of the last days, weeks and months): one pass, sums of conditions."""
    rows = contact.where(in_last(F.col("ts"), baseline, months))
    wanted = [(u, i) for u, most in (("day", days), ("week", weeks), ("month", months)) for i in range(1, most + 1)]
    each = []
    for u, i in wanted:
        here = period_index(F.col("ts"), baseline, u) == i
        each += [F.count_if(here).alias(f"n_{u}_{i}"), F.sum(F.when(here, F.col("charge")).otherwise(0.0)).alias(f"total_{u}_{i}")]
    return rows.groupBy(F.col("src").alias("sub_id")).agg(*each)


def all_blocks(
    contact: DataFrame, session: DataFrame, ticket: DataFrame, handsets: DataFrame, subscribers: DataFrame, pairs: DataFrame, baseline: str = BASELINE, months: int = 6,
) -> dict[str, DataFrame]:
    """Every usage block by name, each one row a subscriber: those of `blocks`, sums by day, week and month, distinct
    values, rates, ratios, traffic, radio types and level, complaints and their gaps, handsets, silent days, services,
    shares of other operators by direction and kind, and of friends on the rival operator."""
    peers = peer_operator_share(contact, subscribers, baseline, months)
    sides = [F.max(F.when((F.col("direction") == d) & (F.col("kind") == k), F.col(f"{op}_share"))).alias(f"{op}_{d}_{k}") for d in ("out", "in") for k in ("call", "sms") for op in ("rival", "landline")]
    return blocks(contact, session, ticket, subscribers, baseline, months) | {
        "periods": period_columns(contact, baseline, months),
        "distinct": category_counts(contact, False, baseline, months).select("sub_id", "devices", "peers"),
        "rate": rate_per_month(contact, "call", baseline, months).withColumnRenamed("rate", "calls_per_month"),
        "ratio": kind_ratio(contact, "call", "sms", baseline, months).withColumnRenamed("ratio", "call_sms_ratio"),
        "traffic": traffic_mean(session),
        "radio": rat_level(session).withColumnRenamed("level", "radio_level"),
        "gaps": ticket_gap(ticket),
        "last_result": ticket_features(ticket).select("sub_id", "last_result"),
        "handset": handset_latest(contact, handsets, baseline).select("sub_id", "brand", "type", F.col("dual").cast("int").alias("dual")),
        "changes": handset_changes(contact, baseline, months).select("sub_id", "changes", F.col("per_month").alias("devices_per_month")),
        "silent": silent_days(contact, subscribers, 60, baseline),
        "services": service_flags(contact, 5, baseline, months),
        "sides": peers.groupBy("sub_id").agg(*sides),
        "rival_friends": friend_rival_share(pairs, subscribers).select(F.col("id").alias("sub_id"), F.col("share").alias("rival_friend_share")),
        "area": subscribers.select("sub_id", "area", "state"),
    }


def feature_table(parts: dict[str, DataFrame], population: DataFrame, only: tuple[str, ...] | None = None) -> DataFrame:
    """One row for each member of the population (sub_id): left joins that are all keyed by sub_id."""
    out = population.select("sub_id")
    for name, part in parts.items():
        if only is None or name in only:
            out = out.join(part, "sub_id", "left")
    return out


def to_long(wide: DataFrame, key: str = "sub_id") -> DataFrame:
    """(key, feature, value) of the known numbers: for tables of thousands of columns, most of them empty."""
    numbers = [c for c in wide.columns if c != key]
    cast = wide.select(key, *[F.col(c).cast("double").alias(c) for c in numbers])
    return cast.unpivot(key, numbers, "feature", "value").where("value IS NOT NULL")


def to_wide(long: DataFrame, features: list[str], key: str = "sub_id") -> DataFrame:
    return long.groupBy(key).pivot("feature", features).agg(F.first("value"))


def place(events: DataFrame, sites: DataFrame) -> DataFrame:
    """Events with their site's area and state; the directory is small and goes to all tasks if Spark measures it so."""
    return events.join(sites, "site", "left")


def enrich(usage: DataFrame, subscribers: DataFrame, how: str = "left") -> DataFrame:
    return usage.join(subscribers, "sub_id", how)
