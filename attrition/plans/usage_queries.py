"""Named queries over the usage features, labels, splits and landing helpers, with the SQL that each must equal."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import draw_sql
from ..functions.periods import BASELINE, EVENT_BASELINE, months_before
from ..operators import outcome as O
from ..operators import resample as B
from ..operators import structure as N
from ..operators import usage as U
from ..operators.contact_graph import build_arcs
from ..sources import landing as L
from ..sources.tables import contact, handset, read_table, session, site, subscriber, ticket, with_roles
from .graph_queries import ARCS, FRIENDS

IDLE = "1999-08-01"


def _rounded(df, digits=6):
    return df.select(*[F.round(F.col(c) + 1e-9, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def _over(fn, *roles, **options):
    return lambda s, d: _rounded(fn(*[r(s, d) for r in roles], **options))


def _features(s, d, only=None):
    subs = subscriber(s, d)
    return U.feature_table(U.blocks(contact(s, d), session(s, d), ticket(s, d), subs), subs, only)


def _labels(s, d):
    orders = read_table(s, d, "orders").select(F.col("o_custkey").alias("sub_id"), F.col("o_orderdate").alias("ts"))
    return O.idle_label(orders, subscriber(s, d), IDLE, 24)


def _place(s, d):
    return _rounded(U.place(session(s, d), site(s, d)).groupBy("area", "state", "rat").agg(F.count("*").alias("n"), F.sum("bytes_down").alias("down")))


def _enrich(s, d):
    usage = U.history(contact(s, d), 6)
    return _rounded(U.enrich(usage, subscriber(s, d)).groupBy("operator", "state").agg(F.count("*").alias("n"), F.sum("total").alias("total")))


def _balance(s, d):
    split = B.split(_labels(s, d)).where("part = 'train'")
    out = None
    for name, fn in (("none", lambda x: x), ("oversample", B.oversample), ("undersample", B.undersample)):
        part = B.balance_report(fn(split)).select(F.lit(name).alias("balance"), "label", "rows")
        out = part if out is None else out.union(part)
    return out


QUERIES = {
    "usage_month": _over(U.period_rollup, contact, unit="month"),
    "usage_week": _over(U.period_rollup, contact, unit="week"),
    "usage_day": _over(U.period_rollup, contact, unit="day"),
    "usage_multi": _over(U.multi_unit_rollup, contact),
    "usage_distinct": _over(U.category_counts, contact),
    "calls_per_month": _over(U.rate_per_month, contact),
    "traffic": _over(U.traffic_mean, session),
    "packages": _over(U.package_count, contact),
    "rat_site": _over(U.rat_share_by_site, session),
    "call_sms_ratio": _over(U.kind_ratio, contact),
    "tickets": _over(U.ticket_features, ticket),
    "ticket_gap": _over(U.ticket_gap, ticket),
    "handset": _over(U.handset_latest, contact, handset),
    "handset_changes": _over(U.handset_changes, contact),
    "peer_share": _over(U.peer_operator_share, contact, subscriber),
    "service_flags": _over(U.service_flags, contact),
    "rat_share": _over(U.rat_share, session),
    "silent_days": _over(U.silent_days, contact, subscriber),
    "friend_share": lambda s, d: _rounded(U.friend_rival_share(N.friends(build_arcs(contact(s, d))), subscriber(s, d))),
    "idle_days": _over(U.idle_days, contact),
    "line_age": _over(U.line_age, contact),
    "rat_level": _over(U.rat_level, session),
    "other_share": _over(U.other_operator_share, contact, subscriber),
    "drop_share": _over(U.drop_share, session),
    "age_band": _over(U.age_band, subscriber),
    "history_windows": _over(U.history_windows, contact),
    "history_all": _over(U.history_all, contact),
    "feature_table": lambda s, d: _rounded(_features(s, d)),
    "warehouse_table": lambda s, d: _rounded(_features(s, d, U.WAREHOUSE)),
    "feature_long": lambda s, d: _rounded(U.to_long(_features(s, d, U.WAREHOUSE))),
    "parse_props": lambda s, d: L.parse(read_table(s, d, "events"), "props", "k INT", "json").select("event_id", F.col("parsed.k").alias("k")),
    "import_slices": lambda s, d: L.slice_counts(read_table(s, d, "orders"), "o_orderkey", 4),
    "place_usage": _place,
    "enrich_usage": _enrich,
    "idle_label": lambda s, d: _labels(s, d),
    "exclude_new": lambda s, d: O.exclude_new(subscriber(s, d), contact(s, d), "1996-01-01", 4).select("sub_id"),
    "split_counts": lambda s, d: B.split(_labels(s, d)).groupBy("part", "label").agg(F.count("*").alias("rows")),
    "fold_counts": lambda s, d: B.folds(_labels(s, d), 10).groupBy("fold", "label").agg(F.count("*").alias("rows")),
    "oversample": lambda s, d: B.oversample(B.split(_labels(s, d)).where("part = 'train'")).select("sub_id", "label", "copy"),
    "undersample": lambda s, d: B.undersample(B.split(_labels(s, d)).where("part = 'train'")).select("sub_id", "label"),
    "balance_report": _balance,
}

# ---------------------------------------------------------------- SQL


def _window(months, alias=""):
    return f"{alias}ts >= '{months_before(BASELINE, months)}' AND {alias}ts < '{BASELINE}'"


def _r(expr, name=None, digits=6):
    return f"round({expr} + 1e-9, {digits}) AS {name or expr}"


BACK = f"date_diff('day', ts::DATE, DATE '{BASELINE}')"
MONTH = "(2001 * 12 + 8 - (year(ts) * 12 + month(ts)))::INT"
PERIOD = {"month": MONTH, "week": f"(({BACK} - 1) // 7 + 1)::INT", "day": f"(({BACK} - 1) // 1 + 1)::INT"}
BOTH = """both_ways AS (SELECT src AS sub_id, dst AS peer, 'out' AS direction, kind, ts FROM contact UNION ALL SELECT dst, src, 'in', kind, ts FROM contact)"""


def _rollup(unit):
    return with_roles(
        "contact",
        f"""SELECT src AS sub_id, {PERIOD[unit]} AS period, kind, count(*) AS n, {_r("sum(charge)", "total")}, {_r("avg(charge)", "mean")}, {_r("min(charge)", "low")}, {_r("max(charge)", "high")}
        FROM contact WHERE {_window(9)} GROUP BY ALL""",
    )


def _history(months):
    return f"SELECT src AS sub_id, count(*) AS n, {_r('sum(charge)', 'total')}, {months}::INT AS months FROM contact WHERE {_window(months)} GROUP BY src"


EV = f"ts < '{EVENT_BASELINE}'"
BLOCKS = (
    f"""contacts AS (SELECT src AS sub_id, count(*) AS n_out, sum(charge) AS charge_sum, avg(charge) AS charge_mean, max(charge) AS charge_max, count(*) FILTER (kind = 'call') AS calls,
    count(*) FILTER (kind = 'sms') AS sms, count(*) FILTER (kind = 'mms') AS mms, sum(duration) AS talk, count(DISTINCT package) AS packages FROM contact WHERE {_window(6)} GROUP BY src)""",
    f"""idle AS (SELECT src AS sub_id, date_diff('day', max(ts)::DATE, DATE '{BASELINE}')::BIGINT AS idle_days, date_diff('day', min(ts)::DATE, DATE '{BASELINE}')::BIGINT AS line_age
    FROM contact WHERE ts < '{BASELINE}' GROUP BY src)""",
    BOTH,
    f"""others AS (SELECT b.sub_id, avg(CASE WHEN s.operator <> p.operator THEN 1.0 ELSE 0.0 END) AS other_share FROM both_ways b JOIN subscriber s ON s.sub_id = b.sub_id
    JOIN subscriber p ON p.sub_id = b.peer WHERE {_window(6, "b.")} GROUP BY b.sub_id)""",
    f"""complaint AS (SELECT sub_id, count(*) AS complaints, avg(CASE WHEN coverage THEN 1.0 ELSE 0.0 END) AS coverage_share, avg(hours_to_close) AS mean_hours FROM ticket
    WHERE opened < '{EVENT_BASELINE}' GROUP BY sub_id)""",
    f"""radio AS (SELECT sub_id, avg(CASE WHEN rat = '2G' THEN 1.0 ELSE 0.0 END) AS share_2g, avg(CASE WHEN rat = '3G' THEN 1.0 ELSE 0.0 END) AS share_3g,
    avg(CASE WHEN rat = '4G' THEN 1.0 ELSE 0.0 END) AS share_4g, avg(CASE WHEN dropped THEN 1.0 ELSE 0.0 END) AS drop_share FROM session WHERE {EV} GROUP BY sub_id)""",
)
FROM_ALL = "subscriber s LEFT JOIN contacts c USING (sub_id) LEFT JOIN idle i USING (sub_id) LEFT JOIN others o USING (sub_id) LEFT JOIN complaint t USING (sub_id) LEFT JOIN radio r USING (sub_id)"
CONTACTS = f"n_out, {_r('charge_sum')}, {_r('charge_mean')}, {_r('charge_max')}, calls, sms, mms, {_r('talk')}, packages"
COMPLAINTS = f"complaints, {_r('coverage_share')}, {_r('mean_hours')}"
OWN = f"{_r('balance')}, age_years"
FEATURES = f"""SELECT sub_id, {CONTACTS}, idle_days, line_age, {_r("other_share")}, {COMPLAINTS}, {_r("share_2g")}, {_r("share_3g")}, {_r("share_4g")}, {_r("drop_share")}, {OWN} FROM {FROM_ALL}"""
WAREHOUSE = f"SELECT sub_id, {CONTACTS}, {COMPLAINTS}, {OWN} FROM {FROM_ALL}"
LONG = ["n_out", "charge_sum", "charge_mean", "charge_max", "calls", "sms", "mms", "talk", "packages", "complaints", "coverage_share", "mean_hours", "balance", "age_years"]

LABEL = f"""labelled AS (SELECT c.c_custkey AS sub_id, CASE WHEN EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderdate >= '{IDLE}'
  AND o.o_orderdate < '2001-08-01') THEN 0 ELSE 1 END AS label FROM customer c)"""
SPLIT = f"split AS (SELECT *, CASE WHEN {draw_sql('sub_id', 'split')} < 0.7 THEN 'train' ELSE 'test' END AS part FROM labelled)"
TRAIN = "train AS (SELECT sub_id, label FROM split WHERE part = 'train')"
SIZES = "sizes AS (SELECT count(*) FILTER (label = 1) AS n1, count(*) FILTER (label = 0) AS n0 FROM train)"
OVER = f"""over_ AS (SELECT sub_id, label, unnest(range(1, 1 + copies)) AS copy FROM (SELECT sub_id, label, CASE WHEN n = greatest(n0, n1) THEN 1
  ELSE greatest(n0, n1) // n + CASE WHEN place <= greatest(n0, n1) % n THEN 1 ELSE 0 END END AS copies FROM (SELECT *, CASE WHEN label = 1 THEN n1 ELSE n0 END AS n,
  row_number() OVER (PARTITION BY label ORDER BY {draw_sql('sub_id', 'over')}, sub_id) AS place FROM train, sizes)))"""
UNDER = f"""under_ AS (SELECT sub_id, label FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY {draw_sql('sub_id', 'under')}, sub_id) AS place FROM train, sizes) WHERE place <= least(n0, n1))"""

ORACLES = {
    "usage_month": _rollup("month"),
    "usage_week": _rollup("week"),
    "usage_day": _rollup("day"),
    "usage_multi": with_roles(
        "contact",
        "\nUNION ALL ".join(
            f"SELECT src AS sub_id, '{u}' AS unit, {PERIOD[u]} AS period, kind, count(*) AS n, {_r('sum(charge)', 'total')}, {_r('min(charge)', 'low')}, {_r('max(charge)', 'high')} FROM contact WHERE {_window(9)} GROUP BY ALL"
            for u in ("day", "week", "month")
        ),
    ),
    "usage_distinct": with_roles("contact", f"SELECT src AS sub_id, count(DISTINCT device) AS devices, count(DISTINCT package) AS packages, count(DISTINCT dst) AS peers FROM contact WHERE {_window(9)} GROUP BY src"),
    "calls_per_month": with_roles("contact", f"SELECT src AS sub_id, {_r('count(*) FILTER (kind = $$call$$) / 6.0::DOUBLE', 'rate')} FROM contact WHERE {_window(6)} GROUP BY src"),
    "traffic": with_roles("session", f"SELECT sub_id, {_r('avg(bytes_up) FILTER (bytes_up > 0)', 'mean_up')}, {_r('avg(bytes_down) FILTER (bytes_down > 0)', 'mean_down')} FROM session WHERE {EV} GROUP BY sub_id"),
    "packages": with_roles("contact", f"SELECT src AS sub_id, count(DISTINCT package) AS packages FROM contact WHERE {_window(9)} GROUP BY src"),
    "rat_site": with_roles(
        "session",
        f"""SELECT site, period, rat, {_r("n / sum(n) OVER (PARTITION BY site, period)::DOUBLE", "share")} FROM (SELECT site, ((date_diff('day', ts::DATE, DATE '{EVENT_BASELINE}') - 1) // 3 + 1)::INT AS period,
        rat, count(*) AS n FROM session WHERE {EV} GROUP BY ALL)""",
    ),
    "call_sms_ratio": with_roles(
        "contact", f"SELECT src AS sub_id, {_r('count(*) FILTER (kind = $$call$$) / nullif(count(*) FILTER (kind = $$sms$$), 0)::DOUBLE', 'ratio')} FROM contact WHERE {_window(6)} GROUP BY src"
    ),
    "tickets": with_roles(
        "ticket",
        f"""SELECT sub_id, count(*) AS complaints, {_r("avg(CASE WHEN coverage THEN 1.0 ELSE 0.0 END)", "coverage_share")}, {_r("avg(hours_to_close)", "mean_hours")}, arg_max(result, opened) AS last_result
        FROM ticket WHERE opened < '{EVENT_BASELINE}' GROUP BY sub_id""",
    ),
    "ticket_gap": with_roles(
        "ticket",
        f"""SELECT sub_id, {_r("avg(gap) / 3.6e9::DOUBLE", "mean_gap_hours")} FROM (SELECT sub_id, epoch_us(opened) - epoch_us(lag(opened) OVER (PARTITION BY sub_id ORDER BY opened)) AS gap
        FROM ticket WHERE opened < '{EVENT_BASELINE}') GROUP BY sub_id""",
    ),
    "handset": with_roles(
        "contact handset",
        f"""SELECT sub_id, brand, type, dual FROM (SELECT src AS sub_id, device, row_number() OVER (PARTITION BY src ORDER BY ts DESC, device DESC) AS place FROM contact WHERE ts < '{BASELINE}')
        LEFT JOIN handset USING (device) WHERE place = 1""",
    ),
    "handset_changes": with_roles(
        "contact",
        f"""SELECT sub_id, changes, {_r("per_month")} FROM (SELECT sub_id, sum(CASE WHEN device <> ago THEN 1 ELSE 0 END)::BIGINT AS changes FROM (SELECT src AS sub_id, device,
        lag(device) OVER (PARTITION BY src ORDER BY ts, device, dst, charge) AS ago FROM contact WHERE {_window(9)}) GROUP BY sub_id)
        JOIN (SELECT sub_id, avg(d) AS per_month FROM (SELECT src AS sub_id, {MONTH} AS p, count(DISTINCT device) AS d FROM contact WHERE {_window(9)} GROUP BY 1, 2) GROUP BY sub_id) USING (sub_id)""",
    ),
    "peer_share": with_roles(
        "contact subscriber",
        f"""SELECT b.sub_id, direction, kind, {_r("avg(CASE WHEN operator = $$rival$$ THEN 1.0 ELSE 0.0 END)", "rival_share")}, {_r("avg(CASE WHEN operator = $$landline$$ THEN 1.0 ELSE 0.0 END)", "landline_share")}
        FROM both_ways b LEFT JOIN subscriber s ON s.sub_id = peer WHERE {_window(6, "b.")} GROUP BY ALL""",
        BOTH,
    ),
    "service_flags": with_roles("contact", "SELECT src AS sub_id, " + ", ".join(f"max((package % 5 = {g})::INT) AS service_{g}" for g in range(5)) + f" FROM contact WHERE {_window(9)} GROUP BY src"),
    "rat_share": with_roles("session", "SELECT sub_id, " + ", ".join(_r(f"avg(CASE WHEN rat = '{g}G' THEN 1.0 ELSE 0.0 END)", f"share_{g}g") for g in (2, 3, 4)) + f" FROM session WHERE {EV} GROUP BY sub_id"),
    "silent_days": with_roles(
        "contact subscriber",
        f"""SELECT sub_id, count(*) AS silent FROM subscriber, (SELECT unnest(generate_series(DATE '{BASELINE}' - INTERVAL 60 DAY, DATE '{BASELINE}' - INTERVAL 1 DAY, INTERVAL 1 DAY))::DATE AS day)
        WHERE NOT EXISTS (SELECT 1 FROM contact WHERE src = sub_id AND ts::DATE = day) GROUP BY sub_id
        UNION ALL SELECT sub_id, 0 FROM subscriber WHERE (SELECT count(DISTINCT ts::DATE) FROM contact WHERE src = sub_id AND ts::DATE >= DATE '{BASELINE}' - INTERVAL 60 DAY AND ts < '{BASELINE}') = 60""",
    ),
    "friend_share": with_roles(
        "contact subscriber", f"SELECT f.id, {_r('avg(CASE WHEN operator = $$rival$$ THEN 1.0 ELSE 0.0 END)', 'share')} FROM friends f LEFT JOIN subscriber ON sub_id = friend GROUP BY f.id", ARCS, FRIENDS
    ),
    "idle_days": with_roles("contact", f"SELECT src AS sub_id, date_diff('day', max(ts)::DATE, DATE '{BASELINE}')::BIGINT AS idle_days FROM contact WHERE ts < '{BASELINE}' GROUP BY src"),
    "line_age": with_roles("contact", f"SELECT src AS sub_id, date_diff('day', min(ts)::DATE, DATE '{BASELINE}')::BIGINT AS line_age FROM contact WHERE ts < '{BASELINE}' GROUP BY src"),
    "rat_level": with_roles("session", f"SELECT sub_id, {_r('avg(CASE rat WHEN $$2G$$ THEN 2.0 WHEN $$3G$$ THEN 3.0 END)', 'level')} FROM session WHERE {EV} GROUP BY sub_id"),
    "other_share": with_roles("contact subscriber", f"SELECT sub_id, {_r('other_share', 'share')} FROM others", BLOCKS[2], BLOCKS[3]),
    "drop_share": with_roles("session", f"SELECT sub_id, {_r('avg(CASE WHEN dropped THEN 1.0 ELSE 0.0 END)', 'share')} FROM session WHERE {EV} GROUP BY sub_id"),
    "age_band": with_roles(
        "subscriber", "SELECT sub_id, age_years, CASE WHEN age_years < 32 THEN 'under 32' WHEN age_years < 50 THEN '32 to 49' ELSE '50 and over' END AS band, (age_years < 32)::INT AS young FROM subscriber"
    ),
    "history_windows": with_roles("contact", "\nUNION ALL ".join(_history(m) for m in (1, 4, 6, 9))),
    "history_all": with_roles(
        "contact",
        "SELECT u.sub_id, m.months::INT AS months, coalesce(h.n, 0) AS n, coalesce(h.total, round(0 + 1e-9, 6)) AS total FROM (SELECT DISTINCT src AS sub_id FROM contact WHERE "
        + _window(9) + ") u CROSS JOIN range(1, 10) m(months) LEFT JOIN (" + "\nUNION ALL ".join(_history(m) for m in range(1, 10)) + ") h ON h.sub_id = u.sub_id AND h.months = m.months",
    ),
    "feature_table": with_roles("contact subscriber session ticket", FEATURES, *BLOCKS),
    "warehouse_table": with_roles("contact subscriber session ticket", WAREHOUSE, *BLOCKS),
    "feature_long": with_roles("contact subscriber session ticket", "\nUNION ALL ".join(f"SELECT sub_id, '{c}' AS feature, {_r(f'{c}::DOUBLE', 'value')} FROM {FROM_ALL} WHERE {c} IS NOT NULL" for c in LONG), *BLOCKS),
    "parse_props": with_roles("event", "SELECT event_id, k FROM event"),
    "import_slices": """SELECT least(3, (o_orderkey - lo) * 4 // (hi - lo + 1))::INT AS slice, count(*) AS rows, min(o_orderkey) AS low, max(o_orderkey) AS high
      FROM orders, (SELECT min(o_orderkey) AS lo, max(o_orderkey) AS hi FROM orders) GROUP BY 1""",
    "place_usage": with_roles("session site", f"SELECT area, state, rat, count(*) AS n, {_r('sum(bytes_down)', 'down')} FROM session LEFT JOIN sites USING (site) GROUP BY ALL"),
    "enrich_usage": with_roles(
        "contact subscriber", f"SELECT operator, state, count(*) AS n, {_r('sum(total)', 'total')} FROM (SELECT src AS sub_id, sum(charge) AS total FROM contact WHERE {_window(6)} GROUP BY src) LEFT JOIN subscriber USING (sub_id) GROUP BY ALL"
    ),
    "idle_label": "WITH " + LABEL + " SELECT * FROM labelled",
    "exclude_new": with_roles("contact subscriber", "SELECT sub_id FROM subscriber WHERE sub_id NOT IN (SELECT src FROM contact WHERE ts < '1996-01-01' GROUP BY src HAVING min(ts) >= '1995-09-01')"),
    "split_counts": f"WITH {LABEL}, {SPLIT} SELECT part, label, count(*) AS rows FROM split GROUP BY ALL",
    "fold_counts": f"WITH {LABEL} SELECT floor({draw_sql('sub_id', 'fold')} * 10)::INT AS fold, label, count(*) AS rows FROM labelled GROUP BY ALL",
    "oversample": f"WITH {LABEL}, {SPLIT}, {TRAIN}, {SIZES}, {OVER} SELECT sub_id, label, copy::INT AS copy FROM over_",
    "undersample": f"WITH {LABEL}, {SPLIT}, {TRAIN}, {SIZES}, {UNDER} SELECT sub_id, label FROM under_",
    "balance_report": f"""WITH {LABEL}, {SPLIT}, {TRAIN}, {SIZES}, {OVER}, {UNDER} SELECT 'none' AS balance, label, count(*) AS rows FROM train GROUP BY label
      UNION ALL SELECT 'oversample', label, count(*) FROM over_ GROUP BY label UNION ALL SELECT 'undersample', label, count(*) FROM under_ GROUP BY label""",
}
