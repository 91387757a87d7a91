"""Named queries of the operators around the methods, with the SQL that each must equal."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import sqlfunctions
from ..functions.hashing import draw_sql
from ..functions.periods import BASELINE, in_last, months_before, period_index
from ..functions.scratch import new_path
from ..operators import relational as X
from ..operators import structure as N
from ..operators.contact_graph import build_arcs
from ..sources.tables import SCHEMAS, contact, read_table, session, site, subscriber, with_roles
from ..streaming import live
from .graph_queries import ARCS, FRIENDS
from .usage_queries import _r, _rounded

T = read_table


def _joins(s, d):
    c, o = T(s, d, "customer").select(F.col("c_custkey").alias("k"), "c_mktsegment"), T(s, d, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("k"), "o_totalprice")
    out = None
    for how in ("inner", "left", "right", "full", "left_semi", "left_anti"):
        part = c.join(o, "k", how).agg(F.count("*").alias("rows"), F.count_distinct("k").alias("keys")).select(F.lit(how).alias("how"), "rows", "keys")
        out = part if out is None else out.union(part)
    return out


JOINS_SQL = "WITH o AS (SELECT o_custkey AS k FROM orders WHERE o_totalprice > 300000) " + " UNION ALL ".join(
    f"SELECT '{name}' AS how, count(*) AS rows, count(DISTINCT {key}) AS keys FROM customer {kind} o ON c_custkey = k"
    for name, kind, key in (("inner", "JOIN", "k"), ("left", "LEFT JOIN", "c_custkey"), ("right", "RIGHT JOIN", "k"), ("full", "FULL JOIN", "coalesce(c_custkey, k)"), ("left_semi", "SEMI JOIN", "c_custkey"), ("left_anti", "ANTI JOIN", "c_custkey"))
)
BANDS = [(0.0, 10.0, "short"), (10.0, 25.0, "medium"), (20.0, 40.0, "overlap"), (40.0, 51.0, "long")]


def _range(s, d):
    bands = s.createDataFrame(BANDS, "low DOUBLE, high DOUBLE, band STRING")
    calls = contact(s, d).where("kind = 'call'").select("src", "duration")
    return X.range_join(calls, bands, "duration", "low", "high", 10.0).groupBy("band").agg(F.count("*").alias("n"), F.sum("duration").alias("total"))


def _as_of(s, d):
    e = T(s, d, "events")
    clicks = e.where("event_type = 'click'").select("event_id", "user_id", "ts")
    buys = e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought_at"), F.col("value").alias("bought"), F.col("event_id").alias("buy_id"))
    return X.as_of_join(clicks, buys, "user_id", "ts", "bought_at", ["buy_id", "bought"], "buy_id").select("event_id", "buy_id", "bought")


def _interval(s, d):
    e = T(s, d, "events")
    errors = e.where("event_type = 'error'").select("user_id", F.col("ts").alias("error_at"), F.col("event_id").alias("error_id"))
    views = e.where("event_type = 'view'").select("user_id", F.col("ts").alias("view_at"), "event_id")
    return X.interval_join(errors, views, "user_id", "error_at", "view_at", 6 * 3600).select("error_id", "event_id")


def _aggregates(s, d):
    o, p = T(s, d, "orders"), F.col("o_totalprice")
    return _rounded(
        o.groupBy("o_orderpriority").agg(
            F.count("*").alias("n"), F.count_distinct("o_custkey").alias("customers"), F.count_distinct("o_orderstatus").alias("states"), F.count_if(p > 200000).alias("large"),
            F.avg(F.when(F.col("o_orderstatus") == "F", p)).alias("mean_f"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest"),
            F.stddev(p).alias("sd"), F.variance(p).alias("var"), F.median(p).alias("mid"), F.percentile(p, F.lit(0.9)).alias("p90"), F.corr(p, F.col("o_custkey").cast("double")).alias("r"),
            F.covar_samp(p, F.col("o_custkey").cast("double")).alias("cov"), F.regr_slope(p, F.col("o_custkey").cast("double")).alias("slope"), F.bool_and(p > 0).alias("all_pos"), F.bool_or(p > 400000).alias("any_large"),
            F.array_join(F.array_sort(F.collect_set("o_orderstatus")), "").alias("letters"),
        ), 3,
    )


AGG_SQL = f"""SELECT o_orderpriority, count(*) AS n, count(DISTINCT o_custkey) AS customers, count(DISTINCT o_orderstatus) AS states, count(*) FILTER (o_totalprice > 200000) AS large,
  {_r("avg(o_totalprice) FILTER (o_orderstatus = 'F')", "mean_f", 3)}, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest,
  {_r("stddev(o_totalprice)", "sd", 3)}, {_r("var_samp(o_totalprice)", "var", 3)}, {_r("median(o_totalprice)", "mid", 3)}, {_r("quantile_cont(o_totalprice, 0.9)", "p90", 3)}, {_r("corr(o_totalprice, o_custkey)", "r", 3)},
  {_r("covar_samp(o_totalprice, o_custkey)", "cov", 3)}, {_r("regr_slope(o_totalprice, o_custkey)", "slope", 3)}, bool_and(o_totalprice > 0) AS all_pos, bool_or(o_totalprice > 400000) AS any_large,
  array_to_string(list_sort(list(DISTINCT o_orderstatus)), '') AS letters FROM orders GROUP BY 1"""


def _sets(s, d, kind):
    usage = session(s, d).join(site(s, d), "site").select("state", "area", "rat", "bytes_down")
    keys = ("state", "area", "rat")
    grouped = usage.rollup(*keys) if kind == "rollup" else usage.cube(*keys)
    return _rounded(grouped.agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("n"), F.sum("bytes_down").alias("down")), 3)


def _sets_sql(kind):
    return with_roles("session site", f"SELECT state, area, rat, grouping(state, area, rat)::BIGINT AS level, count(*) AS n, {_r('sum(bytes_down)', 'down', 3)} FROM session JOIN sites USING (site) GROUP BY {kind} (state, area, rat)")


def _windows(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    run, three = w.rowsBetween(Window.unboundedPreceding, 0), w.rowsBetween(-2, 0)
    days = Window.partitionBy("o_custkey").orderBy(F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date"))).rangeBetween(-30, 0)
    p = F.col("o_totalprice")
    out = T(s, d, "orders").select(
        "o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"),
        F.ntile(4).over(w).cast("long").alias("nt"), F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.first("o_orderkey").over(run).alias("first_key"), F.last("o_orderkey").over(run).alias("last_key"),
        F.nth_value("o_orderkey", 2).over(run).alias("second_key"), F.sum(p).over(run).alias("running"), F.avg(p).over(three).alias("trailing"), F.avg(p).over(w.rowsBetween(-1, 1)).alias("centred"), F.count("*").over(days).alias("in_30_days"),
    )
    return _rounded(out, 3)


WINDOW_SQL = f"""SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, {_r("percent_rank() OVER w", "pr", 3)}, {_r("cume_dist() OVER w", "cd", 3)}, ntile(4) OVER w AS nt,
  lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, first_value(o_orderkey) OVER r AS first_key, last_value(o_orderkey) OVER r AS last_key, nth_value(o_orderkey, 2) OVER r AS second_key,
  {_r("sum(o_totalprice) OVER r", "running", 3)}, {_r("avg(o_totalprice) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)", "trailing", 3)}, {_r("avg(o_totalprice) OVER (w ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING)", "centred", 3)},
  count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate::DATE RANGE BETWEEN INTERVAL 30 DAY PRECEDING AND CURRENT ROW) AS in_30_days
  FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), r AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING)"""


def _set_ops(s, d):
    a = T(s, d, "customer").select(F.col("c_nationkey").alias("k"))
    b = T(s, d, "supplier").where("s_acctbal > 0").select(F.col("s_nationkey").alias("k"))
    ops = {"union": a.union(b).distinct(), "union_all": a.union(b), "intersect": a.intersect(b), "intersect_all": a.intersectAll(b), "except": a.subtract(b), "except_all": a.exceptAll(b), "by_name": a.unionByName(b.withColumn("x", F.lit(1)), allowMissingColumns=True).distinct()}
    out = None
    for name, rows in ops.items():
        part = rows.agg(F.count("*").alias("rows"), F.sum("k").cast("long").alias("total")).select(F.lit(name).alias("op"), "rows", "total")
        out = part if out is None else out.union(part)
    return out


SET_SQL = "WITH a AS (SELECT c_nationkey AS k FROM customer), b AS (SELECT s_nationkey AS k FROM supplier WHERE s_acctbal > 0) " + " UNION ALL ".join(
    f"SELECT '{n}' AS op, count(*) AS rows, sum(k)::BIGINT AS total FROM ({q})"
    for n, q in {
        "union": "FROM a UNION FROM b", "union_all": "FROM a UNION ALL FROM b", "intersect": "FROM a INTERSECT FROM b", "intersect_all": "FROM a INTERSECT ALL FROM b",
        "except": "FROM a EXCEPT FROM b", "except_all": "FROM a EXCEPT ALL FROM b", "by_name": "SELECT DISTINCT k, x FROM (SELECT k, NULL AS x FROM a UNION ALL SELECT k, 1 FROM b)",
    }.items()
)


def _strings(s, d):
    c = F.col("c_name")
    return T(s, d, "customer").select(
        "c_custkey", F.upper(c).alias("up"), F.trim(F.concat(F.lit(" "), c, F.lit(" "))).alias("trimmed"), F.lpad(F.substring(c, 10, 4), 6, "x").alias("padded"), F.split_part(c, F.lit("#"), F.lit(2)).alias("part2"), F.concat_ws("-", c, "c_mktsegment").alias("joined"),
        F.regexp_extract(c, r"([0-9]+)$", 1).alias("digits"), F.regexp_replace(c, "[0-9]", "9").alias("masked"), F.translate(c, "0", "o").alias("translated"), F.levenshtein(c, F.col("c_mktsegment")).cast("long").alias("far"), F.char_length(c).cast("long").alias("size"), F.md5(c).alias("md5"), F.sha2(c, 256).alias("sha"),
    )


STRING_SQL = """SELECT c_custkey, upper(c_name) AS up, trim(' ' || c_name || ' ') AS trimmed, lpad(substr(c_name, 10, 4), 6, 'x') AS padded, split_part(c_name, '#', 2) AS part2, concat_ws('-', c_name, c_mktsegment) AS joined,
  regexp_extract(c_name, '([0-9]+)$', 1) AS digits, regexp_replace(c_name, '[0-9]', '9', 'g') AS masked, translate(c_name, '0', 'o') AS translated, levenshtein(c_name, c_mktsegment)::BIGINT AS far, length(c_name)::BIGINT AS size, md5(c_name) AS md5, sha256(c_name) AS sha FROM customer"""


def _dates(s, d):
    t = F.col("o_orderdate")
    return T(s, d, "orders").select(
        "o_orderkey", F.date_trunc("month", t).cast("date").alias("month"), F.add_months(t, 2).alias("later"), F.datediff(F.lit("2001-08-01").cast("date"), t).cast("long").alias("back"), F.date_add(t.cast("date"), 10).alias("plus10"), F.last_day(t).alias("last"), F.dayofweek(t).cast("long").alias("dow"),
        F.weekofyear(t).cast("long").alias("week"), F.quarter(t).cast("long").alias("quarter"), F.make_date(F.year(t), F.lit(1), F.lit(1)).alias("new_year"), (t + F.expr("INTERVAL 36 HOURS")).cast("date").alias("plus36h"), F.dayofyear(t).cast("long").alias("doy"),
    )


DATE_SQL = """SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, (o_orderdate::DATE + INTERVAL 2 MONTH)::DATE AS later, date_diff('day', o_orderdate::DATE, DATE '2001-08-01') AS back, (o_orderdate::DATE + INTERVAL 10 DAY)::DATE AS plus10, last_day(o_orderdate) AS last,
  (dayofweek(o_orderdate) + 1)::BIGINT AS dow, weekofyear(o_orderdate)::BIGINT AS week, quarter(o_orderdate)::BIGINT AS quarter, make_date(year(o_orderdate), 1, 1) AS new_year, (o_orderdate + INTERVAL 36 HOUR)::DATE AS plus36h, dayofyear(o_orderdate)::BIGINT AS doy FROM orders"""


def _math(s, d):
    v = F.col("c_acctbal")
    return _rounded(T(s, d, "customer").select(
        "c_custkey", F.floor(v).alias("down"), F.ceil(v).alias("up"), F.ln(F.abs(v) + 1).alias("log"), F.exp(v / 10000).alias("e"), F.pow(v / 1000, F.lit(2)).alias("sq"), F.sqrt(F.abs(v)).alias("root"), F.greatest(v, F.lit(0.0)).alias("top"), F.least(v, F.lit(0.0)).alias("low"),
        F.pmod(F.col("c_custkey"), F.lit(7)).alias("mod"), F.sign(v).alias("sgn"), F.try_divide(v, F.col("c_nationkey")).alias("ratio"), F.when(v < 0, "debt").when(v < 1000, "low").otherwise("high").alias("band"), F.nullif("c_nationkey", F.lit(0)).alias("nonzero"), F.nvl2(F.nullif("c_nationkey", F.lit(0)), F.lit("y"), F.lit("n")).alias("has"),
    ), 4)


MATH_SQL = f"""SELECT c_custkey, floor(c_acctbal)::BIGINT AS down, ceil(c_acctbal)::BIGINT AS up, {_r("ln(abs(c_acctbal) + 1)", "log", 4)}, {_r("exp(c_acctbal / 10000)", "e", 4)}, {_r("pow(c_acctbal / 1000, 2)", "sq", 4)}, {_r("sqrt(abs(c_acctbal))", "root", 4)}, {_r("greatest(c_acctbal, 0)", "top", 4)},
  {_r("least(c_acctbal, 0)", "low", 4)}, c_custkey % 7 AS mod, {_r("sign(c_acctbal)::DOUBLE", "sgn", 4)}, {_r("c_acctbal / nullif(c_nationkey, 0)", "ratio", 4)}, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 1000 THEN 'low' ELSE 'high' END AS band, nullif(c_nationkey, 0) AS nonzero,
  CASE WHEN nullif(c_nationkey, 0) IS NOT NULL THEN 'y' ELSE 'n' END AS has FROM customer"""


def _arrays(s, d):
    lists = N.friends(build_arcs(contact(s, d))).groupBy("id").agg(F.array_sort(F.collect_list("friend")).alias("f"))
    even, near = F.filter("f", lambda x: x % 2 == 0), F.slice("f", 1, 3)
    return lists.select(
        "id", F.size("f").cast("long").alias("n"), F.size(even).cast("long").alias("even"), F.array_join(near, ",").alias("first3"), F.exists("f", lambda x: x > F.lit(1000)).alias("far"), F.forall("f", lambda x: x > 0).alias("pos"),
        F.aggregate("f", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size(F.array_intersect("f", even)).cast("long").alias("both"), F.size(F.array_except("f", even)).cast("long").alias("odd"), F.array_max(F.transform("f", lambda x: x % 10)).alias("digit"), F.array_contains("f", F.col("id")).alias("own"),
    )


ARRAY_SQL = with_roles(
    "contact",
    """SELECT id, len(f) AS n, len(list_filter(f, lambda x: x % 2 = 0)) AS even, array_to_string(f[1:3], ',') AS first3, len(list_filter(f, lambda x: x > 1000)) > 0 AS far, len(list_filter(f, lambda x: x <= 0)) = 0 AS pos, list_sum(f)::BIGINT AS total,
    len(list_filter(f, lambda x: x % 2 = 0)) AS both, len(list_filter(f, lambda x: x % 2 <> 0)) AS odd, list_max(list_transform(f, lambda x: x % 10)) AS digit, list_contains(f, id) AS own FROM (SELECT id, list_sort(list(friend)) AS f FROM friends GROUP BY id)""",
    ARCS, FRIENDS,
)


def _maps(s, d):
    m = contact(s, d).groupBy(F.col("src").alias("id"), "kind").agg(F.count("*").alias("n")).groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("kind", "n"))).alias("m"))
    return m.select(
        "id", F.array_join(F.array_sort(F.map_keys("m")), ",").alias("keys"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.try_element_at("m", F.lit("call")).alias("calls"),
        F.size(F.map_filter("m", lambda k, v: v >= 10)).cast("long").alias("busy"), F.try_element_at(F.transform_values("m", lambda k, v: v * 2), F.lit("sms")).alias("twice"), F.size(F.map_concat("m", F.create_map(F.lit("x"), F.lit(0).cast("long")))).cast("long").alias("more"),
    )


MAP_SQL = with_roles(
    "contact",
    """SELECT id, string_agg(kind, ',' ORDER BY kind) AS keys, sum(n)::BIGINT AS total, max(n) FILTER (kind = 'call') AS calls, count(*) FILTER (n >= 10) AS busy, (max(n) FILTER (kind = 'sms') * 2)::BIGINT AS twice, count(*) + 1 AS more
    FROM (SELECT src AS id, kind, count(*) AS n FROM contact GROUP BY 1, 2) GROUP BY id""",
)


def _json(s, d):
    e = T(s, d, "events")
    return e.select(
        "event_id", F.get_json_object("props", "$.k").cast("int").alias("k1"), F.from_json("props", "k INT").getField("k").alias("k2"), F.variant_get(F.parse_json("props"), "$.k", "int").alias("k3"),
        F.to_json(F.struct(F.col("user_id").alias("u"), F.col("event_type").alias("t"))).alias("out"), F.from_xml(F.concat(F.lit("<e><u>"), F.col("user_id"), F.lit("</u></e>")), "u INT").getField("u").alias("x"),
    )


JSON_SQL = with_roles("event", """SELECT event_id, k AS k1, k AS k2, k AS k3, '{"u":' || user_id || ',"t":"' || event_type || '"}' AS out, user_id::INT AS x FROM event""")


def _subqueries(s, d):
    for name in ("customer", "orders"):
        T(s, d, name).createOrReplaceTempView(f"sub_{name}")
    return s.sql(SUBQUERY.format(c="sub_customer", o="sub_orders"))


SUBQUERY = """WITH big AS (SELECT o_custkey, max(o_totalprice) AS top FROM {o} GROUP BY o_custkey)
  SELECT c_custkey, (SELECT count(*) FROM {o} WHERE o_custkey = c_custkey) AS n, top FROM {c} JOIN big ON o_custkey = c_custkey
  WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {c}) AND EXISTS (SELECT 1 FROM {o} x WHERE x.o_custkey = c_custkey AND x.o_totalprice > 200000)
  AND c_nationkey IN (SELECT c_nationkey FROM {c} GROUP BY c_nationkey HAVING count(*) > 2)"""


def _two_hop(s, d):
    """Numbers within two hops of the smallest one, by a recursive expression over the arcs."""
    build_arcs(contact(s, d)).select("src", "dst").createOrReplaceTempView("hop_arcs")
    return s.sql("""WITH RECURSIVE reach(id, hops) AS (SELECT min(src), 0 FROM hop_arcs UNION ALL SELECT dst, hops + 1 FROM reach JOIN hop_arcs ON src = id WHERE hops < 2)
      SELECT id, min(hops) AS hops FROM reach GROUP BY id""")


def _sql_functions(s, d):
    sqlfunctions.register(s)
    N.friends(build_arcs(contact(s, d))).groupBy("id").agg(F.array_sort(F.collect_list("friend")).alias("f")).createOrReplaceTempView("friend_lists")
    return s.sql("""SELECT a.id AS a, b.id AS b, round(friend_jaccard(a.f, b.f), 6) AS jaccard, round(friend_cosine(a.f, b.f), 6) AS cosine
      FROM friend_lists a JOIN friend_lists b ON b.id = a.f[0] WHERE size(a.f) > 3""")


SQL_FUNCTION_SQL = with_roles(
    "contact",
    """SELECT a.id AS a, b.id AS b, round(len(list_intersect(a.f, b.f)) / len(list_distinct(list_concat(a.f, b.f)))::DOUBLE, 6) AS jaccard, round(len(list_intersect(a.f, b.f)) / sqrt(len(a.f)::DOUBLE * len(b.f)), 6) AS cosine
    FROM lists a JOIN lists b ON b.id = a.f[1] WHERE len(a.f) > 3""",
    ARCS, FRIENDS, "lists AS (SELECT id, list_sort(list(friend)) AS f FROM friends GROUP BY id)",
)


def _period_keys(s, d):
    sqlfunctions.register(s)
    T(s, d, "orders").createOrReplaceTempView("period_orders")
    return s.sql("SELECT unit, period, count(*) AS n FROM period_orders, LATERAL period_keys(datediff(DATE '2001-08-01', o_orderdate)) GROUP BY unit, period")


def _nearest(s, d):
    e = T(s, d, "embeddings")
    return X.nearest(e.where("vec_id % 100 = 0"), e, 5).select("query", "vec_id", F.round("cosine", 5).alias("cosine"))


def _vectors(s, d):
    e = T(s, d, "embeddings")
    one = F.array(*[F.lit(1.0)] * 64)
    return e.select("vec_id", F.round(X.dot(F.col("embedding"), F.col("embedding")) + 1e-9, 4).alias("norm2"), F.round(X.dot(F.col("embedding"), one) + 1e-9, 4).alias("total"))



def _naive(df):
    """Zoned times as plain ones, for comparison."""
    return df.select(*[F.col(c).cast("timestamp_ntz").alias(c) if t == "timestamp" else F.col(c) for c, t in df.dtypes])


#: Events of a batch, about.
BATCH = 500_000


def _streamed(s, rows, fn, mode, parts=3, batch=BATCH):
    """What a stream gives at its end: rows land in files in order of their times, each file one batch, so none comes late, and
    a batch and what must be remembered of it stay small however many there are."""
    src, check, cut = new_path(s, "stream-in"), new_path(s, "stream-state"), new_path(s, "stream-parts")
    parts = max(parts, -(-rows.count() // batch))
    ends = rows.agg(F.percentile_approx(F.unix_micros(F.col("ts").cast("timestamp")), [i / parts for i in range(1, parts)], 100 * parts)).first()[0] or []
    part = F.size(F.filter(F.array(*map(F.lit, ends)), lambda end: end < F.unix_micros(F.col("ts").cast("timestamp")))) if ends else F.lit(0)
    rows.withColumn("part", part).repartition("part").write.partitionBy("part").parquet(cut)
    laid = s.read.schema(rows.withColumn("part", part.cast("int")).schema).parquet(cut)
    for i in range(parts):
        laid.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(src)
    return _naive(live.run_to_end(fn(live.event_stream(s, src)), f"stream_{uuid.uuid4().hex}", mode, check))


def _signed(s, d, user=-1):
    """Events, and a last sign far ahead that moves event time past all open windows."""
    events = T(s, d, "events")
    last = events.agg((F.max("event_id") + 1).alias("event_id"), (F.max("ts") + F.expr("INTERVAL 30 DAYS")).alias("ts")).select("event_id", "ts", F.lit(user).cast("long").alias("user_id"), F.lit("view").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    return events.union(last.select(*events.columns))


def _sessions(s, d):
    return _streamed(s, _signed(s, d), live.live_sessions, "append").where("user_id >= 0")


def _once(s, d):
    """Every event, and a third of them again: each id counts once."""
    e = T(s, d, "events")
    got = _streamed(s, e.union(e.where("event_id % 3 = 0")), live.live_once, "append")
    return got.groupBy("event_type").agg(F.count("*").alias("n"))


def _joined(s, d):
    got = _streamed(s, T(s, d, "events"), lambda e: live.live_enrich(e, subscriber(s, d)), "append")
    return got.groupBy("operator", "state").agg(F.count("*").alias("n"))


def _idle(s, d):
    """Idle alarms over all events as one stream; a last sign far ahead moves event time past every user's limit."""
    src, check = new_path(s, "idle-in"), new_path(s, "idle-state")
    events = T(s, d, "events")
    last = events.agg(F.max("event_id").alias("event_id"), (F.max("ts") + F.expr("INTERVAL 30 DAYS")).alias("ts")).select("event_id", "ts", F.lit(-1).cast("long").alias("user_id"), F.lit("view").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    events.union(last.select(*events.columns)).coalesce(1).write.parquet(src)
    got = live.run_to_end(live.live_idle(live.event_stream(s, src)), f"idle_{uuid.uuid4().hex}", "append", check)
    return _naive(got.where("user_id >= 0"))


def _formats(s, d):
    """The same small table through every file format: written, read with its declared schema, counted."""
    nation, schema, out = T(s, d, "nation"), SCHEMAS["nation"], None
    for fmt in ("parquet", "orc", "csv", "json", "xml"):
        path = new_path(s, f"format-{fmt}")
        options = {"csv": {"header": "true"}, "xml": {"rowTag": "row"}}.get(fmt, {})
        nation.write.format(fmt).options(**options).save(path)
        part = s.read.format(fmt).options(**options).schema(schema).load(path).agg(F.count("*").alias("rows"), F.sum("n_nationkey").alias("total"), F.max("n_name").alias("last"))
        part = part.select(F.lit(fmt).alias("fmt"), "rows", "total", "last")
        out = part if out is None else out.union(part)
    path = new_path(s, "format-text")
    nation.select("n_name").write.text(path)
    text = s.read.text(path).agg(F.count("*").alias("rows"), F.lit(None).cast("long").alias("total"), F.max("value").alias("last"))
    return out.union(text.select(F.lit("text").alias("fmt"), "rows", "total", "last"))


def _sketched(s, d):
    """Distinct peers of the last nine months from monthly sketches that merge, so that no month is read twice."""
    rows = contact(s, d).where(in_last(F.col("ts"), BASELINE, 9)).withColumn("period", period_index(F.col("ts"), BASELINE, "month"))
    monthly = rows.groupBy(F.col("src").alias("sub_id"), "period").agg(F.hll_sketch_agg("dst").alias("sketch"))
    return monthly.groupBy("sub_id").agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("peers"))


def _lsh(s, d):
    """Near vectors by random projections: candidates only, for sets too large to compare exactly."""
    return X.near_pairs(T(s, d, "embeddings"), 1.0)


QUERIES = {
    "project": lambda s, d: _rounded(T(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net"), F.struct("l_returnflag", "l_linestatus").alias("s")).select("*", "s.l_returnflag").drop("s").withColumnRenamed("l_returnflag", "flag"), 4),
    "filter": lambda s, d: T(s, d, "orders").where("o_totalprice BETWEEN 1000 AND 150000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE 'F%' AND (nullif(o_custkey, 5) IS NULL OR NOT o_custkey <=> 7) AND o_orderpriority RLIKE '^[12]'").select("o_orderkey"),
    "join_kinds": _joins,
    "join_range": lambda s, d: _rounded(_range(s, d), 3),
    "join_as_of": _as_of,
    "join_interval": _interval,
    "join_salted": lambda s, d: X.salted_join(contact(s, d), subscriber(s, d).select(F.col("sub_id").alias("dst"), "operator"), "dst").groupBy("operator", "kind").agg(F.count("*").alias("n")),
    "join_hints": lambda s, d: T(s, d, "orders").join(T(s, d, "customer").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).join(T(s, d, "nation").hint("broadcast"), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")),
    "aggregates": _aggregates,
    "rollup": lambda s, d: _sets(s, d, "rollup"),
    "cube": lambda s, d: _sets(s, d, "cube"),
    "pivot": lambda s, d: contact(s, d).groupBy(F.col("src").alias("id")).pivot("kind", ["call", "sms", "mms"]).agg(F.count(F.lit(1))),
    "unpivot": lambda s, d: contact(s, d).groupBy(F.col("src").alias("id")).pivot("kind", ["call", "sms", "mms"]).agg(F.count(F.lit(1))).unpivot("id", ["call", "sms", "mms"], "kind", "n").where("n IS NOT NULL"),
    "windows": _windows,
    "top_k": lambda s, d: T(s, d, "customer").orderBy(F.col("c_acctbal").desc_nulls_last(), "c_custkey").offset(5).limit(10).select("c_custkey", "c_acctbal"),
    "top_k_group": lambda s, d: X.top_k(T(s, d, "customer"), ["c_mktsegment"], [F.desc("c_acctbal"), "c_custkey"], 3).select("c_mktsegment", "c_custkey", F.col("place").cast("long").alias("place")),
    "set_operations": _set_ops,
    "strings": _strings,
    "dates": _dates,
    "numbers": _math,
    "arrays": _arrays,
    "maps": _maps,
    "json_xml": _json,
    "subqueries": _subqueries,
    "recursive_hops": _two_hop,
    "sql_functions": _sql_functions,
    "table_function": _period_keys,
    "hash_sample": lambda s, d: X.hash_sample(T(s, d, "customer"), "c_custkey", 0.1).select("c_custkey"),
    "nearest_vectors": _nearest,
    "vector_math": _vectors,
    "vector_lsh": _lsh,
    "usage_sketch": _sketched,
    "file_formats": _formats,
    "stream_idle": _idle,
    "stream_tumbling": lambda s, d: _rounded(_streamed(s, T(s, d, "events"), live.live_usage, "complete"), 3),
    "stream_sliding": lambda s, d: _rounded(_streamed(s, T(s, d, "events"), live.live_sliding, "complete"), 3),
    "stream_session": _sessions,
    "stream_dedup": _once,
    "stream_enrich": _joined,
}

ORACLES = {
    "usage_sketch": with_roles("contact", f"SELECT src AS sub_id, count(DISTINCT dst) AS peers FROM contact WHERE ts >= '{months_before(BASELINE, 9)}' AND ts < '{BASELINE}' GROUP BY src"),  # sketches of few values are exact
    "file_formats": " UNION ALL ".join(f"SELECT '{f}' AS fmt, count(*) AS rows, {'NULL' if f == 'text' else 'sum(n_nationkey)'}::BIGINT AS total, max(n_name) AS last FROM nation" for f in ("parquet", "orc", "csv", "json", "xml", "text")),
    "project": f"SELECT l_orderkey, l_linenumber, l_partkey, {_r('l_extendedprice * (1 - l_discount)', 'net', 4)}, l_returnflag AS flag FROM lineitem",
    "filter": "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 150000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE 'F%' AND (nullif(o_custkey, 5) IS NULL OR o_custkey IS DISTINCT FROM 7)",
    "join_kinds": JOINS_SQL,
    "join_range": with_roles("contact", f"SELECT band, count(*) AS n, {_r('sum(duration)', 'total', 3)} FROM contact JOIN (VALUES {', '.join(map(str, BANDS))}) b(low, high, band) ON duration >= low AND duration < high WHERE kind = 'call' GROUP BY band"),
    "join_as_of": """SELECT c.event_id, b.event_id AS buy_id, b.value AS bought FROM (SELECT * FROM events WHERE event_type = 'click') c ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') b ON c.user_id = b.user_id AND c.ts >= b.ts""",
    "join_interval": "SELECT e.event_id AS error_id, v.event_id FROM events e JOIN events v ON e.user_id = v.user_id AND v.ts >= e.ts AND v.ts <= e.ts + INTERVAL 6 HOUR WHERE e.event_type = 'error' AND v.event_type = 'view'",
    "join_salted": with_roles("contact subscriber", "SELECT operator, kind, count(*) AS n FROM contact JOIN subscriber ON sub_id = dst GROUP BY ALL"),
    "join_hints": "SELECT n_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
    "aggregates": AGG_SQL,
    "rollup": _sets_sql("ROLLUP"),
    "cube": _sets_sql("CUBE"),
    "pivot": with_roles("contact", "SELECT src AS id, " + ", ".join(f"nullif(count(*) FILTER (kind = '{k}'), 0) AS {k}" for k in ("call", "sms", "mms")) + " FROM contact GROUP BY src"),
    "unpivot": with_roles("contact", "SELECT src AS id, kind, count(*) AS n FROM contact GROUP BY ALL"),
    "windows": WINDOW_SQL,
    "top_k": "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 5",
    "top_k_group": "SELECT c_mktsegment, c_custkey, place FROM (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS place FROM customer) WHERE place <= 3",
    "set_operations": SET_SQL,
    "strings": STRING_SQL,
    "dates": DATE_SQL,
    "numbers": MATH_SQL,
    "arrays": ARRAY_SQL,
    "maps": MAP_SQL,
    "json_xml": JSON_SQL,
    "subqueries": SUBQUERY.format(c="customer", o="orders"),
    "recursive_hops": with_roles("contact", "SELECT id, min(hops)::INT AS hops FROM reach GROUP BY id", ARCS, "reach AS (SELECT min(src) AS id, 0 AS hops FROM arcs UNION ALL SELECT dst, hops + 1 FROM reach JOIN arcs ON src = id WHERE hops < 2)"),
    "sql_functions": SQL_FUNCTION_SQL,
    "table_function": " UNION ALL ".join(f"SELECT '{u}' AS unit, ((b - 1) // {n} + 1)::INT AS period, count(*) AS n FROM (SELECT date_diff('day', o_orderdate::DATE, DATE '2001-08-01') AS b FROM orders) WHERE b >= 1 GROUP BY 2" for u, n in (("day", 1), ("week", 7), ("month", 30))),
    "hash_sample": f"SELECT c_custkey FROM customer WHERE {draw_sql('c_custkey', 'sample')} < 0.1",
    "nearest_vectors": """SELECT query, vec_id, round(c, 5) AS cosine FROM (SELECT q.vec_id AS query, e.vec_id, list_cosine_similarity(q.embedding::DOUBLE[], e.embedding::DOUBLE[]) AS c,
      row_number() OVER (PARTITION BY q.vec_id ORDER BY list_cosine_similarity(q.embedding::DOUBLE[], e.embedding::DOUBLE[]) DESC, e.vec_id) AS place FROM embeddings q JOIN embeddings e ON q.vec_id <> e.vec_id WHERE q.vec_id % 100 = 0) WHERE place <= 5""",
    "vector_math": "SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]) + 1e-9, 4) AS norm2, round(list_sum(embedding::DOUBLE[]) + 1e-9, 4) AS total FROM embeddings",
    "stream_tumbling": f"SELECT date_trunc('day', ts)::TIMESTAMP AS start, user_id, count(*) AS n, {_r('sum(value)', 'total', 3)} FROM events GROUP BY ALL",
    "stream_sliding": f"""SELECT start, event_type, count(*) AS n, {_r('sum(value)', 'total', 3)} FROM events, (SELECT unnest(generate_series(TIMESTAMP '2023-12-01', TIMESTAMP '2024-03-01', INTERVAL 1 DAY)) AS start)
      WHERE (epoch(start)::BIGINT // 86400) % 3 = 0 AND ts >= start AND ts < start + INTERVAL 9 DAY GROUP BY ALL""",
    "stream_session": """SELECT min(ts) AS start, max(ts) + INTERVAL 12 HOUR AS "end", user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS run FROM
      (SELECT *, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, run""",
    "stream_dedup": "SELECT event_type, count(*) AS n FROM events GROUP BY event_type",
    "stream_enrich": with_roles("subscriber", "SELECT operator, state, count(*) AS n FROM events LEFT JOIN subscriber ON sub_id = user_id GROUP BY ALL"),
}
