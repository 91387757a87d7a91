"""Named queries over profile, refining, measures and learners, with the SQL that each must equal where SQL can."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import draw, draw_sql

from ..operators import learners as LR
from ..operators import measures as M
from ..operators import profile as P
from ..operators import refine as R
from ..operators import resample as B
from ..operators.second_order import all_splits
from ..sources import landing as L
from ..sources.tables import document_label, read_table, session, subscriber, text_shape, with_roles
from . import experiments as X
from .usage_queries import LABEL, _features, _labels, _r, _rounded

#: Columns of the table that profile and refining queries look at: holes, constants, copies and few values on purpose.
HOLES = {
    "sub_id": "c_custkey",
    "name": "c_name",
    "balance": "c_acctbal",
    "segment": "c_mktsegment",
    "nation": "c_nationkey",
    "nation_copy": "c_nationkey",
    "one": "1",
    "nothing": "CAST(NULL AS DOUBLE)",
    "flag": "c_custkey % 2",
    "mostly_zero": "CASE WHEN c_custkey % 50 = 0 THEN c_acctbal ELSE 0.0 END",
    "rare": "CASE WHEN c_custkey % 100 = 0 THEN c_acctbal END",
    "half": "CASE WHEN c_custkey % 2 = 0 THEN c_acctbal END",
    "double_balance": "c_acctbal * 2",
    "holed_segment": "CASE WHEN c_custkey % 10 > 0 THEN c_mktsegment END",
    "many": "concat('v', CAST(c_custkey % 40 AS VARCHAR({n})))",
}


def _holes(s, d):
    return read_table(s, d, "customer").selectExpr(*[f"{e.replace('VARCHAR({n})', 'STRING')} AS {c}" for c, e in HOLES.items()])


HOLES_SQL = "holes AS (SELECT " + ", ".join(f"{e.replace('VARCHAR({n})', 'VARCHAR')} AS {c}" for c, e in HOLES.items()) + " FROM customer)"
NUMERIC = ["balance", "nation", "one", "nothing", "flag", "mostly_zero", "rare", "half", "double_balance"]
CATEGORY = ["name", "segment", "holed_segment", "many"]


def _profile(columns):
    return lambda s, d: _rounded(P.profile(_holes(s, d), columns))


def _names(fn, **options):
    """The columns that an operator picks, as a table."""
    return lambda s, d: s.createDataFrame([(c,) for c in fn(_holes(s, d), **options)], "column STRING")


def _text_scores(s, d):
    """Documents scored by their share of characters that are not letters."""
    return document_label(s, d).select(F.col("doc_id").alias("sub_id"), "label", F.round("non_letters", 6).alias("score"))


def _refined(s, d):
    base = _features(s, d).join(_labels(s, d), "sub_id")
    parts = B.split(base)
    model = R.Refiner(keys=("sub_id", "label", "part")).fit(parts.where("part = 'train'"))
    return model.transform(parts)


def _stability(s, d):
    orders = read_table(s, d, "orders")
    old = orders.where("o_orderdate < '1998-01-01'").select(F.col("o_totalprice").alias("price"))
    new = orders.where("o_orderdate >= '1998-01-01'").select(F.col("o_totalprice").alias("price"))
    return _rounded(M.stability_index(old, new, "price"))


def _campaign(s, d):
    outcome = _labels(s, d).withColumnRenamed("label", "left")
    people = subscriber(s, d)
    scored = people.select("sub_id", draw(F.col("sub_id"), "score").alias("score"))
    offered = people.where(draw(F.col("sub_id"), "offer") < 0.5).select("sub_id")
    return M.campaign_outcome(scored, offered, outcome)


def _split_gain(s, d):
    """Cuts of the documents' two counts at the root, with the first step's gradients and curvatures."""
    rows = document_label(s, d).select("label", F.array(F.least(F.floor(F.col("words") / 50), F.lit(20)).cast("int"), F.least(F.floor(F.col("chars") / 300), F.lit(20)).cast("int")).alias("b"))
    each = rows.select("label", F.posexplode("b").alias("feature", "bin"))
    hist = each.groupBy(F.lit(0).cast("long").alias("node"), "feature", "bin").agg(F.sum(F.lit(0.5) - F.col("label")).alias("g"), F.sum(F.lit(0.25)).alias("h"))
    return _rounded(all_splits(hist).select("feature", "bin", "gain"))


def _fit(learner):
    def query(s, d):
        train, test, features = X.document_task(s, d)
        return LR.LEARNERS[learner](train, features, **LR.SMALL[learner]).score(test)

    return query


def _score(s, d):
    """A model of the labelled documents scores all others, whose label nobody knows."""
    train, _, features = X.document_task(s, d)
    model = LR.second(train, features, **LR.SMALL["boosted_second"])
    rest = text_shape(s, d).join(read_table(s, d, "labels").select("doc_id"), "doc_id", "left_anti")
    return model.model.score(rest, ["doc_id"])


def _importance(s, d):
    train, _, features = X.document_task(s, d)
    return LR.second(train, features, **LR.SMALL["boosted_second"]).importance(s)


def _storage(s, d):
    return L.storage_trial(read_table(s, d, "lineitem"), "l_extendedprice", "l_returnflag")


def _land(s, d):
    from ..functions.scratch import new_path

    src, dst = new_path(s, "spool-in"), new_path(s, "spool-out")
    read_table(s, d, "nation").coalesce(1).write.option("header", True).csv(src)
    L.spool(s, src, dst, "csv", "n_nationkey INT, n_name STRING, n_regionkey INT")
    return s.read.schema("n_nationkey INT, n_name STRING, n_regionkey INT").option("header", True).csv(f"{dst}/data")


QUERIES = {
    "profile_numeric": _profile(NUMERIC),
    "profile_category": _profile(CATEGORY),
    "profile_constant": lambda s, d: _rounded(P.profile_summary(P.profile(_holes(s, d), NUMERIC + CATEGORY))),
    "profile_sparse": lambda s, d: P.profile(_holes(s, d), NUMERIC).where("zero_or_null_share > 0.97").select("column"),
    "profile_missing": lambda s, d: P.profile(_holes(s, d)).where("nulls > 0.98 * n").select("column"),
    "class_share": lambda s, d: _rounded(P.class_share(_labels(s, d))),
    "null_columns": lambda s, d: P.all_null_columns(_holes(s, d)),
    "dist_category": lambda s, d: _rounded(P.class_categories(_labels(s, d).join(subscriber(s, d), "sub_id"), "segment")),
    "dist_numeric": lambda s, d: P.class_histogram(_labels(s, d).join(subscriber(s, d), "sub_id"), "balance"),
    "drop_identifiers": _names(R.identifiers, keys=("sub_id",)),
    "drop_constant": _names(R.constants, keys=("sub_id",)),
    "duplicate_columns": lambda s, d: s.createDataFrame([(c,) for c in R.duplicates(_holes(s, d), "sub_id")], "column STRING"),
    "few_values": _names(R.few_values, keys=("sub_id",)),
    "drop_any_null": _names(R.with_any_null, keys=("sub_id",)),
    "drop_sparse_rows": lambda s, d: R.drop_sparse_rows(_holes(s, d).select("sub_id", "nothing", "rare", "half", "holed_segment"), ("sub_id",), 0.5).select("sub_id"),
    "drop_sparse_columns": _names(R.sparse_columns, keys=("sub_id",)),
    "fill_category": lambda s, d: R.fill_category(_holes(s, d), ["holed_segment"]).groupBy("holed_segment").agg(F.count("*").alias("rows")),
    "fill_mean": lambda s, d: _rounded(R.fill_mean(_holes(s, d), R.means(_holes(s, d), ["half"])).select("sub_id", "half")),
    "top_categories": lambda s, d: R.keep_categories(_holes(s, d), {"many": R.top_categories(_holes(s, d), "many")}).groupBy("many").agg(F.count("*").alias("rows")),
    "pearson_pairs": lambda s, d: _rounded(R.pearson(_holes(s, d), ["balance", "nation", "double_balance", "mostly_zero", "one"])),
    "refined": _refined,
    "split_gain": _split_gain,
    "auc": lambda s, d: _rounded(M.auc(_text_scores(s, d))),
    "roc": lambda s, d: _rounded(M.roc(_text_scores(s, d))),
    "confusion": lambda s, d: _rounded(M.confusion(_text_scores(s, d), 0.15)),
    "top_lift": lambda s, d: _rounded(M.top_lift(_text_scores(s, d), 20)),
    "stability_index": _stability,
    "campaign_outcome": lambda s, d: _rounded(_campaign(s, d)),
    "campaign_value": lambda s, d: _rounded(M.campaign_value(_campaign(s, d))),
    "internet_churners": lambda s, d: _rounded(M.internet_churners(_labels(s, d), session(s, d))),
    "fit_tree": _fit("decision_tree"),
    "fit_forest": _fit("random_forest"),
    "fit_first": _fit("boosted_first"),
    "fit_second": _fit("boosted_second"),
    "fit_capped": _fit("capped_tree"),
    "score": _score,
    "importance": _importance,
    "storage_trial": _storage,
    "land_spool": _land,
}

# ---------------------------------------------------------------- SQL


def _profile_row(c, number):
    real = f"{c}::DOUBLE" if number else "NULL::DOUBLE"
    zeros = f"count(*) FILTER ({c} = 0)" if number else "0::BIGINT"
    return f"""SELECT '{c}' AS "column", '{"number" if number else "category"}' AS kind, count(*) AS n, count(*) - count({c}) AS nulls, {zeros} AS zeros,
      {_r(f"(count(*) - count({c}) + {zeros}) / count(*)::DOUBLE", "zero_or_null_share")}, count(DISTINCT {c}) AS distinct,
      {_r(f"coalesce((SELECT max(k) FROM (SELECT count(*) AS k FROM holes WHERE {c} IS NOT NULL GROUP BY {c})), 0) / count(*)::DOUBLE", "top_share")},
      {_r(f"min({real})", "low")}, {_r(f"max({real})", "high")}, {_r(f"avg({real})", "mean")}, {_r(f"stddev({real})", "stddev")} FROM holes"""


def _columns(condition, columns):
    rows = " UNION ALL ".join(f"""SELECT '{c}' AS "column", {condition.format(c=c)} AS ok FROM holes""" for c in columns)
    return f"""WITH {HOLES_SQL} SELECT "column" FROM ({rows}) WHERE ok"""


ALL = [c for c in HOLES if c != "sub_id"]
SCORES = """scores AS (SELECT doc_id AS sub_id, 1 - quality AS label, round((length(text) - length(regexp_replace(text, '[^A-Za-zÀ-ɏ\\s]', '', 'g'))) / greatest(length(text), 1)::DOUBLE, 6) AS score
  FROM documents JOIN labels USING (doc_id))"""
CAMPAIGN = f"""{LABEL}, rows_ AS (SELECT {draw_sql("sub_id", "offer")} < 0.5 AS offered, label FROM labelled WHERE {draw_sql("sub_id", "score")} >= 0.5),
  groups AS (SELECT offered, count(*) AS predicted, sum(label)::BIGINT AS n_left, 1 - avg(label) AS retained FROM rows_ GROUP BY offered),
  campaign AS (SELECT offered, predicted, n_left, retained, (SELECT 1 - retained FROM groups WHERE NOT offered) - (1 - retained) AS change FROM groups)"""
PSI = """p AS (SELECT o_totalprice AS v, o_orderdate >= '1998-01-01' AS late FROM orders), e AS (SELECT min(v) AS lo, max(v) AS hi FROM p WHERE NOT late),
  b AS (SELECT greatest(0, least(9, floor((v - lo) / (hi - lo) * 10))) AS bin, count(*) FILTER (NOT late) AS a, count(*) FILTER (late) AS b FROM p, e GROUP BY 1),
  s AS (SELECT (a + 0.5) / (sum(a) OVER () + 5)::DOUBLE AS x, (b + 0.5) / (sum(b) OVER () + 5)::DOUBLE AS y FROM b)"""

ORACLES = {
    "profile_numeric": f"WITH {HOLES_SQL} " + " UNION ALL ".join(_profile_row(c, True) for c in NUMERIC),
    "profile_category": f"WITH {HOLES_SQL} " + " UNION ALL ".join(_profile_row(c, False) for c in CATEGORY),
    "profile_constant": f"""WITH {HOLES_SQL}, p AS ({" UNION ALL ".join(f"SELECT {c in NUMERIC} AS number, count(*) AS n, count(*) - count({c}) AS nulls, count(DISTINCT {c}) AS d, "
      + (f"count(*) FILTER ({c} = 0)" if c in NUMERIC else "0") + " AS z FROM holes" for c in NUMERIC + CATEGORY)})
      SELECT 'numbers with one or two values' AS measure, {_r("avg((d <= 2)::INT) FILTER (number)", "share")} FROM p
      UNION ALL SELECT 'categories with fewer than ten values', {_r("avg((d < 10)::INT) FILTER (NOT number)", "share")} FROM p
      UNION ALL SELECT 'numbers with one value', {_r("avg((d <= 1)::INT) FILTER (number)", "share")} FROM p
      UNION ALL SELECT 'categories with one value', {_r("avg((d <= 1)::INT) FILTER (NOT number)", "share")} FROM p
      UNION ALL SELECT 'numbers over 97% zero or null', {_r("avg(((nulls + z) / n::DOUBLE > 0.97)::INT) FILTER (number)", "share")} FROM p
      UNION ALL SELECT 'columns over 98% missing', {_r("avg((nulls / n::DOUBLE > 0.98)::INT)", "share")} FROM p""",
    "profile_sparse": _columns("(count(*) - count({c}) + count(*) FILTER ({c} = 0)) / count(*)::DOUBLE > 0.97", NUMERIC),
    "profile_missing": _columns("count(*) - count({c}) > 0.98 * count(*)", list(HOLES)),
    "class_share": f"WITH {LABEL}, c AS (SELECT label, count(*) AS rows FROM labelled GROUP BY label) SELECT label, rows, {_r('rows / sum(rows) OVER ()::DOUBLE', 'share')}, min(rows) OVER () / max(rows) OVER ()::DOUBLE <= 0.1 AS unbalanced FROM c",
    "null_columns": _columns("count({c}) = 0", list(HOLES)),
    "dist_category": with_roles("subscriber", f"SELECT label, segment AS value, count(*) AS rows, {_r('count(*) / sum(count(*)) OVER (PARTITION BY label)::DOUBLE', 'share')} FROM labelled JOIN subscriber USING (sub_id) GROUP BY label, segment", LABEL),
    "dist_numeric": with_roles(
        "subscriber",
        """SELECT label, least(floor((balance - lo) / (hi - lo) * 10), 9)::INT AS bin, count(*) AS rows FROM labelled JOIN subscriber USING (sub_id), (SELECT min(balance) AS lo, max(balance) AS hi FROM subscriber) GROUP BY ALL""",
        LABEL,
    ),
    "drop_identifiers": _columns("count({c}) > 1 AND count(DISTINCT {c}) = count({c})", ["name", "segment", "nation", "nation_copy", "one", "flag", "holed_segment", "many"]),
    "drop_constant": _columns("count(DISTINCT {c}) = 0 OR count(DISTINCT {c}) = 1 AND count({c}) = count(*)", ALL),
    "duplicate_columns": f"WITH {HOLES_SQL}, p AS ("
    + " UNION ALL ".join(f"SELECT '{b}' AS \"column\", count(*) FILTER ({a}::VARCHAR IS DISTINCT FROM {b}::VARCHAR) AS differ FROM holes" for i, b in enumerate(ALL) for a in ALL[:i])
    + """) SELECT DISTINCT "column" FROM p WHERE differ = 0""",
    "few_values": _columns("count(DISTINCT {c}) <= 2", [*NUMERIC, "nation_copy"]),
    "drop_any_null": _columns("count({c}) < count(*)", ALL),
    "drop_sparse_rows": f"WITH {HOLES_SQL} SELECT sub_id FROM holes WHERE ((nothing IS NULL)::INT + (rare IS NULL)::INT + (half IS NULL)::INT + (holed_segment IS NULL)::INT) / 4.0 <= 0.5",
    "drop_sparse_columns": _columns("(count(*) - count({c})) / count(*)::DOUBLE > 0.7", ALL),
    "fill_category": f"WITH {HOLES_SQL} SELECT coalesce(holed_segment, 'Other') AS holed_segment, count(*) AS rows FROM holes GROUP BY 1",
    "fill_mean": f"WITH {HOLES_SQL} SELECT sub_id, {_r('coalesce(half, (SELECT avg(half) FROM holes))', 'half')} FROM holes",
    "top_categories": f"""WITH {HOLES_SQL}, t AS (SELECT many FROM holes GROUP BY many ORDER BY count(*) DESC, many LIMIT 31)
      SELECT CASE WHEN many IN (SELECT many FROM t) THEN many ELSE 'Other' END AS many, count(*) AS rows FROM holes GROUP BY 1""",
    "pearson_pairs": f"WITH {HOLES_SQL} "
    + " UNION ALL ".join(
        f"SELECT '{a}' AS left_col, '{b}' AS right_col, " + ("NULL::DOUBLE AS r" if "one" in (a, b) else _r(f"corr({a}, {b})", "r")) + " FROM holes" + " GROUP BY ()"
        for i, a in enumerate(["balance", "nation", "double_balance", "mostly_zero", "one"]) for b in ["balance", "nation", "double_balance", "mostly_zero", "one"][i + 1 :]
    ),
    "split_gain": f"""WITH r AS (SELECT 1 - quality AS y, least(floor(length(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')) / 50), 20)::INT AS b0, least(floor(greatest(length(text), 1) / 300), 20)::INT AS b1 FROM documents JOIN labels USING (doc_id)),
      h AS (SELECT 0 AS feature, b0 AS bin, sum(0.5::DOUBLE - y) AS g, sum(0.25::DOUBLE) AS h FROM r GROUP BY b0 UNION ALL SELECT 1, b1, sum(0.5::DOUBLE - y), sum(0.25::DOUBLE) FROM r GROUP BY b1),
      c AS (SELECT feature, bin, sum(g) OVER o AS gl, sum(h) OVER o AS hl, sum(g) OVER w AS gt, sum(h) OVER w AS ht, max(bin) OVER w AS last FROM h WINDOW w AS (PARTITION BY feature), o AS (PARTITION BY feature ORDER BY bin ROWS UNBOUNDED PRECEDING))
      SELECT feature, bin, {_r("0.5 * (gl * gl / (hl + 1) + (gt - gl) * (gt - gl) / (ht - hl + 1) - gt * gt / (ht + 1))", "gain")} FROM c WHERE bin < last""",
    "auc": f"WITH {SCORES} SELECT {_r('avg(CASE WHEN p.score > n.score THEN 1.0::DOUBLE WHEN p.score = n.score THEN 0.5 ELSE 0 END)', 'auc')} FROM scores p JOIN scores n ON p.label = 1 AND n.label = 0",
    "roc": f"""WITH {SCORES}, c AS (SELECT score, sum(label) AS p, sum(1 - label) AS n FROM scores GROUP BY score)
      SELECT {_r("score", "cut")}, {_r("sum(p) OVER o / (SELECT sum(p) FROM c)::DOUBLE", "tpr")}, {_r("sum(n) OVER o / (SELECT sum(n) FROM c)::DOUBLE", "fpr")} FROM c WINDOW o AS (ORDER BY score DESC ROWS UNBOUNDED PRECEDING)
      UNION ALL SELECT NULL, {_r("0.0::DOUBLE", "tpr")}, {_r("0.0::DOUBLE", "fpr")}""",
    "confusion": f"""WITH {SCORES}, c AS (SELECT count(*) FILTER (score >= 0.15 AND label = 1) AS tp, count(*) FILTER (score >= 0.15 AND label = 0) AS fp, count(*) FILTER (score < 0.15 AND label = 1) AS fn,
      count(*) FILTER (score < 0.15 AND label = 0) AS tn FROM scores) SELECT tp, fp, fn, tn, {_r("tp / (tp + fp)::DOUBLE", "precision")}, {_r("tp / (tp + fn)::DOUBLE", "recall")} FROM c""",
    "top_lift": f"""WITH {SCORES} SELECT 20::INT AS k, sum(label)::BIGINT AS positives, {_r("avg(label)", "share")}, {_r("avg(label) / (SELECT avg(label) FROM scores)", "lift")} FROM (SELECT label FROM scores ORDER BY score DESC, sub_id LIMIT 20)""",
    "stability_index": f"WITH {PSI} SELECT 'price' AS column, {_r('sum((x - y) * ln(x / y))', 'psi')} FROM s",
    "campaign_outcome": f"WITH {CAMPAIGN} SELECT offered, predicted, n_left, {_r('retained', 'retained_share')}, {_r('change')} FROM campaign",
    "campaign_value": f"WITH {CAMPAIGN} SELECT offered, predicted, n_left, {_r('retained', 'retained_share')}, {_r('change')}, {_r('CASE WHEN offered THEN (predicted - n_left) * 6.0::DOUBLE - predicted ELSE 0 END', 'saved')} FROM campaign",
    "internet_churners": with_roles(
        "session",
        f"""SELECT count(*) AS churners, {_r("avg(CASE WHEN coalesce(n, 0) > 0 THEN 1.0 ELSE 0.0 END)", "internet_share")}, {_r("avg(CASE WHEN n > 0 THEN CASE WHEN level < 2.5 THEN 1.0 WHEN level >= 2.5 THEN 0.0 END END)", "low_share")}
        FROM labelled LEFT JOIN (SELECT sub_id, avg(CASE rat WHEN '2G' THEN 2.0 WHEN '3G' THEN 3.0 END) AS level, count(*) FILTER (bytes_down + bytes_up > 0) AS n FROM session GROUP BY sub_id) USING (sub_id) WHERE label = 1""",
        LABEL,
    ),
    "land_spool": "SELECT * FROM nation",
}

