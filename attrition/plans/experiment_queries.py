"""The workloads as named queries, with the SQL that those without fitted models or times must equal."""

from __future__ import annotations

from ..functions.periods import BASELINE, months_before
from . import experiments as X
from . import graph_queries as GQ
from . import model_queries as MQ
from . import usage_queries as UQ

QUERIES = {f"experiment_{k}": (lambda s, d, k=k: X.run(k, s, d)) for k in X.WORKLOADS}


def _oracles() -> dict[str, str]:
    """What SQL can tell of the workloads: everything but fitted models and times."""
    every = "contact subscriber session ticket"
    names = [*UQ.LONG[:9], "idle_days", "line_age", "other_share", "complaints", "coverage_share", "mean_hours", "share_2g", "share_3g", "share_4g", "drop_share", "balance", "age_years"]
    kinds = {"sub_id": True} | {c: True for c in names}
    columns = " UNION ALL ".join(f"SELECT true AS number, count(*) AS n, count(*) - count({c}) AS nulls, count(DISTINCT {c}) AS d, count(*) FILTER ({c} = 0) AS z FROM features" for c in kinds)
    share = lambda what, among="true": f"round(avg(({what})::INT) FILTER ({among}) + 1e-9, 6)"
    measures = {
        "numbers with one or two values": share("d <= 2"), "categories with fewer than ten values": "max(NULL::DOUBLE)", "numbers with one value": share("d <= 1"),
        "categories with one value": "max(NULL::DOUBLE)", "numbers over 97% zero or null": share("(nulls + z) / n::DOUBLE > 0.97"), "columns over 98% missing": share("nulls / n::DOUBLE > 0.98"),
    }
    features = f"features AS ({UQ.FEATURES})"
    size = lambda m: f"SELECT {'NULL' if m is None else m}::INT AS months, (SELECT count(*) FROM (SELECT src FROM a{m} UNION SELECT dst FROM a{m})) AS nodes, (SELECT count(*) FROM a{m}) AS arcs"
    arcs = lambda m: f"a{m} AS (SELECT DISTINCT src, dst FROM contact WHERE ts < '{BASELINE}'" + ("" if m is None else f" AND ts >= '{months_before(BASELINE, m)}'") + ")"
    couples = lambda m: f"SELECT {m}::INT AS months, count(*) AS couples FROM (SELECT DISTINCT x.id, y.id FROM f{m} x JOIN f{m} y ON x.friend = y.friend AND x.id < y.id)"
    friends = lambda m: f"f{m} AS (SELECT src AS id, dst AS friend FROM a{m} UNION SELECT dst, src FROM a{m})"
    bin_of = lambda c: f"SELECT '{c}' AS column, label, CASE WHEN {c} IS NULL THEN '-1' ELSE least(coalesce(floor(({c} - lo) / nullif(hi - lo, 0) * 10), 9), 9)::INT::VARCHAR END AS value, count(*) AS rows FROM classes, (SELECT min({c})::DOUBLE AS lo, max({c})::DOUBLE AS hi FROM classes) GROUP BY ALL"
    by_value = lambda c: f"SELECT '{c}' AS column, label, {c} AS value, count(*) AS rows FROM classes GROUP BY ALL"
    raw = [c for c in X.NUMBERS if c not in ("balance", "age_years")]
    classes = f"classes AS (SELECT {', '.join(f'q.{c}' for c in raw)}, s.balance, s.age_years, {', '.join(f's.{c}' for c in X.CATEGORIES)}, label FROM raw_features q JOIN subscriber s USING (sub_id) JOIN labelled USING (sub_id))"
    nine = f"arcs AS (SELECT DISTINCT src, dst FROM contact WHERE ts >= '{months_before(BASELINE, 9)}' AND ts < '{BASELINE}')"
    return {
        "experiment_w2": UQ.with_roles(every, " UNION ALL ".join(f"SELECT '{k}' AS measure, {v} AS share FROM p" for k, v in measures.items()), *UQ.BLOCKS, features, f"p AS ({columns})"),
        "experiment_w11": UQ.with_roles(
            "contact subscriber",
            """SELECT x.id, x.week, round(max(common / sqrt(p.deg::DOUBLE * q.deg)), 6) AS max_cos_rival FROM couples x
            JOIN wdeg p ON p.week = x.week AND p.id = x.id JOIN wdeg q ON q.week = x.week AND q.id = x.second GROUP BY x.id, x.week""",
            f"""w AS (SELECT src, dst, (15 - ((date_diff('day', ts::DATE, DATE '{BASELINE}') - 1) // 7 + 1))::INT AS week,
            src IN (SELECT sub_id FROM subscriber WHERE operator = 'home') AS home FROM contact WHERE ts < '{BASELINE}')""",
            """c AS (SELECT src, dst, week FROM w WHERE week BETWEEN 1 AND 14 AND NOT (home AND week >= 13)
            UNION ALL SELECT -1 - src, dst, week FROM w WHERE home AND week BETWEEN 7 AND 14 AND dst % 8 <= week - 7)""",
            "wf AS (SELECT week, src AS id, dst AS friend FROM c UNION SELECT week, dst, src FROM c)",
            "wdeg AS (SELECT week, id, count(*) AS deg FROM wf GROUP BY week, id)",
            """couples AS (SELECT x.week, x.id, y.id AS second, count(*) AS common FROM wf x JOIN wf y ON x.week = y.week AND x.friend = y.friend
            WHERE x.id IN (SELECT sub_id FROM subscriber WHERE operator = 'home') AND y.id < 0 GROUP BY ALL)""",
        ),
        "experiment_w12": UQ.with_roles(every, " UNION ALL ".join([*map(bin_of, X.NUMBERS), *map(by_value, X.CATEGORIES)]), *UQ.BLOCKS, f"raw_features AS (SELECT sub_id, {', '.join(raw)} FROM {UQ.FROM_ALL})", UQ.LABEL, classes),
        "experiment_w15": UQ.with_roles("contact", " UNION ALL ".join(map(size, (4, 9, None))), *map(arcs, (4, 9, None))),
        "experiment_w16": UQ.with_roles("contact", " UNION ALL ".join(map(couples, (4, 9, 24))), *map(arcs, (4, 9, 24)), *map(friends, (4, 9, 24))),
        "experiment_w18": UQ.with_roles("contact", "SELECT id, round(value, 6) AS value FROM lcc WHERE value <= (SELECT quantile_disc(value, 0.1) FROM lcc)", nine, GQ.FRIENDS, GQ.DEG, GQ.TRIANGLES, GQ.LCC),
        "experiment_w19": MQ.ORACLES["internet_churners"],
    }


ORACLES = _oracles()
