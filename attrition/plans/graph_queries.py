"""Named queries over the contact graph, with the SQL that each must equal."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.periods import BASELINE, months_before
from ..operators import contact_graph as G
from ..operators import ranks as R
from ..operators import similarity as S
from ..operators import structure as N
from ..sources.tables import contact, subscriber, touch, with_roles

MONTHS, ROUNDS = 4, 10


def _arcs(spark, d, months=MONTHS):
    return G.build_arcs(contact(spark, d), months=months)


def _nodes(spark, d, arcs):
    return G.build_nodes(arcs, subscriber(spark, d))


def _pairs(spark, d):
    return N.friends(_arcs(spark, d))


def _rank(kind, weight="w_count", **options):
    def query(spark, d):
        arcs = _arcs(spark, d)
        got = getattr(R, kind)(G.build_nodes(arcs), G.weigh(arcs), weight, rounds=ROUNDS, **options)
        return got.select("id", F.round(F.col("rank") + 1e-9, 6).alias("rank"))

    return query


def _all_ranks(spark, d):
    arcs = _arcs(spark, d)
    got = R.all_ranks(G.build_nodes(arcs), G.weigh(arcs), rounds=ROUNDS)
    return got.select("id", *[F.round(F.col(c) + 1e-9, 6).alias(c) for c in got.columns[1:]])


def _power(spark, d):
    arcs = _arcs(spark, d)
    got = R.all_ranks(G.build_nodes(arcs), G.weigh(arcs), rounds=ROUNDS)
    return R.power(got).select("id", F.round(F.col("power") + 1e-9, 6).alias("power"))


def _rank_damping(spark, d):
    """Three dampings and both policies that keep mass, on the touch graph, which has sinks."""
    t = touch(spark, d)
    arcs = t.groupBy("src", "dst").agg(F.count("*").alias("n_events"), F.sum("value").alias("talk"))
    nodes, out = G.build_nodes(arcs), None
    for damping in (0.5, 0.85, 0.95):
        for sinks in ("leak", "spread", "self"):
            part = R.receive_rank(nodes, arcs, "n_events", d=damping, sinks=sinks, rounds=ROUNDS)
            row = part.agg(F.round(F.sum("rank"), 6).alias("total"), F.round(F.max("rank"), 6).alias("highest"))
            row = row.select(F.lit(damping).alias("damping"), F.lit(sinks).alias("sinks"), "total", "highest")
            out = row if out is None else out.union(row)
    return out


def _couples(spark, d):
    return S.similar_pairs(_pairs(spark, d))


def _home(spark, d):
    arcs = _arcs(spark, d)
    nodes = _nodes(spark, d, arcs)
    return S.home_couples(N.friends(arcs), nodes), nodes, N.friends(arcs)


def _best(spark, d):
    couples, nodes, _ = _home(spark, d)
    got = S.best_similarity(couples, nodes)
    return got.select("id", *[F.round(c, 6).alias(c) for c in got.columns[1:]])


def _top(spark, d):
    couples, nodes, _ = _home(spark, d)
    return S.top_partners(couples, nodes).select("id", "op", "partner", F.round("score", 6).alias("score"), F.col("place").cast("long").alias("place"))


def _switch(spark, d):
    couples, nodes, pairs = _home(spark, d)
    return S.line_switch_pairs(couples, pairs, nodes).select("id", "partner", F.round("cosine", 6).alias("cosine"), F.round("asymmetry", 6).alias("asymmetry"))


def _track(spark, d):
    subs = subscriber(spark, d)
    nodes, ids = subs.select(F.col("sub_id").alias("id"), "operator"), subs.where("operator = 'home'").select(F.col("sub_id").alias("id"))
    got = S.similarity_track(contact(spark, d), nodes, ids)
    return got.select("id", F.col("period").cast("int").alias("week"), F.round("max_cos_rival", 6).alias("max_cos_rival"))


def _weights(spark, d):
    got = G.weigh(_arcs(spark, d))
    return got.select("src", "dst", *[F.round(c, 9).alias(c) for c in ("w_time", "w_count", "w_mean")])


def _value(fn, digits=6):
    return lambda spark, d: fn(_pairs(spark, d)).select("id", F.round("value", digits).alias("value"))


def _low(spark, d):
    return N.low_clustering(N.local_clustering(_pairs(spark, d)), 0.5).select("id", F.round("value", 6).alias("value"))


def _ego(spark, d):
    arcs = _arcs(spark, d)
    return G.ego_sample(arcs, _nodes(spark, d, arcs), arcs.agg(F.min("src")).first()[0], hops=1)


def _features(spark, d):
    arcs = _arcs(spark, d)
    got = S.graph_features(_nodes(spark, d, arcs), arcs, G.weigh(arcs), rounds=ROUNDS)
    return got.select("id", *[F.round(F.col(c) + 1e-9, 6).alias(c) if t == "double" else F.col(c) for c, t in got.dtypes[1:]])


def _between(**options):
    return lambda spark, d: N.betweenness(_pairs(spark, d), **options).select("id", F.round("bet", 6).alias("bet"))


def _trace(spark, d):
    arcs = _arcs(spark, d)
    return R.rank_trace(G.build_nodes(arcs), G.weigh(arcs), rounds=ROUNDS).select("round", F.round("change", 6).alias("change"))


QUERIES = {
    "arcs": lambda s, d: _arcs(s, d),
    "arc_weights": _weights,
    "graph_size": lambda s, d: G.graph_size(_arcs(s, d)),
    "receive_rank": _rank("receive_rank"),
    "receive_rank_plain": _rank("receive_rank", "one"),
    "send_rank": _rank("send_rank"),
    "send_rank_printed": _rank("send_rank", norm="printed"),
    "all_ranks": _all_ranks,
    "rank_damping": _rank_damping,
    "rank_rounds": _trace,
    "power": _power,
    "degrees": lambda s, d: N.degrees(_arcs(s, d)),
    "degree_centrality": lambda s, d: N.degree_centrality(_pairs(s, d)).select("id", F.round("centrality", 9).alias("centrality")),
    "neighbour_connectivity": _value(N.neighbour_connectivity),
    "two_hop_reach": lambda s, d: N.two_hop_reach(_pairs(s, d)),
    "local_clustering": _value(N.local_clustering),
    "local_clustering_sets": _value(lambda p: N.local_clustering(p, orient=False)),
    "mutual_friends": lambda s, d: S.mutual_friends(_pairs(s, d)),
    "jaccard_pairs": lambda s, d: _couples(s, d).select("a", "b", F.round("jaccard", 9).alias("score")),
    "cosine_pairs": lambda s, d: _couples(s, d).select("a", "b", F.round("cosine", 9).alias("score")),
    "adjacent_pairs": lambda s, d: S.similar_pairs(_pairs(s, d), scope="adjacent").select("a", "b", F.round("cosine", 9).alias("score")),
    "best_similarity": _best,
    "top_partners": _top,
    "line_switch_pairs": _switch,
    "similarity_track": _track,
    "betweenness": _between(),
    "betweenness_count": _between(kind="count"),
    "betweenness_sampled": _between(sources=0.2, depth=6),
    "ego_sample": _ego,
    "low_clustering": _low,
    "jaccard_sketch": lambda s, d: S.jaccard_sketch(_pairs(s, d)),
    "graph_features": _features,
}

# ---------------------------------------------------------------- SQL

ARCS = f"""arcs AS (SELECT src, dst, count(*) AS n_events, sum(duration) AS talk FROM contact
  WHERE ts >= '{months_before(BASELINE, MONTHS)}' AND ts < '{BASELINE}' GROUP BY src, dst)"""
WEIGHTED = """weighted AS (SELECT *, (w_time + w_count) / 2 AS w_mean FROM (
  SELECT src, dst, n_events, talk, coalesce(talk / nullif(max(talk) OVER (), 0), 0) AS w_time, n_events::DOUBLE / max(n_events) OVER () AS w_count FROM arcs))"""
NODES = "nodes AS (SELECT src AS id FROM arcs UNION SELECT dst FROM arcs)"
FRIENDS = "friends AS (SELECT src AS id, dst AS friend FROM arcs UNION SELECT dst, src FROM arcs)"
DEG = "deg AS (SELECT id, count(*) AS deg FROM friends GROUP BY id)"
COUPLES = """couples AS MATERIALIZED (SELECT x.id AS a, y.id AS b, count(*) AS common FROM friends x JOIN friends y ON x.friend = y.friend AND x.id < y.id GROUP BY 1, 2)"""
SCORED = """scored AS MATERIALIZED (SELECT a, b, common, p.deg AS deg_a, q.deg AS deg_b, common / (p.deg + q.deg - common)::DOUBLE AS jaccard,
  common / sqrt(p.deg::DOUBLE * q.deg) AS cosine FROM couples JOIN deg p ON a = p.id JOIN deg q ON b = q.id)"""
MIRROR = """mirror AS (SELECT m.*, s.operator AS op FROM (SELECT a AS id, b AS partner, common, deg_a, deg_b, jaccard, cosine FROM scored
  UNION ALL SELECT b, a, common, deg_a, deg_b, jaccard, cosine FROM scored) m JOIN subscriber s ON s.sub_id = partner
  WHERE id IN (SELECT sub_id FROM subscriber WHERE operator = 'home') AND s.operator IN ('home', 'rival'))"""


def _moves(name, direction, weight):
    w = "1.0" if weight == "one" else weight
    if direction == "receive":
        return f"{name} AS (SELECT src AS giver, dst AS taker, coalesce({w} / nullif(sum({w}) OVER (PARTITION BY src), 0), 0) AS share FROM weighted)"
    if direction == "send":
        return f"{name} AS (SELECT dst AS giver, src AS taker, coalesce({w} / nullif(sum({w}) OVER (PARTITION BY dst), 0), 0) AS share FROM weighted)"
    return f"""{name} AS (SELECT dst AS giver, src AS taker, coalesce({w} / nullif(o, 0), 0) AS share FROM weighted
      JOIN (SELECT src AS oid, sum({w}) AS o FROM weighted GROUP BY src) ON dst = oid)"""


def _rounds(prefix, moves, rounds=ROUNDS, d=0.85):
    out = [f"{prefix}0 AS (SELECT id, 1.0::DOUBLE AS rank FROM nodes)"]
    for r in range(1, rounds + 1):
        out.append(
            f"{prefix}{r} AS MATERIALIZED (SELECT n.id, (1 - {d}) + {d} * coalesce(g.s, 0) AS rank FROM nodes n LEFT JOIN "
            f"(SELECT taker, sum(share * rank) AS s FROM {moves} JOIN {prefix}{r - 1} q ON giver = q.id GROUP BY taker) g ON n.id = g.taker)"
        )
    return out


def _rank_sql(direction, weight="w_count"):
    return with_roles("contact", f"SELECT id, round(rank + 1e-9, 6) AS rank FROM r{ROUNDS}", ARCS, WEIGHTED, NODES, _moves("moves", direction, weight), *_rounds("r", "moves"))


SIX = [(f"{short}_{w}", direction, f"w_{w}") for direction, short in (("receive", "recv"), ("send", "send")) for w in ("time", "count", "mean")]
SIX_PARTS = [x for name, direction, w in SIX for x in (_moves(f"m_{name}", direction, w), *_rounds(f"{name}_", f"m_{name}"))]
SIX_JOIN = "nodes " + " ".join(f"JOIN {n}_{ROUNDS} {n} ON {n}.id = nodes.id" for n, _, _ in SIX)


def _damping_sql():
    parts, rows = [], []
    for i, (d, sinks) in enumerate((d, s) for d in (0.5, 0.85, 0.95) for s in ("leak", "spread", "self")):
        p = f"x{i}_"
        parts.append(f"{p}0 AS (SELECT id, 1.0::DOUBLE AS rank FROM nodes)")
        for r in range(1, ROUNDS + 1):
            extra = {
                "leak": "0",
                "spread": f"(SELECT sum(rank) FROM {p}{r - 1} WHERE id NOT IN (SELECT giver FROM moves)) / (SELECT count(*) FROM nodes)",
                "self": "CASE WHEN n.id IN (SELECT giver FROM moves) THEN 0 ELSE o.rank END",
            }[sinks]
            parts.append(
                f"{p}{r} AS MATERIALIZED (SELECT n.id, (1 - {d}) + {d} * (coalesce(g.s, 0) + coalesce({extra}, 0)) AS rank FROM nodes n JOIN {p}{r - 1} o ON o.id = n.id LEFT JOIN "
                f"(SELECT taker, sum(share * rank) AS s FROM moves JOIN {p}{r - 1} q ON giver = q.id GROUP BY taker) g ON n.id = g.taker)"
            )
        rows.append(f"SELECT {d}::DOUBLE AS damping, '{sinks}' AS sinks, round(sum(rank), 6) AS total, round(max(rank), 6) AS highest FROM {p}{ROUNDS}")
    arcs = "arcs AS (SELECT src, dst, count(*) AS n_events FROM touch GROUP BY src, dst)"
    moves = "moves AS (SELECT src AS giver, dst AS taker, n_events::DOUBLE / sum(n_events) OVER (PARTITION BY src) AS share FROM arcs)"
    return with_roles("touch", "\nUNION ALL ".join(rows), arcs, NODES, moves, *parts)


TRIANGLES = "tri AS (SELECT x.id, count(*) AS t FROM friends x JOIN friends y ON x.id = y.id AND x.friend < y.friend JOIN friends z ON z.id = x.friend AND z.friend = y.friend GROUP BY x.id)"
LCC = """lcc AS (SELECT d.id, CASE WHEN d.deg >= 2 THEN 2.0 * coalesce(t, 0) / (d.deg * (d.deg - 1)) END AS value FROM deg d LEFT JOIN tri ON tri.id = d.id)"""
LCC_SQL = with_roles("contact", "SELECT id, round(value, 6) AS value FROM lcc", ARCS, FRIENDS, DEG, TRIANGLES, LCC)
PAIRS = (ARCS, FRIENDS, DEG, COUPLES, SCORED)
BEST = """best AS (SELECT id, max(CASE WHEN op = 'home' THEN cosine END) AS max_cos_home, max(CASE WHEN op = 'rival' THEN cosine END) AS max_cos_rival,
  max(CASE WHEN op = 'home' THEN jaccard END) AS max_jac_home, max(CASE WHEN op = 'rival' THEN jaccard END) AS max_jac_rival FROM mirror GROUP BY id)"""
FOUR = ("max_cos_home", "max_cos_rival", "max_jac_home", "max_jac_rival")
DEGREES = "degrees AS (SELECT id, sum(i)::BIGINT AS in_deg, sum(o)::BIGINT AS out_deg FROM (SELECT src AS id, 0 AS i, 1 AS o FROM arcs UNION ALL SELECT dst, 1, 0 FROM arcs) GROUP BY id)"
CONNECT = "connect AS (SELECT f.id, avg(deg) AS value FROM friends f JOIN deg d ON d.id = f.friend GROUP BY f.id)"

REACH = """reach AS (SELECT id, count(DISTINCT friend) AS value FROM (SELECT id, friend FROM friends
  UNION ALL SELECT x.id, y.friend FROM friends x JOIN friends y ON x.friend = y.id WHERE x.id <> y.friend) GROUP BY id)"""
#: Distances and numbers of shortest paths, level by level; then shares that flow back, from the farthest level on.
LEVELS = (
    """near AS MATERIALIZED (SELECT s, v, min(dist) AS dist FROM walk GROUP BY ALL)""",
    """paths AS (SELECT id AS s, id AS v, 0 AS dist, 1.0::DOUBLE AS sigma FROM (SELECT DISTINCT id FROM friends)
  UNION ALL SELECT p.s, n.v, n.dist, sum(p.sigma) FROM paths p JOIN friends f ON f.id = p.v JOIN near n ON n.s = p.s AND n.v = f.friend AND n.dist = p.dist + 1 GROUP BY ALL)""",
    "lv AS MATERIALIZED (SELECT * FROM paths)",
)


def _between_sql(kind):
    part = "l.sigma / b.sigma * (1 + b.delta)" if kind == "share" else "1 + b.delta"
    gain = "delta" if kind == "share" else "delta * sigma"
    # a walk goes on only to nodes that no shorter walk from its source has met: cells keep the first distance
    walk = """walk(s, v, dist) USING KEY (s, v) AS (SELECT id, id, 0 FROM (SELECT DISTINCT id FROM friends)
  UNION SELECT w.s, f.friend, min(w.dist) + 1 FROM walk w JOIN friends f ON f.id = w.v
  WHERE NOT EXISTS (SELECT 1 FROM recurring.walk r WHERE r.s = w.s AND r.v = f.friend) GROUP BY w.s, f.friend)"""
    back = f"""back AS (SELECT s, v, dist, sigma, 0.0::DOUBLE AS delta FROM lv WHERE dist = (SELECT max(dist) FROM lv)
  UNION ALL SELECT l.s, l.v, any_value(l.dist), any_value(l.sigma), coalesce(sum({part}), 0) FROM lv l JOIN friends f ON f.id = l.v LEFT JOIN back b ON b.s = l.s AND b.v = f.friend
  WHERE l.dist = (SELECT min(dist) - 1 FROM back) GROUP BY l.s, l.v)"""
    body = f"SELECT id, round(coalesce(bet, 0) / 2, 6) AS bet FROM (SELECT DISTINCT id FROM friends) LEFT JOIN (SELECT v AS id, sum({gain}) AS bet FROM back WHERE dist > 0 GROUP BY v) USING (id)"
    return with_roles("contact", body, ARCS, FRIENDS, walk, *LEVELS, back)


TRACE = [f"SELECT {r}::INT AS round, round(sum(abs(a.rank - b.rank)), 6) AS change FROM r{r} a JOIN r{r - 1} b USING (id)" for r in range(1, ROUNDS + 1)]
ORACLES = {
    "rank_rounds": with_roles("contact", " UNION ALL ".join(TRACE), ARCS, WEIGHTED, NODES, _moves("moves", "receive", "w_count"), *_rounds("r", "moves")),
    "betweenness": _between_sql("share"),
    "betweenness_count": _between_sql("count"),
    "arcs": with_roles("contact", "SELECT * FROM arcs", ARCS),
    "arc_weights": with_roles("contact", "SELECT src, dst, round(w_time, 9) AS w_time, round(w_count, 9) AS w_count, round(w_mean, 9) AS w_mean FROM weighted", ARCS, WEIGHTED),
    "graph_size": with_roles("contact", "SELECT (SELECT count(*) FROM nodes) AS nodes, (SELECT count(*) FROM arcs) AS arcs", ARCS, NODES),
    "receive_rank": _rank_sql("receive"),
    "receive_rank_plain": _rank_sql("receive", "one"),
    "send_rank": _rank_sql("send"),
    "send_rank_printed": _rank_sql("printed"),
    "all_ranks": with_roles("contact", "SELECT nodes.id, " + ", ".join(f"round({n}.rank + 1e-9, 6) AS {n}" for n, _, _ in SIX) + f" FROM {SIX_JOIN}", ARCS, WEIGHTED, NODES, *SIX_PARTS),
    "power": with_roles("contact", f"SELECT nodes.id, round((recv_count.rank + send_count.rank) / 2 + 1e-9, 6) AS power FROM {SIX_JOIN}", ARCS, WEIGHTED, NODES, *SIX_PARTS),
    "rank_damping": _damping_sql(),
    "degrees": with_roles("contact", "SELECT * FROM degrees", ARCS, DEGREES),
    "degree_centrality": with_roles("contact", "SELECT id, round(deg / (SELECT count(*) - 1 FROM deg)::DOUBLE, 9) AS centrality FROM deg", ARCS, FRIENDS, DEG),
    "neighbour_connectivity": with_roles("contact", "SELECT id, round(value, 6) AS value FROM connect", ARCS, FRIENDS, DEG, CONNECT),
    "two_hop_reach": with_roles("contact", "SELECT * FROM reach", ARCS, FRIENDS, REACH),
    "local_clustering": LCC_SQL,
    "local_clustering_sets": LCC_SQL,
    "mutual_friends": with_roles("contact", "SELECT * FROM couples", ARCS, FRIENDS, COUPLES),
    "jaccard_pairs": with_roles("contact", "SELECT a, b, round(jaccard, 9) AS score FROM scored", *PAIRS),
    "cosine_pairs": with_roles("contact", "SELECT a, b, round(cosine, 9) AS score FROM scored", *PAIRS),
    "adjacent_pairs": with_roles("contact", "SELECT a, b, round(cosine, 9) AS score FROM scored JOIN friends ON id = a AND friend = b", *PAIRS),
    "best_similarity": with_roles("contact subscriber", "SELECT id, " + ", ".join(f"round({c}, 6) AS {c}" for c in FOUR) + " FROM best", *PAIRS, MIRROR, BEST),
    "top_partners": with_roles(
        "contact subscriber",
        "SELECT id, op, partner, round(cosine, 6) AS score, place FROM (SELECT *, row_number() OVER (PARTITION BY id, op ORDER BY round(cosine, 9) DESC, partner) AS place FROM mirror) WHERE place <= 3",
        *PAIRS, MIRROR,
    ),
    "line_switch_pairs": with_roles(
        "contact subscriber",
        """SELECT id, partner, round(cosine, 6) AS cosine, round(abs(deg_a - deg_b) / (deg_a + deg_b)::DOUBLE, 6) AS asymmetry FROM mirror m
        WHERE op = 'rival' AND cosine >= 0.2 AND NOT EXISTS (SELECT 1 FROM friends f WHERE f.id = m.id AND f.friend = m.partner)""",
        *PAIRS, MIRROR,
    ),
    "similarity_track": with_roles(
        "contact subscriber",
        """SELECT a AS id, week, round(max(common / sqrt(p.deg::DOUBLE * q.deg)), 6) AS max_cos_rival FROM pairs_c
        JOIN wdeg p USING (week) JOIN wdeg q USING (week) WHERE p.id = a AND q.id = b GROUP BY a, week""",
        f"""weekly AS (SELECT src, dst, ((date_diff('day', ts::DATE, DATE '{BASELINE}') - 1) // 7 + 1)::INT AS week FROM contact WHERE ts < '{BASELINE}')""",
        "wf AS (SELECT week, src AS id, dst AS friend FROM weekly WHERE week BETWEEN 1 AND 14 UNION SELECT week, dst, src FROM weekly WHERE week BETWEEN 1 AND 14)",
        "wdeg AS (SELECT week, id, count(*) AS deg FROM wf GROUP BY week, id)",
        """pairs_c AS (SELECT x.week, x.id AS a, y.id AS b, count(*) AS common FROM wf x JOIN wf y ON x.week = y.week AND x.friend = y.friend AND x.id <> y.id
        WHERE x.id IN (SELECT sub_id FROM subscriber WHERE operator = 'home') AND y.id IN (SELECT sub_id FROM subscriber WHERE operator = 'rival') GROUP BY 1, 2, 3)""",
    ),
    "ego_sample": with_roles(
        "contact subscriber",
        """SELECT src, p.operator AS src_operator, dst, q.operator AS dst_operator, n_events FROM arcs JOIN subscriber p ON p.sub_id = src JOIN subscriber q ON q.sub_id = dst
        WHERE src IN (SELECT id FROM near) AND dst IN (SELECT id FROM near)""",
        ARCS, FRIENDS, "near AS (SELECT friend AS id FROM friends WHERE id = (SELECT min(src) FROM arcs) UNION SELECT min(src) FROM arcs)",
    ),
    "low_clustering": with_roles(
        "contact", "SELECT id, round(value, 6) AS value FROM lcc WHERE value <= (SELECT quantile_disc(value, 0.5) FROM lcc)", ARCS, FRIENDS, DEG, TRIANGLES, LCC
    ),
    "graph_features": with_roles(
        "contact subscriber",
        "SELECT nodes.id, " + ", ".join(f"round({n}.rank + 1e-9, 6) AS {n}" for n, _, _ in SIX)
        + ", round((recv_count.rank + send_count.rank) / 2 + 1e-9, 6) AS power, g.in_deg, g.out_deg, round(k.value + 1e-9, 6) AS connectivity, reach.value AS reach, round(lcc.value + 1e-9, 6) AS clustering, "
        + ", ".join(f"round(coalesce(best.{c}, 0) + 1e-9, 6) AS {c}" for c in FOUR)
        + f" FROM {SIX_JOIN} JOIN degrees g ON g.id = nodes.id JOIN connect k ON k.id = nodes.id JOIN reach ON reach.id = nodes.id JOIN lcc ON lcc.id = nodes.id LEFT JOIN best ON best.id = nodes.id",
        ARCS, WEIGHTED, NODES, FRIENDS, DEG, COUPLES, SCORED, MIRROR, BEST, DEGREES, CONNECT, REACH, TRIANGLES, LCC, *SIX_PARTS,
    ),
}
