"""The experiment workloads, each a table: `run(name, spark, sf_dir)`.

Cells are independent fits. Budgets are small by default (SMALL); pass options=BEST for the
settings reported. The planted label is a declared synthetic rule, used only to compare
families, learners and balancings; the idle label is the real rule on the given orders.
"""

from __future__ import annotations

import threading
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import draw
from ..functions.periods import BASELINE, months_before, period_index
from ..functions.scratch import kept
from ..operators import contact_graph as G
from ..operators import learners as LR
from ..operators import measures as M
from ..operators import outcome as O
from ..operators import profile as P

from ..operators import refine as R
from ..operators import resample as B
from ..operators import similarity as S
from ..operators import structure as N
from ..operators import usage as U
from ..sources import landing as L
from ..sources import tables as T

#: The graph family, both rows of ranks to similarity; every other column of the wide table is of the usage family.
GRAPH = (
    "recv_time", "recv_count", "recv_mean", "send_time", "send_count", "send_mean", "power", "in_deg", "out_deg", "connectivity", "reach", "clustering",
    "betweenness", "max_cos_home", "max_cos_rival", "max_jac_home", "max_jac_rival",
)
KEYS = ("sub_id", "label", "part")
FAMILIES = ("usage", "graph", "both")
#: Columns that a warehouse would hold: billing, calls and messages, complaints.
WAREHOUSE = ("n_out", "charge_sum", "charge_mean", "charge_max", "calls", "sms", "mms", "talk", "packages", "complaints", "coverage_share", "mean_hours", "balance", "age_years")
#: Segments of the home operator whose lines are paid in advance, months without new lines and between baseline and event.
PREPAID, NEW, GAP = ("AUTOMOBILE", "HOUSEHOLD"), 4, 2
#: Share of numbers and depth from which betweenness is told in the wide table.
SOURCES, DEPTH = 0.05, 3
FOUR = ("decision_tree", "random_forest", "boosted_first", "boosted_second")
#: Usage blocks that are joined in one job: each holds a sorter in a task, and its shuffle files until the job ends.
BLOCKS = 4
#: Usage blocks that are the same for every number of months.
FIXED = ("idle", "tickets", "session", "balance", "traffic", "radio", "gaps", "last_result", "handset", "silent", "area")
#: Settings that are tuned: depth, nodes and trees.
TUNING = {
    "decision_tree": ({"depth": 2}, {"depth": 6}, {"depth": 20}),
    "capped_tree": tuple({"depth": d, "max_nodes": n} for d in (6, 20) for n in (20, 100, 398)),
    "random_forest": tuple({"depth": d, "trees": n} for d in (3, 6) for n in (10, 20, 40)),
    "boosted_second": tuple({"depth": d, "trees": n} for d in (2, 3) for n in (6, 12, 24)),
}


def document_task(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, list[str]]:
    """(train, test, features): low quality told from the shape of a text; real labels."""
    rows = T.document_label(spark, sf_dir).withColumnRenamed("doc_id", "sub_id")
    parts = B.split(rows)
    return parts.where("part = 'train'"), parts.where("part = 'test'"), ["chars", "words", "non_letters", "capitals", "lines", "word_length"]


def vector_task(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, list[str]]:
    """(train, test, features): one class of the dense vectors against the rest, at the limit of balance."""
    v = T.vector_label(spark, sf_dir)
    names = [f"v{i}" for i in range(64)]
    rows = v.select(F.col("vec_id").alias("sub_id"), "label", *[F.col("embedding")[i].cast("double").alias(n) for i, n in enumerate(names)])
    parts = B.split(rows)
    return parts.where("part = 'train'"), parts.where("part = 'test'"), names


_made: dict[tuple, object] = {}
_making: dict[tuple, threading.Lock] = {}
_lock = threading.Lock()


def once(spark: SparkSession, name: str, sf_dir: str, key: tuple, make):
    """What several workloads read, made once a session: tables are written."""
    at = (spark.sparkContext.applicationId, name, sf_dir, *key)
    with _lock:
        making = _making.setdefault(at, threading.Lock())
    with making:  # threads that want the same table wait for the one that makes it
        if at not in _made:
            got = make()
            _made[at] = kept(got, name) if isinstance(got, DataFrame) else got
        return _made[at]


def role(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A role view that many blocks read, written once: contacts need two shuffles of all lines, whatever columns are wanted."""
    return once(spark, name, sf_dir, (), lambda: T.ROLES[name](spark, sf_dir))


def population(spark: SparkSession, sf_dir: str, baseline: str = BASELINE) -> DataFrame:
    """Prepaid home subscribers whose line is older than the last months before the baseline."""
    subs = T.subscriber(spark, sf_dir).where("operator = 'home'")
    prepaid = reduce(DataFrame.union, [O.population(subs, s) for s in PREPAID])
    return once(spark, "population", sf_dir, (baseline,), lambda: O.exclude_new(prepaid, role(spark, sf_dir, "contact"), baseline, NEW))


def usage_table(spark: SparkSession, sf_dir: str, baseline: str = BASELINE, months: int = 6) -> DataFrame:
    contacts, subs = role(spark, sf_dir, "contact"), T.subscriber(spark, sf_dir)
    pairs = N.friends(G.build_arcs(contacts, baseline, months))
    parts = U.all_blocks(contacts, role(spark, sf_dir, "session"), role(spark, sf_dir, "ticket"), T.handset(spark, sf_dir), subs, pairs, baseline, months)
    people = population(spark, sf_dir, baseline)

    def joined(names):
        groups = [tuple(names[i : i + BLOCKS]) for i in range(0, len(names), BLOCKS)]
        made = in_threads(groups, lambda group: kept(U.feature_table(parts, people, group), "blocks"), 2)
        return reduce(lambda x, y: x.join(y, "sub_id"), made)

    fixed = once(spark, "fixed", sf_dir, (baseline,), lambda: joined([n for n in parts if n in FIXED]))
    rows = fixed.join(joined([n for n in parts if n not in FIXED]), "sub_id")
    return rows.select("sub_id", *[c for part in parts.values() for c in part.columns if c != "sub_id"])


def graph_table(spark: SparkSession, sf_dir: str, baseline: str = BASELINE, months: int = 4, rounds: int = 10) -> DataFrame:
    contacts, subs = role(spark, sf_dir, "contact"), T.subscriber(spark, sf_dir)
    arcs = kept(G.build_arcs(contacts, baseline, months), "arcs")
    return S.graph_features(G.build_nodes(arcs, subs), arcs, G.weigh(arcs), rounds=rounds, sources=SOURCES, depth=DEPTH).withColumnRenamed("id", "sub_id")


def wide_table(spark: SparkSession, sf_dir: str, baseline: str = BASELINE, usage_months: int = 6, graph_months: int = 4, family: str = "both") -> DataFrame:
    """Feature families of the population, usage alone or both, for a baseline and two windows; nothing at or after the baseline enters."""
    usage = lambda: once(spark, "usage", sf_dir, (baseline, usage_months), lambda: usage_table(spark, sf_dir, baseline, usage_months))
    graph = lambda: once(spark, "graph", sf_dir, (baseline, graph_months), lambda: graph_table(spark, sf_dir, baseline, graph_months))
    if family == "usage":
        return usage()
    left, right = in_threads([usage, graph], lambda make: make(), 2)
    return left.join(right, "sub_id", "left")


def planted_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(sub_id, label) of the population by the planted rule, whose cosine covers nine months."""
    contacts, subs = role(spark, sf_dir, "contact"), T.subscriber(spark, sf_dir)
    arcs = kept(G.build_arcs(contacts, BASELINE, 9), "arcs9")
    nodes = G.build_nodes(arcs, subs)
    cosine = S.best_similarity(S.home_couples(N.friends(arcs), nodes), nodes).select(F.col("id").alias("sub_id"), "max_cos_rival")
    rival = U.both_directions(contacts.where(F.col("ts") < F.lit(BASELINE).cast("timestamp_ntz"))).where("direction = 'out'").groupBy("sub_id", "peer").agg(F.count("*").alias("n"))
    share = rival.join(subs.select(F.col("sub_id").alias("peer"), "operator"), "peer").groupBy("sub_id").agg((F.sum(F.when(F.col("operator") == "rival", F.col("n")).otherwise(0)) / F.sum("n")).alias("out_rival_share"))
    seed = population(spark, sf_dir).select("sub_id", "balance").join(U.idle_days(contacts), "sub_id", "left").join(share, "sub_id", "left").join(cosine, "sub_id", "left")
    return O.planted_label(kept(seed, "seed")).select("sub_id", "label")


def planted_task(
    spark: SparkSession, sf_dir: str, usage_months: int = 6, graph_months: int = 4, refiner: R.Refiner | None = None, family: str = "both",
) -> tuple[DataFrame, DataFrame, dict[str, list[str]]]:
    """(train, test, columns of each family) of the population with the planted label, refined by what the training part shows.
    family: with usage alone, no graph table is made, and columns and rows are refined by the usage columns. The graph family keeps
    both tables: refined by its own columns alone, a learner failed at sf0.001, whose model knew one class."""
    label = lambda: once(spark, "planted", sf_dir, (), lambda: planted_labels(spark, sf_dir))
    wide = lambda: wide_table(spark, sf_dir, BASELINE, usage_months, graph_months, family)
    rows = lambda: B.split(reduce(lambda x, y: x.join(y, "sub_id"), in_threads([wide, label], lambda make: make(), 2)))
    every = once(spark, "rows", sf_dir, (usage_months, graph_months, family), rows)
    return once(spark, "task", sf_dir, (usage_months, graph_months, family, repr(refiner)), lambda: refined(every, refiner))


def refined(rows: DataFrame, refiner: R.Refiner | None = None) -> tuple[DataFrame, DataFrame, dict[str, list[str]]]:
    """Fitted on the training part, replayed on both; the test part keeps all its rows."""
    train, test = rows.where("part = 'train'"), rows.where("part = 'test'")
    model = (refiner or R.Refiner(keys=KEYS)).fit(train)
    a, b = in_threads([train, test], lambda part: kept(model.numeric(model.transform(part, drop_rows=part is train)), "refined"), 2)
    columns = [c for c in a.columns if c not in KEYS]
    graph = [c for c in columns if c in GRAPH]
    usage = [c for c in columns if c not in GRAPH]
    return a, b, {"usage": usage or columns, "graph": graph or columns, "both": columns}


def in_threads(jobs: list, work, threads: int = 4) -> list:
    """Independent fits, a few at a time, in the order of the jobs."""
    with ThreadPoolExecutor(threads) as pool:
        return list(pool.map(work, jobs))


def _cells(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def w1_storage(spark, sf_dir, **_):
    return L.storage_trial(T.read_table(spark, sf_dir, "lineitem"), "l_extendedprice", "l_returnflag")


def w2_exploration(spark, sf_dir, **_):
    """What share of the usage table's columns is constant, sparse, missing."""
    subs = T.subscriber(spark, sf_dir)
    table = U.feature_table(U.blocks(T.contact(spark, sf_dir), T.session(spark, sf_dir), T.ticket(spark, sf_dir), subs), subs)
    got = P.profile_summary(P.profile(kept(table, "explored")))
    return got.select("measure", F.round(F.col("share") + 1e-9, 6).alias("share"))


def _histories(family):
    """Windows of 1 to 9 months of a family; for usage, no graph tables are made."""

    def run(spark, sf_dir, months=range(1, 10), learners=FOUR, options=LR.SMALL, **_):
        tasks = dict(zip(months, in_threads(list(months), lambda m: planted_task(spark, sf_dir, usage_months=m, graph_months=m, family="usage" if family == "usage" else "both"), 3)))

        def ready(m):
            train, test, columns = tasks[m]
            return *[LR.prepared(part, columns[family]) for part in (train, test)], columns[family]

        parts = dict(zip(months, in_threads(list(months), ready)))

        def one(job):
            m, name = job
            return m, family, name, LR.evaluate(*parts[m], name, options[name])

        rows = in_threads([(m, name) for m in months for name in learners], one)
        return _cells(spark, rows, "months INT, family STRING, learner STRING, auc DOUBLE")

    return run


def w6_families(spark, sf_dir, learners=FOUR, options=LR.SMALL, **_):
    """Best windows: usage of six months, graph of four; each family alone and both."""
    train, test, columns = planted_task(spark, sf_dir)
    rows = in_threads([(n, f) for n in learners for f in FAMILIES], lambda j: (*j, LR.evaluate(train, test, columns[j[1]], j[0], options[j[0]])))
    return M.lift_table(_cells(spark, rows, "learner STRING, family STRING, auc DOUBLE"))


def w7_balancing(spark, sf_dir, learners=FOUR, options=LR.SMALL, **_):
    """Three balancings of the training part for each learner; class weights for those that take them."""
    train, test, columns = planted_task(spark, sf_dir)
    features, balances = columns["both"], (*B.BALANCINGS, "weight")
    train, test = in_threads([train, test], lambda part: LR.prepared(part, features), 2)
    made = dict(zip(balances, in_threads(list(balances), lambda b: train if b == "none" else kept(LR.balanced(train, b), "balanced"))))
    jobs = [(n, b) for n in learners for b in balances if b != "weight" or n != "boosted_second"]
    rows = in_threads(jobs, lambda j: (*j, LR.evaluate(train, test, features, j[0], options[j[0]], j[1], made[j[1]])))
    return _cells(spark, rows, "learner STRING, balance STRING, auc DOUBLE")


def w8_tuning(spark, sf_dir, k=10, grid=None, learner="decision_tree", balance="undersample", **_):
    """A grid of one learner, or all of TUNING; training folds are undersampled."""
    train, _, columns = planted_task(spark, sf_dir)
    return LR.cross_validate_all(train, columns["both"], TUNING if grid is None else {learner: grid}, k=k, balance=balance, threads=4)


def w9_roc(spark, sf_dir, learners=FOUR, options=LR.SMALL, **_):
    train, test, columns = planted_task(spark, sf_dir)
    curve = lambda name: M.roc(LR.LEARNERS[name](train, columns["both"], **options[name]).score(test)).withColumn("learner", F.lit(name))
    return reduce(DataFrame.union, in_threads(list(learners), curve))


def w10_importance(spark, sf_dir, options=LR.SMALL, **_):
    train, _, columns = planted_task(spark, sf_dir)
    tables = in_threads(list(FAMILIES), lambda f: LR.second(train, columns[f], **options["boosted_second"]).importance(spark))
    return M.importance_shift(dict(zip(FAMILIES, tables)))


def switched_lines(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """The given contacts with a planted second line, -1 - id, of every home number: from week 7 of 14 on it repeats the contacts with an
    eighth of the friends, an eighth more each week; in the last two weeks the number itself calls nobody."""
    home = T.subscriber(spark, sf_dir).where("operator = 'home'").select(F.col("sub_id").alias("src"), F.lit(True).alias("home"))
    week = (F.lit(15) - period_index(F.col("ts"), BASELINE, "week")).alias("week")
    rows = T.contact(spark, sf_dir).select("src", "dst", "ts", week).where("week BETWEEN 1 AND 14").join(home, "src", "left")
    own = rows.where("home IS NULL OR week < 13").select("src", "dst", "ts")
    second = rows.where("home AND week >= 7 AND dst % 8 <= week - 7").select((F.lit(-1) - F.col("src")).alias("src"), "dst", "ts")
    lines = home.select(F.col("src").alias("id"), F.lit("home").alias("operator")).union(home.select(F.lit(-1) - F.col("src"), F.lit("rival")))
    return own.union(second), lines


def w11_track(spark, sf_dir, **_):
    contact, nodes = switched_lines(spark, sf_dir)
    track = S.similarity_track(contact, nodes, nodes.where("operator = 'home'").select("id"))
    return track.select("id", (F.lit(15) - F.col("period")).cast("int").alias("week"), F.round("max_cos_rival", 6).alias("max_cos_rival"))


#: What the classes are compared by: numbers over even bins, and categories.
NUMBERS, CATEGORIES = ("balance", "age_years", "n_out", "charge_sum", "charge_mean", "talk", "packages", "idle_days", "line_age", "other_share"), ("segment", "operator", "state")


def idle(spark, sf_dir):
    orders = T.read_table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("sub_id"), F.col("o_orderdate").alias("ts"))
    return O.idle_label(orders, T.subscriber(spark, sf_dir), "1999-08-01", 24)


def w12_distributions(spark, sf_dir, **_):
    """(column, label, value, rows): ten numbers by bin and three categories, by class."""
    subs = T.subscriber(spark, sf_dir)
    parts = U.blocks(T.contact(spark, sf_dir), T.session(spark, sf_dir), T.ticket(spark, sf_dir), subs)
    rows = kept(U.feature_table(parts, subs, ("contacts", "idle", "others", "balance")).join(subs.select("sub_id", *CATEGORIES), "sub_id").join(idle(spark, sf_dir), "sub_id"), "classes")
    numbers = [P.class_histogram(rows, c).select(F.lit(c).alias("column"), "label", F.col("bin").cast("string").alias("value"), "rows") for c in NUMBERS]
    categories = [P.class_categories(rows, c).select(F.lit(c).alias("column"), "label", "value", "rows") for c in CATEGORIES]
    return reduce(DataFrame.union, numbers + categories)


def w13_later(spark, sf_dir, learners=FOUR, options=LR.SMALL, horizon=6, **_):
    """Models of one baseline score the population of a later one, unchanged; the event follows two months after each baseline;
    those with an offer are left out of the later one. drift and retrain tell whether a new model is due."""
    early, first = months_before(BASELINE, horizon + GAP), months_before(BASELINE, 2 * (horizon + GAP))
    orders = T.read_table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("sub_id"), F.col("o_orderdate").alias("ts"))
    task = lambda base: wide_table(spark, sf_dir, base).join(O.idle_label(orders, T.subscriber(spark, sf_dir), base, horizon, GAP), "sub_id")
    old, new = in_threads([first, early], task, 2)
    rows = kept(B.split(old), "first")
    train, test = rows.where("part = 'train'"), rows.where("part = 'test'")
    model = R.Refiner(keys=KEYS).fit(train)
    later = new.where(draw(F.col("sub_id"), "offer") >= 0.5).withColumn("part", F.lit("later"))
    train, test, later = in_threads([train, test, later], lambda t: kept(model.numeric(model.transform(t, drop_rows=t is train)), "task"))
    columns = [c for c in train.columns if c not in KEYS]

    def one(name):
        fitted = LR.LEARNERS[name](train, columns, **options[name])
        old, new = kept(fitted.score(test), "scores"), kept(fitted.score(later), "scores")
        now, then = M.auc_value(old, 100_000), M.auc_value(new, 100_000)
        psi = float(M.stability_index(old, new, "score").first()["psi"] or 0.0)
        return name, now, then, psi, M.needs_retrain(psi, now, then)

    return _cells(spark, in_threads(list(learners), one), "learner STRING, same_period DOUBLE, later_no_offer DOUBLE, drift DOUBLE, retrain BOOLEAN")


def w14_offers(spark, sf_dir, options=LR.SMALL, **_):
    """Who a fitted model says will leave is offered something by halves; what became of both halves, and what it saves."""
    train, test, columns = planted_task(spark, sf_dir)
    scored = kept(LR.second(train, columns["both"], **options["boosted_second"]).score(test), "scores")
    cut = scored.agg(F.percentile_approx("score", 0.8, 10_000)).first()[0]
    offered = scored.where(draw(F.col("sub_id"), "offer") < 0.5).select("sub_id")
    return M.campaign_value(M.campaign_outcome(scored, offered, scored.select("sub_id", F.col("label").alias("left")), float(cut)))


def w15_graph(spark, sf_dir, **_):
    contacts, out = T.contact(spark, sf_dir), None
    for months in (4, 9, None):
        part = G.graph_size(G.build_arcs(contacts, BASELINE, months)).withColumn("months", F.lit(months).cast("int"))
        out = part if out is None else out.union(part)
    return out


def w16_similarity(spark, sf_dir, months=(4, 9, 24), **_):
    contacts, out = T.contact(spark, sf_dir), None
    for m in months:
        part = S.mutual_friends(N.friends(G.build_arcs(contacts, BASELINE, m))).agg(F.count("*").alias("couples")).withColumn("months", F.lit(m))
        out = part if out is None else out.union(part)
    return out


def w17_ablations(spark, sf_dir, options=LR.SMALL, **_):
    """Thresholds and imputation against dropping every column with a gap; correlated columns kept; few values as categories."""
    variants = {
        "chosen": R.Refiner(keys=KEYS), "drop any null": R.Refiner(keys=KEYS, any_null=True),
        "keep correlated": R.Refiner(keys=KEYS, correlation=None), "few values kept": R.Refiner(keys=KEYS, few="as_category"),
    }

    def one(name):
        train, test, columns = planted_task(spark, sf_dir, refiner=variants[name])
        return name, len(columns["both"]), LR.evaluate(train, test, columns["both"], "boosted_second", options["boosted_second"])

    return _cells(spark, in_threads(list(variants), one), "variant STRING, features INT, auc DOUBLE")


def w18_business_lines(spark, sf_dir, **_):
    got = N.low_clustering(N.local_clustering(N.friends(G.build_arcs(T.contact(spark, sf_dir), BASELINE, 9))), 0.1)
    return got.select("id", F.round("value", 6).alias("value"))


def w19_internet(spark, sf_dir, **_):
    got = M.internet_churners(idle(spark, sf_dir), T.session(spark, sf_dir))
    return got.select("churners", *[F.round(F.col(c) + 1e-9, 6).alias(c) for c in ("internet_share", "low_share")])


def w20_warehouse(spark, sf_dir, learners=FOUR, options=LR.SMALL, **_):
    train, test, columns = planted_task(spark, sf_dir)
    held = [c for c in columns["both"] if c in WAREHOUSE]
    rows = in_threads(list(learners), lambda name: (name, LR.evaluate(train, test, held, name, options[name])))
    return _cells(spark, rows, "learner STRING, auc DOUBLE")


WORKLOADS = {
    "w1": w1_storage, "w2": w2_exploration, "w3": _histories("usage"), "w4": _histories("graph"), "w5": _histories("both"), "w6": w6_families, "w7": w7_balancing,
    "w8": w8_tuning, "w9": w9_roc, "w10": w10_importance, "w11": w11_track, "w12": w12_distributions, "w13": w13_later, "w14": w14_offers, "w15": w15_graph,
    "w16": w16_similarity, "w17": w17_ablations, "w18": w18_business_lines, "w19": w19_internet, "w20": w20_warehouse,
}


def run(name: str, spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    return WORKLOADS[name](spark, sf_dir, **options)
