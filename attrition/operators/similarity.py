"""Mutual-friend similarity: couples that share a friend, Jaccard and cosine, the best partner by operator.

Couples are formed by their shared friends only. A friend of very many numbers would make the
square of its list in one task, so its list is cut into blocks and every pair of blocks is a
key of its own: the result is the same, the largest task is bounded.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.periods import BASELINE, period_index
from ..functions.scratch import kept
from .structure import friend_counts, friends

#: Numbers in one block of a hub's list.
BLOCK = 1000
#: Hubs up to which their list goes to all tasks (some 30 MB); more of them are joined by a shuffle.
MOST_HUBS = 1_000_000


def mutual_friends(
    pairs: DataFrame, left: DataFrame | None = None, right: DataFrame | None = None, block: int = BLOCK, by: tuple[str, ...] = (), hub_cap: int | None = None,
) -> DataFrame:
    """(a, b, common) for every couple a < b with a mutual friend; with left and right (each (id)), couples with one
    member in left and the other in right. by: further columns of pairs (a period) within which couples are formed.

    hub_cap: friends of more numbers than that form no couples, a choice of the method for directories and call centres;
    None, the default, is exact. Sides are marked and others dropped first, then the few hubs are told, blocks come last."""
    keys = [*by, "friend"]
    rows = pairs.select(*keys, "id")
    if left is not None:
        sides = left.select("id", F.lit(True).alias("_l"), F.lit(False).alias("_r")).union(right.select("id", F.lit(False), F.lit(True)))
        rows = rows.join(sides.groupBy("id").agg(F.max("_l").alias("is_left"), F.max("_r").alias("is_right")), "id")
    counts = rows.groupBy(*keys).agg(F.count("*").alias("_n"))
    if hub_cap is not None:
        rows = rows.join(counts.where(F.col("_n") > hub_cap).select(*keys), keys, "left_anti")
    hubs = kept(counts.where(F.col("_n") > block).select(*keys, F.ceil(F.col("_n") / block).cast("int").alias("blocks")), "hubs")
    few = hubs.count() <= MOST_HUBS
    own, blocks = [c for c in rows.columns], F.coalesce("blocks", F.lit(1))
    rows = rows.join(F.broadcast(hubs) if few else hubs, keys, "left").withColumn("block", F.pmod(F.xxhash64("id"), blocks).cast("int"))
    dealt = rows.withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1))).select(
        *own, "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j")
    )
    x, y = dealt.alias("x"), dealt.alias("y")
    same = [F.col(f"x.{k}") == F.col(f"y.{k}") for k in (*keys, "i", "j")]
    met = x.join(y, same + [F.col("x.id") < F.col("y.id")])
    # a pair of two blocks holds each block's own couples too: those belong to the key where both blocks are one
    met = met.where((F.col("x.i") == F.col("x.j")) | (F.col("x.block") != F.col("y.block")))
    if left is not None:
        met = met.where("x.is_left AND y.is_right OR x.is_right AND y.is_left")
    couple = [F.col(f"x.{k}").alias(k) for k in by] + [F.col("x.id").alias("a"), F.col("y.id").alias("b")]
    return met.groupBy(*couple).agg(F.count("*").alias("common"))


def scored(couples: DataFrame, counts: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Adds jaccard (shared over all friends of the two) and cosine (shared over the root of the product)."""
    side = lambda s: counts.select(*by, F.col("id").alias(s), F.col("deg").alias(f"deg_{s}"))
    out = couples.join(side("a"), [*by, "a"]).join(side("b"), [*by, "b"])
    union = F.col("deg_a") + F.col("deg_b") - F.col("common")
    return out.withColumns({"jaccard": F.col("common") / union, "cosine": F.col("common") / F.sqrt(F.col("deg_a").cast("double") * F.col("deg_b"))})


def similar_pairs(pairs: DataFrame, scope: str = "shared", **options) -> DataFrame:
    """All couples with a mutual friend, or only those that are friends themselves (scope="adjacent"), scored."""
    out = scored(mutual_friends(pairs, **options), friend_counts(pairs))
    if scope == "adjacent":
        out = out.join(pairs.select(F.col("id").alias("a"), F.col("friend").alias("b")), ["a", "b"], "left_semi")
    return out


def mirrored(couples: DataFrame, nodes: DataFrame) -> DataFrame:
    """(id, partner, operator of the partner, scores): each couple from both ends."""
    cols = ["common", "deg_a", "deg_b", "jaccard", "cosine"]
    one = couples.select(F.col("a").alias("id"), F.col("b").alias("partner"), *cols)
    two = couples.select(F.col("b").alias("id"), F.col("a").alias("partner"), *cols)
    return one.union(two).join(nodes.select(F.col("id").alias("partner"), F.col("operator").alias("op")), "partner")


def home_couples(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Couples that matter to home numbers: one member home, the other home or rival; sides are cut before the join."""
    home = nodes.where("operator = 'home'").select("id")
    other = nodes.where("operator IN ('home', 'rival')").select("id")
    return scored(mutual_friends(pairs, home, other), friend_counts(pairs))


def best_similarity(couples: DataFrame, nodes: DataFrame) -> DataFrame:
    """(id, max_cos_home, max_cos_rival, max_jac_home, max_jac_rival) of home numbers."""
    rows = mirrored(couples, nodes).join(nodes.where("operator = 'home'").select("id"), "id", "left_semi")
    best = lambda s, op: F.max(F.when(F.col("op") == op, F.col(s)))
    return rows.where("op IN ('home', 'rival')").groupBy("id").agg(
        best("cosine", "home").alias("max_cos_home"), best("cosine", "rival").alias("max_cos_rival"),
        best("jaccard", "home").alias("max_jac_home"), best("jaccard", "rival").alias("max_jac_rival"),
    )


def top_partners(couples: DataFrame, nodes: DataFrame, k: int = 3, score: str = "cosine") -> DataFrame:
    """(id, op, partner, score, place): the k most similar partners of home numbers in each operator."""
    rows = mirrored(couples, nodes).join(nodes.where("operator = 'home'").select("id"), "id", "left_semi")
    order = Window.partitionBy("id", "op").orderBy(F.desc(F.round(score, 9)), "partner")
    return rows.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).select("id", "op", "partner", F.col(score).alias("score"), "place")


def similarity_track(contact: DataFrame, nodes: DataFrame, ids: DataFrame, baseline: str = BASELINE, unit: str = "week", periods: int = 14) -> DataFrame:
    """(id, period, max_cos_rival): for chosen home numbers, the best cosine with a rival number in each period.

    Only the friends that the chosen numbers have in a period can be shared, so others are cut first."""
    n = period_index(F.col("ts"), baseline, unit)
    rows = contact.withColumn("period", n).where((F.col("period") >= 1) & (F.col("period") <= periods))
    out = rows.select("period", F.col("src").alias("id"), F.col("dst").alias("friend"))
    pairs = out.union(out.select("period", "friend", "id")).distinct()
    mine = pairs.join(ids.select("id"), "id", "left_semi")
    rival = nodes.where("operator = 'rival'").select("id")
    theirs = pairs.join(rival, "id", "left_semi")
    couples = mine.alias("x").join(theirs.alias("y"), (F.col("x.period") == F.col("y.period")) & (F.col("x.friend") == F.col("y.friend")) & (F.col("x.id") != F.col("y.id")))
    common = couples.groupBy(F.col("x.period").alias("period"), F.col("x.id").alias("a"), F.col("y.id").alias("b")).agg(F.count("*").alias("common"))
    counts = pairs.groupBy("period", "id").agg(F.count("*").alias("deg"))
    return scored(common, counts, by=("period",)).groupBy(F.col("a").alias("id"), "period").agg(F.max("cosine").alias("max_cos_rival"))


def line_switch_pairs(couples: DataFrame, pairs: DataFrame, nodes: DataFrame, least: float = 0.2) -> DataFrame:
    """(id, partner, cosine, asymmetry): a home and a rival number who never contact each other but share friends; the
    asymmetry compares the lengths of their lists."""
    rows = mirrored(couples, nodes).where((F.col("op") == "rival") & (F.col("cosine") >= least))
    rows = rows.join(nodes.where("operator = 'home'").select("id"), "id", "left_semi")
    rows = rows.join(pairs.select("id", F.col("friend").alias("partner")), ["id", "partner"], "left_anti")
    gap = F.abs(F.col("deg_a") - F.col("deg_b")) / (F.col("deg_a") + F.col("deg_b"))
    return rows.select("id", "partner", "cosine", gap.alias("asymmetry"))


def jaccard_sketch(pairs: DataFrame, tables: int = 16, limit: float = 0.6, buckets: int = 1 << 18) -> DataFrame:
    """(a, b, jaccard) found by min-hash tables: for graphs whose couples are too many to form; may miss some."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    sets = pairs.groupBy("id").agg(F.collect_set(F.col("friend").cast("string")).alias("names"))
    vectors = HashingTF(inputCol="names", outputCol="v", numFeatures=buckets, binary=True).transform(sets)
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=7).fit(vectors)
    met = model.approxSimilarityJoin(vectors, vectors, limit, "far").where("datasetA.id < datasetB.id")
    return met.select(F.col("datasetA.id").alias("a"), F.col("datasetB.id").alias("b"), (1 - F.col("far")).alias("jaccard"))


def graph_features(nodes: DataFrame, arcs: DataFrame, weighted: DataFrame, rounds: int = 10, sources: float | None = None, depth: int = 4) -> DataFrame:
    """One row for each number: six ranks, power, degrees, connectivity, reach, clustering and the four best similarities;
    with sources, also betweenness from that share of numbers to that depth."""
    from .ranks import all_ranks, power
    from .structure import betweenness, degrees, local_clustering, neighbour_connectivity, two_hop_reach

    pairs = friends(arcs)
    ranks = all_ranks(nodes, weighted, rounds=rounds)
    out = nodes.select("id").join(ranks, "id", "left").join(power(ranks), "id", "left").join(degrees(arcs), "id", "left")
    out = out.join(neighbour_connectivity(pairs).withColumnRenamed("value", "connectivity"), "id", "left")
    out = out.join(two_hop_reach(pairs).withColumnRenamed("value", "reach"), "id", "left")
    out = out.join(local_clustering(pairs).withColumnRenamed("value", "clustering"), "id", "left")
    if sources is not None:
        out = out.join(betweenness(pairs, sources=sources, depth=depth).withColumnRenamed("bet", "betweenness"), "id", "left")
    out = out.join(best_similarity(home_couples(pairs, nodes), nodes), "id", "left")
    zero = ["max_cos_home", "max_cos_rival", "max_jac_home", "max_jac_rival"]
    return out.na.fill(0.0, zero)
