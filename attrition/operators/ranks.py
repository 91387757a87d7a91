"""Weighted receive and send ranks.

Both are one iteration: each node passes its value along its arcs by share of weight; what a
node gets is damped and lifted by a constant. Receive ranks follow arcs with shares of the
source's weight; send ranks follow them backwards, with shares of the target's weight (so
nodes that receive nothing are the sinks), or with the neighbour's outgoing weight, as one
reading of the equation has it. A round is one join and one sum; several weightings share it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import kept, kept_buckets

#: Rounds between two writes that cut the lineage.
CUT = 5
#: Arcs of one giver that stay together; a hub's are dealt to parts of this size, and its rank goes to each.
HUB = 1_000_000


def transition(arcs: DataFrame, weights: dict[str, str], direction: str, norm: str = "in") -> DataFrame:
    """(giver, taker, one share column for each weight). weights: output name -> weight column; "one" weighs arcs equally."""
    given = {n: F.lit(1.0) if w == "one" else F.col(w).cast("double") for n, w in weights.items()}
    base = arcs.select("src", "dst", *[c.alias(f"_{n}") for n, c in given.items()])
    giver, taker = ("src", "dst") if direction == "receive" else ("dst", "src")
    by = giver if direction == "receive" or norm == "in" else "src"
    # sums of a number's arcs are added up in each task first; the look-up splits a hub's arcs as any join does
    whole = base.groupBy(F.col(by).alias("_id")).agg(*[F.sum(f"_{n}").alias(f"_all_{n}") for n in weights])
    met = base.join(whole, F.col(giver) == F.col("_id"))  # in the reading as printed, a neighbour that sends nothing gives nothing
    shares = [F.coalesce(F.try_divide(F.col(f"_{n}"), F.col(f"_all_{n}")), F.lit(0.0)).alias(n) for n in weights]
    return met.select(F.col(giver).alias("giver"), F.col(taker).alias("taker"), *shares)


def dealt(moves: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(moves with part, hubs): moves in buckets by (giver, part), so that rounds never move them again. hubs: (giver, parts)
    of givers with more than HUB arcs, fewer than arcs / HUB rows."""
    counts = moves.groupBy("giver").agg(F.count("*").alias("n")).where(F.col("n") > HUB)
    hubs = kept(counts.select("giver", F.ceil(F.col("n") / HUB).cast("int").alias("parts")), "hubs")
    part = F.pmod(F.xxhash64("taker"), F.coalesce("parts", F.lit(1))).cast("int")
    return kept_buckets(moves.join(F.broadcast(hubs), "giver", "left").withColumn("part", part).drop("parts"), "moves", "giver", "part"), hubs


def iterate(
    nodes: DataFrame, moves: DataFrame, names: list[str], d: float = 0.85, rounds: int = 20, tol: float | None = None, teleport: str = "unit",
    sinks: str = "leak", check_every: int = 5, trace: list | None = None,
) -> DataFrame:
    """(id, one value for each name). nodes: (id). teleport: "unit" adds 1-d to each node, "share" (1-d)/n.

    sinks: what nodes that give nothing do with their value: "leak" loses it, "spread" shares it among all, "self"
    keeps it. tol: stop when the sum of changes over all nodes and names is below it; looked at every check_every rounds."""
    nodes = kept(nodes.select("id").distinct(), "nodes")
    moves, hubs = dealt(moves)
    n = nodes.count() if teleport == "share" or sinks == "spread" else 0
    lift, start = ((1 - d) / max(1, n), 1.0 / max(1, n)) if teleport == "share" else (1 - d, 1.0)
    givers = moves.groupBy(F.col("giver").alias("id")).agg(*[(F.sum(c) > 0).alias(f"_gives_{c}") for c in names]) if sinks != "leak" else None
    ranks = nodes.select("id", *[F.lit(start).alias(c) for c in names])
    for r in range(1, rounds + 1):
        sent = ranks.select(F.col("id").alias("giver"), *[F.col(c).alias(f"_r_{c}") for c in names]).join(F.broadcast(hubs), "giver", "left")
        sent = sent.withColumn("part", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
        passed = moves.join(sent, ["giver", "part"])
        got = passed.groupBy(F.col("taker").alias("id")).agg(*[F.sum(F.col(c) * F.col(f"_r_{c}")).alias(f"_g_{c}") for c in names])
        new = nodes.join(got, "id", "left")
        extra = {c: F.lit(0.0) for c in names}
        if sinks != "leak":
            held = ranks.join(givers, "id", "left").select("id", *[F.when(F.coalesce(f"_gives_{c}", F.lit(False)), F.lit(0.0)).otherwise(F.col(c)).alias(f"_s_{c}") for c in names])
            if sinks == "self":
                new = new.join(held, "id", "left")
                extra = {c: F.coalesce(f"_s_{c}", F.lit(0.0)) for c in names}
            else:
                new = new.crossJoin(F.broadcast(held.agg(*[(F.sum(f"_s_{c}") / n).alias(f"_s_{c}") for c in names])))  # one row
                extra = {c: F.col(f"_s_{c}") for c in names}
        new = new.select("id", *[(F.lit(lift) + F.lit(d) * (F.coalesce(f"_g_{c}", F.lit(0.0)) + extra[c])).alias(c) for c in names])
        look = trace is not None or (tol is not None and r % check_every == 0)
        if look or r % CUT == 0 and r < rounds:
            new = kept(new, "ranks")
        if look:
            both = new.join(ranks.select("id", *[F.col(c).alias(f"_o_{c}") for c in names]), "id")
            change = both.agg(F.sum(sum(F.abs(F.col(c) - F.col(f"_o_{c}")) for c in names))).first()[0] or 0.0
            if trace is not None:
                trace.append((r, float(change)))
            if tol is not None and change < tol:
                return new
        ranks = new
    return ranks


def receive_rank(nodes: DataFrame, arcs: DataFrame, weight: str = "w_count", **options) -> DataFrame:
    """(id, rank): importance by what a number receives."""
    return iterate(nodes, transition(arcs, {"rank": weight}, "receive"), ["rank"], **options)


def send_rank(nodes: DataFrame, arcs: DataFrame, weight: str = "w_count", norm: str = "in", **options) -> DataFrame:
    """(id, rank): importance by what a number sends. norm: "in" or "printed"."""
    return iterate(nodes, transition(arcs, {"rank": weight}, "send", norm), ["rank"], **options)


def all_ranks(nodes: DataFrame, arcs: DataFrame, **options) -> DataFrame:
    """Six ranks: receive and send, by time, count and mean; three weightings share each round."""
    out = None
    for direction, short in (("receive", "recv"), ("send", "send")):
        weights = {f"{short}_time": "w_time", f"{short}_count": "w_count", f"{short}_mean": "w_mean"}
        part = iterate(nodes, transition(arcs, weights, direction), list(weights), **options)
        out = part if out is None else out.join(part, "id")
    return out


def power(ranks: DataFrame, receive: str = "recv_count", send: str = "send_count") -> DataFrame:
    """(id, power): the mean of the two ranks."""
    return ranks.select("id", ((F.col(receive) + F.col(send)) / 2).alias("power"))


def rank_trace(nodes: DataFrame, arcs: DataFrame, weight: str = "w_count", rounds: int = 10, **options) -> DataFrame:
    """(round, change): sum of absolute changes in each round."""
    trace: list = []
    iterate(nodes, transition(arcs, {"rank": weight}, "receive"), ["rank"], rounds=rounds, trace=trace, **options)
    return nodes.sparkSession.createDataFrame(trace or [(0, 0.0)], "round INT, change DOUBLE")
