"""Degrees, neighbourhood connectivity, reach, clustering and betweenness of the contact graph."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import draw
from ..functions.scratch import kept


#: Pairs of a source and a node whose searches run together.
CELLS = 5_000_000_000
#: Pairs up to which a graph goes to all tasks as arrays (4 bytes a pair, 24 a node); larger ones are searched by tables.
MOST_PAIRS = 8_000_000
#: Nodes and pairs, over all their sources, that searches in arrays hold at once, and that make a task.
AT_ONCE, A_TASK = 1_000_000, 100_000_000
#: Nodes and pairs of a component from which its sources are searched together, pairs over all sources whose links are told at once, and
#: levels after which such a search is given up for one that follows each source's own cells, which is taken beyond so many nodes too (64 bytes each).
DENSE, LINKS, LEVELS, MOST_NODES = 2_000, 250_000, 60, 500_000


def friends(arcs: DataFrame, mode: str = "any") -> DataFrame:
    """(id, friend), distinct. mode: "any" direction, "out", "in", or "mutual" (both ways)."""
    out = arcs.select(F.col("src").alias("id"), F.col("dst").alias("friend")).where("id <> friend")
    back = out.select(F.col("friend").alias("id"), F.col("id").alias("friend"))
    if mode == "out":
        return out.distinct()
    if mode == "in":
        return back.distinct()
    if mode == "mutual":
        return out.distinct().join(back.distinct(), ["id", "friend"], "left_semi")
    return out.union(back).distinct()


def friend_counts(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("id").agg(F.count("*").alias("deg"))


def degrees(arcs: DataFrame) -> DataFrame:
    """(id, in_deg, out_deg): distinct numbers that reach it and that it reaches. Arcs are distinct, so counts suffice."""
    ends = arcs.select(F.col("src").alias("id"), F.lit(0).alias("i"), F.lit(1).alias("o")).union(arcs.select(F.col("dst"), F.lit(1), F.lit(0)))
    return ends.groupBy("id").agg(F.sum("i").cast("long").alias("in_deg"), F.sum("o").cast("long").alias("out_deg"))


def degree_centrality(pairs: DataFrame) -> DataFrame:
    """(id, centrality): friends over all other nodes."""
    counts = friend_counts(pairs)
    return counts.crossJoin(F.broadcast(counts.agg(F.count("*").alias("n")))).select("id", F.try_divide(F.col("deg"), F.col("n") - 1).alias("centrality"))


def neighbour_connectivity(pairs: DataFrame) -> DataFrame:
    """(id, value): the mean number of friends of a node's friends."""
    counts = friend_counts(pairs).select(F.col("id").alias("friend"), "deg")
    return pairs.join(counts, "friend").groupBy("id").agg(F.avg("deg").alias("value"))


def two_hop_reach(pairs: DataFrame, exact: bool = True) -> DataFrame:
    """(id, value): how many others are friends or friends of friends; a sketch where exact is false.

    Friends of friends are the couples with a mutual friend, which are formed in blocks of bounded size."""
    from .similarity import mutual_friends

    couples = mutual_friends(pairs).select("a", "b")
    reached = pairs.select("id", "friend").union(couples).union(couples.select("b", "a"))
    if not exact:
        return reached.groupBy("id").agg(F.approx_count_distinct("friend").alias("value"))
    return reached.distinct().groupBy("id").agg(F.count("*").alias("value"))


def triangles(pairs: DataFrame) -> DataFrame:
    """(a, b, c), each triangle once. Arcs point from the smaller to the larger (degree, id), so no node starts more
    than the square root of twice the number of arcs."""
    deg = kept(friend_counts(pairs), "degrees")
    ends = pairs.join(deg, "id").join(deg.select(F.col("id").alias("friend"), F.col("deg").alias("fdeg")), "friend")
    up = kept(ends.where("deg < fdeg OR deg = fdeg AND id < friend").select(F.col("id").alias("u"), F.col("friend").alias("v"), F.struct("fdeg", "friend").alias("key")), "oriented")
    left, right = up.alias("x"), up.alias("y")
    wedges = left.join(right, (F.col("x.u") == F.col("y.u")) & (F.col("x.key") < F.col("y.key"))).select(F.col("x.u").alias("a"), F.col("x.v").alias("b"), F.col("y.v").alias("c"))
    return wedges.join(up.select(F.col("u").alias("b"), F.col("v").alias("c")), ["b", "c"], "left_semi").select("a", "b", "c")


def local_clustering(pairs: DataFrame, orient: bool = True) -> DataFrame:
    """(id, value): the share of a node's pairs of friends who are friends themselves; null for fewer than two friends.

    orient=False intersects friend sets directly: for small graphs and as a check of the other way."""
    counts = friend_counts(pairs)
    if orient:
        hit = triangles(pairs).select(F.explode(F.array("a", "b", "c")).alias("id")).groupBy("id").agg(F.count("*").alias("t"))
    else:
        sets = pairs.groupBy("id").agg(F.collect_set("friend").alias("s"))
        both = pairs.join(sets, "id").join(sets.select(F.col("id").alias("friend"), F.col("s").alias("fs")), "friend")
        hit = both.groupBy("id").agg((F.sum(F.size(F.array_intersect("s", "fs"))) / 2).alias("t"))
    joined = counts.join(hit, "id", "left")
    value = F.when(F.col("deg") >= 2, 2 * F.coalesce("t", F.lit(0)) / (F.col("deg") * (F.col("deg") - 1)))
    return joined.select("id", value.cast("double").alias("value"))


def low_clustering(lcc: DataFrame, q: float = 0.1, accuracy: int = 1_000_000) -> DataFrame:
    """(id, value): nodes in the lowest share q of clustering, with known value. The cut is a value that occurs, from mergeable
    summaries: its rank is off by the rows over accuracy at most."""
    known = lcc.where("value IS NOT NULL")
    cut = known.agg(F.percentile_approx("value", q, accuracy).alias("cut"))
    return known.crossJoin(F.broadcast(cut)).where("value <= cut").select("id", "value")


def betweenness(pairs: DataFrame, kind: str = "share", sources: float | None = None, depth: int | None = None, seed: str = "sources") -> DataFrame:
    """(id, bet): shares of shortest paths through each node, or their number (kind="count"); unweighted, undirected.

    Searches from sources advance level by level together, then shares flow back. sources: share of nodes to
    start from, by hash, scaled up afterwards; depth: levels after which a search stops (both for large graphs): where it
    is None, 12 with sources and no limit without, so that all shortest paths count. A graph of at most MOST_PAIRS pairs goes to
    all tasks and each searches from its own sources, so that no pair of a source and a node becomes a row. In a larger one, levels
    are tables, and sources are searched in batches, so that at most about CELLS pairs of a source and a node are held at once."""
    if depth is None and sources is not None:
        depth = 12
    pairs = kept(pairs, "pairs")
    nodes = pairs.select("id").distinct()
    if pairs.schema["id"].dataType.typeName() in ("byte", "short", "integer", "long") and pairs.count() <= MOST_PAIRS:
        graph = Packed.of(pairs, nodes if sources is None else nodes.where(draw(F.col("id"), seed) < sources))
        scale = 1.0 if sources is None else len(graph.kept) / max(1, len(graph.starts))
        summed = kept(graph.flows(pairs, kind, depth).groupBy("id").agg(F.sum("bet").alias("bet")), "betweenness")
        return nodes.join(summed, "id", "left").select("id", (F.coalesce("bet", F.lit(0.0)) / 2 * scale).alias("bet"))
    nodes = kept(nodes, "nodes")
    starts = nodes if sources is None else nodes.where(draw(F.col("id"), seed) < sources)
    n_nodes, n_starts = nodes.count(), starts.count()
    scale = 1.0 if sources is None else n_nodes / max(1, n_starts)
    batches, summed = max(1, -(-n_starts * n_nodes // CELLS)), None
    for i in range(batches):
        part = _flows(pairs, starts.where(F.pmod(F.xxhash64("id"), F.lit(batches)) == i), kind, depth)
        summed = kept(part if summed is None else summed.union(part).groupBy("id").agg(F.sum("bet").alias("bet")), "betweenness")
    return nodes.join(summed, "id", "left").select("id", (F.coalesce("bet", F.lit(0.0)) / 2 * scale).alias("bet"))


def _components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The smallest place that each of n places reaches by the pairs: larger roots hang on smaller ones until pairs agree."""
    root = np.arange(n)
    while True:
        x, y = root[a], root[b]
        differ = x != y
        if not differ.any():
            return root
        x, y = x[differ], y[differ]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (up := root[root]).tobytes() != root.tobytes():
            root = up


def _given(far: np.ndarray, sources: np.ndarray, near: np.ndarray, to: np.ndarray, kind: str) -> np.ndarray:
    """What shortest paths from some sources pass through each node of their component, by all nodes' distances (a row for each source)
    and its pairs, in order of where they lead: a pair is a link for the sources whose distances it raises by one."""
    many, n = far.shape[0], far.shape[1]
    cell = np.arange(many) * n
    sources = cell + sources
    below = np.take(far, to, axis=1)
    hit = np.flatnonzero((below - np.take(far, near, axis=1)).ravel() == 1)
    level_of = below.ravel()[hit]
    order = np.argsort(level_of, kind="stable")
    upto = np.cumsum(np.bincount(level_of))
    held = np.diff(np.searchsorted(hit, np.arange(many + 1) * len(to)))
    pair, cell = hit - np.repeat(np.arange(many) * len(to), held), np.repeat(cell, held)
    down, up = (cell + to[pair])[order], (cell + near[pair])[order]
    steps = [slice(x, y) for x, y in zip(upto[:-1], upto[1:]) if y > x]
    paths, got = np.zeros(many * n), np.zeros(many * n)
    paths[sources] = 1
    for step in steps:
        np.add.at(paths, down[step], paths[up[step]])
    # what a cell gives to each link from above, without its paths; a cell's links from below are done before those from above
    own = 1 / np.maximum(paths, 1) if kind == "share" else np.ones(len(paths))
    for step in reversed(steps):
        np.add.at(got, up[step], own[down[step]] + got[down[step]])
    got *= paths
    got[sources] = 0
    return got.reshape(many, n).sum(axis=0)


@dataclass
class Packed:
    """A graph as arrays. Nodes have places, those of a component side by side."""

    ids: np.ndarray  # by place
    first: np.ndarray  # where a place's friends begin; one more at the end
    to: np.ndarray  # places of friends
    low: np.ndarray  # the first place of a place's component
    high: np.ndarray  # the place after its last
    kept: np.ndarray  # places of nodes that have friends
    starts: np.ndarray  # places of sources, rising
    cost: np.ndarray  # nodes and pairs of each source's component

    @classmethod
    def of(cls, pairs: DataFrame, starts: DataFrame) -> Packed:
        table = pairs.select("id", "friend").toArrow()  # 16 bytes for each of at most MOST_PAIRS
        a, b = (c.to_numpy().astype(np.int64) for c in table.columns)
        ids = np.unique(np.concatenate([a, b]))
        a, b = np.searchsorted(ids, a), np.searchsorted(ids, b)
        root = _components(len(ids), a, b)
        order = np.argsort(root, kind="stable")
        place = np.empty_like(order)
        place[order] = np.arange(len(order))
        sources = np.sort(place[np.searchsorted(ids, starts.toArrow().column(0).to_numpy().astype(np.int64))])
        a, b, root = place[a], place[b], root[order]
        degree = np.bincount(a, minlength=len(ids))
        first = np.concatenate([[0], np.cumsum(degree)])
        edges = np.flatnonzero(np.diff(root, prepend=-1, append=len(ids)))
        size = np.diff(edges)
        low, high = np.repeat(edges[:-1], size), np.repeat(edges[1:], size)
        cost = (high - low + first[high] - first[low])[sources]
        return cls(ids[order], first, b[np.argsort(a, kind="stable")].astype(np.int32), low, high, np.flatnonzero(degree), sources, cost)

    def flows(self, pairs: DataFrame, kind: str, depth: int | None) -> DataFrame:
        """(id, bet): what shortest paths from the sources pass through each node, a row for each task that met it."""
        spark, ids = pairs.sparkSession, pairs.schema["id"].dataType.simpleString()
        # sources that lie side by side share components, so a task gives back few rows
        upto = np.cumsum(self.cost)
        tasks = max(1, min(len(upto), -(-int(upto[-1] if len(upto) else 0) // A_TASK)))
        cuts = [0, *np.searchsorted(upto, [upto[-1] * i / tasks for i in range(1, tasks)]).tolist(), len(upto)]
        sent = spark.sparkContext.broadcast(self)

        def run(batches):
            for batch in batches:
                for i in batch.column(0).to_pylist():
                    graph, mine = sent.value, slice(cuts[i], cuts[i + 1])
                    starts = graph.starts[mine]
                    if not len(starts):
                        continue
                    low, high = graph.low[starts[0]], graph.high[starts[-1]]
                    total = np.zeros(high - low)
                    nodes = (graph.high - graph.low)[starts]
                    left = (graph.cost[mine] < DENSE) | (nodes > MOST_NODES) | (depth is not None)  # few levels meet few cells: `search` follows them
                    for one in np.split(np.flatnonzero(~left), np.flatnonzero(np.diff(graph.low[starts[~left]])) + 1):
                        left[one] = len(one) and not graph.search_together(starts[one], kind, low, total)
                    starts, upto = starts[left], np.cumsum(graph.cost[mine][left])
                    for part in np.split(starts, np.flatnonzero(np.diff(upto // AT_ONCE)) + 1) if len(starts) else ():
                        graph.search(part, kind, depth, low, total)
                    met = np.flatnonzero(total)
                    yield pa.RecordBatch.from_arrays([pa.array(graph.ids[low:high][met]), pa.array(total[met])], names=["id", "bet"])

        return spark.range(0, tasks, 1, tasks).mapInArrow(run, "id long, bet double").select(F.col("id").cast(ids).alias("id"), "bet")

    def search_together(self, starts: np.ndarray, kind: str, low: int, total: np.ndarray) -> bool:
        """`search` to any depth for sources of one component, 64 at a time: a bit for each source tells whom a level meets, and distances
        tell all links. False, and nothing added, if there are more than LEVELS levels."""
        at, end = int(self.low[starts[0]]), int(self.high[starts[0]])
        n, begin = end - at, self.first[at : end + 1]
        near, to = np.repeat(np.arange(n, dtype=np.int32), np.diff(begin)), self.to[begin[0] : begin[-1]] - np.int32(at)
        order = np.argsort(to, kind="stable")  # pairs by where they lead
        near, to = near[order], to[order]
        cuts = np.flatnonzero(np.diff(to, prepend=-1))
        met = to[cuts]
        unmet, summed = LEVELS + 9, np.zeros(n)
        for x in range(0, len(starts), 64):
            mine = starts[x : x + 64] - at
            front = np.zeros(n, dtype=np.uint64)
            front[mine] = np.uint64(1) << np.arange(len(mine), dtype=np.uint64)
            seen, far = front.copy(), np.full((n, 64), unmet, dtype=np.uint8)
            level = 0
            while front.any():
                if level > LEVELS:
                    return False
                rows = np.flatnonzero(front)
                here = np.unpackbits(front[rows].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
                far[rows] -= here * np.uint8(unmet - level)
                after = np.zeros(n, dtype=np.uint64)
                after[met] = np.bitwise_or.reduceat(front[near], cuts)
                front = after & ~seen
                seen |= front
                level += 1
            far, some = far.T[: len(mine)].copy(), max(1, LINKS // len(to))
            for y in range(0, len(mine), some):
                summed += _given(far[y : y + some], mine[y : y + some], near, to, kind)
        total[at - low : end - low] += summed
        return True

    def search(self, starts: np.ndarray, kind: str, depth: int | None, low: int, total: np.ndarray) -> None:
        """Adds to total, which begins at place low, what shortest paths from some sources pass through each node.

        Each source has a cell for each node of its component. A level holds its cells' nodes, where their sources' cells begin
        and their numbers of paths; between two levels stand the links that shortest paths take, by places in both."""
        size = self.high[starts] - self.low[starts]
        base = np.cumsum(size) - size - self.low[starts]
        far_of, slot = np.full(int(size.sum()), -1, dtype=np.int32), np.empty(int(size.sum()), dtype=np.int32)
        node, paths = starts, np.ones(len(starts))
        far_of[base + node] = 0
        levels, links = [(node, paths)], []
        for far in count(1) if depth is None else range(1, depth + 1):
            degree = self.first[node + 1] - self.first[node]
            nodes, bases, steps, have = [], [], [], 0
            whole = np.cumsum(degree)
            for own in np.split(np.arange(len(node)), np.flatnonzero(np.diff(whole // AT_ONCE)) + 1):
                d = degree[own]
                above = np.repeat(own, d)
                at = np.repeat(self.first[node[own]] - (np.cumsum(d) - d), d)
                at += np.arange(len(at))
                to = self.to[at]
                cell = base[above] + to
                seen = far_of[cell]
                open_ = np.flatnonzero((seen < 0) | (seen == far))
                above, to, cell = above[open_], to[open_], cell[open_]
                new = np.flatnonzero(seen[open_] < 0)
                slot[cell[new]] = new
                new = new[slot[cell[new]] == new]  # one link for each new cell
                slot[cell[new]] = np.arange(have, have + len(new))
                far_of[cell[new]] = far
                have += len(new)
                nodes.append(to[new])
                bases.append(base[above[new]])
                steps.append((above.astype(np.int32), slot[cell]))
            if not have:
                break
            more = np.zeros(have)
            for above, below in steps:
                more += np.bincount(below, weights=paths[above], minlength=have)
            node, base, paths = np.concatenate(nodes), np.concatenate(bases), more
            levels.append((node, paths))
            links.append(steps)
        worth = None  # what a cell gives to each link from above: its own unit and what it got, by its paths
        for i in range(len(levels) - 1, 0, -1):
            node, paths = levels[i]
            got = np.zeros(len(node))
            if worth is not None:
                for above, below in links[i]:
                    got += np.bincount(above, weights=worth[below], minlength=len(node))
                if kind == "share":
                    got *= paths
            total += np.bincount(node - low, weights=got if kind == "share" else got * paths, minlength=len(total))
            worth = (1 + got) / paths if kind == "share" else 1 + got


def _flows(pairs: DataFrame, starts: DataFrame, kind: str, depth: int | None) -> DataFrame:
    """(id, bet): what shortest paths from the sources pass through each node."""
    level = kept(starts.select(F.col("id").alias("s"), F.col("id").alias("v"), F.lit(0).alias("dist"), F.lit(1.0).alias("sigma")), "level")
    levels, seen = [level], level.select("s", "v")
    for dist in count(1) if depth is None else range(1, depth + 1):
        step = level.join(pairs, F.col("v") == F.col("id")).groupBy("s", F.col("friend").alias("w")).agg(F.sum("sigma").alias("sigma"))
        level = kept(step.withColumnRenamed("w", "v").join(seen, ["s", "v"], "left_anti").select("s", "v", F.lit(dist).alias("dist"), "sigma"), "level")
        if level.isEmpty():
            break
        levels.append(level)
        seen = kept(seen.union(level.select("s", "v")), "seen")
    total, below = None, None
    for level in reversed(levels):
        # what a node gets from the level below: its paths' part of the other's own unit and of what that one got
        if below is None:
            flow = level.withColumn("delta", F.lit(0.0))
        else:
            down = below.select("s", F.col("v").alias("w"), F.col("sigma").alias("wsigma"), F.col("delta").alias("wdelta"))
            met = level.join(pairs, F.col("v") == F.col("id")).withColumnRenamed("friend", "w").join(down, ["s", "w"])
            part = F.col("sigma") / F.col("wsigma") * (1 + F.col("wdelta")) if kind == "share" else 1 + F.col("wdelta")
            got = met.groupBy("s", "v").agg(F.sum(part).alias("delta"))
            flow = level.join(got, ["s", "v"], "left").select("s", "v", "dist", "sigma", F.coalesce("delta", F.lit(0.0)).alias("delta"))
        below = kept(flow, "flow")
        gain = F.col("delta") if kind == "share" else F.col("delta") * F.col("sigma")
        here = below.where("dist > 0").groupBy(F.col("v").alias("id")).agg(F.sum(gain).alias("bet"))
        total = here if total is None else total.union(here)
    return total.groupBy("id").agg(F.sum("bet").alias("bet"))
