"""Connected components by alternating stars, for edge tables of any size.

Each round first contracts what a task reads, a bounded number of edges at a time: what they
connect hangs under its smallest node. Then every node's larger neighbours hang under its
smallest neighbour, and every node under its smallest one; chains halve, so rounds grow with the
logarithm of the longest chain. Edges are read in as few tasks as their bound allows, so that a
task contracts much; once all of them are within one task's bound, contracting them is the end. Edges stay in tables: nothing is collected but a count and a sum that
tell the end. A node of very many edges is dealt out with its neighbours' hashes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import saved

#: Edges that a task contracts at once: some 20 MB with what they need.
CHUNK = 100_000
#: Edges from which a node's look-up is dealt out (more in very large tables, so that such nodes stay few), and over how many.
HOT, SALTS, MOST_HOT = 1_000, 32, 200_000


def roots_of(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, the smallest node of each one's component), in arrays alone: some 100 bytes an edge at the peak."""
    nodes, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = ends.reshape(2, -1).astype(np.int32)
    parent = np.arange(len(nodes), dtype=np.int32)
    while len(x):
        x, y = parent[x], parent[y]
        apart = x != y
        x, y = x[apart], y[apart]
        np.minimum.at(parent, np.maximum(x, y), np.minimum(x, y))  # each root hangs under the smallest one it meets
        while True:
            up = parent[parent]
            if np.array_equal(up, parent):
                break
            parent = up
    return nodes, nodes[parent]


def contracted(edges: DataFrame) -> DataFrame:
    """Fewer edges that connect the same: of each CHUNK of a task's edges, every node to its smallest one."""

    def run(batches):
        a, b, held = [], [], 0

        def out():
            nodes, roots = roots_of(np.concatenate(a), np.concatenate(b))
            some = nodes != roots
            return pa.RecordBatch.from_arrays([pa.array(nodes[some]), pa.array(roots[some])], names=["a", "b"])

        for batch in batches:
            a.append(batch.column(0).to_numpy())
            b.append(batch.column(1).to_numpy())
            held += batch.num_rows
            if held >= CHUNK:
                yield out()
                a, b, held = [], [], 0
        if held:
            yield out()

    return edges.select("a", "b").mapInArrow(run, "a long, b long")


def _large_star(edges: DataFrame, many: int) -> DataFrame:
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"), F.count("*").alias("n"))
    up = both.where("b > a")
    if many < HOT:  # no node has so many edges
        met = up.join(least, "a")
    else:
        least = saved(least)
        hot = F.broadcast(least.where(F.col("n") >= max(HOT, 2 * many // MOST_HOT)).select("a", F.lit(SALTS).alias("salts")))  # at most MOST_HOT rows
        spread = up.join(hot, "a", "left").withColumn("salt", F.pmod(F.xxhash64("b"), F.coalesce("salts", F.lit(1))).cast("int"))
        wide = least.join(hot, "a", "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)))
        met = spread.join(wide.select("a", "salt", "m"), ["a", "salt"])
    return met.select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select("a", F.col("m").alias("b"))).where("a <> b")


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) for every node of an edge; root is the smallest node of its component, itself included."""
    state, mark, first = saved(edges.select(F.col(a).alias("a"), F.col(b).alias("b")).where("a <> b")), None, True
    while True:
        now = tuple(state.agg(F.count("*"), F.expr("bit_xor(xxhash64(a, b))")).first())
        if now == mark or not now[0]:
            break
        tasks = -(-now[0] // CHUNK)
        if tasks == 1:
            state = saved(contracted(state.coalesce(1)))
            break
        if first:  # whatever the edges come from has dealt them out: gathered, a task's edges have more nodes in common
            state, first = saved(contracted(state.coalesce(tasks)).distinct()), False
        else:
            mark = now
            state = saved(contracted(_small_star(_large_star(state, now[0]))).distinct())
    roots = state.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct()
    return state.select(F.col("a").alias("node"), F.col("b").alias("root")).union(roots)
