"""Joins and other operators that the methods need and the DataFrame API lacks, as compositions of built-in ones."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import draw


def as_of_join(left: DataFrame, right: DataFrame, by: str, left_time: str, right_time: str, values: list[str], tie: str) -> DataFrame:
    """left with, from right, the values of the latest row at or before each left row, within the same `by`.

    Both sides are laid in one order and the last known value is carried forward: one shuffle by key, no pairs. A key
    with very many rows stays one ordered run, which spills instead of failing. tie orders right rows of one time."""
    own = left.columns
    a = left.select(F.col(by).alias("_by"), F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[tie].dataType).alias("_tie"), F.struct(*own).alias("_row"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("_value"))
    b = right.select(F.col(by).alias("_by"), F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.col(tie).alias("_tie"), F.lit(None).cast(left.select(F.struct(*own)).schema[0].dataType).alias("_row"), F.struct(*values).alias("_value"))
    order = Window.partitionBy("_by").orderBy("_t", "_side", "_tie").rowsBetween(Window.unboundedPreceding, 0)
    laid = a.union(b).withColumn("_last", F.last("_value", ignorenulls=True).over(order))
    return laid.where("_side = 1").select("_row.*", *[F.col(f"_last.{v}").alias(v) for v in values])


def range_join(points: DataFrame, bands: DataFrame, at: str, low: str, high: str, width: float) -> DataFrame:
    """points with every band [low, high) that holds them: an equi-join on buckets of the given width, then the exact test.

    Choose the width near the usual length of a band; each band is repeated once for each bucket it touches."""
    cells = F.sequence(F.floor(F.col(low) / width).cast("long"), F.floor(F.col(high) / width).cast("long"))
    wide = bands.withColumn("_cell", F.explode(cells))
    return points.withColumn("_cell", F.floor(F.col(at) / width).cast("long")).join(wide, "_cell").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("_cell")


def interval_join(left: DataFrame, right: DataFrame, by: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of the same key whose right time lies within `seconds` after the left time. Time is cut into cells of that
    length, so that the join key is (key, cell) and a busy key is dealt out. Columns must not clash but for the key."""
    cell = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (seconds * 1_000_000))
    a = left.withColumn("_cell", F.explode(F.array(cell(left_time), cell(left_time) + 1)))
    met = a.join(right.withColumn("_cell", cell(right_time)), [by, "_cell"])
    late = F.timestamp_diff("MICROSECOND", F.col(left_time), F.col(right_time))
    return met.where((late >= 0) & (late <= seconds * 1_000_000)).drop("_cell")


def salted_join(big: DataFrame, small: DataFrame, on: str, salts: int = 16, how: str = "inner", spread: Column | None = None) -> DataFrame:
    """An equi-join whose hot keys are dealt to `salts` tasks; small is repeated that often."""
    if how not in ("inner", "left", "left_semi", "left_anti"):
        raise ValueError(f"{how}: unmatched rows of the repeated side would repeat")
    salt = F.pmod(F.xxhash64(*big.columns) if spread is None else spread, F.lit(salts)).cast("int")
    wide = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return big.withColumn("_salt", salt).join(wide, [on, "_salt"], how).drop("_salt")


def top_k(df: DataFrame, by: list[str], order: list, k: int) -> DataFrame:
    return df.withColumn("place", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("place") <= k)


def hash_sample(df: DataFrame, key: str, share: float, seed: str = "sample") -> DataFrame:
    """A sample that any engine repeats and that joins keep together."""
    return df.where(draw(F.col(key), seed) < share)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def nearest(queries: DataFrame, rows: DataFrame, k: int, key: str = "vec_id", vector: str = "embedding", block: int | None = None) -> DataFrame:
    """(query, vec_id, cosine): the k nearest rows of each query, exactly. The stated query set goes to all tasks in
    blocks of 64 MB, each a pass over the rows (a set of 100 000 is one); every task compares 512 queries at a time and
    keeps its own k best for each before anything is shuffled."""
    import numpy as np
    import pyarrow as pa

    spark = rows.sparkSession
    asked = queries.select(key, vector).collect()
    block = block or max(512, (64 << 20) // max(8, 8 * len(asked[0][vector]) if asked else 8))
    out = None
    for at in range(0, len(asked), block):
        part = asked[at : at + block]
        m = np.array([r[vector] for r in part], dtype=float)
        sent = spark.sparkContext.broadcast(([r[key] for r in part], m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-12)))

        def run(batches, sent=sent):
            names, q = sent.value
            best: dict = {n: [] for n in names}
            for batch in batches:
                ids, v = batch.column(0).to_pylist(), np.array(batch.column(1).to_pylist(), dtype=float)
                if len(ids):
                    v = v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)
                    for first in range(0, len(names), 512):
                        s = v @ q[first : first + 512].T
                        for j, n in enumerate(names[first : first + 512]):
                            top = np.argpartition(-s[:, j], min(k + 1, len(ids) - 1))[: k + 2]
                            best[n] = sorted(best[n] + [(-float(s[i, j]), ids[i]) for i in top if ids[i] != n])[:k]
            found = [(n, i, -c) for n, rows in best.items() for c, i in rows]
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*found)], names=["query", key, "cosine"])

        near = rows.select(key, vector).mapInArrow(run, f"query BIGINT, {key} BIGINT, cosine DOUBLE")
        out = near if out is None else out.union(near)
    if out is None:
        return spark.createDataFrame([], f"query BIGINT, {key} BIGINT, cosine DOUBLE")
    return top_k(out, ["query"], [F.desc("cosine"), key], k).drop("place")


def near_pairs(rows: DataFrame, limit: float, key: str = "vec_id", vector: str = "embedding", length: float = 0.5, tables: int = 4, block: int = 16_384) -> DataFrame:
    """(a, b, distance) of vectors closer than a limit, found by random projections; may miss some. Exact: `nearest`.

    Vectors of a bucket are candidates. A large bucket is cut into blocks of about `block` vectors; each pair of its blocks
    is a group of its own, compared as matrices, so no pair of candidates becomes a row unless it is near."""
    import numpy as np
    import pyarrow as pa
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v = rows.select(key, vector, array_to_vector(F.col(vector).cast("array<double>")).alias("v"))
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=length, numHashTables=tables, seed=5).fit(v)
    codes = F.array(*[vector_to_array(F.col("h")[i])[0].cast("long") for i in range(tables)])
    spread = model.transform(v).select(F.col(key).alias("id"), F.col(vector).alias("own"), codes.alias("codes")).select("*", F.posexplode("codes").alias("at", "bucket"))
    sizes = spread.groupBy("at", "bucket").agg(F.ceil(F.count("*") / block).cast("int").alias("blocks"))
    met = spread.join(sizes, ["at", "bucket"]).withColumn("mine", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("*", F.least("mine", "other").alias("low"), F.greatest("mine", "other").alias("high"))

    def compare(group):
        at, low, high = (group.column(n)[0].as_py() for n in ("at", "low", "high"))
        mine, ids = group.column("mine").to_numpy(), group.column("id").to_numpy()
        m = np.array(group.column("own").combine_chunks().flatten(), dtype=float).reshape(len(ids), -1)
        buckets = np.array(group.column("codes").combine_chunks().flatten()).reshape(len(ids), -1)
        squares = (m * m).sum(axis=1)
        x, y = np.flatnonzero(mine == low), np.flatnonzero(mine == high)
        found, right = [], m[y].T
        for i in range(0, len(x), 256):
            part = x[i : i + 256]
            near = squares[part][:, None] + squares[y] - 2 * (m[part] @ right)
            a, b = np.nonzero(near < limit * limit + 1e-9 * (1 + squares[part][:, None] + squares[y]))
            a, b = part[a], y[b]
            a, b = np.where(ids[a] <= ids[b], a, b), np.where(ids[a] <= ids[b], b, a)
            first = (buckets[a] == buckets[b]).argmax(axis=1) == at  # in a table before, they were compared there
            once = (ids[a] < ids[b]) & first
            found.append(np.stack([a[once], b[once]]))
        a, b = np.unique(np.concatenate(found, axis=1), axis=1) if found else np.empty((2, 0), dtype=int)
        distance = np.concatenate([np.zeros(0), *(np.sqrt(((m[a[i : i + 9999]] - m[b[i : i + 9999]]) ** 2).sum(axis=1)) for i in range(0, len(a), 9999))])
        hit = distance < limit
        return pa.table({"a": pa.array(ids[a][hit], pa.int64()), "b": pa.array(ids[b][hit], pa.int64()), "distance": pa.array(distance[hit], pa.float64())})

    return met.select("at", "bucket", "low", "high", "mine", "id", "own", "codes").groupBy("at", "bucket", "low", "high").applyInArrow(compare, "a BIGINT, b BIGINT, distance DOUBLE")
