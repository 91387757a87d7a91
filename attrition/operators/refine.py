"""Transformation and selection of features, in the order of the method, fitted on the training part and replayed.

Statistics are one small row for each column: they decide, on the driver, which columns a
`select` keeps and what fills a gap. Nothing of the rows themselves is collected.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .profile import BLOCK, is_number, value_counts

OTHER = "Other"


def _numbers(df: DataFrame, keys: tuple[str, ...]) -> list[str]:
    return [c for c, t in df.dtypes if is_number(t) and c not in keys]


def _categories(df: DataFrame, keys: tuple[str, ...]) -> list[str]:
    return [c for c, t in df.dtypes if t == "string" and c not in keys]


#: What `value_counts` told of columns: {column: (rows, missing, known values)}.
Seen = dict[str, tuple[int, int, int]]


def _seen(df: DataFrame, columns: list[str], seen: Seen | None) -> Seen:
    """Of these columns: from what was counted over the same rows before, or from a pass of its own."""
    return value_counts(df, columns) if seen is None else {c: seen[c] for c in columns}


def identifiers(df: DataFrame, keys: tuple[str, ...] = (), uniqueness: float = 1.0, seen: Seen | None = None) -> list[str]:
    """Columns whose known values are (almost) all different: integers and texts only."""
    seen = _seen(df, [c for c, t in df.dtypes if c not in keys and t in ("string", "bigint", "int")], seen)
    return [c for c, (n, nulls, d) in seen.items() if n - nulls > 1 and d >= uniqueness * (n - nulls)]


def constants(df: DataFrame, keys: tuple[str, ...] = (), seen: Seen | None = None) -> list[str]:
    """Columns with one value, or none."""
    seen = _seen(df, [c for c in df.columns if c not in keys], seen)
    return [c for c, (_, nulls, d) in seen.items() if d == 0 or d == 1 and nulls == 0]


def duplicates(df: DataFrame, key: str, keys: tuple[str, ...] = ()) -> list[str]:
    """Columns equal to an earlier one in every row, nulls included: one pass of fingerprints that depend on the
    row's key, then a count of differing rows for the pairs whose fingerprints agree."""
    columns = [c for c in df.columns if c != key and c not in keys]
    prints = df.agg(*[F.expr(f"bit_xor(xxhash64(`{key}`, CAST(`{c}` AS STRING)))").alias(c) for c in columns]).first()
    first: dict[int, list[str]] = {}
    for c in columns:
        first.setdefault(prints[c], []).append(c)
    pairs = [(g[0], c) for g in first.values() for c in g[1:]]
    if not pairs:
        return []
    differ = df.agg(*[F.count_if(~F.col(a).cast("string").eqNullSafe(F.col(b).cast("string"))).alias(f"{i}") for i, (a, b) in enumerate(pairs)]).first()
    return [b for i, (a, b) in enumerate(pairs) if differ[i] == 0]


def few_values(df: DataFrame, keys: tuple[str, ...] = (), max_distinct: int = 2, seen: Seen | None = None) -> list[str]:
    """Numbers with at most so many different known values."""
    return [c for c, (_, _, d) in _seen(df, _numbers(df, keys), seen).items() if d <= max_distinct]


def apply_few_values(df: DataFrame, columns: list[str], action: str) -> DataFrame:
    """action: "drop" (the final choice), "as_category" (tried and worse) or "keep"."""
    if action == "drop":
        return df.drop(*columns)
    if action == "as_category":
        return df.withColumns({c: F.col(c).cast("string") for c in columns}) if columns else df
    return df


def with_any_null(df: DataFrame, keys: tuple[str, ...] = (), seen: Seen | None = None) -> list[str]:
    """The rejected variant: columns with any missing value."""
    return [c for c, (_, nulls, _) in _seen(df, [c for c in df.columns if c not in keys], seen).items() if nulls > 0]


def drop_sparse_rows(df: DataFrame, keys: tuple[str, ...] = (), limit: float = 0.9) -> DataFrame:
    """Rows whose share of missing features is at most the limit: an expression of the row alone."""
    columns = [c for c in df.columns if c not in keys]
    if not columns:
        return df
    missing = F.aggregate(F.array(*[F.col(c).isNull().cast("int") for c in columns]), F.lit(0), lambda a, x: a + x)
    return df.where(missing / len(columns) <= limit)


def sparse_columns(df: DataFrame, keys: tuple[str, ...] = (), limit: float = 0.7, seen: Seen | None = None) -> list[str]:
    seen = _seen(df, [c for c in df.columns if c not in keys], seen)
    return [c for c, (n, nulls, _) in seen.items() if n and nulls / n > limit]


def fill_category(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.withColumns({c: F.coalesce(c, F.lit(OTHER)) for c in columns}) if columns else df


def means(df: DataFrame, columns: list[str]) -> dict[str, float]:
    out: dict[str, float] = {}
    for at in range(0, len(columns), BLOCK):
        row = df.agg(*[F.avg(F.when(~F.isnan(F.col(c).cast("double")), F.col(c))).alias(c) for c in columns[at : at + BLOCK]]).first()
        out |= {c: float(row[c]) if row[c] is not None else 0.0 for c in columns[at : at + BLOCK]}
    return out


def fill_mean(df: DataFrame, values: dict[str, float]) -> DataFrame:
    """Missing numbers become the mean; the column becomes a double."""
    filled = {c: F.coalesce(F.when(~F.isnan(F.col(c).cast("double")), F.col(c).cast("double")), F.lit(v)) for c, v in values.items()}
    return df.withColumns(filled) if filled else df


def top_categories(df: DataFrame, column: str, keep: int = 31) -> list[str]:
    """The most frequent values, ties by value: at most `keep` of them reach the driver."""
    counts = df.where(F.col(column).isNotNull()).groupBy(column).count()
    return [r[0] for r in counts.orderBy(F.desc("count"), column).limit(keep).collect()]


def keep_categories(df: DataFrame, kept: dict[str, list[str]]) -> DataFrame:
    """Values outside the kept ones become one further category; nulls stay."""
    return df.withColumns({c: F.when(F.col(c).isNull() | F.col(c).isin(v), F.col(c)).otherwise(F.lit(OTHER)) for c, v in kept.items()}) if kept else df


def pearson(df: DataFrame, columns: list[str]) -> DataFrame:
    """(left_col, right_col, r) for every pair of columns; null where one is constant.

    Sums and products of one pass give all pairs: tasks send one small matrix each, whatever their rows."""
    import numpy as np
    import pyarrow as pa

    n = len(columns)

    def partial(batches):
        s, p, m = np.zeros(n), np.zeros((n, n)), 0
        for batch in batches:
            x = np.column_stack([c.to_numpy(zero_copy_only=False).astype(float) for c in batch.columns]) if batch.num_rows else np.zeros((0, n))
            x = x[~np.isnan(x).any(axis=1)]
            s, p, m = s + x.sum(axis=0), p + x.T @ x, m + len(x)
        rows = [(i, j, float(p[i, j]), float(s[i]), float(s[j]), float(p[i, i]), float(p[j, j]), m) for i in range(n) for j in range(i + 1, n)]
        names = ("i", "j", "xy", "x", "y", "xx", "yy", "m")
        types = (pa.int32(), pa.int32(), *[pa.float64()] * 5, pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], type=t) for k, t in enumerate(types)], names=names)

    # columns are moved to a common origin first, so that products do not lose digits
    shift = means(df, columns)
    base = df.select(*[(F.col(c).cast("double") - F.lit(shift[c])).alias(c) for c in columns])
    sums = base.mapInArrow(partial, "i INT, j INT, xy DOUBLE, x DOUBLE, y DOUBLE, xx DOUBLE, yy DOUBLE, m BIGINT").groupBy("i", "j").agg(*[F.sum(c).alias(c) for c in ("xy", "x", "y", "xx", "yy", "m")])
    name = F.array(*[F.lit(c) for c in columns])
    vx, vy = F.col("m") * F.col("xx") - F.col("x") ** 2, F.col("m") * F.col("yy") - F.col("y") ** 2
    small = 1e-12
    ok = (vx > small * F.col("m") * F.greatest("xx", F.lit(1e-300))) & (vy > small * F.col("m") * F.greatest("yy", F.lit(1e-300)))
    r = F.when(ok, (F.col("m") * F.col("xy") - F.col("x") * F.col("y")) / (F.sqrt(vx) * F.sqrt(vy)))
    return sums.select(F.element_at(name, F.col("i") + 1).alias("left_col"), F.element_at(name, F.col("j") + 1).alias("right_col"), r.alias("r"))


def correlated(df: DataFrame, columns: list[str], limit: float = 0.95) -> list[str]:
    """Columns that correlate beyond the limit with one kept before them."""
    strong = {(r["left_col"], r["right_col"]) for r in pearson(df, columns).where(F.abs("r") > limit).collect()} if len(columns) > 1 else set()
    gone: list[str] = []
    for c in columns:
        if any((k, c) in strong for k in columns[: columns.index(c)] if k not in gone):
            gone.append(c)
    return gone


@dataclass
class RefinerModel:
    """What was fitted: replayed on any table with the same columns."""

    keys: tuple[str, ...]
    dropped: dict[str, list[str]]
    as_category: list[str]
    mean: dict[str, float]
    kept: dict[str, list[str]]
    row_limit: float
    report: dict[str, int] = field(default_factory=dict)

    def numeric(self, df: DataFrame) -> DataFrame:
        """df, transformed, with categories as the places of their kept values; the further category is 0."""
        cast = {c: F.array_position(F.array(*[F.lit(x) for x in v]), F.col(c)).cast("double") if v else F.lit(0.0) for c, v in self.kept.items() if c in df.columns}
        return df.withColumns(cast) if cast else df

    def transform(self, df: DataFrame, drop_rows: bool = True) -> DataFrame:
        if drop_rows:
            df = drop_sparse_rows(df, self.keys, self.row_limit)
        df = df.drop(*[c for group in self.dropped.values() for c in group])
        df = apply_few_values(df, [c for c in self.as_category if c in df.columns], "as_category")
        df = keep_categories(fill_category(df, list(self.kept)), {c: [*v, OTHER] for c, v in self.kept.items()})
        return fill_mean(df, self.mean)


@dataclass
class Refiner:
    """The chain: identifiers, constants, duplicates, sparse rows, sparse columns, few values, gaps, categories, correlation."""

    keys: tuple[str, ...] = ("sub_id", "label")
    row_limit: float = 0.9
    column_limit: float = 0.7
    keep: int = 31
    few: str = "drop"
    max_distinct: int = 2
    correlation: float | None = 0.95
    any_null: bool = False

    def fit(self, df: DataFrame) -> RefinerModel:
        keys, dropped, report = self.keys, {}, {"before": len(df.columns)}

        def lose(name: str, columns: list[str]):
            nonlocal df
            dropped[name] = columns
            df = df.drop(*columns)
            report[name] = len(columns)

        # values are counted twice: over all rows, and over those that stay
        seen = value_counts(df, [c for c in df.columns if c not in keys])
        lose("identifiers", identifiers(df, keys, seen=seen))
        lose("constants", constants(df, keys, seen))
        lose("duplicates", duplicates(df, keys[0], keys))
        df = drop_sparse_rows(df, keys, self.row_limit)
        seen = value_counts(df, [c for c in df.columns if c not in keys])
        lose("any null" if self.any_null else "sparse", with_any_null(df, keys, seen) if self.any_null else sparse_columns(df, keys, self.column_limit, seen))
        few = few_values(df, keys, self.max_distinct, seen)
        if self.few == "drop":
            lose("few values", few)
            few = []
        else:
            df = apply_few_values(df, few, self.few)
        numbers = _numbers(df, keys)
        mean = means(df, numbers)
        kept = {c: top_categories(df, c, self.keep) for c in _categories(df, keys)}
        if self.correlation is not None:
            gone = correlated(fill_mean(df, mean), numbers, self.correlation)
            lose("correlated", gone)
            mean = {c: v for c, v in mean.items() if c not in gone}
        report["after"] = len(df.columns)
        return RefinerModel(keys, dropped, few if self.few == "as_category" else [], mean, kept, self.row_limit, report)


def assemble(df: DataFrame, keys: tuple[str, ...] = ("sub_id", "label"), seen: DataFrame | None = None) -> DataFrame:
    """Adds features: one vector of numbers and indexed categories. seen: the rows that fix the indexes (training)."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import StringIndexer, VectorAssembler

    categories, numbers = _categories(df, keys), _numbers(df, keys)
    stages = [StringIndexer(inputCol=c, outputCol=f"{c}_index", handleInvalid="keep") for c in categories]
    stages.append(VectorAssembler(inputCols=[*numbers, *[f"{c}_index" for c in categories]], outputCol="features", handleInvalid="keep"))
    return Pipeline(stages=stages).fit(df if seen is None else seen).transform(df)


def pca(df: DataFrame, k: int, column: str = "features") -> DataFrame:
    from pyspark.ml.feature import PCA

    return PCA(k=k, inputCol=column, outputCol="components").fit(df).transform(df)
