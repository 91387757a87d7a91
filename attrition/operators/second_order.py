"""Second-order boosted trees on binned features.

Rows are binned once. For each level of each tree, tasks sum gradients and curvatures by
(node, feature, bin); the sums are added up by a shuffle whose size depends on nodes, features
and bins only; the best split of each node is found there and goes back to the tasks. Missing
values have a bin of their own and are tried on both sides. Margins are written every few
trees, so a pass never replays more than those.
"""

from __future__ import annotations

import math
import pickle
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Row, Window
from pyspark.sql import functions as F

from ..functions.hashing import draw
from ..functions.scratch import kept

MISSING = -1
#: Trees after which margins are written.
CUT = 8
#: Binned cells (rows times features, two bytes each) up to which one task grows all trees; more are summed by all tasks, level by level.
IN_TASK = 24_000_000
#: What is told of a node's best cut.
CUT_NAMES = ("node", "feature", "bin", "default_left", "gain", "gl", "hl", "gr", "hr", "first", "G", "H")


def gain_of(gl, hl, gr, hr, reg_lambda: float, gamma: float):
    """Half the rise of the score when a node is split; gl .. hr are columns or numbers."""
    return 0.5 * (gl * gl / (hl + reg_lambda) + gr * gr / (hr + reg_lambda) - (gl + gr) * (gl + gr) / (hl + hr + reg_lambda)) - gamma


def all_splits(hist: DataFrame, reg_lambda: float = 1.0, gamma: float = 0.0, min_child: float = 0.0) -> DataFrame:
    """(node, feature, bin, default_left, gain, gl, hl, gr, hr) of each possible cut after a bin, missing values on the
    better side. hist: (node, feature, bin, g, h), bin -1 for missing values."""
    whole, upto = Window.partitionBy("node", "feature"), Window.partitionBy("node", "feature").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    gone = lambda c: F.sum(F.when(F.col("bin") == MISSING, F.col(c)).otherwise(0.0)).over(whole)
    known = lambda c: F.sum(F.when(F.col("bin") == MISSING, 0.0).otherwise(F.col(c))).over(upto)
    rows = hist.select(
        "node", "feature", "bin", F.sum("g").over(whole).alias("G"), F.sum("h").over(whole).alias("H"), gone("g").alias("gm"), gone("h").alias("hm"),
        known("g").alias("gl"), known("h").alias("hl"), F.max("bin").over(whole).alias("last"),
    ).where(F.col("bin") != MISSING)
    side = lambda left: F.struct(
        gain_of(F.col("gl") + left * F.col("gm"), F.col("hl") + left * F.col("hm"), F.col("G") - F.col("gl") - left * F.col("gm"), F.col("H") - F.col("hl") - left * F.col("hm"), reg_lambda, gamma).alias("gain"),
        F.lit(bool(left)).alias("default_left"), (F.col("gl") + left * F.col("gm")).alias("gl"), (F.col("hl") + left * F.col("hm")).alias("hl"),
    )
    both = rows.select("node", "feature", "bin", "G", "H", "last", "hm", F.explode(F.array(side(0), side(1))).alias("s"))
    both = both.where((F.col("bin") < F.col("last")) | (F.col("hm") > 0) & ~F.col("s.default_left"))
    cut = both.select("node", "feature", "bin", F.col("s.default_left"), F.col("s.gain"), F.col("s.gl"), F.col("s.hl"), (F.col("G") - F.col("s.gl")).alias("gr"), (F.col("H") - F.col("s.hl")).alias("hr"))
    fit = cut.where((F.col("hl") >= min_child) & (F.col("hr") >= min_child) & (F.col("hl") > 0) & (F.col("hr") > 0))
    order = Window.partitionBy("node", "feature", "bin").orderBy(F.desc("gain"), "default_left")
    return fit.withColumn("_p", F.row_number().over(order)).where("_p = 1").drop("_p")


def best_splits(hist: DataFrame, **options) -> DataFrame:
    """The best cut of each node; ties by feature and bin."""
    order = Window.partitionBy("node").orderBy(F.desc("gain"), "feature", "bin")
    return all_splits(hist, **options).withColumn("_p", F.row_number().over(order)).where("_p = 1").drop("_p")


def cut_points(df: DataFrame, features: list[str], bins: int = 32) -> dict[str, list[float]]:
    """At most bins-1 rising cuts of each feature, from approximate quantiles: one mergeable summary a feature."""
    steps = [i / bins for i in range(1, bins)]
    out: dict[str, list[float]] = {}
    for at in range(0, len(features), 50):
        part = features[at : at + 50]
        value = lambda c: F.when(~F.isnan(F.col(c).cast("double")), F.col(c).cast("double"))
        row = df.agg(*[F.percentile_approx(value(c), steps, 2000).alias(c) for c in part]).first()
        out |= {c: sorted(set(row[c] or [])) for c in part}
    return out


def node_cuts(total: dict[tuple[int, int], np.ndarray], reg_lambda: float, gamma: float, min_child: float) -> list[tuple]:
    """Rows of `best_of` from the sums of g and of h by bin of each (node, feature)."""
    found: dict[int, list[int]] = {}
    for n, f in sorted(total):
        found.setdefault(n, []).append(f)
    rows = []
    for n, features in found.items():
        g, h = (np.stack([total[n, f][i] for f in features])[:, :, None] for i in (0, 1))
        left = np.array([0.0, 1.0])  # the side of missing values
        G, H = g.sum(axis=1, keepdims=True), h.sum(axis=1, keepdims=True)
        gl, hl = np.cumsum(g[:, 1:], axis=1) + left * g[:, :1], np.cumsum(h[:, 1:], axis=1) + left * h[:, :1]
        gr, hr = G - gl, H - hl
        there = h[:, 1:] > 0
        last = there & (np.cumsum(there[:, ::-1], axis=1)[:, ::-1] == 1)
        fit = there & (~last | (h[:, :1] > 0) & (left == 0)) & (hl >= min_child) & (hr >= min_child) & (hl > 0) & (hr > 0)
        with np.errstate(divide="ignore", invalid="ignore"):
            gain = np.where(fit, gain_of(gl, hl, gr, hr, reg_lambda, gamma), -np.inf)
        at = np.unravel_index(np.argmax(gain), gain.shape)  # the first of equal ones: by feature, by bin, missing values right
        sums = features[0], float(G[0, 0, 0]), float(H[0, 0, 0])
        cut = (features[at[0]], int(at[1]), bool(at[2]), *(float(x[at]) for x in (gain, gl, hl, gr, hr))) if fit[at] else (None,) * 8
        rows.append((n, *cut, *sums))
    return rows


def best_of(hist: DataFrame, bins: int, reg_lambda: float, gamma: float, min_child: float) -> DataFrame:
    """(node, feature, bin, default_left, gain, gl, hl, gr, hr, first, G, H): the best cut of each node by `all_splits`' rule among the
    features that meet in a task, feature null where none is fit; first, G, H: the least of these features and its sums.

    hist: (node, feature, sums), sums of g and of h by bin end to end, missing values first. One shuffle."""
    width = bins + 1

    def run(batches):
        total: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            for n, f, raw in zip(*(c.to_pylist() for c in batch.columns)):
                own = np.frombuffer(raw).reshape(2, width)
                total[n, f] = total[n, f] + own if (n, f) in total else own
        rows = node_cuts(total, reg_lambda, gamma, min_child)
        types = (pa.int64(), pa.int32(), pa.int32(), pa.bool_(), *[pa.float64()] * 5, pa.int32(), pa.float64(), pa.float64())
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], type=t) for i, t in enumerate(types)], names=list(CUT_NAMES))

    schema = "node BIGINT, feature INT, bin INT, default_left BOOLEAN, gain DOUBLE, gl DOUBLE, hl DOUBLE, gr DOUBLE, hr DOUBLE, first INT, G DOUBLE, H DOUBLE"
    return hist.repartition("node", "feature").mapInArrow(run, schema)


@dataclass
class Booster:
    """The trees: for each, arrays by node (children of i are 2i+1 and 2i+2): feature, bin, cut, default_left, gain, leaf, g, h."""

    features: list[str]
    cuts: dict[str, list[float]]
    base: float = 0.0
    eta: float = 0.3
    trees: list[dict[int, dict]] = field(default_factory=list)

    def table(self, spark) -> DataFrame:
        """(tree, node, feature, cut, default_left, gain, leaf, g, h); feature null at leaves."""
        rows = [
            (t, n, self.features[x["feature"]] if "feature" in x else None, x.get("cut"), x.get("default_left"), x.get("gain"), x["leaf"], x["g"], x["h"])
            for t, tree in enumerate(self.trees) for n, x in sorted(tree.items())
        ]
        return spark.createDataFrame(rows, "tree INT, node BIGINT, feature STRING, cut DOUBLE, default_left BOOLEAN, gain DOUBLE, leaf DOUBLE, g DOUBLE, h DOUBLE")

    def importance(self, spark) -> DataFrame:
        """(feature, gain): sum of the gains of a feature's splits, all features listed."""
        total = {f: 0.0 for f in self.features}
        for tree in self.trees:
            for x in tree.values():
                if "feature" in x:
                    total[self.features[x["feature"]]] += x["gain"]
        return spark.createDataFrame(list(total.items()), "feature STRING, gain DOUBLE")

    def binned(self, columns: list[np.ndarray], rows: int = 0) -> np.ndarray:
        out = np.empty((len(columns[0]) if columns else rows, len(columns)), dtype=np.int16)
        for i, (f, x) in enumerate(zip(self.features, columns)):
            out[:, i] = np.searchsorted(self.cuts[f], x, side="left")
            out[np.isnan(x), i] = MISSING
        return out

    @staticmethod
    def leaves(tree: dict[int, dict], bins: np.ndarray) -> np.ndarray:
        """The node where each row ends."""
        node = np.zeros(len(bins), dtype=np.int64)
        live = np.ones(len(bins), dtype=bool)
        while live.any():
            for n in np.unique(node[live]):
                here = live & (node == n)
                x = tree.get(int(n))
                if x is None or "feature" not in x:
                    live &= ~here
                    continue
                b = bins[here, x["feature"]]
                left = np.where(b == MISSING, x["default_left"], b <= x["bin"])
                node[here] = np.where(left, 2 * n + 1, 2 * n + 2)
        return node

    def margins(self, bins: np.ndarray, first: int = 0) -> np.ndarray:
        out = np.zeros(len(bins))
        for tree in self.trees[first:]:
            node = self.leaves(tree, bins)
            leaf = {n: x["leaf"] for n, x in tree.items()}
            out += self.eta * np.array([leaf[int(n)] for n in node]) if len(node) else 0
        return out

    def score(self, df: DataFrame, keep: list[str]) -> DataFrame:
        """keep columns and score, the probability."""
        sent = df.sparkSession.sparkContext.broadcast(self)
        kinds = dict(df.dtypes)
        n = len(keep)

        def run(batches):
            for batch in batches:
                model = sent.value
                bins = model.binned([c.to_numpy(zero_copy_only=False).astype(float) for c in batch.columns[n:]])
                p = 1 / (1 + np.exp(-(model.base + model.margins(bins))))
                yield pa.RecordBatch.from_arrays([*batch.columns[:n], pa.array(p)], names=[*keep, "score"])

        schema = ", ".join(f"`{c}` {kinds[c]}" for c in keep) + ", score double"
        return df.select(*keep, *[F.col(c).cast("double") for c in self.features]).mapInArrow(run, schema)


def grown(model: Booster, tree: dict[int, dict], rows: list, level: int, reg_lambda: float, max_nodes: int | None) -> set[int]:
    """Splits nodes of a level by rows of `best_of` and tells the new leaves."""
    if level == 0:
        one = min(rows, key=lambda r: r["first"], default={"G": 0.0, "H": 0.0})
        tree[0] = _leaf(one["G"], one["H"], reg_lambda)
    best: dict[int, Row | dict] = {}
    for r in sorted((r for r in rows if r["gain"] is not None and r["gain"] > 1e-9), key=lambda r: (-r["gain"], r["feature"], r["bin"])):
        best.setdefault(r["node"], r)
    frontier, held = set(), len(tree)
    for r in sorted(best.values(), key=lambda r: (-r["gain"], r["node"])):
        if max_nodes is not None and held + 2 > max_nodes:
            break
        held += 2
        n, f = r["node"], r["feature"]
        cuts = model.cuts[model.features[f]]
        tree[n] |= {"feature": f, "bin": r["bin"], "cut": float(cuts[r["bin"]]) if r["bin"] < len(cuts) else math.inf, "default_left": r["default_left"], "gain": r["gain"]}
        tree[2 * n + 1], tree[2 * n + 2] = _leaf(r["gl"], r["hl"], reg_lambda), _leaf(r["gr"], r["hr"], reg_lambda)
        frontier |= {2 * n + 1, 2 * n + 2}
    return frontier


def grown_in_task(state: DataFrame, model: Booster, trees: int, depth: int, bins: int, chosen: list[list[int]], reg_lambda: float, gamma: float, min_child: float, max_nodes: int | None) -> list[dict[int, dict]]:
    """All trees over binned rows that fit a task: the rows go to one, the trees come back. The cuts are those of the jobs by level."""
    sent = state.sparkSession.sparkContext.broadcast(model)
    p, width = len(model.features), bins + 1

    def run(batches):
        keys, labels, raw = [], [], []
        for batch in batches:
            keys.append(batch.column(0))
            labels.append(batch.column(1).to_numpy())
            raw.append(np.frombuffer(b"".join(batch.column(2).to_pylist()), dtype=np.int16).reshape(-1, p))
        own = replace(sent.value, trees=[])
        if keys:
            order = pc.sort_indices(pa.chunked_array(keys)).to_numpy()  # sums do not depend on how rows came
            y, b = np.concatenate(labels)[order], np.concatenate(raw)
            raw.clear()
            places = np.ascontiguousarray(b.T)[:, order]
            del b
            places += 1
        else:
            y, places = np.zeros(0), np.zeros((p, 0), dtype=np.int16)
        margin = np.full(len(y), own.base)
        for t in range(trees):
            q = 1 / (1 + np.exp(-margin))
            g, h = q - y, q * (1 - q)
            tree: dict[int, dict] = {}
            at = np.zeros(len(y), dtype=np.int64)
            frontier = {0}
            for level in range(depth + 1):
                total = {}
                for n in sorted(frontier):
                    here = np.flatnonzero(at == n)
                    if not len(here):
                        continue
                    gn, hn = g[here], h[here]
                    for f in chosen[t]:
                        x = places[f] if len(here) == len(y) else places[f][here]
                        total[n, f] = np.stack([np.bincount(x, weights=gn, minlength=width), np.bincount(x, weights=hn, minlength=width)])
                rows = [dict(zip(CUT_NAMES, r)) for r in node_cuts(total, reg_lambda, gamma, min_child)]
                frontier = grown(own, tree, rows, level, reg_lambda, max_nodes)
                for n in {(m - 1) // 2 for m in frontier}:
                    here, x = np.flatnonzero(at == n), tree[n]
                    bin_of = places[x["feature"]][here] - 1
                    at[here] = np.where(np.where(bin_of == MISSING, x["default_left"], bin_of <= x["bin"]), 2 * n + 1, 2 * n + 2)
                if not frontier or level == depth - 1:
                    break
            own.trees.append(tree)
            leaf = {n: x["leaf"] for n, x in tree.items()}
            names, which = np.unique(at, return_inverse=True)
            margin = margin + own.eta * np.array([leaf[int(n)] for n in names])[which]
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(own.trees)], type=pa.binary())], names=["trees"])

    return pickle.loads(state.select("key", "y", "bins").repartition(1).mapInArrow(run, "trees BINARY").first()["trees"])


def binned(df: DataFrame, features: list[str], label: str = "label", key: str = "sub_id", bins: int = 32) -> tuple[Booster, DataFrame, int]:
    """(a booster without trees, binned rows, written, and their number), for fits on the same rows."""
    mean = df.agg(F.avg(label)).first()[0] or 0.5
    mean = min(max(mean, 1e-6), 1 - 1e-6)
    model = Booster(features, cut_points(df, features, bins), math.log(mean / (1 - mean)))
    rows = df.select(F.col(key).alias("key"), F.col(label).cast("double").alias("y"), *[F.col(c).cast("double").alias(f"f{i}") for i, c in enumerate(features)])
    sent = df.sparkSession.sparkContext.broadcast(model)

    def bin_rows(batches):
        for batch in batches:
            b = sent.value.binned([c.to_numpy(zero_copy_only=False) for c in batch.columns[2:]], batch.num_rows)
            packed = pa.array([r.tobytes() for r in b], type=pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), packed, pa.array(np.full(len(b), sent.value.base))], names=["key", "y", "bins", "margin"])

    state = kept(rows.mapInArrow(bin_rows, f"key {rows.dtypes[0][1]}, y double, bins binary, margin double"), "binned")
    return model, state, state.count()


def boosted_second(
    df: DataFrame, features: list[str], label: str = "label", key: str = "sub_id", trees: int = 180, depth: int = 4, eta: float = 0.3, reg_lambda: float = 1.0,
    gamma: float = 0.0, min_child: float = 1.0, row_share: float = 1.0, col_share: float = 1.0, max_nodes: int | None = None, bins: int = 32, trace: list | None = None,
    ready: tuple[Booster, DataFrame, int] | None = None,
) -> Booster:
    """Boosting with gradients and curvatures of the logistic loss.

    max_nodes: nodes a tree may have; of a level's splits the best go first. trace: gets the total gain of each tree.
    ready: what `binned` gave for the same rows, features and bins."""
    spark, p = df.sparkSession, len(features)
    first, state, n = binned(df, features, label, key, bins) if ready is None else ready
    model = replace(first, eta=eta, trees=[])
    drawn = [[i for i in range(p) if col_share >= 1 or np.random.default_rng([t, i]).random() < col_share] or [t % p] for t in range(trees)]
    if row_share >= 1 and n * p <= IN_TASK:
        model.trees = grown_in_task(state, model, trees, depth, bins, drawn, reg_lambda, gamma, min_child, max_nodes)
        if trace is not None:
            trace += [sum(x.get("gain", 0.0) for x in tree.values()) for tree in model.trees]
        return model
    done = 0
    for t in range(trees):
        chosen = drawn[t]
        tree: dict[int, dict] = {}
        frontier = {0}
        for level in range(depth + 1):
            view = spark.sparkContext.broadcast((Booster(features, {}, 0.0, eta, model.trees[done:]), dict(tree), sorted(frontier), chosen))

            def partial(batches, view=view):
                newer, tree, nodes, chosen = view.value
                total: dict[int, np.ndarray] = {}
                width = bins + 1
                for batch in batches:
                    y, raw, margin = (batch.column(i) for i in range(3))
                    b = np.frombuffer(b"".join(raw.to_pylist()), dtype=np.int16).reshape(-1, p)
                    if not len(b):
                        continue
                    q = 1 / (1 + np.exp(-(margin.to_numpy() + newer.margins(b))))
                    g, h = q - y.to_numpy(), q * (1 - q)
                    at = Booster.leaves(tree, b) if tree else np.zeros(len(b), dtype=np.int64)
                    for n in nodes:
                        here = np.nonzero(at == n)[0]
                        if len(here):
                            hist = total.setdefault(n, np.zeros((2, p, width)))
                            for f in chosen:
                                x = b[here, f] + 1
                                hist[0, f] += np.bincount(x, weights=g[here], minlength=width)
                                hist[1, f] += np.bincount(x, weights=h[here], minlength=width)
                for n, hist in total.items():
                    sums = [hist[:, f].tobytes() for f in chosen]
                    yield pa.RecordBatch.from_arrays([pa.array([n] * len(chosen), type=pa.int64()), pa.array(chosen, type=pa.int32()), pa.array(sums)], names=["node", "feature", "sums"])

            used = state if row_share >= 1 else state.where(draw(F.col("key"), f"row{t}") < row_share)
            hist = used.select("y", "bins", "margin").mapInArrow(partial, "node BIGINT, feature INT, sums BINARY")
            # a row for each node of the frontier and task comes back
            rows = best_of(hist, bins, reg_lambda, gamma, min_child).collect()
            frontier = grown(model, tree, rows, level, reg_lambda, max_nodes)
            if not frontier or level == depth - 1:
                break
        model.trees.append(tree)
        if trace is not None:
            trace.append(sum(x.get("gain", 0.0) for x in tree.values()))
        if (t + 1) % CUT == 0 and t + 1 < trees:
            view = spark.sparkContext.broadcast(Booster(features, {}, 0.0, eta, model.trees[done:]))

            def moved(batches, view=view):
                for batch in batches:
                    b = np.frombuffer(b"".join(batch.column(2).to_pylist()), dtype=np.int16).reshape(-1, p)
                    yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(batch.column(3).to_numpy() + view.value.margins(b))], names=["key", "y", "bins", "margin"])

            state = kept(state.mapInArrow(moved, state.schema), "margins")
            done = len(model.trees)
    return model


def _leaf(g: float, h: float, reg_lambda: float) -> dict:
    return {"leaf": -g / (h + reg_lambda), "g": g, "h": h}


def own_tree(df: DataFrame, features: list[str], depth: int = 20, max_nodes: int = 398, **options) -> Booster:
    """One tree with a bound on its nodes, grown by the same splits."""
    return boosted_second(df, features, trees=1, depth=depth, eta=1.0, max_nodes=max_nodes, **options)
