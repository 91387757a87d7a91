"""Quality classifier with hierarchical empirical Bayes.

A logistic model on words and on the shape of a text gives each document's own evidence. Sites
are a hierarchy: host, and path within the host. Grouped sums of the evidence give each host
a posterior that is shrunk towards the global mean, and each path one that is shrunk towards
its host; how strongly, is estimated from the spread between sites (method of moments), so
sparse sites stay near their parent. A document's score is its own log-odds moved by those
of its path against the global mean, its own share taken out of the path first.

The logistic model is fitted on a bounded sample of labelled rows; all sums are over all rows.
Only sums of a host or path are shuffled, so a host with a third of the rows is one row of
each task. Null host or path is a site of its own. Null or empty text has the evidence of a
text without words. Rows without labels are never needed; without any, evidence is 1/2.
Repeated rows repeat; ids may be null (never labelled then); other columns are not read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, crc_bucket, pieces, saved, words_of

SHAPES = 8
OUTER = b".,;:!?\"'()[]{}"
CAPITALS, LETTERS, MARKS = re.compile(r"[A-Z]+"), re.compile(r"[^\W\d_]+"), re.compile(r"[^\w\s.,;:'!?-]+")
#: Words of the model: those in at least so many sampled rows, at most so many, and so telling of a label.
SEEN, WORDS = 5, 100_000
TELLING = 4.5
#: Words that a worker remembers.
REMEMBER = 200_000


def shape(text: str, words: list[bytes], distinct: set[bytes]) -> list[float]:
    n, size = max(1, len(words)), max(1, len(text))
    letters, capitals, marks = (sum(map(len, kind.findall(text))) for kind in (LETTERS, CAPITALS, MARKS))  # by their runs
    return [
        np.log1p(len(words)), len(distinct) / n, letters / size, capitals / size,
        marks / size, min(40.0, size / n), np.log1p(text.count("\n")), len(distinct) / n**0.7,
    ]


def features(text: str | None) -> tuple[set[bytes], list[float]]:
    """Distinct words, and the shape."""
    words = words_of(text)
    distinct = set(words)
    return distinct, shape(text or "", words, distinct)


def name_of(word: bytes) -> int:
    """A word's number: the hash of it without outer punctuation."""
    return xxhash.xxh3_64_intdigest(word.strip(OUTER))


@dataclass
class Logistic:
    """Heads share words and shapes: weight[number of a word] is one number for each head."""

    heads: tuple[str, ...]
    weight: dict[int, np.ndarray]
    mean: np.ndarray
    spread: np.ndarray
    shape_weight: np.ndarray  # shapes x heads
    bias: np.ndarray

    def probabilities(self, texts: list[str | None], known: dict[bytes, int]) -> np.ndarray:
        """known: a worker's memory of words, their number if it has a weight, else -1."""
        z = np.empty((len(texts), len(self.heads)))
        for i, t in enumerate(texts):
            words, form = features(t)
            new = [w for w in words if w not in known]
            if new:
                if len(known) + len(new) > REMEMBER:
                    known.clear()
                    new = words
                known.update((w, n if (n := name_of(w)) in self.weight else -1) for w in new)
            hits = {known[w] for w in words}
            hits.discard(-1)
            z[i] = self.bias + np.clip((np.array(form) - self.mean) / self.spread, -6, 6) @ self.shape_weight
            if hits:
                z[i] += np.sum([self.weight[h] for h in hits], axis=0)
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def telling_words(flat: np.ndarray, own: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Numbers of the words in at least SEEN rows whose rows depart from a head's share by TELLING standard deviations.

    flat: numbers, own: the row of each; y: rows x heads."""
    found, worth = [np.empty(0, dtype=np.uint64)], [np.empty(0)]
    for part in range(16):  # a slice of the numbers at a time: sorting all at once takes several times their memory
        here = np.nonzero(flat >> np.uint64(60) == part)[0]
        names, which = np.unique(flat[here], return_inverse=True)
        rows, best = own[here], np.zeros(len(names))
        for label in y.T:
            known = ~np.isnan(label)
            share = float(np.nanmean(label)) if known.any() else 0.0
            if 0 < share < 1:
                n = np.bincount(which, weights=known[rows], minlength=len(names))
                good = np.bincount(which, weights=np.nan_to_num(label)[rows], minlength=len(names))
                best = np.maximum(best, np.where(n >= SEEN, np.abs(good - n * share) / np.sqrt(np.maximum(n, 1) * share * (1 - share)), 0))
        found.append(names[best >= TELLING])
        worth.append(best[best >= TELLING])
    found, worth = np.concatenate(found), np.concatenate(worth)
    return np.sort(found[np.argsort(-worth, kind="stable")[:WORDS]])


def fit(rows: list[tuple[np.ndarray, list[float], list[float]]], heads: tuple[str, ...], epochs: int = 30, rate: float = 0.05, decay: float = 2e-3, seed: int = 1) -> Logistic:
    """Adam on the cross-entropy of every head; rows are (numbers of words, shape, labels), labels in 0, 1 or NaN (unknown)."""
    if not rows:
        return Logistic(heads, {}, np.zeros(SHAPES), np.ones(SHAPES), np.zeros((SHAPES, len(heads))), np.zeros(len(heads)))
    own = np.repeat(np.arange(len(rows), dtype=np.int32), [len(w) for w, _, _ in rows])
    names = telling_words(np.concatenate([w for w, _, _ in rows]), own, np.array([g for _, _, g in rows], dtype=float))
    del own
    columns = [np.nonzero(np.isin(names, w))[0] for w, _, _ in rows]
    x = np.array([f for _, f, _ in rows])
    mean, spread = x.mean(axis=0), x.std(axis=0) + 1e-6
    x, y = np.clip((x - mean) / spread, -6, 6), np.array([g for _, _, g in rows], dtype=float)
    known = ~np.isnan(y)
    share = np.clip([np.nanmean(c) if k.any() else 0.5 for c, k in zip(y.T, known.T)], 1e-3, 1 - 1e-3)
    p = {"w": np.zeros((len(names), len(heads))), "s": np.zeros((SHAPES, len(heads))), "b": np.log(share / (1 - share))}
    m, v, t = {k: np.zeros_like(a) for k, a in p.items()}, {k: np.zeros_like(a) for k, a in p.items()}, 0
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for start in range(0, len(order), 512):
            pick = order[start : start + 512]
            cols = np.concatenate([columns[i] for i in pick])
            own = np.repeat(np.arange(len(pick)), [len(columns[i]) for i in pick])
            z = x[pick] @ p["s"] + p["b"]
            for h in range(len(heads)):
                z[:, h] += np.bincount(own, weights=p["w"][cols, h], minlength=len(pick))
            e = np.where(known[pick], 1 / (1 + np.exp(-np.clip(z, -30, 30))) - np.nan_to_num(y[pick]), 0) / len(pick)
            g = {"s": x[pick].T @ e, "b": e.sum(axis=0), "w": np.stack([np.bincount(cols, weights=e[own, h], minlength=len(names)) for h in range(len(heads))], axis=1)}
            g["w"] = g["w"] + decay * p["w"] / len(rows) * 512
            t += 1
            for k in p:
                m[k] = 0.9 * m[k] + 0.1 * g[k]
                v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
                p[k] -= rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-4)
    strong = np.abs(p["w"]).max(axis=1) > 1e-3 if len(names) else np.zeros(0, dtype=bool)
    return Logistic(heads, {int(w): p["w"][i] for i, w in enumerate(names) if strong[i]}, mean, spread, p["s"], p["b"])


def labelled_rows(docs: DataFrame, labels: DataFrame, heads, key, text, most) -> list:
    """Features of about `most` labelled rows, by hash of id; so many labels go to every task, and so many rows of features,
    some 3 KB each, to the driver. Labels of one id are averaged; an id's texts, where it has several, all count."""
    n = labels.count()
    draw = F.pmod(F.xxhash64(F.col(key), F.lit("quality")), F.lit(1 << 30)) / F.lit(float(1 << 30))
    known = labels.where(F.col(key).isNotNull() & (draw < min(1.0, most / max(1, n))))
    known = known.groupBy(F.col(key).alias("_id")).agg(*[F.avg(h).alias(f"_{h}") for h in heads])
    own = docs.select(F.col(key).alias("_id"), F.col(text).alias("_text"), F.xxhash64(text).alias("_copy"))
    rows = own.join(F.broadcast(known), "_id").dropDuplicates(["_id", "_copy"])
    schema, arrow = arrow_schema("words binary, shape array<double>, labels array<double>, id string, copy long")

    def run(batches):
        for batch in pieces(batches):
            ids, copies, texts, *given = (c.to_pylist() for c in batch.columns)
            found = [features(t) for t in texts]
            gold = [[np.nan if x is None else float(x) for x in row] for row in zip(*given)]
            arrays = [np.unique(np.fromiter(map(name_of, w), dtype=np.uint64, count=len(w))).tobytes() for w, _ in found], [f for _, f in found], gold, [str(i) for i in ids], copies
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(arrays, arrow)], schema=arrow)

    got = rows.select("_id", "_copy", "_text", *[f"_{h}" for h in heads]).mapInArrow(run, schema).collect()
    return [(np.frombuffer(r["words"], dtype=np.uint64), r["shape"], r["labels"]) for r in sorted(got, key=lambda r: (r["id"], r["copy"]))]


def site_of(url: str) -> tuple[Column, Column]:
    """(host, path) of a column of addresses: the host in lower case without a leading `www.`, and the host with the first
    part of the path. Null or text that is no address: both null, a site of its own."""
    host = F.regexp_replace(F.lower(F.try_parse_url(F.col(url), F.lit("HOST"))), "^www[.]", "")
    return host, F.concat_ws("/", host, F.regexp_extract(F.try_parse_url(F.col(url), F.lit("PATH")), "^/([^/]+)/", 1))


def evidence(docs: DataFrame, model: Logistic, keep: list[Column], names: list[str], text: str) -> DataFrame:
    """The columns kept, and a column `p_<head>` for each head."""
    from pyspark.sql import types as T

    picked = docs.select(*[c.alias(n) for c, n in zip(keep, names)], F.col(text).alias("_text"))
    schema = T.StructType([*picked.schema.fields[:-1], *[T.StructField(f"p_{h}", T.DoubleType()) for h in model.heads]])
    sent = docs.sparkSession.sparkContext.broadcast(model)  # at most WORDS words

    def run(batches):
        known: dict[bytes, int] = {}
        for batch in pieces(batches):
            p = sent.value.probabilities(batch.column(batch.num_columns - 1).to_pylist(), known)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *map(pa.array, p.T.copy())], names=schema.names)

    return picked.mapInArrow(run, schema)


def strength(groups: DataFrame, total: str, n: str, prior: Column | float) -> float:
    """Pseudo-count by which groups are shrunk: within-group variance over between-group variance, by moments."""
    mean = F.col(total) / F.col(n)
    prior = prior if isinstance(prior, Column) else F.lit(prior)
    r = groups.agg(
        F.coalesce(F.sum(n), F.lit(0)), F.count("*"), F.sum(F.col(n) * (mean - prior) ** 2), F.sum(F.col("square") - F.col(n) * mean**2), F.sum(F.col(n).cast("double") ** 2),
    ).first()
    rows, k, between, within, squares = (float(x or 0) for x in r)
    if k < 2 or rows <= k:
        return 10.0
    noise = max(1e-9, within / (rows - k))
    spread = (between - (k - 1) * noise) / max(1e-9, rows - squares / rows)
    return float(np.clip(noise / spread, 0.5, 1e4)) if spread > 0 else 1e4


def log_odds(p: Column) -> Column:
    p = F.least(F.greatest(p, F.lit(1e-6)), F.lit(1 - 1e-6))
    return F.ln(p / (1 - p))


def classify(
    docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", host: Column | None = None, path: Column | None = None,
    most: int = 20_000, folds: int = 5, held: int = 2, least: float = 0.5, poison: float = 0.5,
) -> DataFrame:
    """(key, held_out, host, path, p_quality, host_quality, path_quality, quality, p_toxic, keep) for each row of docs.

    host and path default to the source and to its section by language; `site_of` tells them from an address. keep: quality is at least `least` and the
    evidence for toxic text is below `poison`. Labels of the held-out fold are not learned from."""
    host = F.col("source") if host is None else host
    path = F.concat_ws("/", F.col("source"), F.col("lang")) if path is None else path
    heads = ("quality", "toxic")
    training = labels.where(F.coalesce(crc_bucket(key, folds) != held, F.lit(True)))
    model = fit(labelled_rows(docs, training, heads, key, text, most), heads)
    rows = saved(evidence(docs, model, [F.col(key), host, path], [key, "host", "path"], text))
    p = F.col("p_quality")
    paths = saved(rows.groupBy("host", "path").agg(F.count("*").alias("n"), F.sum(p).alias("total"), F.sum(p * p).alias("square")))
    hosts = paths.groupBy("host").agg(F.sum("n").alias("hn"), F.sum("total").alias("htotal"), F.sum("square").alias("square"))
    mean = hosts.agg(F.sum("htotal") / F.greatest(F.sum("hn"), F.lit(1))).first()[0]
    mean = 0.5 if mean is None else float(mean)
    by_host, = (strength(hosts, "htotal", "hn", mean),)
    hosts = hosts.select(F.col("host").alias("_host"), ((F.col("htotal") + by_host * mean) / (F.col("hn") + by_host)).alias("host_quality"))
    placed = paths.join(hosts, F.col("host").eqNullSafe(F.col("_host"))).drop("_host")
    by_path = strength(placed, "total", "n", F.col("host_quality"))
    sites = placed.select(F.col("host").alias("_host"), F.col("path").alias("_path"), "n", "total", "host_quality")
    met = rows.join(sites, F.col("host").eqNullSafe(F.col("_host")) & F.col("path").eqNullSafe(F.col("_path")))
    others = (F.col("total") - p + by_path * F.col("host_quality")) / (F.col("n") - 1 + by_path)
    moved = log_odds(p) + log_odds(others) - log_odds(F.lit(mean))
    score = 1 / (1 + F.exp(-moved))
    return met.select(
        key, F.coalesce(crc_bucket(key, folds) == held, F.lit(False)).alias("held_out"), "host", "path", "p_quality", "host_quality",
        ((F.col("total") + by_path * F.col("host_quality")) / (F.col("n") + by_path)).alias("path_quality"), score.alias("quality"), "p_toxic",
        ((score >= least) & (F.col("p_toxic") < poison)).alias("keep"),
    )
