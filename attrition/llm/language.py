"""Language identification by a byte convolutional network, trained in numpy.

Texts, their A-Z lower-cased, are cut into fixed windows of bytes that cover all of them. Filters of several widths
slide over a window's byte embeddings, each filter keeps its maximum over the window, and a
softmax layer turns the maxima into language probabilities; a text's answer is the mean of
its windows' log-probabilities, weighted by their bytes.

At prediction the embedding and filter weights fold into lookup tables (one row of filter
outputs for a pair of bytes), so a window costs gathers, additions and a maximum.

Text null or without any letter: ``und`` with score 0. A table without labelled rows learns
one class, ``und``. Rows with null id are never held out. Very long texts are read in blocks
of windows. Repeated rows repeat; clashing other columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_bucket, map_batches, mix64, pieces

WINDOW = 256
WIDTHS = (2, 3, 4)
LETTER = regex.compile(r"\p{L}")
BLOCK = 256


@dataclass
class ByteNet:
    labels: list[str]
    embed: np.ndarray  # 256 x E
    filters: list[np.ndarray]  # width x E x K for each width
    filter_bias: np.ndarray  # len(WIDTHS) * K
    dense: np.ndarray  # len(WIDTHS) * K x L
    dense_bias: np.ndarray

    def folded(self) -> FoldedNet:
        single = [np.einsum("be,wek->wbk", self.embed, f) for f in self.filters]
        k = self.filters[0].shape[2]
        pairs = lambda a, b: (a[:, None, :] + b[None, :, :]).reshape(65536, k).astype(np.float32)
        two, three, four = single
        return FoldedNet(
            self.labels, pairs(two[0], two[1]), pairs(three[0], three[1]), three[2].astype(np.float32),
            pairs(four[0], four[1]), pairs(four[2], four[3]), self.filter_bias.astype(np.float32),
            self.dense.astype(np.float32), self.dense_bias.astype(np.float32),
        )


@dataclass
class FoldedNet:
    labels: list[str]
    w2: np.ndarray
    w3: np.ndarray
    w3_last: np.ndarray
    w4: np.ndarray
    w4_last: np.ndarray
    filter_bias: np.ndarray
    dense: np.ndarray
    dense_bias: np.ndarray

    def maxima(self, windows: np.ndarray) -> np.ndarray:
        """windows: n x (WINDOW + 3) bytes, the last three from the next window so that no position is lost."""
        pair = windows[:, :-1].astype(np.int32) << 8 | windows[:, 1:]
        a = self.w2[pair[:, :WINDOW]].max(axis=1)
        b = (self.w3[pair[:, :WINDOW]] + self.w3_last[windows[:, 2 : WINDOW + 2]]).max(axis=1)
        c = (self.w4[pair[:, :WINDOW]] + self.w4_last[pair[:, 2 : WINDOW + 2]]).max(axis=1)
        return np.maximum(np.concatenate([a, b, c], axis=1) + self.filter_bias, 0)

    def log_probabilities(self, windows: np.ndarray) -> np.ndarray:
        z = self.maxima(windows) @ self.dense + self.dense_bias
        z -= z.max(axis=1, keepdims=True)
        return z - np.log(np.exp(z).sum(axis=1, keepdims=True))

    def judge(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """Label and score of each text."""
        labels, scores = ["und"] * len(texts), np.zeros(len(texts))
        some = [i for i, t in enumerate(texts) if t and LETTER.search(t)]
        for start in range(0, len(some), BLOCK):
            part = some[start : start + BLOCK]
            windows, owner, held = windows_of([texts[i].encode("utf-8", "surrogatepass").lower() for i in part])
            total = np.zeros((len(part), len(self.labels)))
            for at in range(0, len(windows), BLOCK):
                logs = self.log_probabilities(windows[at : at + BLOCK])
                np.add.at(total, owner[at : at + BLOCK], logs * held[at : at + BLOCK, None])
            total /= np.bincount(owner, weights=held)[:, None]
            total = np.exp(total - total.max(axis=1, keepdims=True))
            total /= total.sum(axis=1, keepdims=True)
            best = total.argmax(axis=1)
            scores[part] = total[np.arange(len(part)), best]
            for i, b in zip(part, best):
                labels[i] = self.labels[b]
        return labels, scores


def windows_of(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All windows of all texts, the text each belongs to, and the bytes it holds. Windows end padded by spaces."""
    lengths = np.array([len(t) for t in texts], dtype=np.int64)
    counts = np.maximum(1, -(-lengths // WINDOW))
    out = np.empty((int(counts.sum()), WINDOW + 3), dtype=np.uint8)
    owner, held, at = np.repeat(np.arange(len(texts)), counts), np.full(len(out), WINDOW, dtype=np.int64), 0
    for text, n in zip(texts, counts):
        flat = np.full(n * WINDOW + 3, 32, dtype=np.uint8)
        flat[: len(text)] = np.frombuffer(text, dtype=np.uint8)
        out[at : at + n, :WINDOW] = flat[: n * WINDOW].reshape(n, WINDOW)
        out[at : at + n, WINDOW:] = np.lib.stride_tricks.sliding_window_view(flat[WINDOW:], 3)[::WINDOW][:n]
        held[at + n - 1] = max(1, len(text) - (n - 1) * WINDOW)
        at += n
    return out, owner, held


def train(windows: np.ndarray, targets: np.ndarray, labels: list[str], filters=12, embedding=6, epochs=12, rate=0.01, seed=7) -> ByteNet:
    """Adam on cross-entropy; the maximum passes its gradient to the position that gave it."""
    rng = np.random.default_rng(seed)
    n_out = len(WIDTHS) * filters
    p = {
        "embed": rng.normal(0, 0.5, (256, embedding)),
        **{f"f{w}": rng.normal(0, (w * embedding) ** -0.5, (w, embedding, filters)) for w in WIDTHS},
        "fb": np.zeros(n_out),
        "dense": rng.normal(0, n_out**-0.5, (n_out, len(labels))),
        "db": np.zeros(len(labels)),
    }
    m, v, t = {k: np.zeros_like(x) for k, x in p.items()}, {k: np.zeros_like(x) for k, x in p.items()}, 0
    for _ in range(epochs):
        order = rng.permutation(len(windows))
        for start in range(0, len(order), 128):
            pick = order[start : start + 128]
            x, y = windows[pick].astype(np.int64), targets[pick]
            rows = np.arange(len(pick))
            e = p["embed"][x]
            best, at = [], []
            for w in WIDTHS:
                z = sum(e[:, j : j + WINDOW] @ p[f"f{w}"][j] for j in range(w))
                at.append(z.argmax(axis=1))
                best.append(z.max(axis=1))
            pre = np.concatenate(best, axis=1) + p["fb"]
            h = np.maximum(pre, 0)
            z = h @ p["dense"] + p["db"]
            z = np.exp(z - z.max(axis=1, keepdims=True))
            z /= z.sum(axis=1, keepdims=True)
            z[rows, y] -= 1
            z /= len(pick)
            g = {k: np.zeros_like(a) for k, a in p.items()}
            g["dense"], g["db"] = h.T @ z, z.sum(axis=0)
            back = (z @ p["dense"].T) * (pre > 0)
            g["fb"] = back.sum(axis=0)
            for i, w in enumerate(WIDTHS):
                d, pos = back[:, i * filters : (i + 1) * filters], at[i]
                for j in range(w):
                    letters = x[rows[:, None], pos + j]  # batch x filters
                    seen = p["embed"][letters]
                    g[f"f{w}"][j] = np.einsum("bke,bk->ek", seen, d)
                    np.add.at(g["embed"], letters, d[:, :, None] * p[f"f{w}"][j].T[None])
            t += 1
            for k in p:
                m[k] = 0.9 * m[k] + 0.1 * g[k]
                v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
                p[k] = p[k] - rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
    return ByteNet(labels, p["embed"], [p[f"f{w}"] for w in WIDTHS], p["fb"], p["dense"], p["db"])


def labelled_windows(docs: DataFrame, key: str, text: str, label: str, per_label: int, most: int, per_text: int) -> list:
    """(label, window) rows: of about per_label rows of each label, picked by hash of id and text, up to per_text windows
    each, picked by hash from all of the text. Labels share `most` windows where they are too many for that.

    Two passes: label counts (one row a label), then the rows whose hash falls below the share wanted. Only windows of
    fixed size leave the tasks. More than `most` labels raise an error: a network has one output for each."""
    usable = docs.where(F.col(label).isNotNull() & F.col(text).isNotNull())
    counts = usable.groupBy(label).count()
    n = counts.count()
    if n > most:
        raise ValueError(f"{n} labels: at most {most} can be learned")
    per_label = min(per_label, -(-most // max(1, n * per_text)))
    shares = F.broadcast(counts.select(F.col(label).alias("_label"), F.least(F.lit(1.0), F.lit(float(per_label)) / F.col("count")).alias("_share")))  # at most `most` rows
    draw = F.pmod(F.xxhash64(key, text), F.lit(1 << 30)) / F.lit(float(1 << 30))
    rows = usable.select(F.col(label).alias("_label"), F.col(text).alias("_text"), draw.alias("_draw")).join(shares, "_label").where("_draw < _share")

    def work():
        def step(labels, texts):
            some = [i for i, t in enumerate(texts) if LETTER.search(t)]
            if not some:
                return None
            raw = [texts[i].encode("utf-8", "surrogatepass").lower() for i in some]
            windows, owner, _ = windows_of(raw)
            seeds = np.array([xxhash.xxh3_64_intdigest(r) for r in raw], dtype=np.uint64)
            place = np.arange(len(owner)) - np.searchsorted(owner, owner)
            draws = mix64(seeds[owner] + place.astype(np.uint64))
            order = np.lexsort((draws, owner))
            keep = order[place < per_text]  # place also counts along the order, text by text
            return {"label": [labels[some[i]] for i in owner[keep]], "window": [w.tobytes() for w in windows[keep]]}

        return step

    kind = docs.schema[label].dataType.simpleString()
    return map_batches(rows.select("_label", "_text"), f"label {kind}, window binary", work).collect()  # some 260 bytes each


def fit(
    docs: DataFrame, key: str = "doc_id", text: str = "text", label: str = "lang", per_label: int = 800, most: int = 200_000, per_text: int = 3,
) -> ByteNet:
    """The network fitted on a bounded sample: about per_label rows of each label, up to per_text windows of each, about
    `most` windows in all."""
    rows = sorted((r[0], r[1]) for r in labelled_windows(docs, key, text, label, per_label, most, per_text)) or [("und", b" " * (WINDOW + 3))]
    labels = sorted({r[0] for r in rows})
    place = {a: i for i, a in enumerate(labels)}
    windows = np.frombuffer(b"".join(w for _, w in rows), dtype=np.uint8).reshape(-1, WINDOW + 3)
    return train(windows, np.array([place[a] for a, _ in rows]), labels)


def predict(docs: DataFrame, net: ByteNet, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, lang_pred, score) for each row of docs; the whole text is read."""
    kind = docs.schema[key].dataType.simpleString()
    folded = net.folded()
    sent = docs.sparkSession.sparkContext.broadcast(folded)  # six tables of 65536 x filters at most: 20 MB whatever the data

    def work():
        model = sent.value

        def step(keys, texts):
            labels, scores = model.judge(texts)
            return {key: keys, "lang_pred": labels, "score": scores}

        return step

    return map_batches(docs.select(key, text), f"{key} {kind}, lang_pred string, score double", work)


def identify(docs: DataFrame, key: str = "doc_id", text: str = "text", label: str = "lang", folds: int = 4, held: int = 2, **fitting) -> DataFrame:
    """Learns from the rows outside the held-out fold and labels all rows: (key, held_out, lang_pred, score)."""
    outside = docs.where(F.coalesce(crc_bucket(key, folds) != held, F.lit(True)))
    net = fit(outside, key, text, label, **fitting)
    out = predict(docs, net, key, text)
    return out.select(key, F.coalesce(crc_bucket(key, folds) == held, F.lit(False)).alias("held_out"), "lang_pred", "score")


def accepted(docs: DataFrame, least: float = 0.5, **options) -> DataFrame:
    """Rows of docs whose text has a letter and whose language is told with at least that score; all columns kept.

    The decision travels with the row: no join by id, so repeated ids and null ids stay apart."""
    key, text, label = options.get("key", "doc_id"), options.get("text", "text"), options.get("label", "lang")
    net = fit(docs, key, text, label)
    folded = docs.sparkSession.sparkContext.broadcast(net.folded())

    at = docs.columns.index(text)

    def keep(batches):
        for batch in pieces(batches):
            labels, scores = folded.value.judge(batch.column(at).to_pylist())
            yield batch.filter(pa.array((scores >= least) & (np.array(labels, dtype=object) != "und")))

    return docs.mapInArrow(keep, docs.schema)
