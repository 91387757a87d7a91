"""Language-model scoring: a causal self-attention model on subword ids, and the unigram base.

Base. Words of the training rows are counted over all of them. The commonest words go to every
task (a table of fixed size); occurrences of other words travel to the counts, packed by
slices of the hash range and summed per text and task beforehand.

Model. A text's words, A-Z lower-cased, are spelled as ids of a public byte-pair vocabulary (a
space before each word), closed by an end id. One layer of causal self-attention over windows
predicts the class of the next id; an id's share in its class follows from the id before it, by
counts over all training text that fall back to the id's own frequency (add-one), so the model
is a distribution over all texts of the vocabulary.
Windows overlap: each id is scored once, with at least `OVERLAP` ids of context where there are as
many. How often each class follows each of the commonest ids is counted over all training text and
enters the output; attention corrects it. Frequencies, classes, and the counts of what follows come
from all training texts, gathered in one reading. Attention weights come from gradient steps on every
window of every training text: they start from steps on a bounded number of windows, drawn by hash
from any place of any text; from there each task learns from all of its windows, and the tasks'
weights are averaged. So they depend on how texts are dealt to tasks; reruns on the same files agree.

Scores and weights are held within the range of single precision when the model is fitted, so that
nothing is cut while texts are scored and no text's score depends on its neighbours' range.

Null or empty text: one token, the end. Null ids are training rows. Without training rows all
counts are 0. Repeated rows repeat; other columns are not read. Long texts are scored in
blocks of windows.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, crc_bucket, mix64, pieces, saved, slice_bits, words_of

WINDOW, OVERLAP, WIDTH, CLASSES, SINGLE, ROWS = 32, 8, 16, 128, 104, 4096
#: Words whose counts every task gets: 16 MB. Occurrences of all others are looked up by a shuffle.
COMMON = 1_000_000
#: Words whose counts a worker remembers and whose ids it remembers (some 200 bytes each), words that it counts before it sends
#: them, and occurrences that it packs.
REMEMBER, SPELLED, FLUSH, PACK = 200_000, 500_000, 300_000, 500_000
#: Windows and scored ids that are worked on at once: what fits a core's cache.
BLOCK_WINDOWS, BLOCK_IDS = 128, 512
#: Occurrences that the classes' own shares weigh in the counts of classes after an id, and that an id's share in its class
#: weighs in the counts of ids after an id.
PRIOR, WEIGHT = 10.0, 2.0
#: Pairs of ids in a row whose counts every task gets (16 bytes each; the commonest), and bytes of text for each window, about.
PAIRS, WINDOW_BYTES = 2_000_000, 60
#: Parts in which tasks' weights are averaged.
PARTS = 16
#: What powers may reach in single precision.
RANGE = 60.0


# ---------------------------------------------------------------- counts


def gathered(docs: DataFrame, vocabulary: str, chance: float, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One reading of docs. Rows hold either (word, n) of a part of the texts, or (pair, n), the id before << 16 | the id,
    or a few windows drawn by hash of id, text and place, each window of each text being as likely."""
    schema, arrow = arrow_schema("word binary, pair long, n long, draws binary, inputs binary, targets binary, counts binary")
    limit = np.uint64(min(2**64 - 1, int(chance * 2**64)))

    def row_batch(size, **columns):
        return pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) if f.name in columns else pa.nulls(size, f.type) for f in arrow], schema=arrow)

    def run(batches):
        speller, seen = Speller(vocabulary), Counter()
        pairs, held = [], 0

        def summed():
            names, which = np.unique(np.concatenate([k for k, _ in pairs]), return_inverse=True)
            return names, np.bincount(which, weights=np.concatenate([c for _, c in pairs])).astype(np.int64)

        for batch in pieces(batches):
            keys, texts = (c.to_pylist() for c in batch.columns)
            split = [words_of(t) for t in texts]
            for words in split:
                seen.update(words)
            if len(seen) > FLUSH:
                yield row_batch(len(seen), word=list(seen), n=list(seen.values()))
                seen = Counter()
            windows = speller.windows(split)
            if windows is None:
                continue
            inner = np.ones(len(windows.flat) - 1, dtype=bool)
            inner[windows.first[1:] - 1] = False  # from one text's end to the next one's start
            flat = windows.flat.astype(np.uint32)
            found = np.unique((flat[:-1] << np.uint32(16) | flat[1:])[inner], return_counts=True)
            pairs.append(found)
            held += len(found[0])
            if held > FLUSH:
                names, n = summed()
                pairs, held = [(names, n)], len(names)
                if held > FLUSH // 2:
                    yield row_batch(held, pair=names.astype(np.int64), n=n)
                    pairs, held = [], 0
            seeds = np.fromiter((xxhash.xxh3_64_intdigest(f"{k} {t}".encode("utf-8", "surrogatepass")) for k, t in zip(keys, texts)), dtype=np.uint64, count=len(keys))
            draws = mix64(seeds[windows.owner] + windows.start.astype(np.uint64))
            which = np.nonzero(draws <= limit)[0]
            if len(which):
                inputs, targets, counts = windows.part(which)
                yield row_batch(1, draws=[draws[which].tobytes()], inputs=[inputs.tobytes()], targets=[targets.tobytes()], counts=[counts.tobytes()])
        if seen:
            yield row_batch(len(seen), word=list(seen), n=list(seen.values()))
        if pairs:
            names, n = summed()
            yield row_batch(len(names), pair=names.astype(np.int64), n=n)

    return docs.select(key, text).mapInArrow(run, schema)


def cut_of(counts: DataFrame, most: int) -> int:
    """The least n so that at most `most` rows of counts have it or more, told from the numbers of rows by size of n on a
    logarithmic scale (some hundred rows), so that nothing is sorted."""
    size = F.floor(16 * F.log2("n"))
    rows = sorted(counts.groupBy(size.alias("size")).agg(F.count("*").alias("rows"), F.min("n").alias("least"), F.max("n").alias("top")).collect(), key=lambda r: -r["size"])
    have, cut = 0, rows[0]["top"] + 1 if rows else 1
    for r in rows:
        have += r["rows"]
        if have > most:
            break
        cut = r["least"]
    return cut


def ranks_of(path: str):
    """The vocabulary at path (tiktoken ranks), one per worker process."""
    if path not in _ranks:
        import base64

        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        _ranks[path] = tiktoken.Encoding("words", pat_str=r"[\s\S]+", mergeable_ranks=ranks, special_tokens={}), max(ranks.values()) + 1
    return _ranks[path]


_ranks: dict = {}


def spelled(encoder, word: bytes) -> list[int]:
    return encoder._core_bpe.encode_single_piece(b" " + word) if len(word) < 2000 else encoder.encode_ordinary(" " + word.decode("utf-8", "replace"))


def id_totals(pairs: DataFrame, size: int) -> np.ndarray:
    """Occurrences of each subword id, from (pair, n): at most one row an id, so bounded."""
    out = np.zeros(size, dtype=np.int64)
    for r in pairs.groupBy(F.col("pair").bitwiseAND(F.lit(65535)).alias("id")).agg(F.sum("n").alias("n")).collect():
        out[r["id"]] = r["n"]
    return out


def followers(pairs: DataFrame, totals: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(counts of classes after each embedding row, pairs kept as row << 16 | id, their counts) from (pair, n).

    A row meets in one task: at most one entry for each id of the vocabulary."""
    row_of, class_of, _ = classes(totals)
    sent = pairs.sparkSession.sparkContext.broadcast((row_of, class_of))
    first, first_arrow = arrow_schema("row int, id int, n long")
    last, last_arrow = arrow_schema("row int, follows binary, ids binary, counts binary")

    def rows(batches):
        of, _ = sent.value
        for batch in batches:
            pair, n = (c.to_numpy() for c in batch.columns)
            yield pa.RecordBatch.from_arrays([pa.array(of[pair >> 16]), pa.array((pair & 65535).astype(np.int32)), pa.array(n)], schema=first_arrow)

    table = saved(pairs.select("pair", "n").mapInArrow(rows, first).groupBy("row", "id").agg(F.sum("n").alias("n")))
    cut = cut_of(table, PAIRS)

    def by_row(batches):
        _, classed = sent.value
        follows, kept = {}, {}
        for batch in batches:
            row, ids, n = (c.to_numpy() for c in batch.columns)
            for r in np.unique(row).tolist():
                here = row == r
                total = follows.setdefault(r, np.zeros(CLASSES, dtype=np.int64))
                total += np.bincount(classed[ids[here]], weights=n[here], minlength=CLASSES).astype(np.int64)
                here &= n >= cut
                kept.setdefault(r, []).append((ids[here], n[here]))
        if follows:
            joined = {r: [np.concatenate(x) for x in zip(*parts)] for r, parts in kept.items()}
            cells = list(follows), [f.tobytes() for f in follows.values()], *([joined[r][i].tobytes() for r in follows] for i in (0, 1))
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(cells, last_arrow)], schema=last_arrow)

    follows, keys, counts = np.zeros((ROWS, CLASSES), dtype=np.int64), [np.empty(0, dtype=np.uint32)], [np.empty(0, dtype=np.int64)]
    for r in table.repartition("row").mapInArrow(by_row, last).collect():  # a kilobyte for each of ROWS, and PAIRS pairs of 12 bytes
        follows[r["row"]] = np.frombuffer(r["follows"], dtype=np.int64)
        keys.append(np.uint32(r["row"] << 16) | np.frombuffer(r["ids"], dtype=np.int32).astype(np.uint32))
        counts.append(np.frombuffer(r["counts"], dtype=np.int64))
    keys, counts = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(keys)
    return follows, keys[order], counts[order]


# ---------------------------------------------------------------- model


class PairShares:
    """log10 share of an id in its class after an embedding row: kept pairs in a hash table, others by what is left.

    In a row's class, kept counts and WEIGHT times the ids' own shares add up; so shares of a class add up to one."""

    EMPTY, FACTOR = np.uint32(2**32 - 1), np.uint32(2654435769)

    def __init__(self, keys: np.ndarray, counts: np.ndarray, class_of: np.ndarray, share: np.ndarray):
        row, ids = (keys >> np.uint32(16)).astype(np.int64), (keys & np.uint32(65535)).astype(np.int64)
        cell = row * CLASSES + class_of[ids]
        whole = np.bincount(cell, weights=counts, minlength=ROWS * CLASSES) + WEIGHT
        self.rest = np.log10(WEIGHT / whole).astype(np.float32)
        value = np.log10((counts + WEIGHT * 10.0 ** share[ids].astype(float)) / whole[cell]).astype(np.float32)
        self.bits = max(4, int(2 * len(keys)).bit_length())
        self.keys, self.values = np.full(1 << self.bits, self.EMPTY), np.zeros(1 << self.bits, dtype=np.float32)
        at, todo = self.place(keys), np.arange(len(keys))
        while len(todo):  # each free place takes one of the pairs that want it; the others go on to the next place
            free = todo[self.keys[at[todo]] == self.EMPTY]
            _, one = np.unique(at[free], return_index=True)
            took = free[one]
            self.keys[at[took]], self.values[at[took]] = keys[took], value[took]
            todo = np.setdiff1d(todo, took, assume_unique=True)
            at[todo] = (at[todo] + 1) & (len(self.keys) - 1)

    def place(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * self.FACTOR) >> np.uint32(32 - self.bits)).astype(np.int64)

    def logs(self, rows: np.ndarray, ids: np.ndarray, class_of: np.ndarray, share: np.ndarray) -> np.ndarray:
        keys = rows.astype(np.uint32) << np.uint32(16) | ids
        at = self.place(keys)
        there = self.keys[at]
        hit = there == keys
        out = self.values[at]
        todo = np.flatnonzero(~hit & (there != self.EMPTY))
        while len(todo):
            at[todo] = (at[todo] + 1) & (len(self.keys) - 1)
            there = self.keys[at[todo]]
            good = there == keys[todo]
            out[todo[good]] = self.values[at[todo[good]]]
            hit[todo[good]] = True
            todo = todo[~good & (there != self.EMPTY)]
        gone = np.flatnonzero(~hit)
        out[gone] = share[ids[gone]] + self.rest[rows[gone].astype(np.int64) * CLASSES + class_of[ids[gone]]]
        return out


@dataclass
class Attention:
    """Everything that scoring needs: tables by id, and the weights of one attention layer."""

    row_of: np.ndarray  # id -> embedding row
    class_of: np.ndarray  # id -> class
    share: np.ndarray  # id -> log10 of its share in its class
    embed: np.ndarray
    place: np.ndarray
    qkv: np.ndarray
    out: np.ndarray
    after: np.ndarray  # embedding row -> log share of each class after it, the bias included
    pairs: PairShares

    def asked(self) -> np.ndarray:
        """What an embedding row asks for, answers to and gives, and a one; that of its place is to be added."""
        return np.concatenate([self.embed @ self.qkv, np.ones((ROWS, 1), dtype=np.float32)], axis=1)

    def held(self) -> Attention:
        """Itself, with weights scaled down where a score could leave the range of single precision, whatever the text."""
        x = (self.embed[:, None] + self.place).reshape(-1, WIDTH).astype(float)
        q, k, v = (np.linalg.norm(x @ self.qkv[:, at : at + WIDTH], axis=1).max() for at in (0, WIDTH, 2 * WIDTH))
        if q * k > RANGE:
            self.qkv[:, : 2 * WIDTH] *= np.sqrt(RANGE / (q * k))
        reach = (np.linalg.norm(x, axis=1).max() + v) * np.linalg.norm(self.out, axis=0).max()
        if reach > RANGE:
            self.out *= RANGE / reach
        return self


CAUSAL = np.tril(np.ones((WINDOW, WINDOW), dtype=np.float32))


class Windows:
    """Overlapping windows over many texts' ids, joined end to end (each text's first id is the start mark, its last the end)."""

    def __init__(self, flat: np.ndarray, sizes: np.ndarray):
        self.flat, self.n, self.first = flat, sizes - 1, np.cumsum(sizes) - sizes
        step = WINDOW - OVERLAP
        counts = np.where(self.n <= WINDOW, 1, 1 - (WINDOW - self.n) // step)
        self.owner = np.repeat(np.arange(len(sizes)), counts)
        place = np.arange(len(self.owner)) - np.repeat(np.cumsum(counts) - counts, counts)
        self.start = np.minimum(place * step, np.maximum(0, self.n - WINDOW)[self.owner])
        self.done = np.where(place > 0, (place - 1) * step + WINDOW, 0)

    def __len__(self) -> int:
        return len(self.owner)

    def part(self, which) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Inputs, targets and which targets count, of some windows."""
        at, counts = self.places(which)
        return self.flat[at], self.flat[at + 1], counts

    def places(self, which) -> tuple[np.ndarray, np.ndarray]:
        """Places of inputs of some windows, and which of the ids after them count."""
        n = self.n[self.owner[which]][:, None]
        at = self.start[which][:, None] + np.arange(WINDOW)
        counts = (at < n) & (at >= self.done[which][:, None])
        return np.minimum(at, n - 1) + self.first[self.owner[which]][:, None], counts


def classes(totals: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row_of, class_of, log10 share): the commonest ids have classes of their own, the others share the rest by mass."""
    order = np.argsort(-totals, kind="stable")
    row_of = np.full(len(totals), ROWS - 1, dtype=np.int32)
    row_of[order[: ROWS - 1]] = np.arange(ROWS - 1)
    class_of = np.empty(len(totals), dtype=np.int32)
    class_of[order[:SINGLE]] = np.arange(SINGLE)
    rest = order[SINGLE:]
    mass = np.cumsum(totals[rest] + 1.0)
    class_of[rest] = SINGLE + np.minimum((mass / mass[-1] * (CLASSES - SINGLE)).astype(int), CLASSES - SINGLE - 1)
    share = np.log10((totals + 1.0) / np.bincount(class_of, weights=totals + 1.0, minlength=CLASSES)[class_of])
    return row_of, class_of, share.astype(np.float32)


class Drawn:
    """Windows drawn from many tasks, in the order of their draws."""

    def __init__(self, draws: np.ndarray, inputs: np.ndarray, targets: np.ndarray, counts: np.ndarray):
        order = np.argsort(draws, kind="stable")
        self.inputs, self.targets, self.counts = inputs[order], targets[order], counts[order]

    def __len__(self) -> int:
        return len(self.inputs)

    def part(self, which) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.inputs[which], self.targets[which], self.counts[which]


def train(
    texts: Windows | Drawn | None, totals: np.ndarray, steps: int = 1500, batch: int = 64, rate: float = 0.01, seed: int = 3, follows: np.ndarray | None = None,
    pairs: tuple[np.ndarray, np.ndarray] | None = None,
) -> Attention:
    """Adam on the cross-entropy of the next id's class. follows: counts of classes after embedding rows, from which it
    starts; pairs: sorted keys and counts of ids after embedding rows, which tell shares in a class."""
    row_of, class_of, share = classes(totals)
    rng = np.random.default_rng(seed)
    p = {
        "embed": rng.normal(0, 0.3, (ROWS, WIDTH)), "place": rng.normal(0, 0.1, (WINDOW, WIDTH)),
        "qkv": rng.normal(0, WIDTH**-0.5, (WIDTH, 3 * WIDTH)), "out": np.zeros((WIDTH, CLASSES)), "bias": np.zeros(CLASSES),
    }
    p["qkv"][:, :WIDTH] *= 0.5
    mass = np.bincount(class_of, weights=totals + 1.0, minlength=CLASSES)
    follows = np.zeros((ROWS, CLASSES)) if follows is None else follows
    after = np.log((follows + PRIOR * mass / mass.sum()) / (follows.sum(axis=1, keepdims=True) + PRIOR))
    if texts is not None and len(texts):
        m, v = {k: np.zeros_like(a) for k, a in p.items()}, {k: np.zeros_like(a) for k, a in p.items()}
        for t in range(1, steps + 1):
            inputs, targets, counts = texts.part(rng.integers(0, len(texts), batch))
            rows, goal, w = row_of[inputs], class_of[targets], counts.astype(float)
            w /= max(1.0, w.sum())
            x = p["embed"][rows] + p["place"]
            q, k, val = np.split(x @ p["qkv"], 3, axis=2)
            s = q @ k.transpose(0, 2, 1)
            a = np.exp(np.clip(s, -30, 30)) * CAUSAL
            a /= a.sum(axis=2, keepdims=True)
            h = x + a @ val
            z = h @ p["out"] + p["bias"] + after[rows]
            z = np.exp(z - z.max(axis=2, keepdims=True))
            z /= z.sum(axis=2, keepdims=True)
            np.put_along_axis(z, goal[:, :, None], np.take_along_axis(z, goal[:, :, None], 2) - 1, 2)
            z *= w[:, :, None]
            g = {"out": np.einsum("bwd,bwc->dc", h, z), "bias": z.sum(axis=(0, 1))}
            dh = z @ p["out"].T
            da, dval = dh @ val.transpose(0, 2, 1), a.transpose(0, 2, 1) @ dh
            ds = a * (da - (da * a).sum(axis=2, keepdims=True))
            dqkv = np.concatenate([ds @ k, ds.transpose(0, 2, 1) @ q, dval], axis=2)
            g["qkv"] = np.einsum("bwd,bwe->de", x, dqkv)
            dx = dh + dqkv @ p["qkv"].T
            g["place"] = dx.sum(axis=0)
            g["embed"] = np.zeros_like(p["embed"])
            np.add.at(g["embed"], rows, dx)
            slow = rate * min(1.0, t / 20) * (1 - 0.9 * t / steps)
            for name in p:
                m[name] = 0.9 * m[name] + 0.1 * g[name]
                v[name] = 0.99 * v[name] + 0.01 * g[name] ** 2
                p[name] = p[name] - slow * (m[name] / (1 - 0.9**t)) / (np.sqrt(v[name] / (1 - 0.99**t)) + 1e-8)
    f = {k: a.astype(np.float32) for k, a in p.items()}
    keys, n = (np.empty(0, dtype=np.uint32), np.empty(0, dtype=np.int64)) if pairs is None else pairs
    return Attention(row_of, class_of, share, f["embed"], f["place"], f["qkv"], f["out"], (after + p["bias"]).astype(np.float32), PairShares(keys, n, class_of, share)).held()


class Learner:
    """Adam in single precision over windows as they come, starting from a model. `add` takes windows of some texts."""

    NAMES = ("embed", "place", "qkv", "out", "bias")

    def __init__(self, model: Attention, rate: float = 0.001, batch: int = 256):
        self.model, self.rate, self.batch, self.steps, self.windows = model, rate, batch, 0, 0
        self.p = {n: getattr(model, n).copy() for n in self.NAMES[:-1]} | {"bias": np.zeros(CLASSES, dtype=np.float32)}
        self.m, self.v = ({n: np.zeros_like(a) for n, a in self.p.items()} for _ in range(2))
        self.rng = np.random.default_rng(3)

    def add(self, texts: Windows | None) -> None:
        if texts is None:
            return
        order = self.rng.permutation(len(texts))
        for x in range(0, len(order), self.batch):
            self.step(*texts.part(order[x : x + self.batch]))

    def slopes(self, inputs: np.ndarray, targets: np.ndarray, counts: np.ndarray) -> tuple[float, dict]:
        """Cross-entropy of the classes that count, on the average, and its slope by each weight."""
        p, rows, ones = self.p, self.model.row_of[inputs], np.ones(CLASSES, dtype=np.float32)
        x = p["embed"][rows]
        x += p["place"]
        y = x @ p["qkv"]
        q, k, val = (y[:, :, i : i + WIDTH] for i in (0, WIDTH, 2 * WIDTH))
        a = q @ k.transpose(0, 2, 1)
        free = np.abs(a) < 80  # beyond, powers leave single precision
        every = free.all()
        a = np.exp(a if every else np.clip(a, -80, 80))
        a *= CAUSAL
        a /= a.sum(axis=2, keepdims=True)
        h = a @ val
        h += x
        keep = np.flatnonzero(counts)
        h, own, goal = h.reshape(-1, WIDTH)[keep], rows.reshape(-1)[keep], self.model.class_of[targets.reshape(-1)[keep]]
        loss, back, g = 0.0, np.empty_like(h), {"out": np.zeros_like(p["out"]), "bias": np.zeros_like(p["bias"])}
        for i in range(0, len(keep), BLOCK_IDS):
            at = slice(i, i + BLOCK_IDS)
            z = h[at] @ p["out"]
            z += self.model.after[own[at]]
            z += p["bias"]
            z -= z.max(axis=1, keepdims=True)
            line = np.arange(len(z))
            top = z[line, goal[at]]
            np.exp(z, out=z)
            whole = z @ ones
            loss += float((np.log(whole) - top).sum())
            z *= (1 / (whole * np.float32(len(keep))))[:, None]
            z[line, goal[at]] -= np.float32(1 / len(keep))
            g["out"] += h[at].T @ z
            g["bias"] += z.sum(axis=0)
            back[at] = z @ p["out"].T
        dh = np.zeros((rows.size, WIDTH), dtype=np.float32)
        dh[keep] = back
        dh = dh.reshape(x.shape)
        da = dh @ val.transpose(0, 2, 1)
        da -= (da * a).sum(axis=2, keepdims=True)
        da *= a
        if not every:
            da *= free
        dy = np.concatenate([da @ k, da.transpose(0, 2, 1) @ q, a.transpose(0, 2, 1) @ dh], axis=2)
        g["qkv"] = x.reshape(-1, WIDTH).T @ dy.reshape(-1, 3 * WIDTH)
        dh += dy @ p["qkv"].T
        g["place"] = dh.sum(axis=0)
        flat = rows.reshape(-1)
        order = np.argsort(flat, kind="stable")
        first = np.flatnonzero(np.diff(flat[order], prepend=-1))
        found = flat[order[first]]
        g["embed"] = np.zeros_like(p["embed"])
        g["embed"][found] = np.add.reduceat(dh.reshape(-1, WIDTH)[order], first, axis=0)
        return loss / max(1, len(keep)), g

    def step(self, inputs: np.ndarray, targets: np.ndarray, counts: np.ndarray) -> None:
        _, g = self.slopes(inputs, targets, counts)
        self.steps += 1
        self.windows += len(inputs)
        slow = np.float32(self.rate * min(1.0, self.steps / 20))
        one, two = np.float32(1 - 0.9**self.steps), np.float32(1 - 0.99**self.steps)
        for n in self.NAMES:
            m, v = self.m[n], self.v[n]
            m += np.float32(0.1) * (g[n] - m)
            v += np.float32(0.01) * (g[n] * g[n] - v)
            self.p[n] -= slow * (m / one) / (np.sqrt(v / two) + np.float32(1e-8))

    def raw(self) -> np.ndarray:
        """All weights end to end."""
        return np.concatenate([self.p[n].reshape(-1) for n in self.NAMES])

    def with_weights(self, raw: np.ndarray) -> Attention:
        """The model it started from, with these weights."""
        sizes = np.cumsum([self.p[n].size for n in self.NAMES])[:-1]
        p = {n: a.reshape(self.p[n].shape).astype(np.float32) for n, a in zip(self.NAMES, np.split(raw, sizes))}
        return replace(self.model, after=self.model.after + p.pop("bias"), **p).held()


def learnt(model: Attention, docs: DataFrame, vocabulary: str, key: str = "doc_id", text: str = "text") -> Attention:
    """model, taught by every window of docs: each task goes on from it over all of its windows, and the tasks' weights are
    averaged, each by its number of windows, in PARTS parts, so that no task or driver holds the weights of all."""
    sent = docs.sparkSession.sparkContext.broadcast(replace(model, pairs=None))
    schema, arrow = arrow_schema("part int, windows long, raw binary")

    def run(batches):
        speller, learner = Speller(vocabulary), Learner(sent.value)
        for batch in pieces(batches):
            learner.add(speller.windows([words_of(t) for t in batch.column(0).to_pylist()]))
        if learner.windows:
            rows = np.array_split(learner.raw().astype(float) * learner.windows, PARTS)
            cells = list(range(PARTS)), [learner.windows] * PARTS, [r.tobytes() for r in rows]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(cells, arrow)], schema=arrow)

    def added(batches):
        sums = {}
        for batch in batches:
            for part, n, raw in zip(*(c.to_pylist() for c in batch.columns)):
                windows, total = sums.get(part, (0, 0.0))
                sums[part] = windows + n, total + np.frombuffer(raw)
        if sums:
            cells = list(sums), [n for n, _ in sums.values()], [raw.tobytes() for _, raw in sums.values()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(cells, arrow)], schema=arrow)

    own = saved(docs.select(text).mapInArrow(run, schema))
    rows = sorted(own.repartition("part").mapInArrow(added, schema).collect())  # PARTS rows of some 34 kB
    if not rows:
        return model
    return Learner(model).with_weights(np.concatenate([np.frombuffer(r["raw"]) / r["windows"] for r in rows]))


class Memory(dict):
    """Bytes by word, made when first asked for; it starts anew when full."""

    def __init__(self, make):
        super().__init__()
        self.make = make

    def __missing__(self, word: bytes) -> bytes:
        if len(self) >= SPELLED:
            self.clear()
        out = self[word] = self.make(word)
        return out

    def joined(self, words: list[bytes]) -> bytes:
        return b"".join(map(self.__getitem__, words))


class Speller:
    """Ids of texts, two bytes each, from a memory of words."""

    def __init__(self, vocabulary: str):
        self.encoder, end = ranks_of(vocabulary)
        assert end < 1 << 16
        self.end = np.uint16(end).tobytes()
        two = [np.uint16(i).tobytes() for i in range(end + 1)].__getitem__
        self.known = Memory(lambda word: b"".join(map(two, spelled(self.encoder, word))))

    def windows(self, texts: list[list[bytes]]) -> Windows | None:
        if not texts:
            return None
        raw = [self.end + self.known.joined(words) + self.end for words in texts]
        return Windows(np.frombuffer(b"".join(raw), dtype=np.uint16), np.array([len(r) // 2 for r in raw], dtype=np.int64))


def score_texts(model: Attention, texts: Windows | None) -> np.ndarray:
    """log10 probability of each text. A window after a text's first is asked only from `OVERLAP` on: what stands before is scored already."""
    if texts is None:
        return np.zeros(0)
    inner = np.ones(len(texts.flat) - 1, dtype=bool)
    inner[texts.first[1:] - 1] = False
    rows, goals = model.row_of[texts.flat], model.class_of[texts.flat]
    shares = model.pairs.logs(rows[:-1][inner], texts.flat[1:][inner], model.class_of, model.share)
    total = np.bincount(np.repeat(np.arange(len(texts.n)), texts.n), weights=shares, minlength=len(texts.n))
    by_row, by_place, ones = model.asked(), model.place @ model.qkv, np.ones(CLASSES, dtype=np.float32)
    for group, skip in ((np.flatnonzero(texts.done == 0), 0), (np.flatnonzero(texts.done), OVERLAP)):
        causal = CAUSAL[skip:]
        for x in range(0, len(group), BLOCK_WINDOWS):
            which = group[x : x + BLOCK_WINDOWS]
            owner = texts.owner[which]
            at, counts = texts.places(which)
            y = by_row[rows[at]]
            y[:, :, : 3 * WIDTH] += by_place
            s = y[:, skip:, :WIDTH] @ y[:, :, WIDTH : 2 * WIDTH].transpose(0, 2, 1)
            np.exp(s, out=s)
            s *= causal
            keep = np.flatnonzero(counts[:, skip:])
            h = (s @ y[:, :, 2 * WIDTH :]).reshape(-1, WIDTH + 1)[keep]  # the last column is what attention adds up to
            at = at[:, skip:].reshape(-1)[keep]
            own, goal = rows[at], goals[at + 1]
            h = h[:, :WIDTH] / h[:, WIDTH:]
            h += model.embed[own]
            h += model.place[keep % (WINDOW - skip) + skip]
            logs = np.empty(len(keep), dtype=np.float32)
            for i in range(0, len(keep), BLOCK_IDS):
                z = h[i : i + BLOCK_IDS] @ model.out
                z += model.after[own[i : i + BLOCK_IDS]]
                top = z[np.arange(len(z)), goal[i : i + BLOCK_IDS]]
                np.exp(z, out=z)
                logs[i : i + BLOCK_IDS] = top - np.log(z @ ones)
            low, high = owner[0], owner[-1] + 1
            total[low:high] += np.bincount(np.repeat(owner - low, counts.sum(axis=1)), weights=logs / np.float32(np.log(10)), minlength=high - low)
    return total


# ---------------------------------------------------------------- scoring


def drawn_windows(mapped: DataFrame) -> Drawn:
    """The windows that `gathered` drew, on the driver: 168 bytes each."""
    rows = mapped.where("draws is not null").select("draws", "inputs", "targets", "counts").collect()
    draws, *others = (np.frombuffer(b"".join(r[i] for r in rows), dtype=t) for i, t in enumerate((np.uint64, np.uint16, np.uint16, bool)))
    return Drawn(draws, *(a.reshape(-1, WINDOW) for a in others))


def scores(
    docs: DataFrame, vocabulary: str, key: str = "doc_id", text: str = "text", folds: int = 7, held: int = 2, most: int = 96_000, steps: int = 1500,
) -> DataFrame:
    """(key, held_out, n_tokens, n_known, train_tokens, base_score, score) for each row of docs.

    vocabulary: path, on every node, of a rank file of a public byte-pair vocabulary."""
    spark, kind = docs.sparkSession, docs.schema[key].dataType.simpleString()
    training = docs.where(F.coalesce(crc_bucket(key, folds) != held, F.lit(True)))
    n_train, size = training.agg(F.count("*"), F.coalesce(F.sum(F.octet_length(text)), F.lit(0))).first()
    mapped = saved(gathered(training, vocabulary, min(1.0, most * WINDOW_BYTES / max(1, size + n_train)), key, text))
    words = saved(mapped.where("word is not null").groupBy("word").agg(F.sum("n").alias("n")))
    pairs = saved(mapped.where("pair is not null").groupBy("pair").agg(F.sum("n").alias("n")))
    n_words, distinct = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    total, distinct = n_words + n_train, distinct + (1 if n_train else 0)
    common = hashed_counts(words.where(F.col("n") >= cut_of(words, COMMON)))
    all_common = len(common[0]) == distinct - (1 if n_train else 0)
    ids = id_totals(pairs, ranks_of(vocabulary)[1] + 1)
    follows, keys, counts = followers(pairs, ids)
    model = learnt(train(drawn_windows(mapped), ids, steps, follows=follows, pairs=(keys, counts)), training, vocabulary, key, text)
    sent = spark.sparkContext.broadcast((model, *common, n_train))
    ddl = f"row long, {key} {kind}, n_tokens long, n_known long, base double, score double, slice int, hashes binary, rows binary"
    schema, arrow = arrow_schema(ddl)
    names, bits = arrow.names, slice_bits(docs)

    def run(batches):
        from pyspark import TaskContext

        model, hashes, counts, n_end = sent.value
        speller, next_row = Speller(vocabulary), TaskContext.get().partitionId() << 40
        end_known = int(n_end > 0)
        rare: list[tuple] = []
        held_rare = 0

        seen: dict[bytes, bytes] = {}

        def learn(split):
            """log10(c + 1) of all words not yet seen, as bytes; -1 where it must be looked up."""
            new = [w for w in set().union(*split) if w not in seen]
            if len(seen) + len(new) > REMEMBER:
                seen.clear()
                new = list(set().union(*split))
            h = np.fromiter(map(xxhash.xxh3_64_intdigest, new), dtype=np.uint64, count=len(new))
            logs = np.full(len(new), 0.0 if all_common else -1.0)
            if len(hashes):
                at = np.minimum(np.searchsorted(hashes, h), len(hashes) - 1)
                logs = np.where(hashes[at] == h, np.log10(counts[at] + 1.0), logs)
            raw = logs.tobytes()
            seen.update(zip(new, (raw[i : i + 8] for i in range(0, len(raw), 8))))

        def packed():
            h, r = (np.concatenate(x) for x in zip(*rare))
            order = np.lexsort((r, h))
            h, r = h[order], r[order]
            cut = np.searchsorted(h >> np.uint64(64 - bits), np.arange((1 << bits) + 1, dtype=np.uint64))
            rows = {n: [] for n in names}
            for i, (x, y) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist())):
                if y > x:
                    for n in names:
                        rows[n].append({"slice": i, "hashes": h[x:y].tobytes(), "rows": r[x:y].tobytes()}.get(n))
            return pa.RecordBatch.from_arrays([pa.array(rows[f.name], type=f.type) for f in arrow], schema=arrow)

        for batch in pieces(batches):
            keys, texts = (c.to_pylist() for c in batch.columns)
            rows = {n: [] for n in names}
            split = [words_of(t) for t in texts]
            for i, (k, words) in enumerate(zip(keys, split)):
                if i % 1000 == 0:
                    learn(split[i : i + 1000])
                logs = np.frombuffer(b"".join(map(seen.__getitem__, words)), dtype=np.float64)
                lookup = logs < 0
                if lookup.any():
                    missing = [words[i] for i in np.nonzero(lookup)[0]]
                    h = np.fromiter(map(xxhash.xxh3_64_intdigest, missing), dtype=np.uint64, count=len(missing))
                    rare.append((h, np.full(len(h), next_row, dtype=np.int64)))
                    held_rare += len(h)
                rows["row"].append(next_row)
                rows[key].append(k)
                rows["n_tokens"].append(len(words) + 1)
                rows["n_known"].append(int((logs > 0).sum()) + end_known)
                rows["base"].append(float(logs[~lookup].sum()) + float(np.log10(n_end + 1.0)))
                next_row += 1
            rows["score"] = np.concatenate([score_texts(model, speller.windows(split[x : x + 1000])) for x in range(0, len(split), 1000)])
            for n in ("slice", "hashes", "rows"):
                rows[n] = [None] * len(keys)
            yield pa.RecordBatch.from_arrays([pa.array(rows[f.name], type=f.type) for f in arrow], schema=arrow)
            if held_rare >= PACK:
                yield packed()
                rare, held_rare = [], 0
        if rare:
            yield packed()

    mapped = saved(docs.select(key, text).mapInArrow(run, schema))
    own = mapped.where("slice is null").select("row", key, "n_tokens", "n_known", "base", "score")
    found = looked_up(words, mapped.where("slice is not null").select("slice", "hashes", "rows"))
    scale = float(np.log10(total + distinct + 1.0))
    out = own.join(found, "row", "left")
    base = F.col("base") + F.coalesce("more", F.lit(0.0)) - F.col("n_tokens") * F.lit(scale)
    return out.select(
        key, F.coalesce(crc_bucket(key, folds) == held, F.lit(False)).alias("held_out"), "n_tokens",
        (F.col("n_known") + F.coalesce("known", F.lit(0))).alias("n_known"), F.lit(int(total)).cast("long").alias("train_tokens"), base.alias("base_score"), "score",
    )


def hashed_counts(words: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Hashes, sorted, and counts of words, 16 bytes each."""
    schema, _ = arrow_schema("hashes binary, counts binary")

    def run(batches):
        for batch in batches:
            w, n = (c.to_pylist() for c in batch.columns)
            h = np.fromiter(map(xxhash.xxh3_64_intdigest, w), dtype=np.uint64, count=len(w))
            yield pa.RecordBatch.from_arrays([pa.array([h.tobytes()]), pa.array([np.array(n, dtype=np.int64).tobytes()])], names=["hashes", "counts"])

    rows = words.mapInArrow(run, schema).collect()  # 16 bytes a word
    h = np.concatenate([np.frombuffer(r[0], dtype=np.uint64) for r in rows]) if rows else np.empty(0, dtype=np.uint64)
    n = np.concatenate([np.frombuffer(r[1], dtype=np.int64) for r in rows]) if rows else np.empty(0, dtype=np.int64)
    order = np.argsort(h)
    return h[order], n[order]


def looked_up(words: DataFrame, rare: DataFrame) -> DataFrame:
    """(row, more, known): sums of log10(c + 1) and of known occurrences, over the words that were looked up."""
    schema, arrow = arrow_schema("slice int, hashes binary, rows binary, counts binary")
    out, out_arrow = arrow_schema("row long, more double, known long")
    bits = slice_bits(words)

    def pack(batches):
        for batch in batches:
            w, n = (c.to_pylist() for c in batch.columns)
            h = np.fromiter(map(xxhash.xxh3_64_intdigest, w), dtype=np.uint64, count=len(w))
            order = np.argsort(h)
            h, n = h[order], np.array(n, dtype=np.int64)[order]
            cut = np.searchsorted(h >> np.uint64(64 - bits), np.arange((1 << bits) + 1, dtype=np.uint64))
            rows = [(i, h[x:y].tobytes(), None, n[x:y].tobytes()) for i, (x, y) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist())) if y > x]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    def meet(batches):
        h, n, rare_h, rare_r = ([np.empty(0, dtype=t)] for t in (np.uint64, np.int64, np.uint64, np.int64))
        for batch in batches:
            for _, a, r, c in zip(*(x.to_pylist() for x in batch.columns)):
                if r is None:
                    h.append(np.frombuffer(a, dtype=np.uint64))
                    n.append(np.frombuffer(c, dtype=np.int64))
                else:
                    rare_h.append(np.frombuffer(a, dtype=np.uint64))
                    rare_r.append(np.frombuffer(r, dtype=np.int64))
        h, n, rare_h, rare_r = (np.concatenate(x) for x in (h, n, rare_h, rare_r))
        if not len(rare_h):
            return
        if len(h):
            order = np.argsort(h)
            h, n = h[order], n[order]
            at = np.minimum(np.searchsorted(h, rare_h), len(h) - 1)
            c = np.where(h[at] == rare_h, n[at], 0)
        else:
            c = np.zeros(len(rare_h), dtype=np.int64)
        rows, own = np.unique(rare_r, return_inverse=True)
        more, known = np.bincount(own, weights=np.log10(c + 1.0)), np.bincount(own, weights=c > 0).astype(np.int64)
        for x in range(0, len(rows), 200_000):
            y = x + 200_000
            yield pa.RecordBatch.from_arrays([pa.array(rows[x:y]), pa.array(more[x:y]), pa.array(known[x:y])], schema=out_arrow)

    sides = rare.select("slice", "hashes", "rows", F.lit(None).cast("binary").alias("counts")).union(words.select("word", "n").mapInArrow(pack, schema))
    return sides.repartition("slice").mapInArrow(meet, out).groupBy("row").agg(F.sum("more").alias("more"), F.sum("known").alias("known"))
