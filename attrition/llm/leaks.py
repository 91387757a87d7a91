"""Benchmark decontamination with spaced seeds.

A seed is a fixed mask over a few successive tokens; tokens under a zero are ignored, so a seed
still matches when one of those was substituted. The masks below hit every window of 13
tokens with at most two substitutions. Seeds of all test items meet those of the texts by
their hash; around each hit, item and text are laid side by side and counted: a window of
13 tokens (or the whole item, if shorter) with at most two substitutions (one for 7 to 12
tokens, none for fewer) is a leak. Items below five tokens are never looked for.

Tokens are words without outer punctuation; A-Z lower-cased. The items go to every task in
portions of bounded size; a larger benchmark takes more passes over the texts. Null or
empty texts and items have no tokens. Repeated rows give repeated results.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, mix64, pieces

SPAN, ALLOWED, LEAST = 13, 2, 5
#: Every pattern of at most two misses in 13 places leaves one of these whole at some place (found by search, tested).
MASKS = ("11101011", "11001111")
#: Tokens of test items that are sent to the tasks at once: some 60 MB with their seeds.
PORTION = 1_000_000
#: Words that are looked at together, and words that a worker remembers.
BLOCK_WORDS, REMEMBER = 400_000, 400_000
OUTER = b".,;:!?\"'()[]{}<>*_-#%&$|/\\"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [np.uint64((0x9E3779B97F4A7C15 * (2 * i + 1)) % (1 << 64) | 1) for i in range(SPAN)]
FILTER = 22


def tokens(text: str | None) -> list[bytes]:
    if not text:
        return []
    return [t for w in text.encode("utf-8", "surrogatepass").lower().split() if (t := w.strip(OUTER))]


def kept_places(mask: str) -> list[int]:
    return [i for i, c in enumerate(mask) if c == "1"]


def seed_hashes(ids: np.ndarray, places: list[int], tag: int) -> tuple[np.ndarray, np.ndarray]:
    """(place, hash) of every place where all kept tokens are known (above 0)."""
    n = len(ids) - places[-1]
    if n <= 0:
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64)
    known = ids > 0
    whole = known[:n].copy()
    for p in places[1:]:
        whole &= known[p : n + p]
    at = np.nonzero(whole)[0]
    total = np.full(len(at), tag, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for p in places:
            total += ids[at + p].astype(np.uint64) * ODD[p]
    return at, mix64(total)


@dataclass
class SeedIndex:
    """Test items as numbers, and their seeds sorted by hash."""

    item_ids: list
    vocabulary: dict[bytes, int]
    items: list[np.ndarray]
    shapes: list[list[int]]
    hashes: np.ndarray
    item: np.ndarray
    place: np.ndarray
    near: np.ndarray  # which values of a hash's upper bits occur

    @staticmethod
    def build(rows: list[tuple]) -> SeedIndex:
        vocabulary: dict[bytes, int] = {}
        ids, items = [], []
        for item_id, text in rows:
            words = tokens(text)
            if len(words) >= LEAST:
                ids.append(item_id)
                items.append(np.array([vocabulary.setdefault(w, len(vocabulary) + 1) for w in words], dtype=np.int64))
        halves = sorted({n for x in items if len(x) < SPAN for n in (len(x) // 2, len(x) - len(x) // 2)})
        shapes = [kept_places(m) for m in MASKS] + [list(range(n)) for n in halves]
        hashes, item, place = [np.empty(0, dtype=np.uint64)], [np.empty(0, dtype=np.int64)], [np.empty(0, dtype=np.int64)]
        for i, x in enumerate(items):
            for tag, places in enumerate(shapes):
                at, h = seed_hashes(x, places, tag)
                if tag >= len(MASKS):  # halves of a short item only
                    half = len(x) // 2
                    good = np.isin(at, [0, half]) if len(x) < SPAN and len(places) in (half, len(x) - half) else np.zeros(len(at), dtype=bool)
                    at, h = at[good], h[good]
                hashes.append(h)
                item.append(np.full(len(at), i, dtype=np.int64))
                place.append(at)
        hashes, item, place = (np.concatenate(x) for x in (hashes, item, place))
        order = np.argsort(hashes, kind="stable")
        near = np.zeros(1 << FILTER, dtype=bool)
        near[hashes >> np.uint64(64 - FILTER)] = True
        return SeedIndex(ids, vocabulary, items, shapes, hashes[order], item[order], place[order], near)


def allowed(length: int) -> int:
    return ALLOWED if length >= SPAN else 1 if length >= 7 else 0


def stretches(item: np.ndarray, text: np.ndarray, shift: int) -> list[tuple[int, int, int]]:
    """(first, end, equal tokens) in the text of the parts where item, laid at shift, agrees window by window."""
    window = min(SPAN, len(item))
    low, high = max(0, shift), min(len(text), shift + len(item))
    if high - low < window:
        return []
    same = np.concatenate([[0], np.cumsum(text[low:high] == item[low - shift : high - shift])])
    good = np.nonzero(same[window:] - same[:-window] >= window - allowed(window))[0]
    if not len(good):
        return []
    breaks = np.nonzero(np.diff(good) > window)[0]
    heads, tails = good[np.concatenate([[0], breaks + 1])], good[np.concatenate([breaks, [len(good) - 1]])] + window
    return [(int(a + low), int(b + low), int(same[b] - same[a])) for a, b in zip(heads, tails)]


class Finder:
    """Looks up texts against one portion of items, a block of texts at a time."""

    def __init__(self, index: SeedIndex):
        self.index, self.known = index, {}

    def numbers(self, text: str) -> np.ndarray:
        """Numbers of a text's tokens, 0 for words of no item."""
        known, vocabulary = self.known, self.index.vocabulary
        words = text.encode("utf-8", "surrogatepass").lower().split()
        out = [*map(known.get, words)]
        if None in out:
            for i, x in enumerate(out):
                if x is None:
                    w = words[i]
                    t = w.strip(OUTER)
                    if len(known) >= REMEMBER:
                        known.clear()
                    out[i] = known[w] = vocabulary.get(t, 0) if t else -1
        ids = np.array(out, dtype=np.int64)
        return ids[ids >= 0]

    def search(self, texts: list[str | None]) -> list[list[tuple]]:
        """For each text its (item, first token, end token, equal tokens)."""
        out: list[list[tuple]] = [[] for _ in texts]
        block, owners, size = [], [], 0
        for i, t in enumerate(texts):
            if t:
                ids = self.numbers(t)
                if np.count_nonzero(ids) >= LEAST:
                    block.append(ids)
                    owners.append(i)
                    size += len(ids) + SPAN
            if block and (size >= BLOCK_WORDS or i == len(texts) - 1):
                for o, hit in self.hits(block):
                    out[owners[o]].append(hit)
                block, owners, size = [], [], 0
        if block:
            for o, hit in self.hits(block):
                out[owners[o]].append(hit)
        return out

    def hits(self, block: list[np.ndarray]):
        ix = self.index
        starts = np.concatenate([[0], np.cumsum([len(b) + SPAN for b in block])])[:-1]
        flat = np.zeros(int(starts[-1]) + len(block[-1]), dtype=np.int64)
        for s, b in zip(starts, block):
            flat[s : s + len(b)] = b
        found = []
        for tag, places in enumerate(ix.shapes):
            at, h = seed_hashes(flat, places, tag)
            maybe = ix.near[h >> np.uint64(64 - FILTER)]
            at, h = at[maybe], h[maybe]
            low, high = np.searchsorted(ix.hashes, h, side="left"), np.searchsorted(ix.hashes, h, side="right")
            n = high - low
            if n.sum():
                row = np.repeat(low, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                where = np.repeat(at, n)
                found.append(np.stack([ix.item[row], where - ix.place[row], np.searchsorted(starts, where, side="right") - 1], axis=1))
        if not found:
            return
        for item, shift, owner in np.unique(np.concatenate(found), axis=0).tolist():
            for a, b, same in stretches(ix.items[item], block[owner], shift - int(starts[owner])):
                yield owner, (ix.item_ids[item], a, b, same)


def code_points(text: str) -> list[tuple[int, int]]:
    """Start and end of each token of a text, as tokens() gives them."""
    outer, out = OUTER.decode(), []
    for m in WORD.finditer(text):
        w = m[0]
        left = len(w) - len(w.lstrip(outer))
        if left < len(w):
            out.append((m.start() + left, m.start() + len(w.rstrip(outer))))
    return out


def portions(items: DataFrame, item_key: str, item_text: str) -> list[SeedIndex]:
    """Indexes of the items, each of at most about PORTION tokens: one, as a rule."""
    size = items.agg(F.coalesce(F.sum(F.regexp_count(F.col(item_text), F.lit(r"[^\x20\x09-\x0D]+"))), F.lit(0))).first()[0]
    n = max(1, -(-2 * size // PORTION))
    part = F.pmod(F.xxhash64(item_key, item_text), F.lit(n))
    return [SeedIndex.build(sorted(map(tuple, items.where(part == i).select(item_key, item_text).collect()), key=repr)) for i in range(n)]


def leaks(
    docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text",
) -> DataFrame:
    """(key, item, start, end, n_tokens, n_equal): one row for each agreeing stretch; start and end are code points."""
    kinds = docs.schema[key].dataType.simpleString(), items.schema[item_key].dataType.simpleString()
    schema, arrow = arrow_schema(f"{key} {kinds[0]}, {item_key} {kinds[1]}, start long, end long, n_tokens long, n_equal long")
    out = None
    for index in portions(items, item_key, item_text):
        sent = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, sent=sent):
            finder = Finder(sent.value)
            for batch in pieces(batches):
                keys, texts = (c.to_pylist() for c in batch.columns)
                rows = []
                for k, t, hits in zip(keys, texts, finder.search(texts)):
                    if hits:
                        spots = code_points(t)
                        rows += [(k, i, spots[a][0], spots[b - 1][1], b - a, same) for i, a, b, same in sorted(set(hits), key=repr)]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

        part = docs.select(key, text).mapInArrow(run, schema)
        out = part if out is None else out.union(part)
    return out


def without_leaks(docs: DataFrame, items: DataFrame, text: str = "text", item_key: str = "item_id", item_text: str = "text") -> DataFrame:
    """Rows of docs whose text holds no part of an item; all columns kept, no join."""
    out, at = docs, docs.columns.index(text)
    for index in portions(items, item_key, item_text):
        sent = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, sent=sent):
            finder = Finder(sent.value)
            for batch in pieces(batches):
                yield batch.filter(pa.array([not hits for hits in finder.search(batch.column(at).to_pylist())], type=pa.bool_()))

        out = out.mapInArrow(run, docs.schema)
    return out
