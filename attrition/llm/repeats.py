"""Substring deduplication by hashing lines and paragraphs-by-content.

Units of a text are its lines, and passages that start after a local boundary (a line's end, a
word ending a sentence, or a word whose hash says so) and run to the first boundary at least
``passage_words`` later. Boundaries depend on nothing but the words beside them, so a
passage inside another text falls into the same units. With `gap`, words of locally least hash
are boundaries too where others are farther apart: of `gap` words in a row one is a boundary, so
two texts that share 4 * gap + 8 words share a passage, however they are punctuated or broken
into lines; and passages are lengthened by the equal words around them. A unit's digest is that of its words,
A-Z lower-cased, single-spaced. Of all equal units the one of the smallest (id, start) stays;
the rest are removed and told by their offsets in the original text, in code points.

A task sends each digest once, its earliest occurrence, as packed columns; later ones inside the
task are certain to go and only look up which one stays. So a line that a third of all rows
share costs one entry a task, never one task.

Ids must be integers; null ids rank last. Null, empty and short texts have no units. Rows
that repeat id and text are one document. Texts are read whole, in blocks of words.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_schema, in_filter, map_batches, mix64, pieces, row_filter, saved, slice_bits, spare, unpacked, word_hashes

LINE_WORDS, PASSAGE_WORDS = 7, 10
#: Words of which one is surely a boundary (48 shared words hold a passage), and words by which a passage may be lengthened
#: at each end: more than the three gaps that may lie between the end of a copy and its outermost passage.
GAP, AROUND = 10, 32
#: Least number of slices of the digest range.
SLICES = 1024
#: Bytes of text that are cut into units at once, and units that a task gathers before it sends them.
BLOCK_BYTES, PACK = 1 << 22, 1_500_000
NO_ID = np.iinfo(np.int64).max
BASE = 0x9E3779B97F4A7C15 | 1
INVERSE = pow(BASE, -1, 1 << 64)
SPACE = np.zeros(256, dtype=bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
STOP = np.zeros(256, dtype=bool)
STOP[[ord(c) for c in ".!?"]] = True
WORD = re.compile(r"[^\x20\x09-\x0D]+")
FIELDS = ("digest", "id", "copy", "start", "end")


def powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base & (1 << 64) - 1, dtype=np.uint64)
    if n:
        out[0] = 1
        out = np.multiply.accumulate(out)
    return out


def runs(values: np.ndarray, width: int, pick) -> np.ndarray:
    """pick (np.minimum or np.maximum) over each `width` values in a row."""
    out, have = values, 1
    while have < width:
        more = min(have, width - have)
        out = pick(out[:-more], out[more:])
        have += more
    return out


def least(h: np.ndarray, walls: np.ndarray, gap: int) -> np.ndarray:
    """Which words have the least hash of some `gap` words in a row that hold no wall."""
    if len(h) < gap:
        return np.zeros(len(h), dtype=bool)
    low = np.where(runs(walls, gap, np.logical_or), np.uint64(0), runs(h, gap, np.minimum))
    side = np.zeros(gap - 1, dtype=np.uint64)
    best = runs(np.concatenate([side, low, side]), gap, np.maximum)
    return (best == h) & (best > 0)


def units(texts: list[bytes], gap: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(digest, text's index, start, end) of all units of all texts; offsets in code points. A digest's lowest bit tells lines."""
    raw = b"\n".join(texts) + b"\n"
    lengths = np.array([len(t) for t in texts], dtype=np.int64)
    begins = np.concatenate([[0], np.cumsum(lengths + 1)[:-1]])
    flat = np.frombuffer(raw, dtype=np.uint8)
    blank = SPACE[flat]
    edge = np.diff(blank.astype(np.int8), prepend=1)
    first, last = np.nonzero(edge == -1)[0], np.nonzero(edge == 1)[0]  # word i is flat[first[i]:last[i]]
    n = len(first)
    none = np.empty(0, dtype=np.int64)
    if n < LINE_WORDS:
        return none.astype(np.uint64), none, none, none
    h = word_hashes(raw.lower().split())
    owner = np.searchsorted(begins, first, side="right") - 1
    points = np.cumsum((flat & 0xC0) != 0x80)
    origin = points[begins] - 1
    newline = np.cumsum(flat == 10)
    ends_line = np.ones(n, dtype=bool)
    ends_line[:-1] = newline[first[1:]] > newline[last[:-1] - 1]
    by_word = STOP[flat[last - 1]] | (h >> np.uint64(60) == 0)
    ends_text = np.ones(n, dtype=bool)
    ends_text[:-1] = owner[1:] != owner[:-1]
    if gap:
        by_word |= least(h, by_word | ends_text, gap)
    bound = by_word | ends_line | ends_text
    with np.errstate(over="ignore"):
        prefix = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(mix64(h) * powers(BASE, n), dtype=np.uint64)])
        undo = powers(INVERSE, n)

    def digest(s, e, kind):
        with np.errstate(over="ignore"):
            return mix64((prefix[e] - prefix[s]) * undo[s] + (e - s).astype(np.uint64) * np.uint64(2)) & ~np.uint64(1) | np.uint64(kind)

    stop = np.nonzero(bound)[0] + 1  # words before which a boundary stands, and the end
    text_end = np.nonzero(ends_text)[0] + 1
    starts = np.concatenate([[0], stop[:-1]])

    def ended(starts, stop):
        at = np.searchsorted(stop, starts + PASSAGE_WORDS)
        fits = at < len(stop)
        s, e = starts[fits], stop[at[fits]]
        inside = e <= text_end[np.searchsorted(text_end, s, side="right")]
        return s[inside], e[inside]

    s, e = ended(starts, stop)
    if gap:  # a line's end in one copy only must not cut its passages short: they also run to the first boundary by words
        word_stop = np.nonzero(by_word)[0] + 1
        s2, e2 = ended(word_stop[word_stop < n], word_stop)
        other = ~np.isin(s2 * (n + 1) + e2, s * (n + 1) + e)
        s, e = np.concatenate([s, s2[other]]), np.concatenate([e, e2[other]])
    line_stop = np.nonzero(ends_line | ends_text)[0] + 1
    line_start = np.concatenate([[0], line_stop[:-1]])
    long = line_stop - line_start >= LINE_WORDS
    ls, le = line_start[long], line_stop[long]
    begin, finish = np.concatenate([s, ls]), np.concatenate([e, le])
    digests = np.concatenate([digest(s, e, 0), digest(ls, le, 1)])
    whose = owner[begin]
    return digests, whose, points[first[begin]] - 1 - origin[whose], points[last[finish - 1] - 1] - origin[whose]


def earliest(cols: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorts by (digest, id, start, copy). Tells which rows come first of their digest, which are later ones (not the
    same place of a repeated row), and the place of each row's first."""
    order = np.lexsort((cols["copy"], cols["start"], cols["id"], cols["digest"]))
    for k in cols:
        cols[k] = cols[k][order]
    new = np.ones(len(order), dtype=bool)
    new[1:] = cols["digest"][1:] != cols["digest"][:-1]
    head = np.nonzero(new)[0][np.cumsum(new) - 1]
    later = np.zeros(len(order), dtype=bool)
    for k in ("id", "copy", "start"):
        later |= cols[k] != cols[k][head]
    return new, later, head


def found_units(docs: DataFrame, key: str, text: str, gap: int = 0) -> DataFrame:
    """Packed units: rows with slice >= 0 hold each task's earliest occurrences, rows with slice -1 its later ones."""
    schema, arrow = arrow_schema("slice int, " + ", ".join(f"{c} binary" for c in FIELDS))
    bits = slice_bits(docs, SLICES)

    def send(parts):
        cols = {c: np.concatenate([p[i] for p in parts]) for i, c in enumerate(FIELDS)}
        new, later, _ = earliest(cols)
        head = {c: v[new] for c, v in cols.items()}
        tail = {c: v[later] for c, v in cols.items()}
        cut = np.searchsorted(head["digest"] >> np.uint64(64 - bits), np.arange((1 << bits) + 1, dtype=np.uint64))
        rows = [(i, *(head[c][x:y].tobytes() for c in FIELDS)) for i, (x, y) in enumerate(zip(cut[:-1], cut[1:])) if y > x]
        rows += [(-1, *(tail[c][x : x + 65536].tobytes() for c in FIELDS)) for x in range(0, len(tail["id"]), 65536)]
        return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    def run(batches):
        parts, held = [], 0
        for batch in pieces(batches):
            ids, copies = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(2))
            texts = [(t or "").encode("utf-8", "surrogatepass") for t in batch.column(2).to_pylist()]
            sizes = np.cumsum([len(t) for t in texts])
            at = 0
            while at < len(texts):
                to = max(at + 1, int(np.searchsorted(sizes, (sizes[at - 1] if at else 0) + BLOCK_BYTES)))
                digests, whose, start, end = units(texts[at:to], gap)
                parts.append((digests, ids[at:to][whose], copies[at:to][whose], start.astype(np.int64), end.astype(np.int64)))
                held += len(digests)
                at = to
                if held >= PACK:
                    yield send(parts)
                    parts, held = [], 0
        if held:
            yield send(parts)

    ids = F.coalesce(F.col(key).cast("long"), F.lit(int(NO_ID)))
    return docs.select(ids.alias("id"), F.xxhash64(text).alias("copy"), text).mapInArrow(run, schema)


PLAIN = "digest long, id long, copy long, start long, end long"
OUT = ("digest", "id", "copy", "start", "end", "kept_id", "kept_copy", "kept_start", "kept_end")


def opened(batches):
    """Packed rows as plain columns."""
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns)):
            yield {c: np.frombuffer(x, dtype=np.uint64 if c == "digest" else np.int64) for c, x in zip(FIELDS, row[1:])}


def removed_units(docs: DataFrame, key: str = "doc_id", text: str = "text", gap: int = 0) -> DataFrame:
    """(digest, id, copy, start, end, kept_id, kept_copy, kept_start, kept_end): every unit that is not the earliest of its digest."""
    packed = saved(found_units(docs, key, text, gap))
    ddl = PLAIN + ", kept_id long, kept_copy long, kept_start long, kept_end long, first boolean"
    (_, arrow), (_, plain) = arrow_schema(ddl), arrow_schema(PLAIN)

    def unpack(batches):
        for c in opened(batches):
            yield pa.RecordBatch.from_arrays([pa.array(c[k].view(np.int64)) for k in FIELDS], schema=plain)

    later = packed.where("slice = -1").mapInArrow(unpack, PLAIN)
    raw = docs.sparkSession.sparkContext.broadcast(row_filter(later.select("digest"), "digest"))  # 2 MiB whatever the data

    def resolve(batches):
        parts, bits = list(opened(batches)), unpacked(raw.value)
        if not parts:
            return
        cols = {c: np.concatenate([p[c] for p in parts]) for c in FIELDS}
        new, late, head = earliest(cols)
        cols["digest"] = cols["digest"].view(np.int64)
        kept = [cols[c][head] for c in ("id", "copy", "start", "end")]
        for x in range(0, len(new), 200_000):
            y = x + 200_000
            arrays = [pa.array(cols[c][x:y]) for c in FIELDS] + [pa.array(k[x:y]) for k in kept] + [pa.array(new[x:y])]
            # an earliest one goes on only if some task has later ones that will look it up
            keep = late[x:y] | new[x:y] & in_filter(bits, (b"%d" % d for d in cols["digest"][x:y].tolist()))
            yield pa.RecordBatch.from_arrays(arrays, schema=arrow).filter(pa.array(keep))

    met = saved(packed.where("slice >= 0").repartition("slice").mapInArrow(resolve, ddl))
    names = met.where("first").select("digest", "kept_id", "kept_copy", "kept_start", "kept_end")
    other = (F.col("id") != F.col("kept_id")) | (F.col("copy") != F.col("kept_copy")) | (F.col("start") != F.col("kept_start"))
    looked_up = later.join(names, "digest").where(other).select(*OUT)
    return met.where("not first").select(*OUT).union(looked_up)


NAMES = ("kept_id", "kept_copy", "kept_pos", "kept_end")


def contexts(docs: DataFrame, places: DataFrame, key: str, text: str) -> DataFrame:
    """Places (id, copy, side, pos, ...NAMES) with `words` and `offsets`: halves of the hashes of up to AROUND words before
    (side 0) or after (side 1), the nearest first, and their outer ends from the place, only for places that name a
    kept one. Places without words beside them are left out."""
    ids = F.coalesce(F.col(key).cast("long"), F.lit(int(NO_ID)))
    texts = docs.select(ids.alias("id"), F.xxhash64(text).alias("copy"), F.col(text).alias("_text")).dropDuplicates(["id", "copy"])
    wanted = places.groupBy("id", "copy").agg(F.collect_list(F.struct("side", "pos", *NAMES)).alias("places"))  # at most a text's own units

    def work():
        def step(ids, copies, texts, places):
            out = {c: [] for c in ("id", "copy", "side", "pos", *NAMES, "words", "offsets")}
            for i, copy, t, wanted in zip(ids, copies, texts, places):
                spans = [m.span() for m in WORD.finditer(t)]
                starts, ends = [a for a, _ in spans], [b for _, b in spans]
                for place in wanted:
                    side, pos = place["side"], place["pos"]
                    if side == 0:
                        to = bisect_right(ends, pos)
                        near = spans[max(0, to - AROUND) : to][::-1]
                    else:
                        at = bisect_left(starts, pos)
                        near = spans[at : at + AROUND]
                    if near:
                        for c, x in zip(out, (i, copy, side, pos, *(place[n] for n in NAMES))):
                            out[c].append(x)
                        h = word_hashes([t[a:b].encode("utf-8", "surrogatepass").lower() for a, b in near])
                        out["words"].append((h >> np.uint64(32)).astype(np.uint32).tobytes())
                        out["offsets"].append(None if place["kept_id"] is None else np.array([abs(x[side] - pos) for x in near], dtype=np.int32).tobytes())
            return out

        return step

    met = texts.join(wanted, ["id", "copy"]).select("id", "copy", "_text", "places")
    return map_batches(met, "id long, copy long, side int, pos long, kept_id long, kept_copy long, kept_pos long, kept_end long, words binary, offsets binary", work)


def lengthened(docs: DataFrame, passages: DataFrame, key: str, text: str) -> DataFrame:
    """(id, copy, start, end, kept_id): what stands beside removed passages and, word by word, beside those that stay."""
    own = Window.partitionBy("id", "copy")
    before = F.max("end").over(own.orderBy("start", "end").rowsBetween(Window.unboundedPreceding, -1))
    after = F.min("start").over(own.orderBy(F.desc("end"), F.desc("start")).rowsBetween(Window.unboundedPreceding, -1))
    outer = passages.withColumn("before", before).withColumn("after", after)
    to = ("id", "copy", "side", "pos", *NAMES)
    left = outer.where("before is null or before < start").select("*", F.lit(0).alias("side"), F.col("start").alias("pos"), F.col("kept_start").alias("kept_pos")).select(*to)
    right = outer.where("after is null or after > end").select("*", F.lit(1).alias("side"), F.col("end").alias("pos"), F.col("kept_end").alias("kept_pos")).select(*to)
    edges = saved(left.union(right).where("side = 1 or pos > 0 and kept_pos > 0"))
    nothing = [F.lit(None).cast("long").alias(n) for n in NAMES]
    kept = edges.select(F.col("kept_id").alias("id"), F.col("kept_copy").alias("copy"), "side", F.col("kept_pos").alias("pos")).distinct().select("*", *nothing)
    found = saved(contexts(docs, edges.union(kept), key, text))
    theirs = found.where("kept_id is null").select(F.col("id").alias("kept_id"), F.col("copy").alias("kept_copy"), "side", F.col("pos").alias("kept_pos"), F.col("words").alias("kept_words"))
    met = found.where("kept_id is not null").join(theirs, ["kept_id", "kept_copy", "side", "kept_pos"])

    def work():
        def step(ids, copies, sides, places, kept_ids, kept_copies, kept_ends, words, offsets, kept_words):
            out = {c: [] for c in ("id", "copy", "start", "end", "kept_id")}
            for i, copy, side, pos, kept_id, kept_copy, kept_end, a, o, b in zip(ids, copies, sides, places, kept_ids, kept_copies, kept_ends, words, offsets, kept_words):
                a, b = np.frombuffer(a, dtype=np.uint32), np.frombuffer(b, dtype=np.uint32)
                n = min(len(a), len(b))
                differ = np.nonzero(a[:n] != b[:n])[0]
                n = int(differ[0]) if len(differ) else n
                if n:
                    far = int(np.frombuffer(o, dtype=np.int32)[n - 1])
                    start, end = (pos - far, pos) if side == 0 else (pos, pos + far)
                    if (i, copy) == (kept_id, kept_copy):
                        start = max(start, kept_end)  # the one that stays is not eaten by its own repeat
                    if start < end:
                        for c, x in zip(out, (i, copy, start, end, kept_id)):
                            out[c].append(x)
            return out

        return step

    rows = met.select("id", "copy", "side", "pos", "kept_id", "kept_copy", "kept_end", "words", "offsets", "kept_words")
    return map_batches(rows, "id long, copy long, start long, end long, kept_id long", work)


def merged(items):
    """Expression: spans (start, end) sorted and joined where they touch."""
    step = lambda acc, s: F.when(
        F.coalesce(F.try_element_at(acc, F.lit(-1))["end"] >= s["start"], F.lit(False)),
        F.concat(
            F.slice(acc, F.lit(1), F.greatest(F.size(acc) - 1, F.lit(0))),
            F.array(F.struct(F.try_element_at(acc, F.lit(-1))["start"].alias("start"), F.greatest(F.try_element_at(acc, F.lit(-1))["end"], s["end"]).alias("end"))),
        ),
    ).otherwise(F.concat(acc, F.array(s)))
    return F.aggregate(items, F.array().cast("array<struct<start:bigint,end:bigint>>"), step)


def repeated_spans(docs: DataFrame, key: str = "doc_id", text: str = "text", gap: int = 0) -> DataFrame:
    """One row for each document that loses text: (key, copy, removed array of (start, end), n_removed, kept_ids).

    gap: GAP finds every copy of 48 words and removes the whole of it; 0 takes units by their own boundaries alone."""
    each = removed_units(docs, key, text, gap)
    if gap:
        itself = (F.col("id") == F.col("kept_id")) & (F.col("copy") == F.col("kept_copy"))
        each = saved(each.withColumn("start", F.when(itself, F.greatest("start", "kept_end")).otherwise(F.col("start"))).where("start < end"))
        passages = each.where(F.col("digest").bitwiseAND(F.lit(1)) == 0)
        each = each.select("id", "copy", "start", "end", "kept_id").union(lengthened(docs, passages, key, text))
    each = each.groupBy("id", "copy", "start", "end").agg(F.min("kept_id").alias("kept_id"))
    by_text = each.groupBy("id", "copy").agg(
        F.array_sort(F.collect_list(F.struct("start", "end"))).alias("spans"),  # at most a text's own units
        F.array_sort(F.collect_set(F.when(F.col("kept_id") != int(NO_ID), F.col("kept_id")))).alias("kept_ids"),
    )
    out = by_text.withColumn("removed", merged(F.col("spans")))
    lost = F.aggregate("removed", F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["start"])
    return out.select(F.when(F.col("id") != int(NO_ID), F.col("id")).alias(key), "copy", "removed", lost.alias("n_removed"), "kept_ids")


def without_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", gap: int = 0) -> DataFrame:
    """docs with repeated spans cut out of the text, and a column `removed` of their original offsets (empty where
    nothing was removed; it replaces a column of that name)."""
    own, copy, cut, seen = spare(docs, "own_id", "own_copy", "cut", "seen")
    spans = repeated_spans(docs, key, text, gap).select(F.col(key).alias(own), F.col("copy").alias(copy), F.col("removed").alias(cut))
    rows = docs.withColumn(seen, F.xxhash64(text))
    met = rows.join(spans, rows[key].eqNullSafe(F.col(own)) & (F.col(seen) == F.col(copy)), "left")
    nothing = F.array().cast("array<struct<start:bigint,end:bigint>>")
    cuts = F.coalesce(F.col(cut), nothing)
    size = F.char_length(F.col(text)).cast("long")
    first = F.substring(F.col(text), F.lit(1), F.coalesce(F.try_element_at(cuts, F.lit(1))["start"], size).cast("int"))
    pieces = F.transform(
        cuts, lambda s, i: F.substring(F.col(text), (s["end"] + 1).cast("int"), (F.coalesce(F.try_element_at(cuts, (i + 2).cast("int"))["start"], size) - s["end"]).cast("int"))
    )
    shorter = F.when(F.size(cuts) > 0, F.concat(first, F.array_join(pieces, ""))).otherwise(F.col(text))
    others = [c for c in docs.columns if c not in (text, "removed")]
    return met.select(*others, shorter.alias(text), cuts.alias("removed"))
