"""Jaccard join of word-shingle sets with PartEnum signatures.

Sets of nearly equal size fall into one band or into two neighbours. Two sets of a pair of
bands whose Jaccard similarity reaches 0.8 differ in at most k elements, k following from the
larger size. Each band has an instance of the scheme: the feature domain is hashed into more
than k partitions, and a signature is the hash of a set's part in one of them. Two sets that
differ in at most k places agree on some partition in which they are not empty, provided one
of them fills more than k partitions; a set that does not is given a fresh partitioning too,
and again, so no pair is lost. A set takes part in its own band's instance and the next one's.

How it runs:
* Elements that very many sets share (told by a bounded sample; the choice is free, it only moves
  work) are kept out of the partitions: a signature then never stems from a common passage.
  A set too poor in other elements is partitioned once more, with all of them.
* Equal sets are one node (a 64-bit digest of the set); exact copies never meet as pairs.
* Tasks send signatures as packed columns, a few large rows for each slice of the signature
  range; the slices follow the texts' size, and each is one task. Sets are named by their place in what a task packs at once, so an entry
  takes some six bytes however many slices there are; the places' nodes are sent once. Sets that agree inside one task are linked there
  and sent once, so a signature that a third of all rows share arrives as one entry for each task.
* Agreeing sets form candidate groups. Groups that are large only because of a common
  passage fall apart under a fresh partitioning, and those of sets that are alike but not linked
  by prefixes, rarest elements first; what stays is compared in blocks of bounded size, by exact
  intersection: first with a few sets of the group, then whatever these do not connect with all. Links give the components.

Null or empty texts, and texts without words: no set, linked with nothing. Fewer than five
words: the whole sequence is the one element. Repeated rows have equal sets. Ids may repeat
or be null; null ids take part but never name a component unless it has no other id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import FILTER_BITS, arrow_schema, mix64, pieces, row_filter, saved, slice_bits, spare, unpacked, word_hashes, words_of
from .components import components, roots_of

SHINGLE = 5
#: Signatures that a task packs before it sends them.
PACK = 400_000
#: Bytes of text whose signatures make a slice: a task matches one slice, in some ten times its signatures' bytes.
SLICE = 8 << 20
#: Shingles that are partitioned at once.
CHUNK = 150_000
#: Sets in one block of an exact comparison.
BLOCK = 128
#: Sets of a large group that all its others meet first.
LEADERS = 4
#: Slots for the look-up of sets that are linked or occur more than once.
SALTS = 8
#: Candidate groups above this size are partitioned anew before they are compared.
LARGE = 48
FRESH = 6
#: Sampled sets, and in how many of them an element is frequent.
SAMPLE, FREQUENT = 10_000, 10
#: Bins that tell rare elements of large groups: 4 MB for each task whatever the input. Of more elements than a fourth of them, each is counted.
BINS = 1 << 22
#: Bytes of sets, as a part of the texts' bytes and at least, that are dealt to pairs of blocks at once.
DEALT, LEAST_DEALT = 0.3, 256 << 20
ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def shingles(words: list[bytes]) -> np.ndarray:
    """Distinct shingle hashes, sorted."""
    n = len(words)
    if not n:
        return np.empty(0, dtype=np.uint64)
    h = word_hashes(words)
    width = min(n, SHINGLE)
    s = np.full(n - width + 1, width, dtype=np.uint64)
    for i in range(width):
        s += h[i : n - width + 1 + i] * ODD[i]
    return np.unique(mix64(s))


def digest(s: np.ndarray) -> int:
    """A 64-bit name of a set, signed as Spark's long."""
    with np.errstate(over="ignore"):
        x = mix64(np.array([mix64(s ^ ODD[1]).sum(dtype=np.uint64) + np.uint64(len(s)) * ODD[0]], dtype=np.uint64))
    return int(x.view(np.int64)[0])


def bands(largest: int) -> np.ndarray:
    """Upper ends of the size bands up to the one that holds `largest`, and one more."""
    ends, low = [], 1
    while True:
        ends.append(low * 5 // 4)
        if len(ends) > 1 and ends[-2] >= largest:
            return np.array(ends, dtype=np.int64)
        low = ends[-1] + 1


def among(values: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which values are in a sorted array."""
    if not len(known):
        return np.zeros(len(values), dtype=bool)
    near = np.zeros(1 << 20, dtype=bool)
    near[known >> np.uint64(44)] = True
    out = near[values >> np.uint64(44)]
    maybe = np.nonzero(out)[0]
    at = np.minimum(np.searchsorted(known, values[maybe]), len(known) - 1)
    out[maybe] = known[at] == values[maybe]
    return out


def signatures(sets: list[np.ndarray], frequent: np.ndarray, salt: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(signature, index of set) for all sets and both instances of each.

    The first partitioning leaves frequent elements out. Two sets that differ in at most k places agree on a part in
    which one of them is not empty, if that one fills more than k parts; where neither does, both go on to the next."""
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    ends = bands(int(sizes.max()))
    band = np.searchsorted(ends, sizes)
    value = mix64(flat ^ ODD[2])
    rare = ~among(flat, frequent)
    out_sig, out_set = [], []
    for step in (0, 1):
        instance = band + step
        k = 2 * ends[instance] // 9
        parts = np.where(k > 0, (k + 1) * 106 // 100 + 2, 1)
        todo = np.arange(len(sets))
        for attempt in range(FRESH):
            if not attempt:
                mask = rare
            else:
                wanted = np.zeros(len(sets), dtype=bool)
                wanted[todo] = True
                mask = wanted[owner]
            elements, values, own = flat[mask], value[mask], owner[mask]
            first = np.zeros(len(sets) + 1, dtype=np.int64)
            first[todo + 1] = parts[todo]
            first = np.cumsum(first)
            with np.errstate(over="ignore"):
                spread = mix64(elements + ODD[3] * np.uint64(1 + attempt + FRESH * salt)) >> np.uint64(20)
            part = (spread % parts[own].astype(np.uint64)).astype(np.int64)
            total = np.zeros(first[-1], dtype=np.uint64)
            np.add.at(total, first[own] + part, values)
            filled = total != 0
            whose = np.repeat(todo, parts[todo])
            number = np.arange(len(total)) - first[whose]
            tag = (instance[whose] << 34 | number << 4 | attempt).astype(np.uint64)
            with np.errstate(over="ignore"):
                sig = mix64(total * ODD[0] + tag * ODD[4])
            out_sig.append(sig[filled])
            out_set.append(whose[filled])
            n_filled = np.bincount(whose, weights=filled, minlength=len(sets)).astype(np.int64)
            todo = todo[n_filled[todo] <= k[todo]]
            if not len(todo):
                break
        else:  # sets that no partitioning spreads well all meet under one signature of their instance
            with np.errstate(over="ignore"):
                out_sig.append(mix64(instance[todo].astype(np.uint64) * ODD[1] + np.uint64(77)))
            out_set.append(todo)
    return np.concatenate(out_sig), np.concatenate(out_set)


def starred(sig: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """One (signature, node) for each signature, in order, and edges from it to its other nodes."""
    order = np.argsort(sig)
    sig, node = sig[order], node[order]
    new = np.ones(len(sig), dtype=bool)
    new[1:] = sig[1:] != sig[:-1]
    head = node[new][np.cumsum(new) - 1]
    other = head != node
    return sig[new], node[new], head[other], node[other]


def spanning(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Edges (rows of two) that connect what the given ones connect, fewer than there are nodes."""
    nodes, roots = roots_of(a, b)
    under = nodes != roots
    return np.stack([roots[under], nodes[under]], axis=1)


SENT = "slice int, pack long, values binary, owners binary, a binary, b binary, held binary"
#: An edge (a, b) between labels, or a label and its node.
MET = "a long, b long, label long, node long"
SENT_ARROW = pa.schema([("slice", pa.int32()), ("pack", pa.int64()), *((n, pa.binary()) for n in ("values", "owners", "a", "b", "held"))])
MET_ARROW, EDGE_ARROW = (pa.schema([(n, pa.int64()) for n in names]) for names in (("a", "b", "label", "node"), ("a", "b")))
EDGE = "a long, b long"
#: A set's label is its place among those packed at once, below their number in the task and the task's own.
PLACES = 20
#: Of a signature or an element, its slice and so many lower bits are compared.
LOW = 40


def dealt_out(values: np.ndarray, owner: np.ndarray, bits: int) -> Iterator[tuple[int, bytes, bytes]]:
    """(slice, five bytes of each value, steps from one owner's place to the next) of each slice. Owners stand in order, and their
    steps by bytes of the same weight: one byte each is left when they are compressed."""
    number = (values >> np.uint64(64 - bits)).astype(np.int64)
    order = np.argsort(number << 32 | owner)
    number, owner = number[order], owner[order]
    five = (values[order] >> np.uint64(64 - LOW - bits)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5]
    cut = np.searchsorted(number, np.arange((1 << bits) + 1))
    for i, (x, y) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist())):
        if y > x:
            yield i, five[x:y].tobytes(), np.diff(owner[x:y], prepend=0).astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes()


def values_of(number: int, raw: bytes) -> np.ndarray:
    """The values of a slice: its number and their five bytes."""
    five = np.frombuffer(raw, dtype=np.uint8).reshape(-1, 5)
    wide = np.zeros((len(five), 8), dtype=np.uint8)
    wide[:, :5] = five
    return wide.reshape(-1).view("<u8").astype(np.uint64) | np.uint64(number << LOW)


def owners_of(raw: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(raw, dtype=np.uint8).reshape(4, -1).T.copy().view("<u4").reshape(-1), dtype=np.int64)


def as_batch(rows: list[tuple], arrow: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)


def packed(sig: np.ndarray, node: np.ndarray, bits: int, pack: int) -> pa.RecordBatch:
    """A few rows for each slice: five bytes a signature and its set's place, and once the nodes of all places."""
    held, place = np.unique(node, return_inverse=True)
    sig, place, a, b = starred(sig, place)
    a, b = (spanning(a, b) | pack << PLACES).T.copy()
    rows = [(pack % (1 << bits), pack, b"", b"", b"", b"", held.tobytes())]
    rows += [(i, pack, values, owners, b"", b"", b"") for i, values, owners in dealt_out(sig, place, bits)]
    for x in range(0, len(a), 4096):  # edges ride along, to any slice
        rows.append((int((a[x] ^ b[x]) % (1 << bits)), pack, b"", b"", a[x : x + 4096].tobytes(), b[x : x + 4096].tobytes(), b""))
    return as_batch(rows, SENT_ARROW)


class Packer:
    """Gathers sets until there is enough to partition and to send."""

    def __init__(self, bits: int, frequent: np.ndarray, salt: int = 0):
        self.frequent, self.pack = frequent, first_pack()
        self.bits, self.salt, self.sets, self.nodes, self.n, self.done = bits, salt, [], [], 0, []

    def add(self, s: np.ndarray, node: int) -> None:
        self.sets.append(s)
        self.nodes.append(node)
        self.n += len(s)
        if self.n >= CHUNK:
            self.turn()

    def turn(self) -> None:
        if self.sets:
            nodes, at = np.unique(np.array(self.nodes, dtype=np.int64), return_index=True)
            sig, own = signatures([self.sets[i] for i in at], self.frequent, self.salt)
            self.done.append((sig, nodes[own]))
        self.sets, self.nodes, self.n = [], [], 0

    def ready(self, last: bool = False) -> Iterator[pa.RecordBatch]:
        if last:
            self.turn()
        if self.done and (last or sum(len(s) for s, _ in self.done) >= PACK):
            sig, node = (np.concatenate(x) for x in zip(*self.done))
            self.done = []
            if len(sig):
                yield packed(sig, node, self.bits, self.pack)
                self.pack += 1


def first_pack() -> int:
    """The number of a task's first pack; a task has fewer than 2 ** PLACES."""
    context = TaskContext.get()
    return (context.partitionId() if context else 0) << PLACES


def met_by(rows) -> Iterator[pa.RecordBatch]:
    """Of one task's packed rows, the labels with their nodes, and candidate edges: they connect labels of sets that share a
    signature, and are fewer than those labels."""
    slices, a, b = {}, [np.empty(0, dtype=np.int64)], [np.empty(0, dtype=np.int64)]
    none = lambda n: pa.nulls(n, pa.int64())
    for number, pack, s, n, x, y, held in rows:
        if s:
            slices.setdefault(number, []).append((s, owners_of(n) | pack << PLACES))
        if x:
            a.append(np.frombuffer(x, dtype=np.int64))
            b.append(np.frombuffer(y, dtype=np.int64))
        if held:
            nodes = np.frombuffer(held, dtype=np.int64)
            yield pa.RecordBatch.from_arrays([none(len(nodes)), none(len(nodes)), pa.array(np.arange(len(nodes)) | pack << PLACES), pa.array(nodes)], schema=MET_ARROW)
    rows.clear()
    for number in list(slices):  # a slice at a time: no signature is in two of them
        parts = slices.pop(number)
        _, _, x, y = starred(values_of(number, b"".join(s for s, _ in parts)), np.concatenate([n for _, n in parts]))
        a.append(x)
        b.append(y)
    pairs = spanning(np.concatenate(a), np.concatenate(b))
    for at in range(0, len(pairs), 100_000):
        part = pairs[at : at + 100_000]
        yield pa.RecordBatch.from_arrays([pa.array(part[:, 0]), pa.array(part[:, 1]), none(len(part)), none(len(part))], schema=MET_ARROW)


def grouped(met: DataFrame) -> DataFrame:
    """(node, root) of sets that share signatures with others, from what met_by tells. Copies of a set have all signatures in
    common, so their labels have one root; groups of such copies alone go."""
    roots = components(met.where("a is not null").select("a", "b").distinct()).withColumnRenamed("node", "label")
    both = saved(met.where("label is not null").select("label", "node").join(roots, "label").select("node", "root").distinct())
    lone = both.groupBy("root").agg(F.min("node").alias("node"), F.count("*").alias("n")).where("n = 1")
    return both.join(lone.select("node"), "node", "left_anti")


def frequent_elements(docs: DataFrame, text: str, n: int) -> np.ndarray:
    """Elements that at least FREQUENT of about SAMPLE of the n sets hold, sorted; sampled by hash of the text."""
    draw = F.pmod(F.xxhash64(text, F.lit("sample")), F.lit(1 << 30)) / F.lit(float(1 << 30))
    schema, arrow = arrow_schema("slice int, elements binary")

    def run(batches):
        seen = set()
        for batch in pieces(batches):
            found = []
            for t in batch.column(0).to_pylist():
                s = shingles(words_of(t))
                if len(s) and (d := digest(s)) not in seen:
                    seen.add(d)
                    found.append(s)
            if found:
                flat = np.sort(np.concatenate(found))
                cut = np.searchsorted(flat >> np.uint64(58), np.arange(65, dtype=np.uint64))
                rows = [(i, flat[x:y].tobytes()) for i, (x, y) in enumerate(zip(cut[:-1], cut[1:])) if y > x]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

    def reduce(batches):
        parts = [np.frombuffer(b, dtype=np.uint64) for batch in batches for b in batch.column(1).to_pylist()]
        if parts:
            values, counts = np.unique(np.concatenate(parts), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array([0], type=pa.int32()), pa.array([values[counts >= FREQUENT].tobytes()])], schema=arrow)

    sampled = docs.where(draw < min(1.0, SAMPLE / max(1, n))).select(text)
    rows = sampled.mapInArrow(run, schema).repartition("slice").mapInArrow(reduce, schema).collect()  # a tenth of the sample's elements at most
    return np.sort(np.concatenate([np.empty(0, dtype=np.uint64), *[np.frombuffer(r["elements"], dtype=np.uint64) for r in rows]]))


def names_and_edges(docs: DataFrame, key: str, text: str, frequent, bits: int) -> DataFrame:
    """One reading of the texts gives both: a row (key, copy, n_shingles, node) for each row of docs, node null where
    there is no set; and rows of MET with candidate edges and labels, copy null. Packed signatures pass through one shuffle, with the names."""
    kind = docs.schema[key].dataType.simpleString()
    name_ddl = f"{key} {kind}, copy long, n_shingles long, node long"
    named = list(arrow_schema(name_ddl)[1])
    sent, sent_arrow = arrow_schema(f"{SENT}, {name_ddl}")
    out, out_arrow = arrow_schema(f"a long, b long, label long, {name_ddl}")

    def widen(batch: pa.RecordBatch, to: pa.Schema) -> pa.RecordBatch:
        have = dict(zip(batch.schema.names, batch.columns))
        return pa.RecordBatch.from_arrays([have[f.name] if f.name in have else pa.nulls(batch.num_rows, f.type) for f in to], schema=to)

    def run(batches):
        packer, turn = Packer(bits, frequent.value), None
        for batch in pieces(batches):
            keys, copies, texts = (c.to_pylist() for c in batch.columns)
            sizes, nodes = [], []
            for t in texts:
                s = shingles(words_of(t))
                sizes.append(len(s))
                nodes.append(digest(s) if len(s) else None)
                if len(s):
                    packer.add(s, nodes[-1])
            arrays = [pa.array(c, type=f.type) for c, f in zip((keys, copies, sizes, nodes), named)]
            turn = copies[0] % (1 << bits) if turn is None else turn  # tasks begin anywhere
            anywhere = pa.array((np.arange(turn, turn + len(keys)) % (1 << bits)).astype(np.int32))  # in turn: copies of one text are dealt out
            turn += len(keys)
            yield widen(pa.RecordBatch.from_arrays([anywhere, *arrays], names=["slice", *(f.name for f in named)]), sent_arrow)
            for ready in packer.ready():
                yield widen(ready, sent_arrow)
        for ready in packer.ready(last=True):
            yield widen(ready, sent_arrow)

    def reduce(batches):
        rows = []
        for batch in batches:
            is_name = pa.compute.is_valid(batch.column("copy"))
            yield widen(batch.filter(is_name).select([f.name for f in named]), out_arrow)
            rest = batch.filter(pa.compute.invert(is_name)).select(SENT_ARROW.names)
            rows += zip(*(c.to_pylist() for c in rest.columns))
        for met in met_by(rows):
            yield widen(met, out_arrow)

    mapped = docs.select(key, F.xxhash64(text).alias("copy"), text).mapInArrow(run, sent)
    return mapped.repartitionById(1 << bits, F.col("slice")).mapInArrow(reduce, out)


def meet(sent: DataFrame, bits: int) -> DataFrame:
    """Candidate edges and labels, as rows of MET, from packed signatures."""

    def reduce(batches):
        yield from met_by([row for batch in batches for row in zip(*(c.to_pylist() for c in batch.columns))])

    return saved(sent.repartitionById(1 << bits, F.col("slice")).mapInArrow(reduce, MET))


def spots_of(names: DataFrame, wanted: DataFrame, key: str) -> bytes:
    """A row filter (2 MiB whatever the data) that passes one row of docs for each wanted node, and few others."""
    return row_filter(names.join(wanted, "node").groupBy("node").agg(F.min(key).alias("first")), "first")


def reread(docs: DataFrame, spots, key: str, text: str, ddl: str, start, each, end) -> DataFrame:
    """Runs each(state, node, set) over the sets of the rows that pass; end(state, last) yields batches."""

    def run(batches):
        bits, seen, state = unpacked(spots.value), set(), start()
        for batch in pieces(batches):
            for spot, t in zip(*(c.to_pylist() for c in batch.columns)):
                if t and (spot is None or bits[spot]):
                    s = shingles(words_of(t))
                    if len(s) and (d := digest(s)) not in seen:
                        seen.add(d)
                        each(state, d, s)
            if len(seen) > 100_000:
                seen.clear()
            yield from end(state, False)
        yield from end(state, True)

    spot = (F.crc32(F.col(key).cast("string")) % FILTER_BITS).alias("spot")
    return docs.select(spot, text).mapInArrow(run, ddl)


def finer(docs: DataFrame, names: DataFrame, groups: DataFrame, frequent, salt: int, bits: int, key: str, text: str) -> DataFrame:
    """groups (node, root) cut by a fresh partitioning: sets stay together if they meet again; lone ones go."""
    spots = docs.sparkSession.sparkContext.broadcast(spots_of(names, groups, key))
    bits = max(4, bits - 3)  # few sets are left: fewer slices name each pair less often
    sent = reread(docs, spots, key, text, SENT, lambda: Packer(bits, frequent.value, salt), lambda p, d, s: p.add(s, d), lambda p, last: p.ready(last))
    again = grouped(meet(sent, bits)).withColumnRenamed("root", "again")
    both = groups.join(again, "node")
    size = both.groupBy("root", "again").agg(F.min("node").alias("node"), F.count("*").alias("n"))
    # groups are named by hash: a group's rows meet no table of names, however many they are
    return saved(both.join(size.where("n = 1").select("node"), "node", "left_anti").select("node", F.xxhash64("root", "again").alias("root")))


def rarity(docs: DataFrame, spots, key: str, text: str) -> np.ndarray:
    """How often the elements of the sets that pass occur, by hash into BINS bins, as eights of a power of two: a fixed size."""
    schema, arrow = arrow_schema("slice int, bins binary, counts binary")
    width = BINS >> 6

    def count(state, _, s):
        state.append(s)

    def rows(state, last):
        if state and (last or sum(map(len, state)) >= PACK):
            bins, counts = np.unique(np.concatenate(state) % np.uint64(BINS), return_counts=True)
            cut = np.searchsorted(bins, np.arange(65, dtype=np.uint64) * np.uint64(width))
            out = [(i, bins[x:y].astype(np.uint32).tobytes(), counts[x:y].astype(np.int64).tobytes()) for i, (x, y) in enumerate(zip(cut[:-1], cut[1:])) if y > x]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*out), arrow)], schema=arrow)
            state.clear()

    def reduce(batches):
        sums = {}
        for batch in batches:
            for i, bins, counts in zip(*(c.to_pylist() for c in batch.columns)):
                held = sums.setdefault(i, np.zeros(width, dtype=np.int64))
                held[np.frombuffer(bins, dtype=np.uint32).astype(np.int64) - i * width] += np.frombuffer(counts, dtype=np.int64)
        for i, held in sums.items():
            level = np.minimum(255, np.round(8 * np.log2(1.0 + held))).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([pa.array([i], type=pa.int32()), pa.array([b""]), pa.array([level.tobytes()])], schema=arrow)

    levels = np.zeros(BINS, dtype=np.uint8)
    for i, _, level in reread(docs, spots, key, text, schema, list, count, rows).repartition("slice").mapInArrow(reduce, schema).collect():
        levels[i * width : (i + 1) * width] = np.frombuffer(level, dtype=np.uint8)
    return levels


#: The level of a bin of one occurrence: 8 * log2(2).
ONCE = 8


def prefix(s: np.ndarray, levels: np.ndarray) -> np.ndarray:
    """The first n - ceil(0.8 n) + 1 elements of a set, rarest first, but for those that occur nowhere else."""
    level = levels[(s % np.uint64(BINS)).astype(np.int64)]
    first = np.lexsort((s, level))[: len(s) - -(-4 * len(s) // 5) + 1]
    return s[first[level[first] > ONCE]]


COUNTED = "pack long, values binary, owners binary, counts binary, held binary, sizes binary"


def prefixes(docs: DataFrame, spots, bits: int, key: str, text: str) -> DataFrame:
    """(node, element): what `prefix` tells of the sets that pass, by counts of their own for all elements.

    Elements go to their slices, packed like signatures, and are counted there; those that occur again come back to the
    sets' packs with their counts, so that each set's elements are put in order. No table of counts is sent to tasks."""
    counted, arrow = arrow_schema(f"slice int, {COUNTED}")
    out, out_arrow = arrow_schema("node long, element long")

    class State:
        def __init__(self):
            self.pack, self.sets, self.n = first_pack(), {}, 0

    def note(state, d, s):
        state.sets[d] = s
        state.n += len(s)

    def send(state, last):
        if state.sets and (last or state.n >= PACK):
            sizes = np.array([len(s) for s in state.sets.values()], dtype=np.int64)
            rows = [(state.pack % (1 << bits), state.pack, b"", b"", b"", np.array(list(state.sets), dtype=np.int64).tobytes(), sizes.tobytes())]
            flat = np.concatenate(list(state.sets.values()))
            rows += [(i, state.pack, values, owners, b"", b"", b"") for i, values, owners in dealt_out(flat, np.repeat(np.arange(len(sizes)), sizes), bits)]
            yield as_batch(rows, arrow)
            state.pack, state.sets, state.n = state.pack + 1, {}, 0

    def count(batches):
        slices = {}
        for batch in batches:
            for number, pack, values, owners, _, held, sizes in zip(*(c.to_pylist() for c in batch.columns)):
                if held:
                    yield as_batch([(0, pack, b"", b"", b"", held, sizes)], arrow)
                else:
                    slices.setdefault(number, []).append((pack, values, owners))
        for number in list(slices):
            parts = slices.pop(number)
            values = values_of(number, b"".join(v for _, v, _ in parts))
            _, place, counts = np.unique(values, return_inverse=True, return_counts=True)
            n = counts[place]
            at, rows = 0, []
            for pack, _, owners in parts:
                owner = owners_of(owners)
                again = np.flatnonzero(n[at : at + len(owner)] > 1)
                if len(again):
                    rows.append((0, pack, values[at + again].tobytes(), owner[again].astype(np.int32).tobytes(), n[at + again].astype(np.int64).tobytes(), b"", b""))
                at += len(owner)
            if rows:
                yield as_batch(rows, arrow)

    def first(rows):
        held, sizes = next((np.frombuffer(h, dtype=np.int64), np.frombuffer(z, dtype=np.int64)) for *_, h, z in rows if h)
        value, owner, n = (np.frombuffer(b"".join(r[i] for r in rows), dtype=t) for i, t in ((1, np.uint64), (2, np.int32), (3, np.int64)))
        order = np.lexsort((value, n, owner))
        value, owner = value[order], owner[order]
        met = np.bincount(owner, minlength=len(held))
        # elements that occur once stand first: they take up places of the prefix
        left = sizes - -(-4 * sizes // 5) + 1 - (sizes - met)
        rank = np.arange(len(owner)) - (np.cumsum(met) - met)[owner]
        taken = rank < left[owner]
        return pa.RecordBatch.from_arrays([pa.array(held[owner[taken]]), pa.array(value[taken].view(np.int64))], schema=out_arrow)

    def choose(batches):
        at, rows = None, []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if row[0] != at:
                    if rows:
                        yield first(rows)
                    at, rows = row[0], []
                rows.append(row)
        if rows:
            yield first(rows)

    sent = reread(docs, spots, key, text, counted, State, note, send)
    back = sent.repartitionById(1 << bits, F.col("slice")).mapInArrow(count, counted).drop("slice")
    return back.repartition("pack").sortWithinPartitions("pack").mapInArrow(choose, out)


def kept_apart(docs: DataFrame, names: DataFrame, groups: DataFrame, bits: int, key: str, text: str) -> DataFrame:
    """groups (node, root) cut by prefixes: linked sets share one of the first n - ceil(0.8 n) + 1 of their n elements, whatever
    order all elements are put in. The rarest stand first here, so sets that are alike by what a whole group holds fall apart."""
    context = docs.sparkSession.sparkContext
    spots = context.broadcast(spots_of(names, groups, key))
    ddl = "node long, element long"
    if names.join(groups, "node").groupBy("node").agg(F.min("n_shingles").alias("n")).agg(F.sum("n")).first()[0] > BINS // 4:
        first = prefixes(docs, spots, max(4, bits - 3), key, text)
    else:
        levels = context.broadcast(rarity(docs, spots, key, text))

        def note(state, d, s):
            state.append((d, prefix(s, levels.value)))

        def rows(state, last):
            if state:
                node = np.repeat(np.array([d for d, _ in state], dtype=np.int64), [len(p) for _, p in state])
                yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(np.concatenate([p for _, p in state]).view(np.int64))], names=["node", "element"])
                state.clear()

        first = reread(docs, spots, key, text, ddl, list, note, rows)
    met = saved(first.join(groups, "node").select("node", "root", "element").distinct())
    heads = met.groupBy("root", "element").agg(F.min("node").alias("head"), F.count("*").alias("n")).where("n > 1").drop("n")
    edges = met.join(heads, ["root", "element"]).where("node <> head").select(F.col("head").alias("a"), F.col("node").alias("b")).distinct()
    return components(edges)


def linked(left: list[np.ndarray], right: list[np.ndarray] | None) -> list[tuple[int, int]]:
    """Index pairs that span the links among left, or between left and right (whose indexes go on after left's)."""
    sets = left + (right or [])
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    if len(sets) == 2:
        common = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        return [(0, 1)] if 9 * common >= 4 * sizes.sum() else []
    flat, own = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    order = np.argsort(flat)
    flat, own = flat[order], own[order]
    new = np.ones(len(flat), dtype=bool)
    new[1:] = flat[1:] != flat[:-1]
    value = np.cumsum(new) - 1
    shared = np.bincount(value)[value] > 1
    value, own = value[shared], own[shared]
    n = len(left)
    common = np.zeros((n, len(sets) if right is None else len(right)), dtype=np.float32)
    if len(value):
        value = np.unique(value, return_inverse=True)[1]
        for at in range(0, int(value.max()) + 1, 16_384):
            here = (value >= at) & (value < at + 16_384)
            m = np.zeros((len(sets), 16_384), dtype=np.float32)
            m[own[here], value[here] - at] = 1
            common += m[:n] @ (m.T if right is None else m[n:].T)
    others = sizes if right is None else sizes[n:]
    x, y = np.nonzero(9 * common.astype(np.int64) >= 4 * (sizes[:n, None] + others[None]))
    if right is None:
        x, y = x[x < y], y[x < y]
    else:
        y = y + n
    parent = list(range(len(sets)))

    def top(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    out = []
    for i, j in zip(x.tolist(), y.tolist()):
        p, q = top(i), top(j)
        if p != q:
            parent[p] = q
            out.append((i, j))
    return out


def verified(docs: DataFrame, names: DataFrame, groups: DataFrame, size: int, key: str, text: str) -> DataFrame:
    """Links (a, b) that connect all sets of each group of groups(node, root) that links connect: exact.

    First each block of a group meets a few leaders of the group. What they link is connected already, so the group's
    largest family is not compared with itself again: only pairs of blocks with sets outside of it are. Groups and blocks
    are laid out on the narrow table; each wanted set moves once to meet its place, and once to each pair of blocks it is in.
    Where pairs of blocks hold more than a part of the texts' size, they are dealt in turns, so that disk does not follow their number."""
    counts = groups.groupBy("root").agg(F.count("*").alias("n"))
    spots = docs.sparkSession.sparkContext.broadcast(spots_of(names, groups, key))
    schema, arrow = arrow_schema("node long, elements binary")

    def rows(held, last):
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(list(c), type=f.type) for c, f in zip((held.keys(), held.values()), arrow)], schema=arrow)
            held.clear()

    read = reread(docs, spots, key, text, schema, dict, lambda held, d, s: held.__setitem__(d, s.tobytes()), rows)
    order = F.pmod(F.xxhash64("node", F.lit("leader")), F.lit(1 << 40))
    sized = groups.join(counts, "root").withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int")).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    small, large = sized.where("blocks = 1").select("node", "root", "blocks", "block", F.lit(False).alias("leads")), sized.where("blocks > 1")
    # the sets with the least hash, one for each of LEADERS parts of a group: sums of one row each, whatever its size
    first = large.groupBy("root", F.pmod(F.xxhash64("node", F.lit("part")), F.lit(LEADERS)).alias("part")).agg(F.min(F.struct(order.alias("o"), "node")).alias("f"))
    leaders = first.select("root", F.col("f.node").alias("node"), F.lit(True).alias("leads"))
    placed = saved(small.union(large.join(leaders, ["root", "node"], "left").select("node", "root", "blocks", "block", F.coalesce("leads", F.lit(False)).alias("leads"))))
    # leaders stand as block -1 in each block of their group; a group of one block has none
    where = F.when(F.col("leads"), F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array("block"))
    met = read.join(placed, "node").dropDuplicates(["node"])
    links = saved(
        compared(
            met.withColumn("j", F.explode(where)).select(
                "root", F.when(F.col("blocks") == 1, 0).otherwise(-1).alias("i"), "j", F.when(F.col("leads"), -1).otherwise(F.col("block")).alias("block"), "node", "elements"
            )
        )
    )
    led = placed.where("blocks > 1")
    # families of large groups: the largest is put into blocks of its own, and those never meet one another
    family = components(links.join(led.select(F.col("node").alias("a")), "a", "left_semi")).withColumnRenamed("root", "family")
    inside = led.select("root", "node").join(family, "node", "left").select("root", "node", F.coalesce("family", "node").alias("family"))
    sizes = inside.groupBy("root", "family").agg(F.count("*").alias("n"))
    main = sizes.groupBy("root").agg(F.max(F.struct("n", "family")).alias("m"), F.sum("n").alias("all")).select("root", F.col("m.family").alias("main"), F.col("m.n").alias("held"), "all")
    rest = saved(
        inside.join(main.where("held < all"), "root")
        .withColumn("own", F.ceil(F.col("held") / BLOCK).cast("int")).withColumn("others", F.ceil((F.col("all") - F.col("held")) / BLOCK).cast("int"))
        .withColumn("block", F.when(F.col("family") == F.col("main"), F.pmod(F.xxhash64("node"), F.col("own"))).otherwise(F.col("own") + F.pmod(F.xxhash64("node"), F.col("others"))).cast("int"))
        .select("root", "node", "block", "own", "others")
    )
    if rest.isEmpty():
        return links
    few = docs.sparkSession.sparkContext.broadcast(spots_of(names, rest, key))  # their texts are read once more: no sets are kept
    again = reread(docs, few, key, text, schema, dict, lambda held, d, s: held.__setitem__(d, s.tobytes()), rows)
    met = again.join(rest, "node").dropDuplicates(["node"])
    theirs = F.sequence(F.col("own"), F.col("own") + F.col("others") - 1)
    dealt = met.withColumn("other", F.explode(F.when(F.col("block") < F.col("own"), theirs).otherwise(F.sequence(F.lit(0), F.col("own") + F.col("others") - 1)))).select(
        "root", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "node", "elements"
    )
    copies = F.when(F.col("block") < F.col("own"), F.col("others")).otherwise(F.col("own") + F.col("others")).cast("long")
    sizes = names.join(rest, "node").groupBy("node").agg(F.min(8 * F.col("n_shingles") * copies).alias("bytes"))
    turns = turns_of(sizes.agg(F.sum("bytes")).first()[0], size)
    for turn in range(turns):
        part = dealt if turns == 1 else dealt.where(F.pmod(F.xxhash64("root", "i", "j"), F.lit(turns)) == turn)
        links = links.union(saved(compared(part)))  # written, so that no task runs two Python workers, one to compare and one to contract
    return links


def turns_of(dealt: int, size: int) -> int:
    """In how many turns so many bytes are dealt beside texts of that size."""
    return max(1, -(-dealt // max(LEAST_DEALT, int(DEALT * size))))


def compared(dealt: DataFrame) -> DataFrame:
    """Links (a, b) from (root, i, j, block, node, elements): all pairs of block i, where it is block j too, else all pairs of
    a set of block i and one of block j."""

    def run(batches):
        at, rows = None, []

        def close():
            if len(rows) < 2:
                return [], []
            i, j = at[1:]
            left = [r for r in rows if r[0] == i]
            right = [r for r in rows if r[0] != i] if i != j else None
            if right is not None and not (left and right):
                return [], []
            sets = [np.frombuffer(r[2], dtype=np.uint64) for r in left], None if right is None else [np.frombuffer(r[2], dtype=np.uint64) for r in right]
            nodes = [r[1] for r in left + (right or [])]
            found = linked(*sets) if len(nodes) > 1 else []
            return [nodes[x] for x, _ in found], [nodes[y] for _, y in found]

        a, b = [], []
        for batch in batches:
            for root, i, j, block, node, raw in zip(*(c.to_pylist() for c in batch.columns)):
                if (root, i, j) != at:
                    x, y = close() if at else ([], [])
                    a += x
                    b += y
                    at, rows = (root, i, j), []
                rows.append((block, node, raw))
            if a:
                yield pa.RecordBatch.from_arrays([pa.array(a, type=pa.int64()), pa.array(b, type=pa.int64())], schema=EDGE_ARROW)
                a, b = [], []
        x, y = close() if at else ([], [])
        if a + x:
            yield pa.RecordBatch.from_arrays([pa.array(a + x, type=pa.int64()), pa.array(b + y, type=pa.int64())], schema=EDGE_ARROW)

    return dealt.repartition("root", "i", "j").sortWithinPartitions("root", "i", "j").mapInArrow(run, EDGE)


def similar(docs: DataFrame, key: str = "doc_id", text: str = "text", rounds: int = 3) -> tuple[DataFrame, DataFrame]:
    """(names, roots): set_names of all rows, and (node, root) of the sets that have a link."""
    n, size = docs.agg(F.count("*"), F.coalesce(F.sum(F.octet_length(text)), F.lit(0))).first()
    bits = slice_bits(docs, max(64, size // SLICE))
    frequent = docs.sparkSession.sparkContext.broadcast(frequent_elements(docs, text, n))
    both = saved(names_and_edges(docs, key, text, frequent, bits))
    names = both.where("copy is not null").select(key, "copy", "n_shingles", "node")
    groups = saved(grouped(both.where("copy is null").select("a", "b", "label", "node")))
    for salt in range(1, rounds + 1):
        large = groups.groupBy("root").agg(F.count("*").alias("n")).where(F.col("n") > LARGE)
        crowd = large.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        if not crowd:
            break
        inside = saved(groups.join(large.select("root"), "root", "left_semi").select("node", "root"))
        cut = finer(docs, names, inside, frequent, salt, bits, key, text)
        groups = saved(groups.join(large.select("root"), "root", "left_anti").select("node", "root").union(cut))
        if cut.groupBy("root").agg(F.count("*").alias("n")).where(F.col("n") > LARGE).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0] > 0.8 * crowd:
            break  # what is left belongs together, or is alike without a link
    large = groups.groupBy("root").agg(F.count("*").alias("n")).where(F.col("n") > LARGE).select("root")
    if not large.isEmpty():
        cut = kept_apart(docs, names, saved(groups.join(large, "root", "left_semi").select("node", "root")), bits, key, text)
        groups = saved(groups.join(large, "root", "left_anti").select("node", "root").union(cut))
    return names, saved(components(verified(docs, names, groups, size, key, text)))


def near_copies(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_shingles, component_id) for each row: the smallest id reachable by links, the row's own included."""
    names, roots = similar(docs, key, text)
    least = names.where("node is not null").groupBy("node").agg(F.min(key).alias("least"), F.count("*").alias("rows"))
    rooted = least.join(roots, "node", "left").where("rows > 1 OR root IS NOT NULL").select("node", F.coalesce("root", "node").alias("root"), "least")
    shared = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    # rows without a set, and sets that stand alone, name themselves; a text's many copies are dealt out
    component = rooted.join(shared, "root").select("node", "component_id", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    some = names.where("node is not null").withColumn("salt", F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int"))
    met = some.join(component, ["node", "salt"], "left").select(key, "n_shingles", F.coalesce("component_id", key).alias("component_id"))
    return met.union(names.where("node is null").select(key, "n_shingles", F.col(key).alias("component_id")))


def one_of_each(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with one row of each component: that of the smallest id; rows without a set all stay.

    Rows that repeat both id and text are one row. Texts move once, to meet the list of rows that stay."""
    names, roots = similar(docs, key, text)
    own, seen = spare(docs, "own_id", "seen")
    order = F.struct(F.col(key).isNull().alias("no_id"), F.col(key).alias("id"), F.col("copy").alias("copy"))
    least = names.where("node is not null").groupBy("node").agg(F.min(order).alias("least"))
    rooted = least.join(roots, "node", "left").select(F.coalesce("root", "node").alias("root"), "least")
    kept = rooted.groupBy("root").agg(F.min("least").alias("least")).select(F.struct(F.col("least.id").alias("id")).alias(own), F.col("least.copy").alias(seen))
    bare = names.where("node is null").select(F.struct(F.col(key).alias("id")).alias(own), F.col("copy").alias(seen)).distinct()
    # ids in a struct: null ids are equal there, and rows lie for the join as they do for telling repeated ones
    rows = docs.withColumns({own: F.struct(F.col(key).alias("id")), seen: F.xxhash64(text)})
    return rows.join(kept.union(bare), [own, seen], "left_semi").dropDuplicates([own, seen]).select(*docs.columns)
