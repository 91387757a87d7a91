"""Personal data by bootstrapped contextual extraction.

1. Every whole text is read once. The base rules give seed entities (e-mail, ip, card, phone);
   looser shapes give candidates of the same kinds that break a rule (an address without a
   dot, a number without a plus sign, a card whose check digit fails, ...).
2. Seeds and candidates stand in contexts: the word before and the word after, lower-cased.
   Words end at blanks, after a colon or an equals sign, and where an identifier begins or ends,
   so a label that touches its value is a word too. (kind, side, word) is a lexical pattern, the
   identifier's text an instance; together they are the edges of a bipartite graph, summed in Spark.
3. A pattern's confidence is the share of all places of its word in the corpus where an
   accepted instance of its kind stands beside it. Only words that are in some pattern are counted:
   a fixed-size bit filter built from the patterns goes to the tasks. Words that only the border of an
   identifier makes are counted where it is found.
4. Rounds: confident patterns accept the instances beside them, which support more patterns.
5. Accepted instances add spans wherever they occur; base spans always stay.

Null and empty texts have no spans. Positions are code points, ends exclusive. Repeated rows
each get their spans: rows are told apart by a number of their own, never by id. Hot patterns
or instances (many rows with the same words) are summed before they are shuffled, and looked
up with a salt. An empty table gives an empty result; other columns are never read.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_left, bisect_right
from collections import Counter

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import FILTER_BITS, map_batches, pieces, row_filter, saved, spare, unpacked

KINDS = ("email", "ip", "card", "phone")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
LOOSE_DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)*")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
#: Looser shapes: what a candidate of a kind may look like when a rule fails.
LOOSE_NUMBER = re.compile(r"(?<![\w.@+-])\(?[0-9][0-9 ().-]{5,}[0-9](?![\w@])")
DIGIT = re.compile(r"[0-9]")
#: Words of contexts: a run without blanks ends after a colon or an equals sign.
TOKEN = re.compile(r"[^\x20\x09-\x0D:=]*[:=]|[^\x20\x09-\x0D:=]+")
#: Words above this length are named by a hash of the whole of them.
NAMED = 64
BLANK = "\x20\x09\x0a\x0b\x0c\x0d"
EDGE = "\"'`.,;!?()[]{}<>*#$%&|"
#: Slots for the look-up of hot instances.
SALTS = 16
#: Discovered spans up to which they are sent to all tasks (some 10 MB); beyond, they are joined by a shuffle.
SENT = 200_000


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def emails(text: str, domain=DOMAIN) -> list[tuple[int, int]]:
    """Leftmost non-overlapping matches: all starts of a run before an @ share its fate, so the run is walked once."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in LOCAL:
            start -= 1
        nxt = at + 1
        if start < at and (m := domain.match(text, at + 1)):
            out.append((start, m.end()))
            nxt = end = m.end()
        at = text.find("@", nxt)
    return out


def base_spans(text: str | None) -> list[tuple[int, int, int]]:
    """(kind's place, start, end) of all base matches, by kind, then start."""
    if not text:
        return []
    out = [(0, a, b) for a, b in emails(text)] if "@" in text else []
    if DIGIT.search(text):
        for m in IP.finditer(text):
            if all(len(p := part.lstrip("0")) <= 3 and int(p or 0) <= 255 for part in m[0].split(".")):
                out.append((1, *m.span()))
        for m in CARD.finditer(text):
            if m.end() - m.start() >= 16:
                digits = m[0].replace(" ", "").replace("-", "")
                if 16 <= len(digits) <= 19 and luhn(digits):
                    out.append((2, *m.span()))
        if "+" in text:
            for m in PHONE.finditer(text):
                if 8 <= sum(c.isdigit() for c in m[0]) <= 15:
                    out.append((3, *m.span()))
    return out


def loose_spans(text: str, taken: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Candidates: identifier-like spans that touch no base span."""
    found = []
    if "@" in text:
        found += [(0, a, b) for a, b in emails(text, LOOSE_DOMAIN)]
    if DIGIT.search(text):
        for m in LOOSE_NUMBER.finditer(text):
            digits = sum(c.isdigit() for c in m[0])
            if m[0].count(".") == 3 and re.fullmatch(r"[0-9]+(?:\.[0-9]+){3}", m[0]):
                found.append((1, *m.span()))
            elif 12 <= digits <= 19:
                found.append((2, *m.span()))
            elif 7 <= digits < 12:
                found.append((3, *m.span()))
    if not found:
        return []
    spans = sorted((a, b) for _, a, b in taken)
    starts = [a for a, _ in spans]
    out, last = [], -1
    for k, a, b in sorted(found, key=lambda s: (s[1], s[2])):
        i = bisect_left(starts, b)
        if a >= last and not any(y > a for _, y in spans[max(0, i - 4) : i]):
            out.append((k, a, b))
            last = b
    return out


def contexts(text: str, spans: list[tuple[int, int, int]]) -> list[tuple[str, str, int, int]]:
    """For each span, in their order: the word before and the word after, and whether it is a word of the text as it stands
    (0) or made by the border of an identifier (1). Spans must not overlap inside a kind; a word never reaches into one."""
    tokens = [m.span() for m in TOKEN.finditer(text)]
    starts, ends = [a for a, _ in tokens], [b for _, b in tokens]
    borders = sorted({x for _, a, b in spans for x in (a, b)})
    out = []
    for _, a, b in spans:
        i = bisect_left(starts, a) - 1  # the last token that begins before the span
        left, made = "", 0
        if i >= 0:
            low, high = starts[i], min(ends[i], a)
            j = bisect_left(borders, high) - 1
            if j >= 0 and borders[j] > low:
                low = borders[j]
            left, made = cleaned(text[low:high]), int((low, high) != tokens[i])
        i = bisect_right(ends, b)  # the first token that ends after the span
        right, after = "", 0
        if i < len(tokens):
            low, high = max(starts[i], b), ends[i]
            j = bisect_right(borders, low)
            if j < len(borders) and borders[j] < high:
                high = borders[j]
            right, after = cleaned(text[low:high]), int((low, high) != tokens[i])
        out.append((left, right, made, after))
    return out


def cleaned(word: str) -> str:
    """Lower-cased, without outer punctuation but for a colon or an equals sign; long words by name."""
    word = word.strip(EDGE).lower()
    return word if len(word) <= NAMED else f"#{xxhash.xxh3_128_hexdigest(word.encode('utf-8', 'surrogatepass'))}"


def spell(spans) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for k, a, b in spans)


def instance(kind: int, found: str) -> str:
    """An identifier's own form: digits and letters only, lower-cased."""
    return found.lower() if kind < 2 else re.sub(r"[^0-9]", "", found)


def scan(docs: DataFrame, key: str, text: str) -> DataFrame:
    """One row per row of docs, whatever its text: base spans, and seeds and candidates with their contexts."""
    kind = docs.schema[key].dataType.simpleString()
    ddl = (
        f"{key} {kind}, n_email long, n_ip long, n_card long, n_phone long, base string, "
        "found array<struct<kind:int,start:int,end:int,seed:boolean,inst:string,left:string,right:string,left_made:int,right_made:int>>"
    )

    def work():
        def step(keys, texts):
            out = {c: [] for c in (key, "n_email", "n_ip", "n_card", "n_phone", "base", "found")}
            for k, t in zip(keys, texts):
                base = base_spans(t)
                rows = []
                if t:
                    spans = base + loose_spans(t, base)
                    for i, ((kd, a, b), (left, right, made, after)) in enumerate(zip(spans, contexts(t, spans) if spans else ())):
                        rows.append({"kind": kd, "start": a, "end": b, "seed": i < len(base), "inst": instance(kd, t[a:b]), "left": left, "right": right, "left_made": made, "right_made": after})
                n = Counter(s[0] for s in base)
                out[key].append(k)
                for i, name in enumerate(KINDS):
                    out[f"n_{name}"].append(n[i])
                out["base"].append(spell(base))
                out["found"].append(rows)
            return out

        return step

    return map_batches(docs.select(key, text), ddl, work)


def background(docs: DataFrame, text: str, words: DataFrame) -> DataFrame:
    """(word, places) for the words given: how often each stands anywhere in the corpus, as the texts stand."""
    raw = docs.sparkSession.sparkContext.broadcast(row_filter(words, "word"))  # 2 MiB whatever the data

    def work():
        bits, seen, passed = unpacked(raw.value), Counter(), {}

        def flush():
            rows = [(w, n) for w, n in seen.items()]
            seen.clear()
            passed.clear()
            return {"word": [w for w, _ in rows], "places": [n for _, n in rows]} if rows else None

        def names(word):
            """Those of a blank-separated word's parts that may be wanted."""
            parts = (word,) if ":" not in word and "=" not in word else TOKEN.findall(word)
            return tuple(c for p in parts if (c := cleaned(p)) and bits[zlib.crc32(c.encode("utf-8", "surrogatepass")) % FILTER_BITS])

        def step(texts):
            for t in texts:
                if t:
                    for raw_word, n in Counter(t.encode("utf-8", "surrogatepass").split()).items():
                        ok = passed.get(raw_word)
                        if ok is None:
                            ok = passed[raw_word] = names(raw_word.decode("utf-8", "surrogatepass"))
                        for c in ok:
                            seen[c] += n
            return flush() if len(passed) > 300_000 else None

        step.rest = flush
        return step

    counted = map_batches(docs.select(text), "word string, places long", work)
    return counted.groupBy("word").agg(F.sum("places").alias("places"))


def discover(docs: DataFrame, scanned: DataFrame, text: str, rounds: int, least: float, support: int) -> DataFrame:
    """(kind, inst) of the candidates that confident patterns accept."""
    each = scanned.select(F.explode("found").alias("f")).select("f.*")
    edges = (
        each.groupBy("kind", "inst", "seed", "left", "right").agg(F.count("*").alias("n"), F.sum("left_made").alias("left_made"), F.sum("right_made").alias("right_made"))
        .select("kind", "inst", "seed", "n", F.explode(F.array(
            F.struct(F.lit("L").alias("side"), F.col("left").alias("word"), F.col("left_made").alias("made")),
            F.struct(F.lit("R").alias("side"), F.col("right").alias("word"), F.col("right_made").alias("made")),
        )).alias("p"))
        .select("kind", "inst", "seed", "p.side", "p.word", "n", "p.made").where("word <> ''")
        .groupBy("kind", "inst", "seed", "side", "word").agg(F.sum("n").alias("n"), F.sum("made").alias("made"))
    )
    edges = saved(edges)
    # a pattern with fewer instances, or beside seeds only, can accept nothing: its word is not counted
    able = edges.groupBy("kind", "side", "word").agg(F.count_distinct("inst").alias("k"), F.count_if(~F.col("seed")).alias("c")).where((F.col("k") >= support) & (F.col("c") > 0))
    seeds = edges.where("seed").select("kind", "inst").distinct()
    edges = saved(edges.join(able.select("kind", "side", "word"), ["kind", "side", "word"], "left_semi").select(*edges.columns))
    made = edges.groupBy("word").agg(F.sum("made").alias("places"))  # every pattern's word has a row here
    places = saved(made.union(background(docs, text, edges.select("word").distinct())).groupBy("word").agg(F.sum("places").alias("places")))
    accepted = seeds
    found = None
    for _ in range(rounds):
        patterns = (
            edges.join(accepted, ["kind", "inst"], "left_semi")
            .groupBy("kind", "side", "word").agg(F.sum("n").alias("hits"), F.count_distinct("inst").alias("instances"))
            .where(F.col("instances") >= support).join(places, "word")
            .withColumn("confidence", F.col("hits") / F.greatest("places", "hits")).where(F.col("confidence") >= least)
        )
        more = (
            edges.where("not seed").join(patterns.select("kind", "side", "word", "confidence"), ["kind", "side", "word"])
            .groupBy("kind", "inst").agg((1 - F.exp(F.sum(F.ln(F.greatest(F.lit(1e-9), 1 - F.col("confidence")))))).alias("score"))
            .where(F.col("score") >= least).select("kind", "inst")
        )
        found = saved(more)
        accepted = seeds.union(found).distinct()
    return found


def spans(
    docs: DataFrame, key: str = "doc_id", text: str = "text", rounds: int = 3, least: float = 0.6, support: int = 3,
) -> DataFrame:
    """(key, n_email, n_ip, n_card, n_phone, base, spans, n_found): base counts and base spans as the rules give
    them, and all spans with those discovered; spans is ordered by kind, then start.

    least: confidence that a pattern and an instance need; support: distinct instances a pattern needs."""
    scanned = saved(scan(docs, key, text).withColumn("row", F.monotonically_increasing_id()))
    accepted = discover(docs, scanned, text, rounds, least, support)
    spots = scanned.select("row", F.explode("found").alias("f")).where("not f.seed").select("row", "f.kind", "f.inst", "f.start", "f.end")
    salted = accepted.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    extra = (
        spots.withColumn("salt", F.pmod(F.col("row"), F.lit(SALTS)).cast("int")).join(salted, ["kind", "inst", "salt"])
        .groupBy("row").agg(F.collect_list(F.struct("kind", "start", "end")).alias("more"))  # at most a text's own spans
    )
    own = F.transform(F.filter("found", lambda f: f["seed"]), lambda f: F.struct(f["kind"], f["start"], f["end"]))
    every = F.array_sort(F.concat(own, F.coalesce(F.col("more"), F.array().cast("array<struct<kind:int,start:int,end:int>>"))))
    name = F.array(*[F.lit(k) for k in KINDS])
    said = F.array_join(F.transform(every, lambda s: F.concat_ws(":", F.element_at(name, s["kind"] + 1), s["start"], s["end"])), ",")
    return scanned.join(extra, "row", "left").select(
        key, "n_email", "n_ip", "n_card", "n_phone", "base", said.alias("spans"), F.coalesce(F.size("more"), F.lit(0)).cast("long").alias("n_found")
    )


def redacted(docs: DataFrame, text: str = "text", rounds: int = 3, least: float = 0.6, support: int = 3) -> DataFrame:
    """docs with every span replaced by its kind in square brackets; rows, ids and other columns stay.

    Base spans are masked where the text is read. Discovered spans join by the digest of the text: sent to all
    tasks while they are at most SENT in number, else by a shuffle whose hot keys Spark splits."""
    names, at = docs.columns, docs.columns.index(text)
    digest, found_here = spare(docs, "digest", "found")
    scanned = saved(scan(docs.select(F.xxhash64(text).alias("digest"), F.col(text).alias("text")), "digest", "text"))
    accepted = discover(docs, scanned, text, rounds, least, support)
    salted = accepted.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    extra = saved(
        scanned.select("digest", F.explode("found").alias("f")).where("not f.seed").select("digest", "f.kind", "f.inst", "f.start", "f.end").distinct()
        .withColumn("salt", F.pmod(F.col("digest"), F.lit(SALTS)).cast("int")).join(salted, ["kind", "inst", "salt"])
        .groupBy(F.col("digest").alias(digest)).agg(F.collect_list(F.struct("kind", "start", "end")).alias(found_here))
    )
    number = extra.agg(F.coalesce(F.sum(F.size(found_here)), F.lit(0))).first()[0]
    joined = docs.withColumn(digest, F.xxhash64(text)).join(F.broadcast(extra) if number <= SENT else extra, digest, "left")

    def mask(batches):
        for batch in pieces(batches):
            texts, more = batch.column(at).to_pylist(), batch.column(len(names)).to_pylist()
            columns = [batch.column(i) for i in range(len(names))]
            new = [cut(t, base_spans(t) + [(m["kind"], m["start"], m["end"]) for m in ms or ()]) for t, ms in zip(texts, more)]
            columns[at] = pa.array(new, type=columns[at].type)
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return joined.select(*names, found_here).mapInArrow(mask, docs.schema)


def cut(text: str | None, found: list[tuple[int, int, int]]) -> str | None:
    """text with spans replaced; overlapping ones are replaced together, by the first one's kind."""
    if not found:
        return text
    out, at = [], 0
    for k, a, b in sorted(found, key=lambda s: (s[1], s[0])):
        if a >= at:
            out += [text[at:a], f"[{KINDS[k].upper()}]"]
        at = max(at, b)
    return "".join(out) + text[at:]
