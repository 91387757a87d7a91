"""Token counts by byte-pair merging with a heap over a linked list; no identifier is ever made.

A piece starts as one symbol per byte. Adjacent pairs that have a rank wait in a heap; the
lowest rank (leftmost on ties) is merged, the list is relinked and the two new neighbours
are pushed; entries whose symbols have changed are skipped. Tokens = symbols - merges.
The heap makes a piece of n bytes cost O(n log n), so one very long word is no trap.

Null or empty text: 0 bytes, 0 tokens. Occurrences of special tokens' strings count one
token each, as in the tokenizer's default. Repeated rows repeat; other columns are ignored.
"""

from __future__ import annotations

import heapq
import json

import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches

#: Fixed value: white space as Unicode defines it, the class that the vocabulary's own splitter uses.
SPACE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Fixed value: the splitter of the byte-level vocabularies.
SPLIT = regex.compile(
    rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{SPACE}\p{{L}}\p{{N}}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+"
)
#: A space that has white space or an end beside it: such texts are split as a whole, the others word by word.
ODD_SPACE = regex.compile(rf"^ | $|[{SPACE}] | [{SPACE}]")
#: Entries that a worker remembers; beyond it the memory starts anew. It changes speed, never counts.
REMEMBER = 300_000


class MergeRanks:
    """Ranks of adjacent pairs, in the vocabulary's byte alphabet, read from a tokenizer's JSON file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.ranks = {tuple(m if isinstance(m, list) else m.split(" ")): r for r, m in enumerate(spec["model"]["merges"])}
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.special_split = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in set(plain)]
        self.alphabet = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}
        self.pieces: dict[str, int] = {}
        self.chunks: dict[str, int] = {}

    def symbols(self, piece: str) -> list[str]:
        return [*piece.encode("utf-8", "surrogatepass").decode("latin-1").translate(self.alphabet)]

    def merged(self, piece: str) -> int:
        """Tokens of one piece."""
        symbol = self.symbols(piece)
        n = tokens = len(symbol)
        if n < 2:
            return n
        rank_of = self.ranks.get
        before, after = list(range(-1, n - 1)), list(range(1, n + 1))
        heap = [(r, i) for i in range(n - 1) if (r := rank_of((symbol[i], symbol[i + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            rank, left = heapq.heappop(heap)
            right = after[left]
            if right >= n or not symbol[left] or rank_of((symbol[left], symbol[right])) != rank:
                continue
            symbol[left] += symbol[right]
            symbol[right] = ""
            tokens -= 1
            beyond = after[left] = after[right]
            if beyond < n:
                before[beyond] = left
                if (r := rank_of((symbol[left], symbol[beyond]))) is not None:
                    heapq.heappush(heap, (r, left))
            ahead = before[left]
            if ahead >= 0 and (r := rank_of((symbol[ahead], symbol[left]))) is not None:
                heapq.heappush(heap, (r, ahead))
        return tokens

    def chunk(self, chunk: str) -> int:
        """Tokens of a text that is split as a whole."""
        total, known = 0, self.pieces
        for piece in SPLIT.findall(chunk):
            n = known.get(piece)
            if n is None:
                n = self.merged(piece)
                if len(piece) < 64:
                    if len(known) >= REMEMBER:
                        known.clear()
                    known[piece] = n
            total += n
        return total

    def plain(self, text: str) -> int:
        """Tokens of a text without special strings. A space between two other characters always starts a
        piece, so such a text is counted word by word, each with its leading space, from memory."""
        if ODD_SPACE.search(text):
            return self.chunk(text)
        first, *words = text.split(" ")
        total, known = self.chunk(first), self.chunks
        seen = known.get
        for word in words:
            n = seen(word)
            if n is None:
                n = self.chunk(" " + word)
                if len(word) < 64:
                    if len(known) >= REMEMBER:
                        known.clear()
                    known[word] = n
            total += n
        return total

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if not any(s in text for s in self.special):
            return self.plain(text)
        parts = self.special_split.split(text)
        return len(parts) - 1 + sum(self.plain(p) for p in parts if p)


_loaded: dict[str, MergeRanks] = {}


def ranks_at(path: str) -> MergeRanks:
    """One per worker process and file."""
    if path not in _loaded:
        _loaded[path] = MergeRanks(path)
    return _loaded[path]


def token_counts(docs: DataFrame, vocabulary: str, text: str = "text", key: str = "doc_id", limit: int = 1024) -> DataFrame:
    """(key, n_bytes, n_tokens, over_limit) for each row. vocabulary: path of a byte-level BPE JSON file on every node."""
    kind = docs.schema[key].dataType.simpleString()

    def work():
        table = ranks_at(vocabulary)

        def step(keys, texts):
            return {
                key: keys,
                "n_bytes": [len((t or "").encode("utf-8", "surrogatepass")) for t in texts],
                "n_tokens": [table.count(t) for t in texts],
            }

        return step

    counted = map_batches(docs.select(key, text), f"{key} {kind}, n_bytes long, n_tokens long", work)
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
