"""Token counts without tokens: byte-pair merging over a linked list of symbols, driven by a heap."""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import ship_package, trim_memory

#: The pre-tokenising pattern of the byte-level vocabularies.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Unicode's white space; \s of Python's libraries holds four more control characters.
SPACES = "\\t\\n\\x0b\\f\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
REMEMBERED = 200_000


def byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary: itself if printable, else the next from U+0100 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letters, spare = [""] * 256, 256
    for b in shown:
        letters[b] = chr(b)
    for b in range(256):
        if not letters[b]:
            letters[b], spare = chr(spare), spare + 1
    return letters


class Merger:
    """Ranks of symbol pairs, and merging of one word's symbols by them."""

    def __init__(self, merges: list, vocabulary: dict[str, int]):
        self.vocabulary, self.ranks = vocabulary, {}
        for rank, pair in enumerate(merges):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.ranks[vocabulary[a], vocabulary[b]] = (rank, vocabulary[a + b])

    def merge(self, symbols: list[int]) -> list[int]:
        """Symbols after all merges."""
        symbols = list(symbols)
        self.run(symbols)
        return [s for s in symbols if s >= 0]

    def run(self, symbols: list[int]) -> int:
        """Merge in place, each time the pair of the lowest rank and leftmost, and tell the number of merges; a symbol that goes becomes -1. n log n for any length."""
        n, ranks, merges = len(symbols), self.ranks, 0
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = []
        for i in range(n - 1):
            if found := ranks.get((symbols[i], symbols[i + 1])):
                heap.append((found[0], i, found[1]))
        heapq.heapify(heap)
        while heap:
            rank, i, joined = heapq.heappop(heap)
            j = after[i]
            # a stale entry: one of its symbols has been merged meanwhile
            if symbols[i] < 0 or j >= n or ranks.get((symbols[i], symbols[j])) != (rank, joined):
                continue
            symbols[i], symbols[j] = joined, -1
            merges += 1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if found := ranks.get((joined, symbols[k])):
                    heapq.heappush(heap, (found[0], i, found[1]))
            if (h := before[i]) >= 0 and (found := ranks.get((symbols[h], joined))):
                heapq.heappush(heap, (found[0], h, found[1]))
        return merges


class TokenCounter:
    """Counts of a byte-level BPE file in the tokenizers library's format, special strings in texts counted as one token each."""

    def __init__(self, spec: str):
        import regex

        j = json.loads(spec)
        model, before = j["model"], j["pre_tokenizer"]
        if j.get("normalizer") or before["type"] != "ByteLevel" or before.get("add_prefix_space") or not before.get("use_regex", True):
            raise ValueError("only plain byte-level vocabularies are counted")
        self.merger = Merger(model["merges"], model["vocab"])
        self.symbol = [model["vocab"][c] for c in byte_letters()]
        special = sorted((t["content"] for t in j.get("added_tokens", ())), key=len, reverse=True)
        self.special = regex.compile("|".join(map(regex.escape, special))) if special else None
        self.pieces = regex.compile(PIECES.replace(r"\s", "[" + SPACES + "]").replace("[^[" + SPACES + "]", "[^" + SPACES).replace(r"\S", "[^" + SPACES + "]"))
        self.known: dict[str, int] = {}

    def word(self, piece: str) -> int:
        """Initial symbols minus merges."""
        symbols = [self.symbol[b] for b in piece.encode("utf-8", "replace")]
        return len(symbols) - self.merger.run(symbols)

    def plain(self, text: str) -> int:
        known, pieces = self.known, self.pieces.findall(text)
        for p in set(pieces).difference(known):
            known[p] = self.word(p)
        total = sum(map(known.__getitem__, pieces))
        if len(known) > REMEMBERED:
            known.clear()
        return total

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if not self.special or not self.special.search(text):
            return self.plain(text)
        marks = len(self.special.findall(text))
        return marks + sum(self.plain(t) for t in self.special.split(text) if t)


@lru_cache(2)
def counter(spec: str) -> TokenCounter:
    return TokenCounter(spec)


def token_counts(docs: DataFrame, vocabulary_path: str, limit: int = 512, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per input row: doc_id, n_bytes, n_tokens, over_limit.

    Null and empty texts have 0 of both. Null ids and repeated rows are counted like others; other columns aren't read. The vocabulary
    (a file of the driver, of fixed size) is broadcast; each task remembers a bounded number of words.
    """
    ship_package(docs.sparkSession)
    with open(vocabulary_path, encoding="utf-8") as f:
        spec = docs.sparkSession.sparkContext.broadcast(f.read())

    @F.pandas_udf("long")
    def counted(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        own = counter(spec.value)
        for texts in batches:
            yield pd.Series([own.count(t) for t in texts], dtype="int64")
        own.known.clear()
        trim_memory()

    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.col(id_col).alias("doc_id"), F.octet_length(text).cast("long").alias("n_bytes"), counted(text).alias("n_tokens")).withColumn("over_limit", F.col("n_tokens") > limit)
