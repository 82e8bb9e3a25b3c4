"""BPE encoding and decoding with a trie of the distinct words.

In a merge-ordered BPE with one merge per token, a sequence of tokens is the encoding of its text exactly when every two neighbours
are the encoding of theirs; so the encoding of a word is that of a shorter prefix and one last token. Going depth first through
a trie of the distinct words, each prefix gets its last token once, for all the words that share it; an encoding is read back along the last tokens.
The trie's edges are strings and it is gone through without recursion, so words may be as long as texts.
"""

from __future__ import annotations

import gc
import hashlib
import json
import re
import unicodedata
from array import array
from collections.abc import Iterator
from functools import lru_cache
from itertools import islice

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import ship_package, trim_memory
from .token_count import SPACES, Merger, byte_letters

REMEMBERED, COMMON = 250_000, 60_000
#: Longer words aren't remembered between batches.
LONG_WORD = 256


class TrieEncoder:
    """Encoder of a word-level BPE file of the tokenizers library: NFC, lower case, white space dropped, an end mark on the last symbol."""

    def __init__(self, spec: str):
        import regex

        j = json.loads(spec)
        model, split = j["model"], j["pre_tokenizer"]["pretokenizers"][0]
        kinds = [n["type"] for n in (j.get("normalizer") or {}).get("normalizers", [])]
        if kinds != ["NFC", "Replace", "Lowercase"] or split["behavior"] != "Removed" or not split["invert"] or j.get("decoder"):
            raise ValueError("only lower-case word vocabularies without a decoder are encoded")
        self.end, self.vocabulary = model["end_of_word_suffix"], model["vocab"]
        if len(model["merges"]) != len({a + b for a, b in (m if isinstance(m, list) else m.split(" ") for m in model["merges"])}):
            raise ValueError("a token with two merges")
        self.merger, self.letters = Merger(model["merges"], self.vocabulary), byte_letters()
        self.names = {i: t for t, i in self.vocabulary.items()} | {t["id"]: t["content"] for t in j["added_tokens"]}
        self.width = max(map(len, self.vocabulary))
        self.length = {i: len(t) - len(self.end) * (t != self.end and t.endswith(self.end)) for t, i in self.vocabulary.items()}
        self.closing = {t.removesuffix(self.end): i for t, i in self.vocabulary.items() if t != self.end and t.endswith(self.end)}
        # the longest token for each four last letters bounds the search at a node
        self.reach, self.reach_end = {}, {}
        for reach, names in ((self.reach, self.vocabulary), (self.reach_end, self.closing)):
            for t in names:
                reach[t[-4:]] = max(reach.get(t[-4:], 3), len(t))
        special = sorted(((t["content"], t["id"]) for t in j["added_tokens"]), key=lambda x: -len(x[0]))
        self.special, self.special_ids = regex.compile("(" + "|".join(regex.escape(t) for t, _ in special) + ")"), dict(special)
        self.words = regex.compile(split["pattern"]["Regex"].replace(r"[^\s", "[^" + SPACES))
        # the same for ASCII texts, where letters are a-z and digits 0-9, by the faster engine
        plain = split["pattern"]["Regex"].replace(r"\p{L}", "a-z").replace(r"\p{N}", "0-9").replace(r"[^\s", r"[^\t\n\x0b\f\r ")
        self.ascii_words = re.compile(plain)
        self.parts: dict[int, list[int]] = {}
        self.fits: dict[tuple[int, int], bool] = {}
        self.ids_of: dict[str, bytes] = {}

    def symbols(self, token: int) -> list[int]:
        """Initial symbols of a token."""
        if (found := self.parts.get(token)) is None:
            name = self.names[token]
            bare = name.removesuffix(self.end) if len(name) > len(self.end) else name
            out = [self.vocabulary[c] for c in bare]
            if bare != name:
                out[-1] = self.vocabulary[bare[-1] + self.end]
            found = self.parts[token] = out
        return found

    def follows(self, first: int, second: int) -> bool:
        """Whether the two tokens are the encoding of their joint text (first -1: the second of its own)."""
        if (found := self.fits.get((first, second))) is None:
            if len(self.fits) > 2 * REMEMBERED:
                self.fits.clear()
            tokens = [second] if first < 0 else [first, second]
            found = self.fits[first, second] = self.merger.merge([s for t in tokens for s in self.symbols(t)]) == tokens
        return found

    def last_token(self, tail: str, depth: int, ends: bool, lasts: list[int]) -> int:
        """The one token that ends the encoding of a path of `depth` letters, of which tail has the last; lasts has those of its prefixes by length."""
        fits, have = self.fits, len(tail)
        get, reach = (self.closing.get, self.reach_end) if ends else (self.vocabulary.get, self.reach)
        for at in range(max(0, have - reach.get(tail[-4:], 3)), have):
            if (token := get(tail[at:])) is not None:
                before = lasts[depth - have + at]
                if (good := fits.get((before, token))) is None:
                    good = self.follows(before, token)
                if good:
                    return token
        raise ValueError(f"no token ends {tail!r}")

    def grow(self, words: set[str]) -> list:
        """The trie of the words' letters without the last one: a node is [letters of the edge to it, children by first letter, (last letter, word) of the words that end below it]."""
        root, letters = ["", {}, []], self.letters
        for w in words:
            mapped = w if w.isascii() and w.isprintable() else "".join([letters[b] for b in w.encode("utf-8", "replace")])
            body, node, at = mapped[:-1], root, 0  # the last symbol bears the end mark, so no word goes on below it
            while at < len(body):
                child = node[1].get(body[at])
                if child is None:
                    child = node[1][body[at]] = [body[at:], {}, []]
                elif not body.startswith(child[0], at):
                    edge, k = child[0], 1
                    while k < len(edge) and at + k < len(body) and edge[k] == body[at + k]:
                        k += 1
                    child[0] = edge[k:]
                    child = node[1][body[at]] = [edge[:k], {edge[k]: child}, []]
                node, at = child, at + len(child[0])
            node[2].append((mapped[-1], w))
        return root

    def encode_words(self, words: set[str]) -> None:
        """Fill ids_of for the words."""
        width, last_token = self.width, self.last_token
        lasts, stack = [-1], [(self.grow(words), 0, "")]  # lasts follows the branch from the root
        while stack:
            (edge, children, ended), depth, tail = stack.pop()
            del lasts[depth + 1 :]
            for c in edge:
                tail, depth = (tail + c)[-width:], depth + 1
                lasts.append(last_token(tail, depth, False, lasts))
            for c, word in ended:
                self.finish(word, (tail + c)[-width:], depth + 1, lasts)
            for below in children.values():
                stack.append((below, depth, tail))

    def finish(self, word: str, tail: str, depth: int, lasts: list[int]) -> None:
        out, at, length = [token := self.last_token(tail, depth, True, lasts)], depth, self.length
        while at := at - length[token]:
            out.append(token := lasts[at])
        out.reverse()
        self.ids_of[word] = array("I", out).tobytes()

    def rest(self) -> None:
        """Between tasks: forget most words, and keep what is known of token pairs."""
        self.forget()
        trim_memory()

    def forget(self) -> None:
        """Keep the words met first, which are the common ones."""
        self.ids_of = dict(islice(((w, ids) for w, ids in self.ids_of.items() if len(w) <= LONG_WORD), COMMON))

    def segment(self, text: str) -> list[str]:
        """Words of a text without special strings, in the vocabulary's normal form."""
        # white space parts words and is in none, so it needn't be made even;
        # letter by letter: str.lower() has another small sigma at the end of words
        if text.isascii():
            return self.ascii_words.findall(text.lower())
        return self.words.findall(unicodedata.normalize("NFC", text).replace("Σ", "σ").lower())

    def encode_all(self, texts) -> list[bytes]:
        """For each text its ids as little-endian unsigned 32-bit integers.

        The new words of all the texts go into one trie. Nothing here forms cycles, so the collector rests meanwhile.
        """
        gc.disable()
        try:
            return self._encode_all(texts)
        finally:
            gc.enable()

    def _encode_all(self, texts) -> list[bytes]:
        special, split, out = self.special_ids, [], []
        for text in texts:
            split.append([p if p in special else self.segment(p) for p in self.special.split(text or "") if p])
        words = [p for parts in split for p in parts if not isinstance(p, str)]
        if new := set().union(*words).difference(self.ids_of):
            self.encode_words(new)
        ids_of = self.ids_of.__getitem__
        for parts in split:
            out.append(b"".join([array("I", [special[p]]).tobytes() if isinstance(p, str) else b"".join(map(ids_of, p)) for p in parts]))
        if len(self.ids_of) > REMEMBERED:
            self.forget()
        return out

    def encode(self, text: str | None) -> bytes:
        return self.encode_all([text])[0]

    def decode(self, ids: bytes) -> str:
        """Names of the ids with blanks between, special ones included: what the library gives where the file names no decoder."""
        return " ".join(map(self.names.__getitem__, array("I", ids)))


def slices(texts, letters: int = 4_000_000):
    """Runs of texts of about so many letters together."""
    some, held = [], 0
    for t in texts:
        some.append(t)
        held += len(t or "")
        if held >= letters:
            yield some
            some, held = [], 0
    if some:
        yield some


@lru_cache(2)
def encoder(spec: str) -> TrieEncoder:
    return TrieEncoder(spec)


def _spec(docs: DataFrame, vocabulary_path: str):
    ship_package(docs.sparkSession)
    with open(vocabulary_path, encoding="utf-8") as f:
        return docs.sparkSession.sparkContext.broadcast(f.read())


def _digests(own: TrieEncoder, ids: bytes) -> tuple[int, str, str]:
    """Number of ids, their digest, and that of the text that they decode to."""
    return len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(own.decode(ids).encode("utf-8", "replace")).hexdigest()


DIGESTS = ("n_tokens", "ids_sha256", "decoded_sha256")


def encoded_digests(docs: DataFrame, vocabulary_path: str, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per input row: doc_id, n_tokens, ids_sha256, decoded_sha256.

    Null texts are empty ones, with 0 tokens and the digests of nothing. Null ids and repeated rows count like others; other columns aren't read.
    The decoded text is made from the ids, not from the text.
    """
    spec = _spec(docs, vocabulary_path)

    @F.pandas_udf("n_tokens long, ids_sha256 string, decoded_sha256 string")
    def digests(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        own = encoder(spec.value)
        for texts in batches:
            yield pd.DataFrame([_digests(own, ids) for some in slices(texts) for ids in own.encode_all(some)], columns=list(DIGESTS))
        own.rest()

    return docs.select(F.col(id_col).alias("doc_id"), digests(F.col(text_col).cast("string")).alias("e")).select("doc_id", "e.*")


def encode_column(docs: DataFrame, vocabulary_path: str, text_col: str = "text", ids_col: str = "token_ids", digests: bool = False) -> DataFrame:
    """docs with a column of token ids (array<int>; an empty one for null and empty texts), and if asked n_tokens, ids_sha256 and decoded_sha256.

    Columns of docs by those names are replaced.
    """
    spec = _spec(docs, vocabulary_path)
    extra = DIGESTS if digests else ()

    @F.arrow_udf("ids array<int>" + (", n_tokens long, ids_sha256 string, decoded_sha256 string" if digests else ""))
    def encoded(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        own = encoder(spec.value)
        for texts in batches:
            found = [ids for some in slices(texts.to_pylist()) for ids in own.encode_all(some)]
            ends = np.cumsum([0, *(len(i) // 4 for i in found)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(found), "<i4")))
            rows = [_digests(own, ids) for ids in found] if digests else []
            told = [pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.string(), pa.string())[: len(extra)])]
            yield pa.StructArray.from_arrays([lists, *told], ["ids", *extra])
        own.rest()

    kept = [F.col(f"`{c}`") for c in docs.columns if c not in (ids_col, *extra)]
    made = docs.select(*kept, encoded(F.col(text_col).cast("string")).alias("__encoded"))
    return made.select(*kept, F.col("__encoded.ids").alias(ids_col), *[F.col(f"__encoded.{c}").alias(c) for c in extra])


def decode_column(docs: DataFrame, vocabulary_path: str, ids_col: str = "token_ids", text_col: str = "decoded") -> DataFrame:
    """docs with the decoded text of a column of token ids; a null list decodes to the empty text."""
    spec = _spec(docs, vocabulary_path)

    @F.pandas_udf("string")
    def text_of(lists: pd.Series) -> pd.Series:
        decode = encoder(spec.value).decode
        return pd.Series([decode(array("I", [] if x is None else list(x)).tobytes()) for x in lists])

    return docs.withColumn(text_col, text_of(F.col(ids_col)))
