"""Secret scans: fixed patterns, and a battery of randomness tests over encoded-looking strings.

A candidate's encoding is the narrowest alphabet that has its characters. Three tests look at it under the hypothesis that its symbols are independent and uniform:
chi-squared over cells of the alphabet, runs, and serial correlation of neighbours; their p-values are combined into one score, which is low for a random string and
grows with the length of a string that words or numbers made. To call a string a secret is to reject that words made it: the chance that such a string of its encoding and length
scores as low is found from strings made by rule of a fixed list of words, and goes, with those of all candidates of all documents, through
false-discovery control within classes of encoding and length. What it rejects is a secret; at most a share of `LEVEL` of those is expected to be none.
Long strings are told apart more surely, so in a class of short ones with many words around only a better score will do.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from bisect import bisect_right
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import materialise, ship_package

ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
HEX = re.compile(r"[0-9a-f]{24,}")
CANDIDATE = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20,}={0,6}(?![A-Za-z0-9+/_=-])")
KINDS = ("assign", "access", "hex")
DIGITS, LOWER, VOWELS, RARE = "0123456789", "abcdefghijklmnopqrstuvwxyz", "aeiou", "bfgjkpqvwxyz"
UPPER = LOWER.upper()
#: Symbols in the order of their values, narrow alphabets first.
ALPHABETS = {
    "hex": DIGITS + "abcdef", "HEX": DIGITS + "ABCDEF", "lower": LOWER, "upper": UPPER, "base32": UPPER + "234567", "base32lower": LOWER + "234567",
    "base36": DIGITS + LOWER, "BASE36": DIGITS + UPPER, "letters": UPPER + LOWER, "base62": UPPER + LOWER + DIGITS, "base64url": UPPER + LOWER + DIGITS + "-_", "base64": UPPER + LOWER + DIGITS + "+/", "mixed": UPPER + LOWER + DIGITS + "+/-_",
}
#: Words that names are made of.
WORDS = """account action active address agent array attribute backup batch before binary block boolean bridge buffer builder button cache callback category channel client cluster column command
component config connection container context controller counter create customer database default delete description device directory document driver element endpoint engine error event exception
export factory field file filter format function generator group handler header history identifier image index input instance integer interface internal invoice item iterator language layout level library
listener loader location logger manager mapper message method model module monitor network number object operator option order output package parameter parser password path pattern payload policy
position process product profile project property provider query queue reader record reference region register registry report request resource response result router schedule schema search section
selector sender sequence server service session setting signal source status storage stream string system table target template thread timeout token transaction transfer update user value vector version
widget window worker wrapper strasse nachricht verwaltung regierung entreprise bonjour maison travail gracias trabajo ciudad pregunta""".split()
#: Other words than those of the list vary more: their scores are taken to spread so much wider.
WIDER = 1.5
#: Strings made by rule for each encoding and length; lengths that have their own null distribution; the share of false ones among the secrets.
DRAWS, LENGTHS, LEVEL = 800, (*range(20, 64), *range(64, 128, 8), *range(128, 513, 32)), 0.1


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the fixed patterns, by start and kind."""
    out = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text)]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def inferred(s: str) -> str:
    """The first alphabet that has all symbols."""
    chars = set(s)
    return next(name for name, alphabet in ALPHABETS.items() if chars <= set(alphabet))


@lru_cache(None)
def symbol_table(encoding: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """By byte: value, cell, and side for the runs test; and the share of the alphabet in each cell.

    Hex has cells of four values, and its sides are the halves. In alphabets of letters the cells part vowels, rare and other letters by case, digits and signs,
    as words favour some of them, and the sides are vowels and all else.
    """
    alphabet = ALPHABETS[encoding]
    kinds = [VOWELS, RARE, "".join(sorted(set(LOWER) - set(VOWELS + RARE))), VOWELS.upper(), RARE.upper(), "".join(sorted(set(UPPER) - set((VOWELS + RARE).upper()))), DIGITS, "+/-_"]
    cell_of = (lambda c: alphabet.index(c) // 4) if encoding.lower() == "hex" else (lambda c: next(i for i, k in enumerate(kinds) if c in k))
    used = sorted({cell_of(c) for c in alphabet})
    value, cell, side = (np.zeros(128, np.int64) for _ in range(3))
    for i, c in enumerate(alphabet):
        value[ord(c)], cell[ord(c)] = i, used.index(cell_of(c))
        side[ord(c)] = i >= len(alphabet) / 2 if encoding.lower() == "hex" else c in VOWELS + VOWELS.upper()
    return value, cell, side, np.array([sum(cell_of(c) == u for c in alphabet) for u in used]) / len(alphabet)


def normal_tail(z: np.ndarray) -> np.ndarray:
    """P(Z >= z), never 0."""
    return np.array([max(1e-300, 0.5 * math.erfc(min(37.0, x) / math.sqrt(2))) for x in z])


def battery(strings: list[str], encoding: str) -> np.ndarray:
    """p-values of the three tests, a row for each of the strings (all of one length)."""
    value, cell, side, share = symbol_table(encoding)
    raw = np.frombuffer("".join(strings).encode("ascii"), np.uint8).reshape(len(strings), -1)
    n, v, sides = raw.shape[1], value[raw].astype(float), side[raw].astype(bool)
    counts = np.stack([(cell[raw] == c).sum(axis=1) for c in range(len(share))], axis=1)
    x, df = ((counts - n * share) ** 2 / (n * share)).sum(axis=1), len(share) - 1
    uniform = normal_tail(((np.maximum(x, 1e-12) / df) ** (1 / 3) - (1 - 2 / (9 * df))) / math.sqrt(2 / (9 * df)))  # by the cube root
    a = sides.sum(axis=1)
    b = n - a
    runs, mean = 1 + (sides[:, 1:] != sides[:, :-1]).sum(axis=1), 1 + 2 * a * b / n
    spread = np.sqrt(np.maximum(1e-9, 2 * a * b * (2 * a * b - n) / (n * n * max(1, n - 1))))
    by_runs = np.where((a == 0) | (b == 0), 1.0, 2 * normal_tail(np.abs(runs - mean) / spread))  # one side alone is the first test's matter
    d = v - v.mean(axis=1, keepdims=True)
    power = (d * d).sum(axis=1)
    r = np.where(power > 0, (d[:, 1:] * d[:, :-1]).sum(axis=1) / np.maximum(power, 1e-12), 1.0)
    return np.stack([uniform, np.minimum(1, by_runs), np.minimum(1, 2 * normal_tail(np.abs(r + 1 / n) * math.sqrt(n)))], axis=1)


def score(p: np.ndarray) -> np.ndarray:
    """The combined score of the tests: the root of -2 times the sum of logarithms."""
    return np.sqrt(-2 * np.log(p).sum(axis=1))


def made_of_words(draw: random.Random, encoding: str, length: int) -> str:
    """A name, path or number of about the look that such strings have in an encoding's alphabet."""
    if encoding.lower() == "hex":
        kind, unit = draw.randrange(4), "".join(draw.choice(ALPHABETS[encoding]) for _ in range(draw.randrange(1, 7)))
        out = (str(draw.randrange(1, 10**6)).zfill(length), unit * length, "".join(draw.choice(["19", "20", "0", "00", "1", "12"]) + str(draw.randrange(10, 32)) for _ in range(length)), draw.choice(["00", "ff", "dead", "cafe", "beef"]) * length)[kind]
        out = out[:length]
        return out.upper() if encoding == "HEX" else out.lower()
    joint = {"base64": "/", "base64url": draw.choice("_-"), "mixed": draw.choice("/-_")}.get(encoding, "")
    cased = encoding in ("letters", "base62", "base64", "base64url", "mixed")
    style = draw.randrange(3)
    out, digits = "", draw.randrange(4) if draw.random() < 0.5 else 0
    while len(out) < length - digits:
        w = draw.choice(WORDS)
        out += (w.capitalize() if cased and (style < 2 or not joint) else w) + (joint if style else "")
        if draw.random() < 0.1 and DIGITS[2] in ALPHABETS[encoding]:
            out += str(draw.randrange(2, 8))
    tail = "".join(draw.choice(DIGITS) for _ in range(digits))
    out = out[: length - digits] + tail
    out = out.upper() if ALPHABETS[encoding].isupper() else out
    known = set(ALPHABETS[encoding])
    return "".join(c if c in known else draw.choice("aeinrst" if "a" in known else "AEINRST") for c in out)


@lru_cache(None)
def null_of(encoding: str, length: int) -> tuple[float, float]:
    """Middle and spread of the lower half of the scores of strings that words made."""
    draw = random.Random(f"{encoding}:{length}")
    low, middle = np.quantile(score(battery([made_of_words(draw, encoding, length) for _ in range(DRAWS)], encoding)), [0.1, 0.5])
    return float(middle), max(0.05, WIDER * float(middle - low) / 1.2816)


def log_p(s: str, encoding: str) -> int:
    """Ten times the negative logarithm, rounded down, of the chance that a string that words made scores as low; at most 300.

    A length without a null distribution of its own has that of the next shorter one: words' scores grow with length, so its chance is no smaller than it should be.
    """
    middle, spread = null_of(encoding, LENGTHS[bisect_right(LENGTHS, len(s)) - 1])
    p = normal_tail(np.array([(middle - float(score(battery([s], encoding))[0])) / spread]))[0]
    return min(300, max(0, int(-10 * math.log10(p))))


def scan_text(text: str | None):
    """The base spans, and the candidates as (start, end, encoding, log_p)."""
    text = text or ""
    tested = []
    for m in CANDIDATE.finditer(text):
        s = m[0].rstrip("=")
        tested.append((m.start(), m.end(), encoding := inferred(s), log_p(s, encoding)))
    return base_spans(text), tested


def secret_scan(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", level: float = LEVEL) -> DataFrame:
    """One row per input row: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_random.

    spans has kind:start:end of the base spans and, of kind random, of the strings that the tests add where no base span has the same bounds. Null and empty texts have none.
    Null ids and repeated rows count like others; other columns aren't read; an empty table gives an empty result.
    """
    ship_package(docs.sparkSession)

    @F.pandas_udf("n_assign long, n_access long, n_hex long, base string, base_sha256 string, tested array<struct<start:int,stop:int,encoding:string,width:int,bin:int>>")
    def scan(texts: pd.Series) -> pd.DataFrame:
        rows = []
        for t in texts:
            base, tested = scan_text(t)
            joined = ",".join(f"{k}:{a}:{b}" for a, b, k in base)
            counts = [sum(k == kind for _, _, k in base) for kind in KINDS]
            bounds = {(a, b) for a, b, _ in base}
            kept = [{"start": a, "stop": b, "encoding": e, "width": int(math.log2(b - a)), "bin": p} for a, b, e, p in tested if (a, b) not in bounds]
            rows.append((*counts, joined, hashlib.sha256(joined.encode()).hexdigest(), kept))
        return pd.DataFrame(rows, columns=["n_assign", "n_access", "n_hex", "base", "base_sha256", "tested"])

    found = materialise(docs.select(F.col(id_col).alias("doc_id"), scan(F.col(text_col).cast("string")).alias("s")).select("doc_id", "s.*"), "secrets")
    # step-up control: in each class the largest chance at which the share of expected false discoveries is at most the level
    binned = found.select(F.explode("tested").alias("t")).groupBy("t.encoding", "t.width", "t.bin").agg(F.count(F.lit(1)).alias("n"))
    below = Window.partitionBy("encoding", "width").orderBy(F.col("bin").desc())
    every = Window.partitionBy("encoding", "width")
    passing = binned.withColumn("rank", F.sum("n").over(below)).withColumn("all", F.sum("n").over(every)).where(F.col("all") * F.pow(F.lit(10.0), -F.col("bin") / 10) <= level * F.col("rank"))
    rows = passing.groupBy("encoding", "width").agg(F.min("bin").alias("cut")).collect()  # thirteen encodings, about thirty widths
    cuts = F.create_map(*[x for r in rows for x in (F.lit(f"{r['encoding']}:{r['width']}"), F.lit(r["cut"]))]) if rows else F.expr("map('', 0)")
    secret = F.filter("tested", lambda t: t["bin"] >= F.coalesce(F.element_at(cuts, F.concat_ws(":", t["encoding"], t["width"].cast("string"))), F.lit(1000)))
    base = F.transform(F.filter(F.split("base", ","), lambda x: x != ""), lambda x: F.struct(F.split(x, ":")[1].cast("int").alias("start"), F.array_position(F.array(*map(F.lit, KINDS)), F.split(x, ":")[0]).cast("int").alias("kind"), x.alias("name")))
    added = F.transform("secret", lambda t: F.struct(t["start"].alias("start"), F.lit(len(KINDS) + 1).alias("kind"), F.concat_ws(":", F.lit("random"), t["start"].cast("string"), t["stop"].cast("string")).alias("name")))
    joined = F.array_join(F.transform(F.array_sort(F.concat(base, added)), lambda x: x["name"]), ",")
    return found.withColumn("secret", secret).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", joined.alias("spans"), F.size("secret").cast("long").alias("n_random"))
