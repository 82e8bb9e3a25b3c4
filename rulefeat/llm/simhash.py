"""SimHash near-duplicates through vantage-point trees over the fingerprints.

The tree has one level for each of `levels` disjoint blocks of bits. The vantage points of its levels are the blocks of one of the fingerprints;
a node's children are the rings of equal Hamming distance to its level's vantage point. Distances over blocks add up to the
Hamming distance, so by the triangle bound the ring numbers of two fingerprints within radius r differ by at most r in
all levels together. A leaf (a path of ring numbers) is a shard; a fingerprint is stored in its own
and queries the shards whose boundary its ball overlaps. Both are equi-join keys, so the
tree is walked by one shuffle join, and the pairs found are exact at any size. The number of levels and the vantage point are those
of the least expected cost, by how a sample of the fingerprints falls into leaves.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import materialise, release, settings, ship_package, small_broadcasts, trim_memory
from .components import connected
from .marks import marked

#: Levels to choose from, and how many fingerprints are tried as vantage points.
DEPTHS, CANDIDATES = (6, 8, 10, 12, 16, 21), 4
#: Fingerprints by which a tree is chosen, at most about so many; all fingerprints are stored and asked for in it.
TRIAL = 50_000
SHINGLE, SEED, CHUNK = 3, 42, 1 << 16


def fingerprint(text: str | None, width: int = SHINGLE) -> int:
    """Signed 64-bit SimHash of a text's shingles of `width` words, repeats included."""
    import numpy as np
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: only A-Z and ASCII white space
    if not words:
        return 0
    buffer = b" ".join(words)
    width = min(width, len(words))
    starts, at = [0], 0
    for w in words:
        at += len(w) + 1
        starts.append(at)
    n, votes = len(words) - width + 1, np.zeros(64, np.int64)
    digest = xxhash.xxh64_intdigest
    for low in range(0, n, CHUNK):
        high = min(n, low + CHUNK)
        hashes = np.fromiter((digest(buffer[a : b - 1], SEED) for a, b in zip(starts[low:high], starts[low + width : high + width])), np.uint64, high - low)
        votes += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(votes * 2 > n, bitorder="little")
    return int(bits.view(np.int64)[0])


def fingerprint_column(text_col: str, width: int = SHINGLE) -> Column:
    @F.pandas_udf("long")
    def of(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            yield pd.Series([fingerprint(t, width) for t in texts], dtype="int64")
        trim_memory()

    return of(F.col(text_col).cast("string"))


def fingerprints(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", width: int = SHINGLE) -> DataFrame:
    ship_package(docs.sparkSession)
    return docs.select(F.col(id_col).alias("doc_id"), fingerprint_column(text_col, width).alias("fp"))


def _blocks(levels: int) -> list[int]:
    edges = [round(i * 64 / levels) for i in range(levels + 1)]
    return [(((1 << (b - a)) - 1) << a) for a, b in itertools.pairwise(edges)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _bits_per_ring(levels: int) -> int:
    return max(bin(m).count("1") for m in _blocks(levels)).bit_length()


def leaf(fp: Column, levels: int, vantage: int = 0) -> Column:
    """Path of ring numbers of a fingerprint, packed in a long with one spare ring on both sides' account; vantage is a signed long."""
    shift, parts = _bits_per_ring(levels), []
    for i, mask in enumerate(_blocks(levels)):
        ring = F.bit_count(fp.bitwiseXOR(F.lit(vantage).cast("long")).bitwiseAND(F.lit(_signed(mask)).cast("long"))).cast("long")
        parts.append(F.shiftleft(ring, shift * i))
    out = parts[0]
    for p in parts[1:]:
        out = out.bitwiseOR(p)
    return out


def overlapped(levels: int, radius: int) -> list[int]:
    """Differences between a leaf and the leaves its ball overlaps, half of them: of a difference and its opposite just one."""
    shift, found = _bits_per_ring(levels), {(0,) * levels}
    for _ in range(radius):
        found |= {(*d[:i], d[i] + s, *d[i + 1 :]) for d in found for i in range(levels) for s in (1, -1)}
    half = [d for d in found if sum(map(abs, d)) <= radius and d > tuple(-x for x in d)]
    # as numbers the paths add without mixing: a ring outside its block names no leaf at all or one that the exact distance rejects
    return sorted(sum(x << (shift * i) for i, x in enumerate(d)) for d in half)


def choose_tree(points: DataFrame, radius: int = 2) -> tuple[int, int]:
    """(levels, vantage) of points(fp). A point asks overlapped() shards, and is compared with what its shards hold.

    How many that is follows from the share of pairs of sampled points that fall into one leaf; the sample is of the least hashes, bounded by TRIAL.
    The pairs found are the same with any tree.
    """
    n = points.count()
    if n < 2:
        return DEPTHS[0], 0
    drawn = materialise(points.where(F.pmod(F.xxhash64("fp"), F.lit(1 << 30)) < int(min(1.0, TRIAL / n) * (1 << 30))).select("fp"), "tree-sample")
    vantages = [r["fp"] for r in drawn.orderBy(F.xxhash64("fp")).limit(CANDIDATES).collect()] or [0]
    trees = [(d, v) for d in DEPTHS for v in vantages]
    fallen = drawn.select(F.explode(F.array(*[F.struct(F.lit(i).alias("tree"), leaf(F.col("fp"), d, v).alias("leaf")) for i, (d, v) in enumerate(trees)])).alias("t"))
    held = fallen.groupBy("t.tree", "t.leaf").agg(F.count(F.lit(1)).alias("c")).groupBy("tree").agg(F.sum(F.col("c") * (F.col("c") - 1)).alias("same"), F.sum("c").alias("m")).collect()
    release(drawn)

    def cost(r) -> float:
        asked = len(overlapped(trees[r["tree"]][0], radius)) + 1
        met = n * r["same"] / max(1, r["m"] * (r["m"] - 1))  # points in a point's own leaf; its neighbours hold about as many
        return asked * (1 + 0.1 * met)  # a comparison is some ten times cheaper than a shuffled question

    return min(((cost(r), *trees[r["tree"]]) for r in held), default=(0, DEPTHS[0], 0))[1:]


def near_pairs(points: DataFrame, radius: int = 2, levels: int = 8, vantage: int = 0) -> DataFrame:
    """points(fp), distinct longs, to all pairs (u, v) with u <> v at `radius` differing bits or fewer, each once.

    Copies were one point before, so a leaf holds different fingerprints only; a leaf that is large all the same is split by the engine's skew join.
    The questions are hundreds a point, which the engine takes for one when it sizes a join, so it is told to shuffle both sides.
    """
    homes = points.select("fp", leaf(F.col("fp"), levels, vantage).alias("leaf"))
    close = F.bit_count(F.col("u").bitwiseXOR(F.col("v"))) <= radius
    stored = homes.select(F.col("fp").alias("v"), "leaf")
    inside = homes.select(F.col("fp").alias("u"), "leaf").join(stored.hint("merge"), "leaf").where((F.col("u") < F.col("v")) & close)
    steps = F.array(*[F.lit(x).cast("long") for x in overlapped(levels, radius)])
    asked = homes.select(F.col("fp").alias("u"), F.explode(steps).alias("step"), "leaf").select("u", (F.col("leaf") + F.col("step")).alias("leaf"))
    across = asked.join(stored.hint("merge"), "leaf").where(close)
    return inside.select("u", "v").unionByName(across.select("u", "v"))


def near_components(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", radius: int = 2, levels: int | None = None, width: int = SHINGLE) -> DataFrame:
    """One row per input row: doc_id, fingerprint (16 hex digits), component_id, and as longs fp and root (the component's least fingerprint).

    component_id is the smallest id reachable over links of `radius` bits or fewer. Texts without words (null, empty, white space)
    have fingerprint zero and link like others. Null ids get a row and don't count as smallest; a component of null ids alone has a null id.
    Repeated rows are repeated in the result; an empty table gives an empty one. Copies share a fingerprint and never form pairs.
    """
    spark = docs.sparkSession
    with settings(spark, small_broadcasts(spark)):
        marked = materialise(fingerprints(docs, text_col, id_col, width), "fingerprints")
        points = materialise(marked.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "points")
        chosen, vantage = choose_tree(points, radius)
        roots = connected(near_pairs(points.select("fp"), radius, levels or chosen, vantage))
    rooted = points.join(roots, points.fp == roots.node, "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    ids = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = rooted.join(ids.hint("merge"), "root").select("fp", "component_id", "root")
    return marked.join(named.hint("merge"), "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "fp", "root")


def keep_one_of_each(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """docs with one row of each component: the one with its smallest id. All columns are kept.

    Where several rows of a component bear that id (or no row of it has an id), the one with the longest text, then the least hash, stays.
    """
    return keep_least(docs, materialise(near_components(docs, text_col, id_col), "near-components"), fingerprint_column(text_col), text_col, id_col)


def keep_least(docs: DataFrame, found: DataFrame, own: Column, text_col: str, id_col: str) -> DataFrame:
    """docs with one row of each component of found(doc_id, component_id, fp, root), a stored table; own is a row's fp. Where ids are unique, only rows that may go move."""
    if found.groupBy("doc_id").count().where("count > 1 or doc_id is null").isEmpty():
        gone = found.where("doc_id <> component_id").select(F.col("doc_id").alias("__id"))
        told = marked(docs, F.xxhash64(F.col(id_col)), gone, F.xxhash64("__id"))
        some = told.where("__maybe").select(*[F.col(f"`{c}`") for c in docs.columns])
        return told.where("NOT __maybe").select(*some.columns).unionByName(some.join(gone, some[id_col] == gone["__id"], "left_anti"))
    named = found.select(F.col("fp").alias("__fp"), F.col("component_id").alias("__component"), F.col("root").alias("__root")).distinct()
    held = docs.select("*", own.alias("__own"))
    heads = held.join(named, F.col("__own") == F.col("__fp")).where(F.col(id_col).eqNullSafe(F.col("__component")))
    rank = F.struct((-F.length(F.coalesce(F.col(text_col), F.lit("")))).alias("a"), F.xxhash64(text_col).alias("b"))
    return heads.groupBy("__root").agg(F.min_by(F.struct(*[F.col(f"`{c}`") for c in docs.columns]), rank).alias("__row")).select("__row.*")
