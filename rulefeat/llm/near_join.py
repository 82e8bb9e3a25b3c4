"""Near copies of texts: groups by chains of pairs whose sets of five-word shingles have a Jaccard similarity of `LEAST` or more, whole and exact.

Two sets that similar must have 4/9 of the sum of their sizes in common; so in any one order of all shingles they share one among the first ones of both, as many as may be missing and one more. The order here puts
shingles that a fixed table of counts shows as common last, so that groups by a shared shingle stay small. Pairs are asked for in two rounds. The first takes the pairs that the SimHash tree finds,
and links each member of a group to the group's most typical one, the set with the commonest shingles: of copies of a text with edits that is the text itself, as edits bring rare
shingles in. What is confirmed is put together. The second takes the pairs of a group whose members aren't together yet; a copy too far from the typical one has so many rare shingles that they fill its first ones, and
only copies with the same edits meet it. So a large group of near copies is linked to one member and not pair by pair. Where a shingle still holds more than `GROUP` texts apart, the texts of such groups are
ordered anew by a table of their own shingles only, which tells rare from common more finely, until none is so large or an order no longer helps; a pair that is alike is in a small group of some order, or meets in the last one.
Every pair is confirmed on the words of its two texts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import ROWS_PER_BATCH, SMALL_BATCHES, materialise, settings, ship_package, small_broadcasts, trim_memory
from .components import connected
from .marks import marked
from .simhash import choose_tree, fingerprint, keep_least, near_pairs

WIDTH = 5
#: Least similarity, as a fraction.
LEAST = (4, 5)
#: The order's table hangs on the cost only: with more shingles than it can tell apart the groups become larger, and the pairs the same.
#: Slots of the table of counts; of fixed size whatever the data.
SLOT_BITS, BLOCK = 20, 1 << 16
#: Texts that share a shingle up to which all their pairs are looked at; larger groups are ordered anew first.
GROUP = 16
_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def shingles_of(text: str | None) -> set[tuple[bytes, ...]]:
    """The set of a text's shingles; a text of fewer words is one shingle, one without words has none."""
    w = words_of(text)
    return {tuple(w[i : i + WIDTH]) for i in range(max(1, len(w) - WIDTH + 1))} if w else set()


def alike(a: set, b: set) -> bool:
    both = len(a & b)
    return both * LEAST[1] >= LEAST[0] * (len(a) + len(b) - both)


def hashed(text: str | None, cache: dict[bytes, int]) -> np.ndarray:
    """Distinct 64-bit hashes of the shingles, sorted. Equal shingles have equal hashes."""
    import xxhash

    w = words_of(text)
    if not w:
        return np.zeros(0, np.uint64)
    if len(cache) > 200_000:
        cache.clear()
    digest = xxhash.xxh64_intdigest
    numbers = np.empty(len(w), np.uint64)
    for i, x in enumerate(w):
        h = cache.get(x)
        if h is None:
            h = cache[x] = digest(x)
        numbers[i] = h
    n = max(1, len(w) - WIDTH + 1)
    out = np.full(n, min(len(w), WIDTH), np.uint64)
    for k in range(min(len(w), WIDTH)):
        out = (out ^ numbers[k : k + n]) * _MULTIPLIER
        out ^= out >> np.uint64(29)
    return np.unique(out)


def _levels(texts: DataFrame) -> bytes:
    """For each slot of the hash's first bits, eight times the power of two of its count of shingles."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, cache = np.zeros(1 << SLOT_BITS, np.int64), {}
        for batch in batches:
            for text in batch.column(0):
                np.add.at(n, (hashed(text.as_py(), cache) >> np.uint64(64 - SLOT_BITS)).astype(np.int64), 1)
        blocks = np.minimum(n, 2**31 - 1).astype("<u4").reshape(-1, BLOCK)
        yield pa.RecordBatch.from_arrays([pa.array(range(len(blocks)), pa.int32()), pa.array([b.tobytes() for b in blocks], pa.binary())], ["block", "counts"])
        trim_memory()

    def total(rows: pa.Table) -> pa.Table:
        n = sum(np.frombuffer(c.as_py(), "<u4").astype(np.int64) for c in rows.column("counts"))
        return pa.table({"block": pa.array([rows.column("block")[0].as_py()], pa.int32()), "levels": pa.array([np.minimum(255, 8 * np.log2(1 + n)).astype(np.uint8).tobytes()], pa.binary())})

    rows = texts.select("text").mapInArrow(count, "block int, counts binary").groupBy("block").applyInArrow(total, "block int, levels binary").collect()
    held = {r["block"]: bytes(r["levels"]) for r in rows}
    return b"".join(held.get(b, bytes(BLOCK)) for b in range((1 << SLOT_BITS) // BLOCK))


def _marked(texts: DataFrame, id_type: str) -> DataFrame:
    """doc_id, key (of the text), node (of the set of shingles), fp, n (size of the set), typical (how common its shingles are), first (its first shingles in the common order)."""
    levels = texts.sparkSession.sparkContext.broadcast(_levels(texts))

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        level, cache = np.frombuffer(levels.value, np.uint8), {}
        for batch in batches:
            nodes, prints, sizes, typical, firsts = [], [], [], [], []
            for t in batch.column(2):
                text = t.as_py()
                h = hashed(text, cache)
                common = level[(h >> np.uint64(64 - SLOT_BITS)).astype(np.int64)]
                order = np.lexsort((h, common))
                typical.append(float(common.mean()) if len(h) else 0.0)
                nodes.append(int(np.uint64(xxhash.xxh64_intdigest(h.tobytes())).view(np.int64)))
                prints.append(fingerprint(text, WIDTH))
                sizes.append(len(h))
                firsts.append(h[order[: len(h) // LEAST[1] + 1]].view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(nodes, pa.int64()), pa.array(prints, pa.int64()), pa.array(sizes, pa.int32()), pa.array(typical, pa.float64()), pa.array(firsts, pa.list_(pa.int64()))],
                ["doc_id", "key", "node", "fp", "n", "typical", "first"],
            )
        trim_memory()

    return materialise(texts.select("doc_id", "key", "text").mapInArrow(mark, f"doc_id {id_type}, key long, node long, fp long, n int, typical double, first array<long>"), "marked")


def _shared(named: DataFrame) -> DataFrame:
    """(shingle, pos, node, n, typical) of the first shingles that two nodes or more have."""

    def several(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if held:
            rows = pa.Table.from_batches(held)
            shingle, node = rows.column("shingle").to_numpy(), rows.column("node").to_numpy()
            order = np.lexsort((node, shingle))
            shingle, node = shingle[order], node[order]
            new = np.r_[True, (shingle[1:] != shingle[:-1]) | (node[1:] != node[:-1])]  # copies of a set count once
            order, shingle = order[new], shingle[new]
            same = shingle[1:] == shingle[:-1]
            stay = np.r_[same, False] | np.r_[False, same]
            yield from rows.take(pa.array(order[stay])).combine_chunks().to_batches(max_chunksize=10_000)
        trim_memory()

    rows = named.select("node", "n", "typical", F.posexplode("first").alias("pos", "shingle")).select("shingle", "pos", "node", "n", "typical").repartition("shingle")
    with settings(named.sparkSession, {ROWS_PER_BATCH: "20000"}):  # narrow rows
        return materialise(rows.mapInArrow(several, "shingle long, pos int, node long, n int, typical double"), "shared")


def _texts_of(texts: DataFrame, named: DataFrame, nodes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(asked(node, key), the rows of texts whose key may be asked for) of nodes(node). A chance hit takes a row along for nothing, no more."""
    asked = materialise(named.select("node", "key").join(nodes, "node").groupBy("node").agg(F.min("key").alias("key")), "asked")
    return asked, marked(texts, F.col("key"), asked, F.col("key")).where("__maybe").select("doc_id", "key", "text")


def _confirmed(texts: DataFrame, named: DataFrame, pairs: DataFrame) -> DataFrame:
    """Of pairs(u, v) of nodes, those whose texts are alike."""
    ends = pairs.select(F.col("u").alias("node")).unionByName(pairs.select(F.col("v").alias("node"))).distinct()
    asked, hits = _texts_of(texts, named, ends)
    found = materialise(hits.select("key", "text").join(asked, "key").groupBy("node").agg(F.any_value("text").alias("text")), "asked-texts")

    @F.pandas_udf("boolean")
    def are_alike(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for left, right in batches:
            yield pd.Series([alike(shingles_of(a), shingles_of(b)) for a, b in zip(left, right)], dtype="bool")
        trim_memory()

    left, right = found.select(F.col("node").alias("u"), F.col("text").alias("a")), found.select(F.col("node").alias("v"), F.col("text").alias("b"))
    return materialise(pairs.join(left, "u").join(right, "v").where(are_alike("a", "b")).select("u", "v"), "alike")


def _may_be_alike() -> Column:
    """For a shingle that u and v share at places pos_u and pos_v of theirs: whether it is among as many first ones as the two may lack, and one more, and what can be common before and after is enough."""
    both, whole = F.col("n_u") + F.col("n_v"), sum(LEAST)
    must = F.ceil(both * LEAST[0] / whole)
    near = (F.col("pos_u") <= F.col("n_u") - must) & (F.col("pos_v") <= F.col("n_v") - must)
    room = F.least("pos_u", "pos_v") + F.least(F.col("n_u") - F.col("pos_u"), F.col("n_v") - F.col("pos_v"))
    return near & (room >= must) & (F.least("n_u", "n_v") * LEAST[1] >= F.greatest("n_u", "n_v") * LEAST[0])


def alike_pairs(docs: DataFrame, text_col: str, id_col: str) -> tuple[DataFrame, DataFrame]:
    """(marked rows, links (u, v) between their nodes): the links join exactly the nodes that chains of similar pairs join."""
    ship_package(docs.sparkSession)
    text = F.col(text_col).cast("string")
    texts = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text).alias("key"), text.alias("text"))
    named = _marked(texts, dict(texts.dtypes)["doc_id"])
    shared = _shared(named)

    prints = materialise(named.groupBy("fp").agg(F.min("node").alias("node")), "points")
    tree = near_pairs(prints.select("fp"), 2, *choose_tree(prints, 2))
    ends = tree.join(prints.select(F.col("fp").alias("u"), F.col("node").alias("a")), "u").join(prints.select(F.col("fp").alias("v"), F.col("node").alias("b")), "v").select("a", "b")
    one_print = named.select(F.col("fp").alias("fp"), F.col("node").alias("a")).join(prints.select("fp", F.col("node").alias("b")), "fp").select("a", "b")
    side = lambda df, s: df.select("shingle", F.col("node").alias(s), *[F.col(c).alias(f"{c}_{s}") for c in df.columns if c in ("pos", "n", "root")])
    centre = shared.groupBy("shingle").agg(F.min(F.struct((-F.col("typical")).alias("rare"), "node", "pos", "n")).alias("c")).select("shingle", "c.node", "c.pos", "c.n")
    star = side(centre, "u").join(side(shared, "v"), "shingle").where((F.col("u") != F.col("v")) & _may_be_alike()).select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    asked = ends.unionByName(one_print).where("a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).unionByName(star).distinct()
    first = materialise(asked, "pairs")
    links = _confirmed(texts, named, first)

    roots = connected(links)
    root_of = lambda df: df.join(roots, df.node == roots.node, "left").select("shingle", "pos", df.node, "n", F.coalesce("root", df.node).alias("root"))
    second = materialise(_pairs_apart(texts, named, materialise(root_of(shared), "rooted"), root_of, side).join(first, ["u", "v"], "left_anti"), "pairs")
    return named, links.unionByName(_confirmed(texts, named, second))


def _pairs_apart(texts: DataFrame, named: DataFrame, entries: DataFrame, root_of, side, group: int | None = None) -> DataFrame:
    """(u, v), each once, of all nodes of different roots that share a first shingle and may be alike, of entries(shingle, pos, node, n, root); hot groups are ordered anew."""
    found, before, kind = None, float("inf"), dict(texts.dtypes)["doc_id"]
    while True:
        groups = entries.groupBy("shingle").agg(F.count(F.lit(1)).alias("many"), F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select("shingle", "many")
        open_ = materialise(entries.join(groups, "shingle"), "open")
        nodes = materialise(open_.where(F.col("many") > (group or GROUP)).select("node").distinct(), "hot")
        hot = nodes.count()
        last = not hot or hot > 0.9 * before
        chosen = (open_ if last else open_.where(F.col("many") <= (group or GROUP))).drop("many")
        pairs = side(chosen, "u").join(side(chosen, "v"), "shingle").where((F.col("u") < F.col("v")) & (F.col("root_u") != F.col("root_v")) & _may_be_alike()).select("u", "v").distinct()
        found = pairs if found is None else found.unionByName(pairs)
        if last:
            return found.distinct()
        own = _marked(_texts_of(texts, named, nodes)[1], kind).join(nodes, "node", "left_semi")
        before, entries = hot, materialise(root_of(_shared(own)), "rooted")


def near_groups(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per input row: doc_id, component_id (the smallest id that chains of similar pairs reach), and as longs fp (a hash of the text) and root.

    Texts without words are alike. Null ids get a row and don't count as smallest.
    """
    with settings(docs.sparkSession, SMALL_BATCHES | small_broadcasts(docs.sparkSession)):
        named, links = alike_pairs(docs, text_col, id_col)
        roots = connected(links)
        rooted = named.groupBy("node").agg(F.min("doc_id").alias("first_id")).withColumnRenamed("node", "own").join(roots, F.col("own") == roots.node, "left").select("own", "first_id", F.coalesce("root", "own").alias("root"))
        ids = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
        told = rooted.join(ids, "root").select("own", "component_id", "root")
        return materialise(named.select("doc_id", F.col("key").alias("fp"), "node").join(told, F.col("node") == F.col("own")).select("doc_id", "component_id", "fp", "root"), "groups")


def keep_one_of_near(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """docs with one row of each group of near copies: the one with its smallest id. All columns are kept."""
    return keep_least(docs, near_groups(docs, text_col, id_col), F.xxhash64(F.col(text_col).cast("string")), text_col, id_col)
