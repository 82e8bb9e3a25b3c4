"""Toxicity scores: logistic regression by FTRL-proximal over hashed word n-grams and skip-grams.

Rates are per coordinate, and L1 keeps most weights at zero, so that the model is a short list of (coordinate, weight)
of bounded size, which is broadcast for scoring. Training reads a bounded sample of labelled rows, bounded in coordinates too.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import SMALL_BATCHES, materialise, release, settings, ship_package, trim_memory

BITS = 20
#: At most so many labelled rows are learnt from; beyond, those with the least hashes of their ids.
SAMPLE = 20_000
#: Coordinates of all learnt rows together at most (four bytes each); the first rows by hash that fit are learnt from, each whole.
COORDINATES = 1 << 25
WORDS = re.compile(r"\w+")
_MIX = np.uint64(0x9E3779B97F4A7C15)


class Hasher:
    """Coordinates of a text: its distinct words, word pairs, and pairs with one word skipped."""

    def __init__(self, bits: int = BITS):
        self.bits, self.known = bits, {}

    def coordinates(self, text: str | None) -> np.ndarray:
        import xxhash

        words, known = WORDS.findall((text or "").lower()), self.known
        for w in set(words).difference(known):
            known[w] = xxhash.xxh64_intdigest(w.encode("utf-8", "replace"))
        h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        if len(known) > 200_000:
            known.clear()
        kinds = [h]
        for gap in (1, 2):
            if len(h) > gap:
                kinds.append((h[:-gap] * _MIX + (h[gap:] ^ (h[gap:] >> np.uint64(29))) * np.uint64(2 * gap + 1)) * _MIX)
        return np.unique(np.concatenate(kinds) >> np.uint64(64 - self.bits)).astype(np.int64)


@dataclass
class FtrlModel:
    bits: int
    bias: float
    at: np.ndarray  # sorted coordinates
    weights: np.ndarray

    def score(self, coordinates: np.ndarray) -> float:
        place = np.searchsorted(self.at, coordinates)
        place[place == len(self.at)] = 0
        hit = self.at[place] == coordinates if len(self.at) else np.zeros(len(coordinates), bool)
        return float(1 / (1 + np.exp(-np.clip(self.bias + self.weights[place[hit]].sum(), -35, 35))))


def train_ftrl(examples: list[np.ndarray], labels: np.ndarray, bits: int = BITS, alpha: float = 1.5, beta: float = 1.0, l1: float = 6.0, l2: float = 0.1, passes: int = 8, seed: int = 11) -> FtrlModel:
    """FTRL-proximal: for each example in turn, weights in closed form from the sums z and n of its coordinates; inputs are 0/1, the bias is free of penalty."""
    z, n = np.zeros(1 << bits), np.zeros(1 << bits)
    bias_z, bias_n = 0.0, 0.0
    order = np.random.default_rng(seed)

    def weights_of(zc, nc):
        return np.where(np.abs(zc) <= l1, 0.0, -(zc - np.sign(zc) * l1) / ((beta + np.sqrt(nc)) / alpha + l2))

    for _ in range(passes):
        for i in order.permutation(len(examples)):
            c = examples[i]
            zc, nc = z[c], n[c]
            w = weights_of(zc, nc)
            bias = -bias_z / ((beta + np.sqrt(bias_n)) / alpha)
            p = 1 / (1 + np.exp(-np.clip(bias + w.sum(), -35, 35)))
            g = p - labels[i]
            grown = nc + g * g
            z[c] = zc + g - (np.sqrt(grown) - np.sqrt(nc)) / alpha * w
            n[c] = grown
            after = bias_n + g * g
            bias_z, bias_n = bias_z + g - (np.sqrt(after) - np.sqrt(bias_n)) / alpha * bias, after
    at = np.flatnonzero(np.abs(z) > l1)
    return FtrlModel(bits, float(-bias_z / ((beta + np.sqrt(bias_n)) / alpha)), at, weights_of(z[at], n[at]))


def is_held_out(id_col: str, folds: int = 5) -> Column:
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % folds == 0


def fit(labelled: DataFrame, text_col: str = "text", label_col: str = "toxic", id_col: str = "doc_id", sample: int = SAMPLE, bits: int = BITS, coordinates: int = COORDINATES, **rates) -> FtrlModel:
    """Learn from labelled rows whose id isn't held out; rows without text or label teach nothing.

    Coordinates are made on the executors; one task then goes through at most `sample` rows and `coordinates` coordinates in the order of the ids' hashes, and sends back the weights that aren't zero.
    Without examples of both labels the model knows the share of label 1 only (1/2 without any rows).
    """
    ship_package(labelled.sparkSession)
    taught = labelled.where(~is_held_out(id_col) & F.col(label_col).isNotNull() & F.col(text_col).isNotNull())
    chosen = taught.select(F.col(text_col).alias("text"), F.col(label_col).cast("int").alias("label"), F.xxhash64(id_col).alias("turn"), F.xxhash64(text_col).alias("tie")).orderBy("turn", "tie", "label").limit(sample)

    def to_coordinates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Hasher(bits)
        for batch in batches:
            found = [own.coordinates(t.as_py()).astype(np.int32) for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.list_(pa.int32())), *batch.columns[1:]], ["at", "label", "turn", "tie"])
        trim_memory()

    with settings(labelled.sparkSession, SMALL_BATCHES):
        made = materialise(chosen.repartition("turn").mapInArrow(to_coordinates, "at array<int>, label int, turn long, tie long"), "coordinates")
    order = Window.orderBy("turn", "tie", "label").rowsBetween(Window.unboundedPreceding, 0)  # over `sample` rows of three numbers
    sizes = made.select("turn", "tie", "label", F.sum(F.size("at").cast("long")).over(order).alias("so_far"))
    last = sizes.where(F.col("so_far") <= coordinates).agg(F.max(F.struct("turn", "tie", "label")).alias("last")).first()["last"]
    learnt = made.where(F.struct("turn", "tie", "label") <= F.struct(*[F.lit(x).cast(t) for x, t in zip(last, ("long", "long", "int"))]) if last else F.lit(False))

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        examples, labels, turns = [], [], []
        for b in batches:
            flat, ends = b.column(0).flatten().to_numpy(), b.column(0).offsets.to_numpy()
            ends = ends - ends[0]
            examples.extend(flat[s:e] for s, e in zip(ends[:-1], ends[1:]))  # views: a batch's coordinates stay one buffer
            labels.extend(b.column(1).to_pylist())
            turns.extend(zip(b.column(2).to_pylist(), b.column(3).to_pylist(), b.column(1).to_pylist()))
        order = sorted(range(len(turns)), key=turns.__getitem__)
        examples, y = [examples[i] for i in order], np.array([labels[i] for i in order], float)
        if len(set(labels)) == 2:
            m = train_ftrl(examples, y, bits, **rates)
        else:
            m = FtrlModel(bits, 0.0 if not labels else 4.0 * (2 * y[0] - 1), np.zeros(0, np.int64), np.zeros(0))
        examples.clear()
        trim_memory()
        yield pa.RecordBatch.from_arrays([pa.array([m.bias]), pa.array([m.at], pa.list_(pa.int64())), pa.array([m.weights], pa.list_(pa.float64()))], ["bias", "at", "weights"])

    with settings(labelled.sparkSession, SMALL_BATCHES):
        got = learnt.repartition(1).mapInArrow(learn, "bias double, at array<long>, weights array<double>").first()
    release(made)
    if got is None:
        return FtrlModel(bits, 0.0, np.zeros(0, np.int64), np.zeros(0))
    return FtrlModel(bits, got["bias"], np.array(got["at"], np.int64), np.array(got["weights"], float))


def score_column(docs: DataFrame, model: FtrlModel, text_col: str = "text") -> Column:
    ship_package(docs.sparkSession)
    small = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        m, own = small.value, Hasher(small.value.bits)
        for texts in batches:
            yield pd.Series([m.score(own.coordinates(t)) for t in texts], dtype="float64")
        trim_memory()

    return score(F.col(text_col).cast("string"))


def sampled_labels(labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", label_col: str = "toxic") -> DataFrame:
    """(id, label) of at most `sample` labelled rows that aren't held out, in the order of their ids' hashes."""
    usable = labels.where(~is_held_out(id_col) & F.col(label_col).isNotNull() & F.col(id_col).isNotNull())
    return usable.select(F.col(id_col).alias("id"), F.col(label_col).alias("label"), F.xxhash64(id_col).alias("turn")).orderBy("turn", "id", "label").limit(sample).select("id", "label")


def trained(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, text_col: str = "text", id_col: str = "doc_id", label_col: str = "toxic", **rates) -> FtrlModel:
    """The model of docs' texts with labels' labels; the sample's ids and labels are broadcast (its bound is theirs), so no other text moves."""
    chosen = sampled_labels(labels, sample, id_col, label_col)
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return fit(texts.join(F.broadcast(chosen), "id"), "text", "label", "id", sample, **rates)


def toxicity(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, model: FtrlModel | None = None, text_col: str = "text", id_col: str = "doc_id", label_col: str = "toxic") -> DataFrame:
    """One row per input row: doc_id, held_out, score, predicted.

    Null texts score like empty ones; the id only tells whether a label may be learnt from (a null id is like an empty one). Repeated rows are repeated; an empty table gives an empty result.
    """
    model = model or trained(docs, labels, sample, text_col, id_col, label_col)
    scored = docs.select(F.col(id_col).alias("doc_id"), is_held_out(id_col).alias("held_out"), score_column(docs, model, text_col).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def drop_toxic(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, text_col: str = "text", id_col: str = "doc_id", label_col: str = "toxic") -> DataFrame:
    """docs without the rows predicted toxic; all columns are kept."""
    return docs.where(score_column(docs, trained(docs, labels, sample, text_col, id_col, label_col), text_col) < 0.5)
