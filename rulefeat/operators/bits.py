"""Records whose features are all '0', '1' or null, as bit planes: some 1000 times fewer objects than a table of strings. Counts for the miner, and of records by the features that they hold.

A block has records of one part (a trial, a fold); a view says which group of the miner a part belongs to.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import BLOCK_READS, BLOCK_WRITES, ROWS_PER_BATCH, materialise, settings, ship_package

#: Records that are packed at once, and rows of a batch on the way there. Sums of single precision over a block are exact below 2^24 records.
ROWS, WIDE = 1 << 19, "20000"


@dataclass
class Bits:
    """Blocks (part, n, data); data: a draw (0 or 1) and a class code of each record, its ones, and which of its features are known."""

    blocks: DataFrame
    p: int
    names: list[str]
    by: str = "part"
    group: Callable[[int], int | None] = int

    @property
    def classes(self) -> int:
        return len(self.names)

    def view(self, by: str, group: Callable[[int], int | None]) -> Bits:
        """The records by group (a column `by` of what is counted); those of a part whose group is None are left out."""
        return replace(self, by=by, group=group)

    def opened(self):
        width = -(-self.p // 8)

        def opened(batches):
            for batch in batches:
                for part, n, data in zip(*(batch.column(i) for i in range(3))):
                    n, raw = n.as_py(), data.as_buffer()
                    small = np.frombuffer(raw, np.uint8, 2 * n).reshape(2, n)
                    planes = np.frombuffer(raw, np.uint8, 2 * n * width, 2 * n).reshape(2, n, width)
                    yield part.as_py(), small[0], small[1].astype(int), planes[0], planes[1]

        return opened

    def _counted(self, per_block, rows_of, schema: str) -> DataFrame:
        """Each task's totals by (group, class) of per_block(group, y, ones, known) -> array of a matrix for each class, as rows_of(group, class, matrix) -> columns."""
        opened, group, arrow = self.opened(), self.group, [pa.int32(), pa.string()]
        names, by = self.names, self.by
        columns = [c.split() for c in schema.split(", ")]
        kinds = arrow + [{"int": pa.int32(), "string": pa.string(), "long": pa.int64()}[t] for _, t in columns]
        labels = [by, "y", *(c for c, _ in columns)]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict = {}
            for part, _, y, ones, known in opened(batches):
                if (g := group(part)) is not None:
                    for c, new in per_block(g, y, ones, known):
                        new = np.rint(new).astype(np.int64)
                        total[g, c] = total[g, c] + new if (g, c) in total else new
            for (g, c), matrix in total.items():
                made = rows_of(g, names[c], matrix)
                n = len(made[0])
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(([g] * n, [names[c]] * n, *made), kinds)], names=labels)

        with settings(self.blocks.sparkSession, BLOCK_READS):
            kept = materialise(self.blocks.mapInArrow(run, f"`{by}` int, y string, {schema}"), "counted")
        keys = [c for c, _ in columns if c != "supp"]
        return kept.groupBy(by, *keys, "y").agg(F.sum("supp").alias("supp"))

    def singles(self) -> DataFrame:
        """(group, f, v, y, supp), with the classes' own counts as feature 0: counts.singles() of the records."""
        p, classes = self.p, self.classes

        def per_block(g, y, ones, known):
            hot = (y == np.arange(classes)[:, None]).astype(np.float32)
            one, there = (hot @ np.unpackbits(x, axis=1, count=p).astype(np.float32) for x in (ones, known))
            many = hot.sum(axis=1)
            for c in np.flatnonzero(many):
                yield int(c), np.append([many[c]], np.concatenate([one[c], there[c] - one[c]]))

        def rows_of(g, name, counts):
            at = np.flatnonzero(counts)
            return [int(i - 1) % p + 1 if i else 0 for i in at], [str(int(i <= p)) if i else name for i in at], counts[at]

        return self._counted(per_block, rows_of, "f int, v string, supp long")

    def pairs_of(self, kept: DataFrame) -> tuple[DataFrame, int]:
        """(group, f1, v1, f2, v2, y, supp) of the pairs of each group's own items kept(group, f1, v1), a budget's number, and the number of different items."""
        items: dict[int, list[tuple[int, str]]] = {}
        for r in kept.select(self.by, "f1", "v1").distinct().collect():
            items.setdefault(r[0], []).append((r[1], r[2]))
        items = {g: sorted(own) for g, own in items.items()}
        p = self.p

        def per_block(g, y, ones, known):
            if own := items.get(g):
                at, high = np.array([f - 1 for f, _ in own]), np.array([v == "1" for _, v in own])
                one, there = (np.unpackbits(x, axis=1, count=p)[:, at].astype(bool) for x in (ones, known))
                held = (there & (one == high)).astype(np.float32)
                for c in np.unique(y).tolist():
                    rows = held[y == c]
                    yield c, np.triu(rows.T @ rows, 1)

        def rows_of(g, name, total):
            own, (a, b) = items[g], np.nonzero(total)
            return [own[i][0] for i in a], [own[i][1] for i in a], [own[i][0] for i in b], [own[i][1] for i in b], total[a, b]

        return self._counted(per_block, rows_of, "f1 int, v1 string, f2 int, v2 string, supp long"), len({i for own in items.values() for i in own})

    def patterns(self, wanted: dict[int, dict]) -> dict:
        """By (name, part): {(pattern, draw, class): records}, where bit j of a pattern says whether the j-th of wanted[group][name], antecedents (f1, v1, f2, v2), holds. A pass for all names."""
        opened, group, p, classes = self.opened(), self.group, self.p, self.classes

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict = {}
            for part, draw, y, ones, known in opened(batches):
                if not (of := wanted.get(group(part))):
                    continue
                one, there = (np.unpackbits(x, axis=1, count=p).astype(bool) for x in (ones, known))
                holds = lambda f, v: there[:, f - 1] & (one[:, f - 1] == (v == "1"))
                for name, antecedents in of.items():
                    code = np.zeros(len(y), np.int64)
                    for j, (f1, v1, f2, v2) in enumerate(antecedents):
                        code |= (holds(f1, v1) if f2 is None else holds(f1, v1) & holds(f2, v2)).astype(np.int64) << j
                    found, n = np.unique((code * 2 + draw) * classes + y, return_counts=True)
                    own = total.setdefault((name, part), {})
                    for k, m in zip(found.tolist(), n.tolist()):
                        own[k] = own.get(k, 0) + m
            yield pa.RecordBatch.from_pydict({"sums": pa.array([pickle.dumps(total)], pa.binary())})

        out: dict = {}
        with settings(self.blocks.sparkSession, BLOCK_READS):
            rows = self.blocks.mapInArrow(run, "sums binary").collect()  # one a core, of a budget's patterns
        for r in rows:
            for key, own in pickle.loads(r["sums"]).items():
                both = out.setdefault(key, {})
                for k, m in own.items():
                    at = (k // classes // 2, k // classes % 2, k % classes)
                    both[at] = both.get(at, 0) + m
        return out


def pack(rows: DataFrame, part: str, draw: str, label: str, p: int, names: list[str], columns: list[str], read: Callable) -> Bits:
    """Bits of rows with an integer `part`, a column `draw` and a label among `names`; read() makes an array (records x p) of 1, 0 and -1 (null) of a batch with `columns`. Rows without part or label are left out."""
    ship_package(rows.sparkSession)
    code = F.array_position(F.array(*[F.lit(n) for n in names]), F.col(label).cast("string")) - 1
    wide = rows.where(F.col(part).isNotNull() & F.col(label).isNotNull()).select(F.col(part).cast("int").alias("__p"), F.col(draw).cast("int").alias("__d"), code.cast("int").alias("__y"), *columns)

    def packed(held: list[tuple]) -> pa.RecordBatch:
        of, small, ones, known = (np.concatenate(x) for x in zip(*held))
        order = np.argsort(of, kind="stable")
        parts, first = np.unique(of[order], return_index=True)
        own = np.split(order, first[1:])
        data = [small[i].T.tobytes() + ones[i].tobytes() + known[i].tobytes() for i in own]
        return pa.RecordBatch.from_pydict({"part": pa.array(parts, pa.int32()), "n": pa.array([len(i) for i in own], pa.int32()), "data": pa.array(data, pa.binary())})

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, many = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            of, d, y = (batch.column(i).to_numpy() for i in range(3))
            if (y < 0).any():
                raise ValueError("a label that isn't among the names")
            x = read(batch)
            held.append((of, np.column_stack([d, y]).astype(np.uint8), np.packbits(x == 1, axis=1), np.packbits(x >= 0, axis=1)))
            many += batch.num_rows
            if many >= ROWS:
                yield packed(held)
                held, many = [], 0
        if held:
            yield packed(held)

    with settings(rows.sparkSession, {ROWS_PER_BATCH: WIDE}):
        kept = materialise(wide.mapInArrow(blocks, "part int, n int, data binary"), "bits", options=BLOCK_WRITES)
    return Bits(kept.coalesce(rows.sparkSession.sparkContext.defaultParallelism), p, list(names))


def of_strings(df: DataFrame, part: str, draw: str, label: str, features: list[str], names: list[str]) -> Bits:
    """pack() of a table of strings '0', '1' and null."""

    def read(batch: pa.RecordBatch) -> np.ndarray:
        out = np.empty((batch.num_rows, len(features)), np.int8)
        for i, c in enumerate(features):
            column = batch.column(3 + i)
            one, zero = (pc.fill_null(pc.equal(column, v), False).to_numpy(zero_copy_only=False) for v in "10")
            if (~one & ~zero).sum() != column.null_count:
                raise ValueError(f"{c} has other values than 0 and 1")
            out[:, i] = np.where(one, 1, np.where(zero, 0, -1))
        return out

    return pack(df, part, draw, label, len(features), names, features, read)
