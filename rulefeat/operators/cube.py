"""Counts of packed codes at the finest intervals of any fold: items and pairs of items by part and class, from one pass. Those of coarser intervals and of any parts together are sums of them, so
all mining runs of a query read the table once.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession


@dataclass
class Cube:
    """rows[part, class], pairs[part, class] (items x items, an item's own count on the diagonal); names: the classes as the miner has them; first: the place of each column's first item.

    A group is what one mining run of its own would see: for each feature, the place of its first item and the value of each of its items there, and the parts.
    """

    spark: SparkSession
    rows: np.ndarray
    pairs: np.ndarray
    names: list[str]
    first: dict[str, int]
    groups: dict[int, tuple[list[tuple[int, list[str]]], list[int]]] = field(default_factory=dict)
    by: str = "cv"

    @property
    def p(self) -> int:
        return len(next(iter(self.groups.values()))[0])

    def _of(self, group: int, kept: list[tuple[int, str]] | None = None) -> tuple[list[tuple[int, str]], np.ndarray, np.ndarray]:
        """The group's items (f, v), or those kept of them, the 0/1 table of fine items by these, and the counts of fine pairs by class."""
        columns, parts = self.groups[group]
        fine = [(f, v, first + j) for f, (first, values) in enumerate(columns, 1) for j, v in enumerate(values)]
        items = sorted({(f, v) for f, v, _ in fine}) if kept is None else kept
        place, table = {item: i for i, item in enumerate(items)}, np.zeros((self.pairs.shape[-1], len(items)))
        for f, v, at in fine:
            if (f, v) in place:
                table[at, place[f, v]] = 1
        return items, table, self.pairs[parts].sum(axis=0)

    def singles(self) -> DataFrame:
        """(group, f, v, y, supp), with the classes' own counts as feature 0: counts.singles() of each group's records."""
        out = []
        for group, (_, parts) in self.groups.items():
            items, table, pairs = self._of(group)
            for c, name in enumerate(self.names):
                if many := int(self.rows[parts, c].sum()):
                    out.append((group, 0, name, name, many))
                    own = np.diag(pairs[c]) @ table
                    out += [(group, f, v, name, int(n)) for (f, v), n in zip(items, own) if n]
        return self.spark.createDataFrame(out, f"`{self.by}` int, f int, v string, y string, supp long")

    def pairs_of(self, kept: DataFrame) -> tuple[DataFrame, int]:
        """(group, f1, v1, f2, v2, y, supp) of the pairs of each group's own items kept(group, f1, v1), a budget's number, and the number of different items."""
        wanted: dict[int, set[tuple[int, str]]] = {}
        for r in kept.select(self.by, "f1", "v1").distinct().collect():
            wanted.setdefault(r[0], set()).add((r[1], r[2]))
        out = []
        for group, own in wanted.items():
            items, table, pairs = self._of(group, sorted(own))
            feature = np.array([f for f, _ in items])
            for c, name in enumerate(self.names):
                counts = np.rint(table.T @ pairs[c] @ table).astype(np.int64)
                a, b = np.nonzero(counts * (feature[:, None] < feature))
                out += [(group, *items[i], *items[j], name, int(n)) for i, j, n in zip(a.tolist(), b.tolist(), counts[a, b])]
        return self.spark.createDataFrame(out, f"`{self.by}` int, f1 int, v1 string, f2 int, v2 string, y string, supp long"), len(set().union(*wanted.values()))
