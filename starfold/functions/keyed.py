"""Components within a key, for keys whose edges fit one task: a table function and the forest that it keeps."""

from __future__ import annotations

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F


class Forest:
    """Disjoint sets named by their least member. Memory is proportional to the vertices seen."""

    def __init__(self, labels: dict[int, int] | None = None):
        self.up = dict(labels or {})

    def root(self, x: int) -> int:
        up = self.up
        while up.setdefault(x, x) != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def link(self, a: int, b: int) -> None:
        x, y = self.root(a), self.root(b)
        if x != y:
            self.up[max(x, y)] = min(x, y)

    def labels(self) -> dict[int, int]:
        return {v: self.root(v) for v in list(self.up)}


class StarMerge:
    """Table function over rows with ``key``, ``a`` and ``b``, partitioned by ``key``: (key, vertex, component) with the least vertex as name.

    A row with a null end links nothing; a loop makes a vertex. One key is one task's work, so a key of unbounded
    size belongs to ``alternating.connected_components``.
    """

    def __init__(self):
        self.key, self.forest = None, Forest()

    def eval(self, row: Row):
        self.key = row["key"]
        if row["a"] is not None and row["b"] is not None:
            self.forest.link(row["a"], row["b"])

    def terminate(self):
        for vertex, component in self.forest.labels().items():
            yield self.key, vertex, component


star_merge = F.udtf(StarMerge, returnType="key: bigint, vertex: bigint, component: bigint")


def components_by_key(edges: DataFrame) -> DataFrame:
    """Components of ``edges`` (key, a, b) within each key. For SQL, register ``star_merge`` and call it over TABLE(...) PARTITION BY key."""
    rows = edges.select(*[F.col(c).cast("long").alias(c) for c in ("key", "a", "b")])
    return star_merge(rows.asTable().partitionBy("key"))
