"""Connected components: spanning forests within tasks, then alternating large-star and small-star rounds."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.llm.tables import written

#: Edges of a forest that one task joins; larger ones take rounds over all executors, with the same answer.
ONE_TASK = 500_000
#: Nodes that a task remembers while it drops edges that close a cycle.
REMEMBERED = 300_000


class Roots:
    """Union by the smaller node."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def of(self, x: int) -> int:
        up = self.up
        top = x
        while (y := up.get(top, top)) != top:
            top = y
        while x != top:
            up[x], x = top, up.get(x, x)
        return top

    def join(self, a: int, b: int) -> bool:
        """Whether a and b were apart."""
        a, b = self.of(a), self.of(b)
        if a < b:
            a, b = b, a
        self.up[a] = b
        self.up.setdefault(b, b)
        return a != b


def _spanning(batches):
    roots = Roots()
    for batch in batches:
        keep = [roots.join(a, b) for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())]
        yield batch.filter(pa.array(keep, pa.bool_()))
        if len(roots.up) > REMEMBERED:
            roots = Roots()


def spanning_forest(edges: DataFrame) -> DataFrame:
    """edges(a BIGINT, b BIGINT) without those that close a cycle among the edges of their task: what is connected
    stays so, and a dense group of n nodes leaves a task as n - 1 edges."""
    return edges.select("a", "b").mapInArrow(_spanning, "a long, b long")


def _rooted(batches):
    roots = Roots()
    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            roots.join(a, b)
    nodes = list(roots.up)
    for k in range(0, len(nodes), 65536):
        part = nodes[k : k + 65536]
        yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array([roots.of(x) for x in part], pa.int64())], ["node", "root"])


def _linked_to_smallest(pairs: DataFrame, strict: bool) -> DataFrame:
    """For each a with its neighbours b: edges from (larger) neighbours, and a, to the smallest."""
    smallest = pairs.groupBy("a").agg(F.min("b").alias("low")).withColumn("low", F.least("a", "low"))
    joined = pairs.join(smallest, "a")
    if strict:
        return joined.filter(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("low").alias("b"))
    return joined.filter(F.col("b") != F.col("low")).select(F.col("b").alias("a"), F.col("low").alias("b")).union(
        smallest.filter(F.col("a") != F.col("low")).select("a", F.col("low").alias("b"))
    )


def smallest_reachable(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of edges(a BIGINT, b BIGINT); root is the least node it reaches.

    The edges are first cut down to a forest of each task. At most ONE_TASK of them are joined in a single task; for
    more, each round is two joins and ends in a written table, and the number of rounds grows with the logarithm of
    the longest chain. Only two scalars a round reach the driver.
    """
    now = written(spanning_forest(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))), "edges")
    if now.count() <= ONE_TASK:
        return now.coalesce(1).mapInArrow(_rooted, "node long, root long")
    mark = None
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        large = _linked_to_smallest(both, True).distinct()
        small = _linked_to_smallest(large, False).distinct()
        now = written(small, "edges")
        row = now.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(a, b))")).first()
        if (row[0], row[1]) == mark:
            break
        mark = (row[0], row[1])
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select("b", "b").distinct())
