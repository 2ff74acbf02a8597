"""Connected components of an edge table: union-find in one task while it is small, alternating star contractions beyond."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from narrative_engine.llm.common import staged

ROUNDS = 40
#: Edges (16 bytes each) that one executor task may hold.
ONE_TASK = 1_000_000


def _union(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    up: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while (y := up.get(top, top)) != top:
            top = y
        while (y := up.get(x, x)) != top:
            up[x], x = top, y
        return top

    for b in batches:
        for x, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            one, two = root(x), root(y)
            up[max(one, two)] = min(one, two)
    nodes = [x for x in up if root(x) != x]
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([up[x] for x in nodes], pa.int64())], names=["node", "root"])


def _print(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of (a, b) that isn't its own root; roots are the smallest nodes."""
    if edges.count() <= ONE_TASK:
        return staged(edges.select("a", "b").coalesce(1).mapInArrow(_union, "node long, root long"))
    return star_components(edges)


def star_components(edges: DataFrame) -> DataFrame:
    """The same by joins alone, for any number of edges.

    Each round hangs the larger neighbours of a node on its smallest one, then the smaller ones;
    minima are pre-aggregated, so a hub costs its edges and no task gathers them.  Rounds grow with
    the logarithm of the longest path.
    """
    now = staged(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    seen = _print(now)
    for _ in range(ROUNDS):
        if not seen[0]:
            break
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = staged(both.groupBy(F.col("a").alias("n")).agg(F.least(F.min("b"), F.first("a")).alias("m")))
        large = both.where("b > a").join(least, F.col("a") == F.col("n")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.where("a <> b").distinct()
        down = staged(large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
        least = staged(down.groupBy(F.col("a").alias("n")).agg(F.min("b").alias("m")))
        small = down.join(least, F.col("a") == F.col("n")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        new = staged(small.unionByName(least.select(F.col("n").alias("a"), F.col("m").alias("b"))).where("a <> b").distinct())
        if (mark := _print(new)) == seen:
            break
        now, seen = new, mark
    else:
        raise RuntimeError(f"components haven't settled in {ROUNDS} rounds; each halves the longest path, so the edges must have changed between reads")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
