"""Connected components of an edge table by alternating star contractions; nothing reaches the driver but two numbers a round.

A table of few edges is contracted by one task, by union-find: each round is a dozen stages, which the driver keeps records of.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sharetree.llm.storage import materialize

#: Edges that one task contracts (some 100 MB of Python objects at most); more go through the rounds.
FEW = 1 << 18


def _united(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    up: dict[int, int] = {}

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    for batch in batches:
        for u, v in zip(*(c.to_pylist() for c in batch.columns)):
            x, y = root(up.setdefault(u, u)), root(up.setdefault(v, v))
            up[max(x, y)] = min(x, y)
    nodes = list(up)
    for i in range(0, len(nodes), 10_000):
        some = nodes[i : i + 10_000]
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(map(root, some), pa.int64())], names=["node", "component"])


def components(edges: DataFrame, a: str = "a", b: str = "b", few: int = FEW) -> DataFrame:
    """(node, component) for every node of an edge; the component is the smallest node that can be reached.

    With more than ``few`` edges, each round hangs every larger neighbour of a node, then every node with its smaller neighbours, on the smallest of them; the
    rounds are logarithmic in the length of the paths.  Minima are aggregated before they are joined, so a node with very
    many edges is a skewed join, which Spark splits, never a list in one row.
    """
    pairs = edges.select(F.greatest(a, b).cast("long").alias("u"), F.least(a, b).cast("long").alias("v")).where("u <> v")
    pairs = materialize(pairs, "edges")
    if pairs.count() <= few:
        return materialize(pairs.coalesce(1).mapInArrow(_united, "node long, component long"), "components")
    pairs = materialize(pairs.distinct(), "edges")
    seen = None
    while True:
        both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
        pairs = materialize(small.select("e.*").where("u <> v").distinct(), "edges")
        now = tuple(pairs.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == seen:
            break
        seen = now
    roots = pairs.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return pairs.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
