"""Baselines over the uncompressed trees: structural joins on intervals, label paths, and marks lifted to filter context nodes."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sharetree.plans.query import CHILD, DESCENDANT, QueryError, parse, path_dfa
from sharetree.sources.forests import Forest, nodes


def structural(forest: Forest, query: str) -> DataFrame:
    """unit and pre of the nodes that a query, entered at the units' roots, selects: one join a step, an interval join for descendants."""
    steps = parse(query).steps
    tree = nodes(forest, keyed=True).select("unit", "top", "before", "pre", "parent_pre", "size", "label")
    now = None
    for s in steps:
        own = tree if s.test == "*" else tree.where(F.col("label") == s.test)
        if now is None:
            now = own.where("parent_pre is null") if s.axis == CHILD else own if s.axis == DESCENDANT else own.where("false")
        else:
            a, b = now.alias("a"), own.alias("b")
            same = (F.col("a.top") == F.col("b.top")) & (F.col("a.before") == F.col("b.before"))
            if s.axis == CHILD:
                near = same & (F.col("b.parent_pre") == F.col("a.pre"))
            elif s.axis == DESCENDANT:
                near = same & (F.col("b.pre") > F.col("a.pre")) & (F.col("b.pre") < F.col("a.pre") + F.col("a.size"))
            else:
                near = same & (F.col("b.parent_pre") == F.col("a.parent_pre")) & (F.col("b.pre") > F.col("a.pre"))
            now = b.join(a, near, "left_semi").select("b.*")
        for p in s.probes:
            now = _lifted(tree, now, p)
    return now.select("unit", "pre")


def _lifted(tree: DataFrame, context: DataFrame, probe) -> DataFrame:
    """Context nodes below which a child-only path exists: its last nodes are found, then marks move up a parent a step."""
    if any(s.axis != CHILD for s in probe):
        raise QueryError("lifting takes filters of child steps only")
    test = lambda s: F.lit(True) if s.test == "*" else F.col("label") == s.test
    marks = tree.where(test(probe[-1])).select("top", "before", F.col("parent_pre").alias("pre")).distinct()
    for s in reversed(probe[:-1]):
        marks = tree.where(test(s)).join(marks, ["top", "before", "pre"], "left_semi").select("top", "before", F.col("parent_pre").alias("pre")).distinct()
    return context.join(marks, ["top", "before", "pre"], "left_semi")


def paths(forest: Forest, query: str) -> DataFrame:
    """unit and n by the path automaton, run over the label path of every node (child and descendant steps)."""
    rules = path_dfa(query)
    names = {w for _, w in rules if w is not None}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = []
            for labels, depths in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                way, n = [1], 0  # the states along the way down; 1 is the automaton's first
                for w, d in zip(labels, depths):
                    del way[d + 1 :]
                    q = rules[way[-1], w if w in names else None]
                    n += q < 0
                    way.append(-1 - q if q < 0 else q)
                counts.append(n)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64())], names=["unit", "n"])

    return forest.units.select("unit", "labels", "depths").mapInArrow(run, "unit long, n long").where("n > 0")
