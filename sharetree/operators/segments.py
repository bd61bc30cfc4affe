"""Units too large for one row or task: a unit's nodes in pre-order, cut into segments of bounded size.

A segment is a template with slots: what it selects, and in which states it leaves the depths that are still open, depends on the states in which
it finds the depths that it touches.  Each segment is walked once for all states of the walker; a unit's segments are then put together in
order, which takes a few numbers from each, and ``locate`` walks each segment once more from the states that it really meets.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sharetree.operators.evaluate import _unit_states, entry_states
from sharetree.plans.query import QueryError, Walker, compile_query, parse
from sharetree.sources.forests import Forest, _under_root
from sharetree.sources.scratch import scratch
from sharetree.sources.tables import ranked, table

#: Nodes of a segment.
SIZE = 1_000_000
SEGMENT = "unit long, segment long, labels array<string>, depths array<int>"
FUNCTION = "unit long, segment long, counts array<struct<level:int,n:array<long>>>, open array<struct<depth:int,level:int,q:array<long>>>"


def sequence(df: DataFrame, unit: str, order: list[str], label: str, root: str, size: int = SIZE) -> DataFrame:
    """Segments of units that are a root and one leaf for each row, in order: no task holds more than a segment, however many rows a unit has."""
    rows = ranked(df.select(F.col(unit).cast("long").alias("unit"), *order, F.col(label).alias("label")), "unit", *order)
    path = scratch(df.sparkSession, "places")
    rows.select("unit", "place", "label").write.parquet(path)
    rows = df.sparkSession.read.parquet(path)
    first = rows.groupBy("unit").agg(F.min("place").alias("first"))
    node = lambda at, label, depth: F.struct(at.cast("long").alias("at"), label.alias("label"), F.lit(depth).alias("depth"))
    at = F.col("place") - F.col("first") + 1
    leaf, top = node(at, F.col("label"), 1), node(F.lit(0), F.lit(root), 0)
    # a unit's first row brings its root: a union's rows may be grouped where they lie, though the parts of its two sides don't match at size
    every = rows.join(first.withColumnRenamed("unit", "of"), F.col("unit").eqNullSafe(F.col("of"))).select("unit", F.inline(F.when(at == 1, F.array(top, leaf)).otherwise(F.array(leaf))))
    every = every.withColumn("segment", F.floor(F.col("at") / size).cast("long")).repartition("unit", "segment")
    own = every.groupBy("unit", "segment").agg(F.sort_array(F.collect_list(F.struct("at", "label", "depth"))).alias("own"))
    path = scratch(df.sparkSession, "segments")
    own.select("unit", "segment", F.col("own.label").alias("labels"), F.col("own.depth").alias("depths")).write.parquet(path)
    return df.sparkSession.read.schema(SEGMENT).parquet(path)


def log(spark: SparkSession, sf_dir: str, size: int = SIZE) -> tuple[Forest, DataFrame]:
    """The log forest's units as bare roots, and their segments."""
    cut = sequence(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "event_type", "user", size)
    bare = cut.where("segment = 0").select("unit", F.array(F.lit("user")).alias("labels"), F.array(F.lit(0)).alias("depths"))
    return _under_root(bare, "log"), cut


def functions(segments: DataFrame, walker: Walker) -> DataFrame:
    """For each segment and depth that it touches: nodes selected below, for each state found there; and what each depth left open is in then.

    ``level``: the depth whose state decides; the arrays go by the walker's states in order.
    """
    states = _states(walker)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict = {}
        for batch in batches:
            rows = []
            for unit, segment, labels, depths in zip(*(c.to_pylist() for c in batch.columns)):
                waiting: dict[int, tuple] = {}
                counts: dict[int, list[int]] = {}
                for w, d in zip(labels, depths):
                    level, qs = waiting.get(d) or (d, states)
                    got = known.get((qs, w))
                    if got is None:
                        ruled = [walker.rule(q, w) for q in qs]
                        got = known[qs, w] = tuple(tuple(int(r[i]) for r in ruled) for i in range(3))
                    hits, left, right = got
                    own = counts.setdefault(level, [0] * len(states))
                    if any(hits):
                        counts[level] = [a + b for a, b in zip(own, hits)]
                    for x in [x for x in waiting if x > d]:
                        del waiting[x]
                    waiting[d], waiting[d + 1] = (level, right), (level, left)
                rows.append((unit, segment, [{"level": k, "n": n} for k, n in counts.items()], [{"depth": d, "level": k, "q": list(q)} for d, (k, q) in waiting.items()]))
            kinds = [pa.int64(), pa.int64(), pa.list_(pa.struct([("level", pa.int32()), ("n", pa.list_(pa.int64()))])), pa.list_(pa.struct([("depth", pa.int32()), ("level", pa.int32()), ("q", pa.list_(pa.int64()))]))]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=["unit", "segment", "counts", "open"])

    return segments.select("unit", "segment", "labels", "depths").mapInArrow(run, FUNCTION)


def _states(walker: Walker) -> tuple[int, ...]:
    walker.close()
    return tuple(sorted({q for q, _, _ in walker.rules} | {p for r in walker.rules.values() for p in r[1:]}))


def _composed(functions_: DataFrame, entered: DataFrame, walker: Walker) -> DataFrame:
    """unit, n, and the states at each depth that each segment begins in: a unit's segments one after the other, a few numbers from each."""
    states = {q: i for i, q in enumerate(_states(walker))}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for unit, state, own in zip(*(c.to_pylist() for c in batch.columns)):
                now, n, begins = {0: state}, 0, []
                for x in sorted(own, key=lambda x: x["segment"]):
                    begins.append({"segment": x["segment"], "depths": [*now], "q": [*now.values()]})
                    n += sum(c["n"][states[now[c["level"]]]] for c in x["counts"])
                    after = {o["depth"]: o["q"][states[now[o["level"]]]] for o in x["open"]}
                    now = {d: q for d, q in now.items() if d < min(after, default=0)} | after if after else now
                rows.append((unit, n, begins))
            kinds = [pa.int64(), pa.int64(), pa.list_(pa.struct([("segment", pa.int64()), ("depths", pa.list_(pa.int32())), ("q", pa.list_(pa.int64()))]))]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=["unit", "n", "begins"])

    by_unit = functions_.groupBy("unit").agg(F.collect_list(F.struct("segment", "counts", "open")).alias("own"))
    return by_unit.join(entered.select("unit", "state"), "unit").select("unit", "state", "own").mapInArrow(run, "unit long, n long, begins array<struct<segment:long,depths:array<int>,q:array<long>>>")


def _entered(bare: Forest, query: str) -> tuple[Walker, DataFrame]:
    if parse(query).probes:
        raise QueryError("segments take queries without filters")
    walker = compile_query(query)
    return walker, _unit_states(bare, walker, entry_states(bare, walker, {})[0])


def count_by_unit(bare: Forest, segments: DataFrame, query: str) -> DataFrame:
    """unit and n of every unit."""
    walker, entered = _entered(bare, query)
    return _composed(functions(segments, walker), entered, walker).select("unit", "n")


def locate(bare: Forest, segments: DataFrame, query: str, size: int = SIZE) -> DataFrame:
    """unit and pre of the selected nodes; ``size`` is that of the segments."""
    walker, entered = _entered(bare, query)
    begins = _composed(functions(segments, walker), entered, walker).select("unit", F.explode("begins").alias("b")).select("unit", "b.segment", F.col("b.depths").alias("at"), "b.q")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            units, found = [], []
            for unit, segment, labels, depths, at, q in zip(*(c.to_pylist() for c in batch.columns)):
                waiting = dict(zip(at, q))
                for i, (w, d) in enumerate(zip(labels, depths)):
                    selects, waiting[d + 1], waiting[d] = walker.rule(waiting[d], w)
                    if selects:
                        units.append(unit)
                        found.append(segment * size + i + 1)
            yield pa.RecordBatch.from_arrays([pa.array(units, pa.int64()), pa.array(found, pa.int64())], names=["unit", "pre"])

    return segments.join(begins, ["unit", "segment"]).select("unit", "segment", "labels", "depths", "at", "q").mapInArrow(run, "unit long, pre long")
