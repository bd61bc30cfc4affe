"""Count, locate and serialize over a forest, without expanding what is shared.

Equal units are one entry of a dictionary.  An entry is compressed into a grammar once, which is stored; a query walks it once for each state in
which it enters it, however many units have it; answers then join back by (entry, state).  The top tree, which the driver holds, gives the
entry states: a state passes from sibling to sibling by the labels of the units' roots.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from decimal import Decimal
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sharetree.functions import grammar as G
from sharetree.plans.query import FOLLOWING, PathQuery, QueryError, StepWalker, Walker, compile_query, parse, probe_bits
from sharetree.sources.forests import Forest
from sharetree.sources.scratch import scratch

#: Bytes that one string value can hold.
MAX_STRING = 2**31 - 16
#: Nodes or symbols that a task holds as Python objects at a time.
SLICE = 100_000
#: Sibling units that one task passes a state along.
CHUNK = 100_000
#: Rows that are sent to every task of a join, and chunks of siblings that the driver puts together.
MAX_BROADCAST = 1_000_000
#: Bits of filter states that the top tree's nodes can hold.
MAX_FILTER_BITS = 62
COMPRESSORS: dict[str, Callable[[list[str], list[int]], G.Grammar]] = {
    "binary": G.binary_dag,
    "hybrid": G.hybrid_dag,
    "digrams": lambda labels, depths: G.digrams(G.binary_dag(labels, depths)),
    "tree": lambda labels, depths: G.inline_single(_plain(labels, depths)),
}
GRAMMAR = "labels array<string>, ranks array<int>, lengths array<int>, symbols array<int>"


def _plain(labels: list[str], depths: list[int]) -> G.Grammar:
    """The tree itself, as a grammar of one template."""
    kids, roots = G.from_tree(labels, depths)
    body, todo = [], [(roots, 0)]
    while todo:
        some, i = todo.pop()
        if i >= len(some):
            body.append(G.NULL)
        else:
            body.append(("l", labels[some[i]]))
            todo += [(some, i + 1), (kids[some[i]], 0)]
    return G.Grammar(0, {0: body}, {0: 0})


def _stored(forest: Forest, df: DataFrame, name: str) -> DataFrame:
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    forest.built.setdefault("paths", []).append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def sliced(batches: Iterator[pa.RecordBatch], column: int, most: int = SLICE) -> Iterator[pa.RecordBatch]:
    """Batches of at most so many list items in a column (or one row): a row's lists become Python objects, whose size rows don't bound."""
    for batch in batches:
        ends = pc.cumulative_sum(pc.fill_null(pc.list_value_length(batch.column(column)), 0).cast(pa.int64())).to_numpy()
        a = 0
        while a < batch.num_rows:
            b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + most, "right")))
            yield batch.slice(a, b - a)
            a = b


def _dealt(df: DataFrame) -> DataFrame:
    """Rows by entry over a fixed number of tasks: what follows is work in Python, which small partitions joined into one would leave to one task."""
    spark = df.sparkSession
    return df.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism), "entry")


def dictionary(forest: Forest) -> tuple[DataFrame, DataFrame]:
    """(entry, roots, nodes, labels, depths) of the distinct unit trees, and the units (unit, top, before) with their entry; written once for a forest."""
    if "dictionary" not in forest.built:
        units = forest.units.withColumn("entry", F.md5(F.to_json(F.struct("labels", "depths"))))
        entries = units.groupBy("entry").agg(F.first("labels").alias("labels"), F.first("depths").alias("depths"))
        roots = F.expr("filter(labels, (w, i) -> depths[i] = 0)")
        entries = entries.select("entry", roots.alias("roots"), F.size("labels").cast("long").alias("nodes"), "labels", "depths")
        forest.built["dictionary"] = _stored(forest, _dealt(entries), "entries"), _stored(forest, units.select("unit", "top", F.col("before").cast("long").alias("before"), "entry"), "units")
    return forest.built["dictionary"]


def grammars(forest: Forest, compress: str = "binary") -> DataFrame:
    """(entry, labels, ranks, lengths, symbols): the compressed entries, as ``grammar.encode`` has them; written once for a forest and compressor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches, 1):
            rows = [G.encode(COMPRESSORS[compress](labels, depths)) for labels, depths in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())]
            kinds = [pa.list_(pa.string()), *[pa.list_(pa.int32())] * 3]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds))], names=["entry", "labels", "ranks", "lengths", "symbols"])

    if compress not in forest.built:
        trees = dictionary(forest)[0].select("entry", "labels", "depths")
        forest.built[compress] = _stored(forest, trees.mapInArrow(run, f"entry string, {GRAMMAR}"), f"grammars-{compress}")
    return forest.built[compress]


def _decoded(batch: pa.RecordBatch, first: int) -> Iterator[G.Grammar]:
    return (G.decode(*row) for row in zip(*(batch.column(i).to_pylist() for i in range(first, first + 4))))


def _children(top: list) -> dict:
    out: dict = {}
    for i, parent, _ in top:
        out.setdefault(parent, []).append(i)
    return out


def _top_held(forest: Forest, query: PathQuery, compress: str) -> dict[int, int]:
    """Bits of the filters that hold at each top node: unit roots' filter states are or-ed per top node, then go up."""
    probes = query.probes
    if any(p[0].axis == FOLLOWING for p in probes) and any(s.probes and s.accepts(label) for s in query.steps for _, _, label in forest.top):
        raise QueryError("a filter that begins with a sibling step can't be put on the nodes above units")

    if sum(2 * len(p) for p in probes) > MAX_FILTER_BITS:
        raise QueryError("too many filter steps for the nodes above units")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches, 2 if compress == "tree" else 4):
            if compress == "tree":
                states = [_tree_states(labels, depths, probes)[0] for labels, depths in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())]
            else:
                states = []
                for g in _decoded(batch, 1):
                    stats: dict = {}
                    G.annotate(g, query, stats=stats)
                    states.append(stats["root"])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(states, pa.int64())], names=["entry", "state"])

    entries = dictionary(forest)[0].select("entry", "labels", "depths") if compress == "tree" else grammars(forest, compress)
    units = dictionary(forest)[1]
    states = entries.mapInArrow(run, "entry string, state long")
    below = {r["top"]: r["state"] for r in units.join(states, "entry").groupBy("top").agg(F.bit_or("state").alias("state")).collect()}  # a row a top node
    kids, label, held = _children(forest.top), {i: w for i, _, w in forest.top}, {}

    def up(i: int) -> int:
        left = below.get(i, 0)
        for k in kids.get(i, []):
            left |= up(k)
        state, held[i] = _combined(probes, label[i], left, 0)
        return state

    for root in kids[None]:
        up(root)
    return held


def _combined(probes, label: str, left: int, right: int) -> tuple[int, int]:
    state = held = shift = 0
    for k, p in enumerate(probes):
        m = (1 << 2 * len(p)) - 1
        bits, true = probe_bits(p, label, left >> shift & m, right >> shift & m)
        state, held, shift = state | bits << shift, held | true << k, shift + 2 * len(p)
    return state, held


def _tree_states(labels: list[str], depths: list[int], probes) -> tuple[int, list[int]]:
    """The filter state of a unit's roots, and which filters hold at each node: one pass from the last node to the first."""
    rows, held = [0], [0] * len(labels)  # by depth: the state of the sibling chain that begins at the next node seen there
    for i in reversed(range(len(labels))):
        d = depths[i]
        rows += [0] * (d + 2 - len(rows))
        rows[d], held[i] = _combined(probes, labels[i], rows[d + 1], rows[d])
        rows[d + 1] = 0
    return rows[0], held


def entry_states(forest: Forest, walker: Walker, held: dict[int, int]) -> tuple[dict[int, int], list[int]]:
    """State in which each top node's first unit is entered, and the top nodes that are selected."""
    kids, label = _children(forest.top), {i: w for i, _, w in forest.top}
    entered, selected, todo = {}, [], [(None, walker.start)]
    while todo:
        parent, q = todo.pop()
        for i in kids.get(parent, []):
            hit, left, q = walker.rule(q, label[i], held.get(i, 0))
            entered[i] = left
            if hit:
                selected.append(i)
            todo.append((i, left))
    return entered, selected


def _unit_states(forest: Forest, walker: Walker, entered: dict[int, int]) -> DataFrame:
    """unit, top, entry and state of every unit.

    Where every unit has one root of one label, the states along siblings run into a circle and are a small table; else they
    are passed along the roots as they stand.
    """
    entries, units = dictionary(forest)
    if "roots" not in forest.built:
        forest.built["roots"] = [r["roots"] for r in entries.select("roots").distinct().limit(2).collect()]
    kinds, spark = forest.built["roots"], entries.sparkSession
    if kinds and (len(kinds) > 1 or len(kinds[0]) != 1):
        return _passed_along(units.join(entries.select("entry", "roots"), "entry"), walker, entered)
    rows = []
    for top, q in entered.items():
        seen: dict[int, int] = {}
        while q not in seen:
            seen[q] = len(seen)
            q = walker.rule(q, kinds[0][0] if kinds else "")[2]
        loop = seen[q]
        rows += [(top, k, p, loop, len(seen) - loop) for p, k in seen.items()]
    table = spark.createDataFrame(rows, "top int, k long, state long, loop long, period long")
    turn = F.when(F.col("before") < F.col("loop"), F.col("before")).otherwise(F.col("loop") + F.pmod(F.col("before") - F.col("loop"), F.col("period")))
    # (top nodes) * (states) short rows
    return units.join(F.broadcast(table) if len(rows) <= MAX_BROADCAST else table, "top").where(F.col("k") == turn).select("unit", "top", "entry", "state")


def _passed_along(units: DataFrame, walker: Walker, entered: dict[int, int]) -> DataFrame:
    """States of units (with their roots) whose roots differ: siblings are cut into chunks, each chunk gives its function on states, the driver applies
    them one after the other (a row a chunk and state), and then each chunk is walked from its own first state."""
    states, todo = set(entered.values()), list(entered.values())
    while todo:  # what siblings can be entered in; labels that the query doesn't name are alike
        q = todo.pop()
        for w in [*sorted(walker.names), "\0"]:
            p = walker.rule(q, w)[2]
            if p not in states:
                states.add(p)
                todo.append(p)
    order = sorted(states)

    def chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        """(rows of a chunk, in order) with top and chunk, as they come."""
        key, held = None, []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if held and row[:2] != key:
                    yield key, held
                    held = []
                key = row[:2]
                held.append(row)
        if held:
            yield key, held

    def functions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (top, chunk), rows in chunks(batches):
            now = list(order)
            for row in rows:
                for w in row[2]:
                    now = [walker.rule(q, w)[2] for q in now]
            yield pa.RecordBatch.from_arrays([pa.array([top], pa.int32()), pa.array([chunk], pa.int64()), pa.array([now], pa.list_(pa.int64()))], names=["top", "chunk", "ends"])

    cut = units.select("top", F.floor(F.col("before") / CHUNK).cast("long").alias("chunk"), "roots", "before", "unit", "entry")
    cut = cut.repartition("top", "chunk").sortWithinPartitions("top", "chunk", "before")
    found = cut.select("top", "chunk", "roots").mapInArrow(functions, "top int, chunk long, ends array<long>").limit(MAX_BROADCAST + 1).collect()
    if len(found) > MAX_BROADCAST:
        raise QueryError("too many chunks of siblings with different roots")
    begins, now = {}, dict(entered)
    for r in sorted(found, key=lambda r: (r["top"], r["chunk"])):
        q = now[r["top"]]
        begins[r["top"], r["chunk"]] = q
        now[r["top"]] = r["ends"][order.index(q)]

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, rows in chunks(batches):
            q, out = begins[key], []
            for row in rows:
                out.append(q)
                for w in row[2]:
                    q = walker.rule(q, w)[2]
            columns = [pa.array([r[3] for r in rows], pa.int64()), pa.array([key[0]] * len(rows), pa.int32()), pa.array([r[4] for r in rows], pa.string()), pa.array(out, pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, names=["unit", "top", "entry", "state"])

    return cut.select("top", "chunk", "roots", "unit", "entry").mapInArrow(walk, "unit long, top int, entry string, state long")


_FOUND, _SPANS = [("pre", pa.int64()), ("label", pa.string())], [("pre", pa.int64()), ("start", pa.int64()), ("stop", pa.int64())]
RESULTS = {
    "count": ("n", "decimal(38,0)", pa.decimal128(38, 0)),
    "size": ("s", "decimal(38,0)", pa.decimal128(38, 0)),
    "locate": ("found", "array<struct<pre:long,label:string>>", pa.list_(pa.struct(_FOUND))),
    "serialize": ("found", "array<struct<pre:long,xml:string>>", pa.list_(pa.struct([("pre", pa.int64()), ("xml", pa.string())]))),
    "spans": ("found", "array<struct<xml:string,results:array<struct<pre:long,start:long,stop:long>>>>", pa.list_(pa.struct([("xml", pa.string()), ("results", pa.list_(pa.struct(_SPANS)))]))),
}


def _of_grammar(g: G.Grammar, w: Walker, query: PathQuery | None, what: str, options: dict):
    if query is not None and query.probes:
        g = G.annotate(g, query, options.get("filters", "table"))
    if what == "count":
        return Decimal(G.count(g, w, options.get("mode", "demand")))
    if what == "size":
        return Decimal(G.serialized_size(g, w))
    if what == "locate":
        return [{"pre": u, "label": x} for u, x in G.locate(g, w, options.get("limit"), options.get("offsets", "lazy"), True)]
    if what == "serialize":
        return [{"pre": u, "xml": x} for u, x in G.serialize(g, w, options.get("nested", True))]
    return [{"xml": text, "results": [{"pre": u, "start": a, "stop": b} for u, a, b in spans]} for text, spans in G.serialize_spans(g, w, options.get("nested", True))]


def _of_tree(labels: list[str], depths: list[int], w: Walker, query: PathQuery | None, what: str, options: dict):
    """The same by a walk over the uncompressed tree, the baseline: a state waits at each depth for the next node there."""
    held = _tree_states(labels, depths, query.probes)[1] if query is not None and query.probes else None
    waiting, hits, rule = [w.start], [], w.rule
    for i, d in enumerate(depths):
        selects, left, right = rule(waiting[d], labels[i], held[i] if held else 0)
        waiting[d:] = right, left
        if selects:
            hits.append(i)
    if what == "count":
        return Decimal(len(hits))
    if what == "locate":
        return [{"pre": i + 1, "label": labels[i]} for i in hits[: options.get("limit")]]
    stops = {i: next((j for j in range(i + 1, len(depths)) if depths[j] <= depths[i]), len(depths)) for i in hits}
    if what == "size":
        return Decimal(sum(stops[i] - i for i in hits))
    if what == "spans":
        raise QueryError("spans are a form of the compressed methods")
    if not options.get("nested", True):
        hits, last = [], hits
        for i in last:
            if not hits or i >= stops[hits[-1]]:
                hits.append(i)
    return [{"pre": i + 1, "xml": _xml(labels[i : stops[i]], [d - depths[i] for d in depths[i : stops[i]]])} for i in hits]


def _task(what: str, query: PathQuery | None, walker: Walker, compress: str, options: dict):
    column, _, kind = RESULTS[what]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches, 3 if compress == "tree" else 5):
            states = batch.column(1).to_pylist()
            if compress == "tree":
                out = [_of_tree(labels, depths, walker.entered(q), query, what, options) for q, labels, depths in zip(states, batch.column(2).to_pylist(), batch.column(3).to_pylist())]
            else:
                out = [_of_grammar(g, walker.entered(q), query, what, options) for q, g in zip(states, _decoded(batch, 2))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, kind)], names=["entry", "state", column])

    return run


def _entered(forest: Forest, query: str | Walker, compress: str) -> tuple[DataFrame, list[int], PathQuery | None, Walker]:
    """Units with the state that they are entered in, the selected top nodes, and the query and its walker."""
    parsed = parse(query) if isinstance(query, str) else None
    walker = compile_query(parsed) if parsed else query
    held = _top_held(forest, parsed, compress) if parsed and parsed.probes else {}
    if parsed and any(t.axis == FOLLOWING and s.probes for s, t in zip(parsed.steps, parsed.steps[1:])):
        roots = {w for r in dictionary(forest)[0].select(F.explode("roots").alias("w")).distinct().limit(MAX_BROADCAST).collect() for w in r}
        if any(t.axis == FOLLOWING and s.probes and any(map(s.accepts, roots)) for s, t in zip(parsed.steps, parsed.steps[1:])):
            raise QueryError("a filtered step on unit roots can't be followed by a sibling step")
    entered, selected = entry_states(forest, walker, held)
    return _unit_states(forest, walker, entered), selected, parsed, walker


def _source(forest: Forest, compress: str) -> DataFrame:
    return dictionary(forest)[0].select("entry", "labels", "depths") if compress == "tree" else grammars(forest, compress)


def _answers(forest: Forest, query: str | Walker, what: str, compress: str = "binary", outer: bool = False, **options) -> tuple[DataFrame, list[int]]:
    """unit, top, entry and the answer of every unit in which something can be selected (``outer``: of all units, null for the others); selected top nodes."""
    at, selected, parsed, walker = _entered(forest, query, compress)
    alive = at if walker.dead is None else at.where(F.col("state") != walker.dead)  # nothing can be selected in other units
    column, kind, _ = RESULTS[what]
    source = _source(forest, compress)
    todo = _dealt(alive.select("entry", "state")).distinct().join(_dealt(source), "entry").select("entry", "state", *source.columns[1:])
    done = todo.mapInArrow(_task(what, parsed, walker, compress, options), f"entry string, state long, {column} {kind}")
    return at.join(done, ["entry", "state"], "left" if outer else "inner").select("unit", "top", "entry", column), selected


def count_by_unit(forest: Forest, query: str | Walker, **options) -> DataFrame:
    """unit and n for the units with at least one selected node."""
    return _answers(forest, query, "count", **options)[0].where("n > 0").select("unit", F.col("n").cast("long").alias("n"))


def count(forest: Forest, query: str | Walker, **options) -> DataFrame:
    """One row: the number of selected nodes, top nodes included."""
    rows, selected = _answers(forest, query, "count", **options)
    return rows.agg((F.coalesce(F.sum("n"), F.lit(0)) + F.lit(len(selected))).cast("long").alias("n"))


def count_many(forest: Forest, queries: list[str], compress: str = "binary", **options) -> DataFrame:
    """query and n of several queries at once: an entry is read and decoded once, and walked for every query and state that asks for it."""
    asked, above, compiled = [], [], []
    for k, text in enumerate(queries):
        at, selected, parsed, walker = _entered(forest, text, compress)
        asked.append((at if walker.dead is None else at.where(F.col("state") != walker.dead)).select(F.lit(k).alias("k"), "entry", "state"))
        above.append((k, text, len(selected)))
        compiled.append((parsed, walker))
    every = reduce(DataFrame.unionByName, asked)
    source = _source(forest, compress)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            trees = zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()) if compress == "tree" else _decoded(batch, 2)
            for entry, pairs, g in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), trees):
                for x in pairs:
                    parsed, walker = compiled[x["k"]]
                    own = _of_tree(*g, walker.entered(x["state"]), parsed, "count", options) if compress == "tree" else _of_grammar(g, walker.entered(x["state"]), parsed, "count", options)
                    rows.append((entry, x["k"], x["state"], own))
            kinds = [pa.string(), pa.int32(), pa.int64(), pa.decimal128(38, 0)]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names=["entry", "k", "state", "n"])

    # the pairs of an entry: at most (queries) * (states)
    todo = _dealt(every.distinct()).groupBy("entry").agg(F.collect_set(F.struct("k", "state")).alias("asked")).join(_dealt(source), "entry").select("entry", "asked", *source.columns[1:])
    done = todo.mapInArrow(run, "entry string, k int, state long, n decimal(38,0)")
    sums = every.join(done, ["entry", "k", "state"]).groupBy("k").agg(F.sum("n").alias("n"))
    base = source.sparkSession.createDataFrame(above, "k int, query string, own long")
    return base.join(sums, "k", "left").select("query", (F.coalesce("n", F.lit(0)) + F.col("own")).cast("long").alias("n"))


def exists(forest: Forest, query: str | Walker, **options) -> DataFrame:
    """unit and hit of every unit."""
    return _answers(forest, query, "count", outer=True, **options)[0].select("unit", (F.coalesce("n", F.lit(0)) > 0).alias("hit"))


def accepts(forest: Forest, walker: Walker, **options) -> DataFrame:
    """unit and accepted: whether a tree automaton (``query.acceptor``) gets through the unit without its reject state."""
    return exists(forest, walker, **options).select("unit", (~F.col("hit")).alias("accepted"))


def node_at(forest: Forest, numbers: DataFrame, compress: str = "binary") -> DataFrame:
    """unit, pre, label and template of the nodes (unit, pre) asked for, each by one way down its unit's grammar; units are told by their id here."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for entry, wanted, g in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), _decoded(batch, 2)):
                table = G.gaps(g)
                rows += [(entry, u, *G.node_at(g, u, table)[::-1]) for u in wanted]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate([pa.string(), pa.int64(), pa.string(), pa.int64()])], names=["entry", "pre", "label", "template"])

    entries, units = dictionary(forest)
    asked = numbers.select("unit", "pre").join(units, "unit").select("unit", "entry", "pre")
    # numbers of an entry: no more than its nodes
    todo = _dealt(asked.groupBy("entry").agg(F.collect_set("pre").alias("wanted"))).join(_dealt(grammars(forest, compress)), "entry").select("entry", "wanted", "labels", "ranks", "lengths", "symbols")
    return asked.join(todo.mapInArrow(run, "entry string, pre long, label string, template long"), ["entry", "pre"]).select("unit", "pre", "label", "template")


def spans(forest: Forest, query: str | Walker, **options) -> DataFrame:
    """unit, xml and results (pre, start, stop): the text of each outermost result of the units, once, and where in it every result stands."""
    rows, _ = _answers(forest, query, "spans", **options)
    return rows.select("unit", F.explode("found").alias("f")).select("unit", "f.xml", "f.results")


def tree_size(forest: Forest) -> DataFrame:
    entries, units = dictionary(forest)
    return units.join(entries.select("entry", "nodes"), "entry").agg((F.coalesce(F.sum("nodes"), F.lit(0)) + F.lit(len(forest.top))).cast("long").alias("total"))


def selectivity(forest: Forest, query: str | Walker) -> DataFrame:
    """n, total and their ratio."""
    both = count(forest, query).withColumn("k", F.lit(1)).join(tree_size(forest).withColumn("k", F.lit(1)), "k")
    return both.select("n", "total", (F.col("n") / F.col("total")).alias("ratio"))


def _places(forest: Forest) -> dict[int, int]:
    """Numbers of the top nodes in the top tree's pre-order, from 1."""
    return {i: n for n, (i, _, _) in enumerate(forest.top, 1)}


def _above(forest: Forest, selected: list[int]) -> dict[int, int]:
    """For each top node, how many selected top nodes hold it, itself included."""
    chosen, out = set(selected), {}
    for i, parent, _ in forest.top:
        out[i] = out.get(parent, 0) + (i in chosen)
    return out


def locate(forest: Forest, query: str | Walker, with_label: bool = False, top: bool = True, **options) -> DataFrame:
    """unit and pre (from 1, inside the unit) of every selected node.

    A selected top node has a null unit, and its pre is its number in the top tree; ``limit`` holds for the top tree as for a unit.
    ``top``: False gives the nodes of the units only.
    """
    rows, selected = _answers(forest, query, "locate", **options)
    rows = rows.select("unit", F.explode("found").alias("f")).select("unit", "f.pre", *(["f.label"] if with_label else []))
    if top and selected:
        place, label = _places(forest), {i: w for i, _, w in forest.top}
        own = sorted((place[i], label[i]) for i in selected)[: options.get("limit")]
        above = rows.sparkSession.createDataFrame([(None, n, w) for n, w in own], "unit long, pre long, label string")
        rows = rows.unionByName(above.select(*rows.columns))
    return rows


def _xml(labels: list[str], depths: list[int]) -> str:
    out, way = [], []
    for w, d in zip(labels, depths):
        while len(way) > d:
            out.append(G.token_text((">", way.pop())))
        out.append(G.token_text(("<", w)))
        way.append(w)
    return "".join([*out, *(G.token_text((">", w)) for w in reversed(way))])


def _written(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [_xml(labels, depths) for labels, depths in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist())]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["entry", "xml"])


def top_pieces(forest: Forest, chosen: list[int]) -> DataFrame:
    """pre, step, before and xml: the XML of each chosen top node (pre: its number in the top tree) in pieces, to be joined in the order of step and before.

    A piece is a bracket of a top node or the whole XML of a unit, so no row grows with the corpus.
    """
    spark, place, kids, label = dictionary(forest)[0].sparkSession, _places(forest), _children(forest.top), {i: w for i, _, w in forest.top}
    brackets, slots = [], []
    for i in chosen:
        todo, step = [("<", i)], 0
        while todo:
            kind, k = todo.pop()
            brackets.append((place[i], step, 0, G.token_text((kind, label[k]))))
            if kind == "<":
                slots.append((k, place[i], step + 1))
                todo += [(">", k), *(("<", x) for x in reversed(kids.get(k, [])))]
            step += 2
    entries, units = dictionary(forest)
    below = units.join(F.broadcast(spark.createDataFrame(slots, "top int, pre long, step long")), "top")
    texts = entries.select("entry", "labels", "depths").mapInArrow(_written, "entry string, xml string")
    own = below.join(texts, "entry").select("pre", "step", F.col("before").cast("long").alias("before"), "xml")
    return own.unionByName(spark.createDataFrame(brackets, "pre long, step long, before long, xml string"))


def serialize(forest: Forest, query: str | Walker, top: bool = True, **options) -> DataFrame:
    """unit, pre and xml of every selected node; top nodes as in ``locate``.

    The XML of a top node is one string, put together from its units; one beyond what a string can hold is an error (``top_pieces``
    gives any).  ``nested=False`` leaves out what lies below a selected top node as well.  ``top``: False looks at the units alone.
    """
    rows, selected = _answers(forest, query, "serialize", **options)
    rows = rows.select("unit", "top", F.explode("found").alias("f")).select("unit", "top", "f.pre", "f.xml")
    if not top or not selected:
        return rows.drop("top")
    if not options.get("nested", True):
        above, parent = _above(forest, selected), {i: p for i, p, _ in forest.top}
        selected = [i for i in selected if above.get(parent[i], 0) == 0]
        covered = rows.sparkSession.createDataFrame([(i,) for i, n in above.items() if n], "top int")
        rows = rows.join(F.broadcast(covered), "top", "left_anti")
    rows = rows.drop("top")
    pieces = top_pieces(forest, selected)
    longest = pieces.groupBy("pre").agg(F.sum(F.octet_length("xml")).alias("bytes")).agg(F.max("bytes")).first()[0]
    if longest > MAX_STRING:
        raise QueryError("the XML of a selected top node is longer than a string can be; top_pieces gives it in pieces")
    whole = F.array_join(F.sort_array(F.collect_list(F.struct("step", "before", "xml")))["xml"], "")
    return rows.unionByName(pieces.groupBy("pre").agg(whole.alias("xml")).select(F.lit(None).cast("long").alias("unit"), "pre", "xml"))


def serialized_size(forest: Forest, query: str | Walker, top: bool = True, **options) -> DataFrame:
    """One row: nodes of all selected subtrees together.  ``top``: False leaves out the subtrees of selected top nodes."""
    rows, selected = _answers(forest, query, "size", **options)
    size = rows.agg(F.coalesce(F.sum("s"), F.lit(0)).alias("s"))
    if top and selected:
        # a node counts once for each selected top node that holds it
        above = _above(forest, selected)
        weights = rows.sparkSession.createDataFrame([x for x in above.items() if x[1]], "top int, above long")
        entries, units = dictionary(forest)
        held = units.join(F.broadcast(weights), "top").join(entries.select("entry", "nodes"), "entry")
        more = held.agg(F.coalesce(F.sum((F.col("nodes") * F.col("above")).cast("decimal(38,0)")), F.lit(0)).alias("more"))
        size = size.crossJoin(more).select((F.col("s") + F.col("more") + F.lit(sum(above.values()))).alias("s"))
    return size.select(F.col("s").cast("long").alias("s"))
