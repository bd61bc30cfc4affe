"""String programs of traversals and of selected subtrees, per unit, and walker measures."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sharetree.functions import grammar as G
from sharetree.operators.evaluate import COMPRESSORS
from sharetree.plans.query import compile_query, parse
from sharetree.sources.forests import Forest


SUBTREES = {"plain": G.subtrees_program_dag, "general": G.subtrees_program, "balanced": G.subtrees_program_balanced}


def _by_unit(forest: Forest, fields: str, measure: Callable[[list[str], list[int]], tuple]) -> DataFrame:
    """unit and whole numbers that a function gives for its tree."""
    names = fields.split()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(unit, *measure(labels, depths)) for unit, labels, depths in zip(*(c.to_pylist() for c in batch.columns))]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(len(names) + 1)], names=["unit", *names])

    return forest.units.select("unit", "labels", "depths").mapInArrow(run, ", ".join(f"{n} long" for n in ["unit", *names]))


def count_work(forest: Forest, query: str, mode: str = "full", compress: str = "binary") -> DataFrame:
    """unit, body symbols that a count visits, states, symbols, and their product: the bound on the visits."""

    def measure(labels: list[str], depths: list[int]) -> tuple:
        walker, g, seen = compile_query(query), COMPRESSORS[compress](labels, depths), []
        G.behaviours(g, walker, mode, seen)
        states, symbols = walker.close().states, sum(map(len, g.bodies.values()))
        return seen[0], states, symbols, states * symbols

    return _by_unit(forest, "visits states symbols bound", measure)


def mark_sizes(forest: Forest, query: str, compress: str = "digrams") -> DataFrame:
    """unit, templates, marked templates as made and as kept, states, and edges before and after marking."""

    def measure(labels: list[str], depths: list[int]) -> tuple:
        walker, g, stats = compile_query(query), COMPRESSORS[compress](labels, depths), {}
        marked = G.mark(g, walker, stats=stats)
        return len(g.bodies), stats["made"], len(marked.bodies), walker.close().states, g.edges(), marked.edges()

    return _by_unit(forest, "templates made kept states edges marked_edges", measure)


def lift_costs(forest: Forest, query: str, compress: str = "digrams") -> DataFrame:
    """unit, templates, copies that lifting made, and templates after it."""

    def measure(labels: list[str], depths: list[int]) -> tuple:
        g, stats = COMPRESSORS[compress](labels, depths), {}
        G.annotate(g, parse(query), "lift", stats)
        return len(g.bodies), stats["copies"], stats["templates"]

    return _by_unit(forest, "templates copies lifted", measure)


def output_sizes(forest: Forest, query: str, method: str = "plain", compress: str = "binary") -> DataFrame:
    """unit, results, tokens of their XML written out, size of their string program, and the bound on it: the grammar's for plain grammars."""

    def measure(labels: list[str], depths: list[int]) -> tuple:
        g, walker = COMPRESSORS[compress](labels, depths), compile_query(query)
        numbers = G.locate(g, walker)
        p, _ = SUBTREES[method](g, numbers)
        symbols = sum(map(len, g.bodies.values()))
        return len(numbers), 2 * G.serialized_size(g, walker), G.program_size(p), 2 * symbols + len(numbers) if method == "plain" else 4 * symbols * (len(numbers) + 1)

    return _by_unit(forest, "r tokens size bound", measure)


def subtree_programs(forest: Forest, query: str, method: str = "plain", compress: str = "binary", text: bool = True) -> DataFrame:
    """unit, selected nodes, grammar edges, size and length of the string program of their subtrees, and (``text``) what it spells.

    ``plain``: for plain grammars, size O(|G| + r).  ``general``: any rank, a start body for each node, size O(|G| r).  ``balanced``: any rank,
    substrings of the unit's balanced program, O(log) rules a node.  The query is entered at the unit's root.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        walker = compile_query(query)
        for batch in batches:
            rows = []
            for unit, labels, depths in zip(*(c.to_pylist() for c in batch.columns)):
                g = COMPRESSORS[compress](labels, depths)
                noted = G.annotate(g, parse(query)) if parse(query).probes else g
                numbers = G.locate(noted, walker)
                p, start = SUBTREES[method](g, numbers)
                spelt = "".join(map(G.token_text, G.program_tokens(p, start))) if text else None
                rows.append((unit, len(numbers), g.edges(), G.program_size(p), G.program_length(p, start), spelt))
            yield pa.RecordBatch.from_arrays([*(pa.array([r[i] for r in rows], pa.int64()) for i in range(5)), pa.array([r[5] for r in rows], pa.string())], names=["unit", "r", "edges", "size", "length", "text"])

    return forest.units.select("unit", "labels", "depths").mapInArrow(run, "unit long, r long, edges long, size long, length long, text string")


def traversal_programs(forest: Forest, compress: str = "binary") -> DataFrame:
    """unit, grammar edges, size and length of the string program of the whole unit's brackets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for unit, labels, depths in zip(*(c.to_pylist() for c in batch.columns)):
                g = COMPRESSORS[compress](labels, depths)
                p = G.traversal(g)
                rows.append((unit, g.edges(), G.program_size(p), G.program_length(p, (g.start, 0))))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(4)], names=["unit", "edges", "size", "length"])

    return forest.units.select("unit", "labels", "depths").mapInArrow(run, "unit long, edges long, size long, length long")


def _of_rows(df: DataFrame, schema: str, f) -> DataFrame:
    """The rows that ``f`` gives for each row of a few distinct ones, by tasks."""
    kinds = [pa.int64() if "long" in c else pa.bool_() if "boolean" in c else pa.string() for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [r for own in zip(*(c.to_pylist() for c in batch.columns)) for r in f(*own)]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=[c.split()[0] for c in schema.split(", ")])

    return df.mapInArrow(run, schema)


def walker_states(ends: DataFrame) -> DataFrame:
    """ancestor, wildcards, label and states of //ancestor/*.../label for each row (ancestor, wildcards, label)."""
    states = lambda a, k, b: [(a, k, b, compile_query(f"//{a}" + "/*" * k + f"/{b}").close().states)]
    return _of_rows(ends.select("ancestor", F.col("wildcards").cast("long"), "label"), "ancestor string, wildcards long, label string, states long", states)


def walker_rules(queries: DataFrame) -> DataFrame:
    """query and the rules of its walker, for each row (query)."""
    return _of_rows(queries.select("query"), "query string, q long, label string, selects boolean, q_left long, q_right long", lambda x: [(x, *r) for r in compile_query(x).close().rows()])


def chain_counts(chains: DataFrame, modulus: int = 3) -> DataFrame:
    """Selected nodes of a^(2^L)(e) by depth modulo, over grammars of L templates, for each row (doublings); n as text, of any length."""
    from sharetree.plans.query import user_walker

    rules = [(q, None, q == modulus - 1, (q + 1) % modulus, 0) for q in range(modulus)] + [(q, "e", False, 0, 0) for q in range(modulus)]
    return _of_rows(chains.select(F.col("doublings").cast("long")), "doublings long, n string", lambda n: [(n, str(G.count(G.chain("a", n), user_walker(rules))))])


def filter_costs(forest: Forest, query: str, mode: str, compress: str = "digrams") -> DataFrame:
    """unit, templates before and after filter states specialise them, the most states of one template, and the state's bits."""

    def measure(labels: list[str], depths: list[int]) -> tuple:
        stats: dict = {}
        G.annotate(COMPRESSORS[compress](labels, depths), parse(query), mode, stats)
        return stats["templates"], stats["specialised"], stats["most_tuples"], stats["bits"]

    return _by_unit(forest, "templates specialised most_tuples bits", measure)
