"""SQL surface: a table function over markup, and the tree's relational functions."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, udtf
from pyspark.sql.types import LongType


@udtf(returnType="pre: long, label: string")
class PathSelect:
    """path_select(html, query): number and label of every selected element."""

    def eval(self, html: str, query: str):
        from sharetree.functions.grammar import annotate, binary_dag, locate
        from sharetree.plans.query import compile_query, parse
        from sharetree.sources.forests import html_tree

        labels, depths = html_tree(html or "")
        roots = [i for i, d in enumerate(depths) if d == 0] + [len(labels)]
        for a, b in zip(roots, roots[1:]):
            g, q = binary_dag(labels[a:b], depths[a:b]), parse(query)
            for u in locate(annotate(g, q) if q.probes else g, compile_query(q)):
                yield a + u, labels[a + u - 1]


@udtf(returnType="q: long, label: string, selects: boolean, q_left: long, q_right: long")
class WalkerRules:
    """walker_rules(query): the rules of a query's walker."""

    def eval(self, query: str):
        from sharetree.plans.query import compile_query

        yield from compile_query(query).close().rows()


@udtf(returnType="template: long, rank: int, size: int, body: string")
class GrammarRules:
    """grammar_rules(html, compressor): the templates of a page's grammar."""

    def eval(self, html: str, compress: str):
        from sharetree.operators.evaluate import COMPRESSORS
        from sharetree.functions.grammar import decode, encode
        from sharetree.sources.forests import html_tree

        g = decode(*encode(COMPRESSORS[compress](*html_tree(html or ""))))
        for t, body in g.bodies.items():
            yield t, g.ranks[t], len(body) - 1, " ".join("_" if len(s) < 2 else f"<{s[1]}>" if s[0] == "t" else f"${s[1]}" if s[0] == "y" else s[1] for s in body)


def walk_count(query: str):
    """An Arrow function (labels, depths) -> nodes that a query selects, entered at the roots."""

    @arrow_udf(returnType=LongType())
    def run(labels: pa.Array, depths: pa.Array) -> pa.Array:
        from sharetree.plans.query import compile_query

        walker, out = compile_query(query), []
        for own, deep in zip(labels.to_pylist(), depths.to_pylist()):
            waiting, n = [walker.start], 0
            for w, d in zip(own, deep):
                selects, left, right = walker.rule(waiting[d], w)
                waiting[d:] = right, left
                n += selects
            out.append(n)
        return pa.array(out, pa.int64())

    return run


def register(spark: SparkSession) -> None:
    spark.udtf.register("grammar_rules", GrammarRules)
    spark.udtf.register("path_select", PathSelect)
    spark.udtf.register("walker_rules", WalkerRules)
