"""Sharing measured over a whole corpus: minimal unranked DAG, minimal binary DAG, hybrid DAG, and grammars of higher rank.

Each unit emits its distinct nodes by a 128-bit digest of label and children; the corpus then keeps each digest once, in a partial
aggregation, so subtrees shared between units count once.  Edges to absent nodes don't count.  ``ratios`` measures all kinds at once, by names over
arrays (``functions/naming.py``) of which 96 bits are kept.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sharetree.functions import grammar as G
from sharetree.functions import naming
from sharetree.operators.evaluate import COMPRESSORS, sliced
from sharetree.sources.forests import Forest

PIECES = "digest binary, edges int"
KINDS = ("unranked", "binary", "hybrid")
#: Nodes that a task names at once (or one unit), as arrays, and leading bits of names that deal them to groups, of which a task holds one.
NODES, BUCKET_BITS = 250_000, 10
#: The words of a tail's and an element's name, and an element's number of children.
WORDS = {"tails": {"first": "<u8", "second": "<u4"}, "elements": {"first": "<u8", "second": "<u4", "kids": "<i4"}}
PACKED = ["bucket", "edges", *WORDS]
PIECES_PACKED = "bucket int, edges long, " + ", ".join(f"{kind} struct<{', '.join(f'{x}: binary' for x in words)}>" for kind, words in WORDS.items())
PACKED_AS = pa.schema([("bucket", pa.int32()), ("edges", pa.int64()), *((kind, pa.struct([(x, pa.binary()) for x in words])) for kind, words in WORDS.items())])
EDGES_AS = pa.schema([(x, pa.int64()) for x in (*KINDS, "trees")])


def _digest(*parts: bytes) -> bytes:
    return hashlib.blake2b(b"".join(len(p).to_bytes(4, "little") + p for p in parts), digest_size=16).digest()


def unit_pieces(labels: list[str], depths: list[int], kind: str) -> dict[bytes, int]:
    """Digest -> edges of the distinct nodes of one unit under a kind of sharing."""
    return _named(labels, *G.from_tree(labels, depths), kind)


def _named(labels: list[str], kids: list[list[int]], roots: list[int], kind: str) -> dict[bytes, int]:
    element, out = [b""] * len(labels), {}
    tails: list[bytes] = [b""] * len(labels)
    # several roots are a sibling chain, whose digests its element names; the root of one tree has no chain of its own in the hybrid
    for i in [*reversed(range(len(labels))), *([-1] if kind != "unranked" and roots and (kind == "binary" or len(roots) > 1) else [])]:
        w, own = labels[i].encode() if i >= 0 else b"", kids[i] if i >= 0 else roots
        if kind == "unranked":
            element[i] = _digest(w, *(element[k] for k in own))
            out[element[i]] = len(own)
            continue
        tail = b""
        for k in reversed(own):
            left = tails[k] if kind == "binary" else element[k]
            name = _digest(labels[k].encode(), left, tail) if kind == "binary" else _digest(b"chain", left, tail)
            out[name] = bool(tail) + (kind == "binary" and bool(left))
            tail = name
        if i >= 0:
            tails[i] = tail
            if kind == "hybrid":
                element[i] = _digest(b"element", w, tail)
                out[element[i]] = int(bool(own))
    return out


def _pieces(kind: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches, 1):
            out: dict[bytes, int] = {}
            for labels, depths in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                out |= unit_pieces(labels, depths, kind)
            yield pa.RecordBatch.from_arrays([pa.array(list(out), pa.binary()), pa.array(list(out.values()), pa.int32())], names=["digest", "edges"])

    return run


def sharing(forest: Forest, kind: str) -> DataFrame:
    """One row: edges of the units' trees, and edges and nodes of what is left when the corpus shares them."""
    trees = forest.units.agg(F.sum(F.greatest(F.size("labels") - 1, F.lit(0))).cast("long").alias("tree_edges"), F.lit(1).alias("k"))
    pieces = forest.units.select("labels", "depths").mapInArrow(_pieces(kind), PIECES)
    shared = pieces.groupBy("digest").agg(F.first("edges").alias("edges")).agg(F.sum("edges").cast("long").alias("shared_edges"), F.count("*").cast("long").alias("shared_nodes"), F.lit(1).alias("k"))
    return trees.join(shared, "k").drop("k")


def grammar_stats(forest: Forest, compress: str) -> DataFrame:
    """unit, tree edges, and edges, templates and rank of the unit's grammar under a compressor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for unit, labels, depths in zip(*(c.to_pylist() for c in batch.columns)):
                g = COMPRESSORS[compress](labels, depths)
                rows.append((unit, 2 * len(labels), g.edges(), len(g.bodies), g.rank()))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(5)], names=["unit", "tree_edges", "grammar_edges", "templates", "rank"])

    return forest.units.select("unit", "labels", "depths").mapInArrow(run, "unit long, tree_edges long, grammar_edges long, templates long, rank long")


def dictionary_update(known: DataFrame, fresh: DataFrame) -> DataFrame:
    """Digests of a batch of pieces that a dictionary doesn't have yet."""
    return fresh.dropDuplicates(["digest"]).join(known.select("digest"), "digest", "left_anti")


def piece_rows(units: DataFrame, kind: str) -> DataFrame:
    """digest and edges of the distinct nodes of units (labels, depths), a batch of rows at a time."""
    return units.select("labels", "depths").mapInArrow(_pieces(kind), PIECES)


def _all_pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of each slice of units: its trees' edges, and its distinct tails and elements, packed by their first words' leading bits."""
    for batch in sliced(batches, 1, NODES):
        labels, depths, lengths = batch.column(0).flatten(), batch.column(1).flatten().to_numpy(), pc.fill_null(pc.list_value_length(batch.column(1)), 0).to_numpy()
        if len(labels) != len(depths):
            raise ValueError("as many labels as depths are needed")
        yield pa.RecordBatch.from_pydict({"bucket": [-1], "edges": [int(np.maximum(lengths.astype(np.int64) - 1, 0).sum())]} | dict.fromkeys(PACKED[2:], [None]), PACKED_AS)
        for kind, own in zip(PACKED[2:], naming.pieces(labels, depths, lengths)):
            words = naming.distinct(*own)
            buckets, at = np.unique(words[0] >> np.uint64(64 - BUCKET_BITS), return_index=True)
            ends = np.append(at, len(words[0]))
            rows = pa.StructArray.from_arrays([pa.Array.from_buffers(pa.large_binary(), len(at), [None, pa.py_buffer(ends * w.itemsize), pa.py_buffer(w)]).cast(pa.binary()) for w in words], list(WORDS[kind]))
            columns = {"bucket": pa.array(buckets.astype(np.int32)), kind: rows}
            yield pa.RecordBatch.from_arrays([columns.get(f.name, pa.nulls(len(at), f.type)) for f in PACKED_AS], schema=PACKED_AS)


def _edges(packed: pa.Table) -> pa.Table:
    """Edges of the distinct pieces of a bucket under each kind of sharing, or of the trees."""
    trees = pc.sum(packed["edges"]).as_py()
    if trees is not None:
        return pa.Table.from_pylist([dict.fromkeys(KINDS) | {"trees": trees}], EDGES_AS)
    got = {}
    for kind, names in WORDS.items():
        column = packed[kind].filter(packed[kind].is_valid()).combine_chunks()
        got[kind] = naming.distinct(*(np.frombuffer(b"".join(pc.struct_field(column, [i]).to_pylist()), t) for i, t in enumerate(names.values())))
    flags, kids = got["tails"][1], got["elements"][2].astype(np.int64)
    on = int(np.count_nonzero(flags & naming.GOES_ON))
    edges = {"unranked": int(kids.sum()), "binary": on + int(np.count_nonzero(flags & naming.HAS_KIDS)), "hybrid": on + len(kids)}
    return pa.Table.from_pylist([edges | {"trees": None}], EDGES_AS)


def ratios(forest: Forest) -> DataFrame:
    """kind, tree_edges, shared_edges and their ratio for the three kinds of sharing; the units' trees are read once.

    A node of the binary DAG is a tail of a sibling list, and one of the hybrid's a tail or an element, so distinct tails and distinct elements (subtrees)
    give all kinds: unranked, an element has an edge to each child; binary, a tail has one to the next and one to its first member's children; hybrid, a
    tail has one to the next, and an element one to its first child.  What has no edge under any kind isn't moved.
    """
    pieces = forest.over_trees(_all_pieces, PIECES_PACKED)
    counts = pieces.groupBy("bucket").applyInArrow(_edges, ", ".join(f"{x} long" for x in EDGES_AS.names))
    sums = counts.agg(*(F.sum(x).cast("long").alias(x) for x in EDGES_AS.names))
    rows = sums.select(F.inline(F.array(*(F.struct(F.lit(k).alias("kind"), F.col("trees").alias("tree_edges"), F.col(k).alias("shared_edges")) for k in KINDS))))
    return rows.select("kind", "tree_edges", "shared_edges", (F.col("shared_edges") / F.col("tree_edges")).alias("ratio"))


def hybrid_is_least(forest: Forest) -> DataFrame:
    """One row: whether the hybrid has no more edges than either other kind, as it must."""
    edges = ratios(forest).agg(*(F.max(F.when(F.col("kind") == k, F.col("shared_edges"))).alias(k) for k in KINDS))
    return edges.select((F.col("hybrid") <= F.least("unranked", "binary")).alias("holds"))


def frequent_pairs(forest: Forest, least: int) -> DataFrame:
    """parent, child (binary form), side and n of the pairs that occur at least so often in the units' trees."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            count: Counter = Counter()
            for labels, depths in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                kids, roots = G.from_tree(labels, depths)
                for i, own in enumerate(kids):
                    if own:
                        count[labels[i], "first child", labels[own[0]]] += 1
                for own in [*kids, roots]:
                    for a, b in zip(own, own[1:]):
                        count[labels[a], "next sibling", labels[b]] += 1
            yield pa.RecordBatch.from_arrays([*(pa.array([k[i] for k in count], pa.string()) for i in range(3)), pa.array(list(count.values()), pa.int64())], names=["parent", "side", "child", "n"])

    rows = forest.units.select("labels", "depths").mapInArrow(run, "parent string, side string, child string, n long")
    return rows.groupBy("parent", "side", "child").agg(F.sum("n").alias("n")).where(F.col("n") >= least)
