"""Where equal stretches of a corpus may lie, found without comparing documents.

Every window of L units (bytes or words) has an anchor: the leftmost of those of its k-unit windows whose hash is smallest.
It depends on the window alone, so equal windows have the same anchor at the same offset, and all that can be equal meets under the
anchor's hash.  About two anchors come on L - k + 2 units.  Anchors that occur once are dropped; the others get their context,
L - k units before and L units from the anchor on, which holds every window that they are the anchor of.

Copies are handled by their digest: each distinct text is looked at once, with its smallest document id and whether it has copies.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sharetree.llm.storage import join_counted, materialize

#: Bits of a packed number that hold the position; the others hold the leading bits of the hash.
POSITION_BITS = np.uint64(31)
#: Contexts that one task sorts; an anchor with more is divided by what its windows have in common.
GROUP = 20_000
#: The place of a null doc_id: after all others.
LAST = (1 << 63) - 1


def anchors(hashes: np.ndarray, reach: int) -> np.ndarray:
    """Positions of the leftmost smallest hash of every run of ``reach`` hashes, each once, ascending."""
    n = len(hashes)
    if n < reach:
        return np.zeros(0, np.int64)
    packed = (hashes >> POSITION_BITS << POSITION_BITS) | np.arange(n, dtype=np.uint64)
    rows = -(-n // reach)
    table = np.full(rows * reach, np.iinfo(np.uint64).max, np.uint64)
    table[:n] = packed
    table = table.reshape(rows, reach)
    ahead = np.minimum.accumulate(table[:, ::-1], 1)[:, ::-1].ravel()
    behind = np.minimum.accumulate(table, 1).ravel()
    least = np.minimum(ahead[: n - reach + 1], behind[reach - 1 : n])
    at = (least & ((np.uint64(1) << POSITION_BITS) - np.uint64(1))).astype(np.int64)
    return at[np.concatenate(([True], at[1:] != at[:-1]))]


def text_key(text: Column | None = None) -> Column:
    return F.unhex(F.md5(F.coalesce(F.col("text") if text is None else text, F.lit(""))))


def distinct_texts(docs: DataFrame) -> DataFrame:
    """text_key, text, first (smallest doc_id) and copies (rows) of every distinct text."""
    rows = docs.select(text_key().alias("text_key"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("doc"))
    return rows.groupBy("text_key").agg(F.first("text").alias("text"), F.min("doc").alias("first"), F.count("*").alias("copies"))


def _anchor_rows(find: Callable[[bytes], tuple[np.ndarray, np.ndarray]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(a, 500) for b in batches for a in range(0, b.num_rows, 500)):
            hashes, rows, places = [np.zeros(0, np.int64)], [], [np.zeros(0, np.int64)]
            for text in batch.column(1).to_pylist():
                h, at = find(text.encode())
                hashes.append(h.view(np.int64))
                places.append(at)
                rows.append(len(at))
            keys = batch.column(0).take(pa.array(np.repeat(np.arange(batch.num_rows), rows)))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(hashes)), keys, pa.array(np.concatenate(places).astype(np.int32))], names=["anchor", "text_key", "at"])

    return run


def shared_anchors(docs: DataFrame, find: Callable[[bytes], tuple[np.ndarray, np.ndarray]], least_bytes: int, within_text: bool, group: int) -> DataFrame:
    """text_key and spots (anchor, at, large) of the texts that have anchors which occur elsewhere.

    ``within_text``: a second place in the same text is elsewhere too.  ``large``: more than ``group`` places share the anchor.
    """
    rows = docs.where(F.octet_length("text") >= least_bytes).select(text_key().alias("text_key"), "text")
    found = materialize(rows.mapInArrow(_anchor_rows(find), "anchor long, text_key binary, at int"), "anchors")
    # two places of equal hash would hide each other only where an anchor has no third one: 2**-64 for each anchor
    place = F.xxhash64("text_key", "at") if within_text else F.xxhash64("text_key")
    twice = found.groupBy("anchor").agg(F.min(place).alias("a"), F.max(place).alias("b"), F.count("*").alias("n")).where("a <> b").select("anchor", "n", (F.col("n") > group).alias("large"))
    shared = join_counted(found, materialize(twice, "shared-anchors"), ["anchor"], "n", found.count())
    # sets merge before they are shuffled, so many copies of a text arrive as one
    spots = shared.groupBy("text_key").agg(F.collect_set(F.struct("anchor", "at", "large")).alias("spots"))
    return materialize(spots, "anchor-spots")
