"""MinHash near-duplicates with sequential Bayesian verification.

A document's set is its distinct five-word shingles.  Documents with equal sets form a class by a 128-bit digest, so copies
never meet as pairs.  Classes that agree in a band of their signatures are candidates.  A candidate's signatures are
compared batch by batch; it is dropped as soon as the posterior probability that its similarity reaches the threshold,
under a flat prior, is below ``MISS``; what is left is verified on the full sets.

Buckets are not spelt out into pairs.  First every member meets only the bucket's hub (its member first in one global order),
links are verified and components formed.  Then, in buckets whose members are still in different components, a forest of the most similar
pairs across components is verified.  What is still apart then is compared whole, every pair across components, in tasks of two blocks of a
bucket: by signatures first, which gives the members that are not ruled out, each once; then those bring their texts, each once, and the task
verifies their pairs on full sets and gives the links that join components, fewer than it has members.  So no rows grow with the
pairs of a bucket.  (For the forest, which only saves work, a bucket of more than ``BUCKET`` members is divided by other bands.)

Chance that a link is missed: by the bands (1 - 0.75**4)**32 < 6e-6 at the threshold itself, less above; by the prune below MISS.

Defined cases: null and empty texts, or texts without words, have the empty set and are linked with nothing; fewer than five words
count as one shingle; rows with equal doc_id are rows of their own, of which the smallest (doc_id, then text digest) stays; a null doc_id comes
last and its rows form components as others do; an empty table gives an empty result; other columns are ignored or carried.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sharetree.llm.components import components
from sharetree.llm.rolling import mix, word_hashes
from sharetree.llm.storage import materialize

WORDS, PERCENT = 5, 75
HASHES, ROWS = 128, 4
BANDS = HASHES // ROWS
BATCH, MISS = 16, 1e-6
#: Members of a bucket that one task compares with each other, about; larger buckets are cut into blocks.
BUCKET = 4_000
#: Bytes of text that weigh as much as a member.
TEXT_BYTES = 4_096
#: Members that meet one copy of a hub's text.
HUB_SHARE = 500

_FACTORS = mix(np.arange(1, HASHES + 1, dtype=np.uint64)) | np.uint64(1)
_PLACES = mix(np.arange(101, 101 + WORDS, dtype=np.uint64)) | np.uint64(1)


def shingles(text: bytes) -> np.ndarray:
    """The sorted distinct 64-bit hashes of a text's shingles."""
    words = word_hashes(np.frombuffer(text.lower(), np.uint8))  # bytes.lower() lowers A-Z alone
    k = min(WORDS, len(words))
    if not k:
        return words
    n = len(words) - k + 1
    total = np.full(n, k, np.uint64)
    for i in range(k):
        total += words[i : i + n] * _PLACES[i]
    return np.unique(mix(total))


def signature(items: np.ndarray) -> np.ndarray:
    out = np.full(HASHES, np.iinfo(np.uint64).max, np.uint64)
    for a in range(0, len(items), 2048):
        np.minimum(out, (items[a : a + 2048, None] * _FACTORS).min(0), out=out)
    return (out >> np.uint64(32)).astype("<u4")


def least_matches(threshold: float = PERCENT / 100, miss: float = MISS) -> list[int]:
    """For each number of compared hashes, a multiple of the batch: the fewest matches with which a pair goes on.

    With m matches of n and a flat prior, the similarity has a Beta(m + 1, n - m + 1) posterior, and its mass above t is the chance of at
    most m successes in n + 1 trials of chance t.
    """
    out = []
    for n in range(BATCH, HASHES + 1, BATCH):
        mass, m = 0.0, 0
        while True:
            mass += comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
            if mass >= miss:
                break
            m += 1
        out.append(m)
    return out


def likely(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Which rows of two signature tables may be links: batch after batch, over the rows that are left."""
    rows, matches = np.arange(len(left)), np.zeros(len(left), np.int64)
    for i, least in enumerate(least_matches()):
        at = slice(i * BATCH, (i + 1) * BATCH)
        matches = matches + (left[rows, at] == right[rows, at]).sum(1)
        keep = matches >= least
        rows, matches = rows[keep], matches[keep]
    return rows


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sizes, keys, signatures = [], [], []
        for x in batch.column(0).to_pylist():
            items = shingles((x or "").encode())
            sizes.append(len(items))
            keys.append(hashlib.blake2b(items.tobytes(), digest_size=16).digest() if len(items) else None)
            signatures.append(signature(items).tobytes() if len(items) else None)
        yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), pa.array(signatures, pa.binary())], names=["doc_id", "text_key", "n_shingles", "set_key", "signature"])


def _text_key():
    return F.md5(F.coalesce("text", F.lit("")))


def shingle_sets(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, n_shingles, set_key and signature of every row."""
    rows = docs.select("text", F.col("doc_id").cast("long").alias("doc_id"), _text_key().alias("text_key"))
    return rows.mapInArrow(_sets, "doc_id long, text_key string, n_shingles long, set_key binary, signature binary")


def _prune(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        left, right = (np.frombuffer(b"".join(batch.column(i).to_pylist()), "<u4").reshape(-1, HASHES) for i in (2, 3))
        rows = pa.array(likely(left, right))
        yield pa.RecordBatch.from_arrays([batch.column(0).take(rows), batch.column(1).take(rows)], names=["hub", "node"])


def _forest(floor: int):
    """A forest of pairs across components of a bucket, hub left out, that joins the components, the most equal pairs first.

    Only pairs with at least so many equal hashes; the rows come sorted by bucket.
    """

    def found(nodes: np.ndarray, comps: np.ndarray, signatures: np.ndarray) -> Iterator[np.ndarray]:
        for i in range(len(nodes) - 1):
            others = np.flatnonzero(comps[i + 1 :] != comps[i]) + i + 1
            if not len(others):
                continue
            equal = (signatures[others] == signatures[i]).sum(1)
            hit = equal >= floor
            others, equal = others[hit], equal[hit]
            yield np.stack([equal, np.full(len(others), i), others])

    def pairs(rows: list[tuple]) -> pa.RecordBatch:
        nodes, comps, signatures = _stacked(rows)
        some = np.concatenate([np.zeros((3, 0), np.int64), *found(nodes, comps, signatures)], 1)
        up = {c: c for c in set(comps.tolist())}

        def root(c: int) -> int:
            while up[c] != c:
                up[c] = c = up[up[c]]
            return c

        keep = []
        for k in np.argsort(-some[0], kind="stable").tolist():
            x, y = root(int(comps[some[1, k]])), root(int(comps[some[2, k]]))
            if x != y:
                up[x] = y
                keep.append(k)
        some = some[:, keep]
        return pa.RecordBatch.from_arrays([pa.array(nodes[some[1]]), pa.array(nodes[some[2]])], names=["hub", "node"])

    return lambda batches: map(pairs, _tasks(batches, (0,)))


def _across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The members of a task (two blocks of a bucket, or one with itself) that the posterior doesn't rule out with one of another component.

    Rows of (bucket, node, component, signature, x, y, block), sorted by bucket, x and y.  A member comes out once for its task, however
    many partners it has.
    """
    least = least_matches()[0]

    def members(rows: list[tuple]) -> pa.RecordBatch:
        nodes, comps, signatures = _stacked(rows)
        first = np.ascontiguousarray(signatures[:, :BATCH])
        side = np.array([r[6] == r[4] for r in rows])
        one = rows[0][4] == rows[0][5]
        left, right = (np.arange(len(rows)),) * 2 if one else (np.flatnonzero(side), np.flatnonzero(~side))
        if len(left) > len(right):
            left, right = right, left
        there, theirs = first[right], comps[right]
        open_ = np.zeros(len(rows), bool)
        for k, i in enumerate(left.tolist()):
            at = k + 1 if one else 0
            apart = np.flatnonzero(theirs[at:] != comps[i]) + at
            others = right[apart[(there[apart] == first[i]).sum(1) >= least]]
            if len(others):
                others = others[likely(np.broadcast_to(signatures[i], (len(others), HASHES)), signatures[others])]
                open_[others] = True
                open_[i] |= len(others) > 0
        task = [pa.array([rows[0][i]] * int(open_.sum()), pa.int64()) for i in (0, 4, 5)]
        blocks = pa.array(np.array([r[6] for r in rows], np.int64)[open_])
        return pa.RecordBatch.from_arrays([*task, blocks, pa.array(nodes[open_]), pa.array(comps[open_])], names=["bucket", "x", "y", "block", "node", "component"])

    yield from map(members, _tasks(batches, (0, 4, 5)))


def _tasks(batches: Iterator[pa.RecordBatch], key: tuple[int, ...]) -> Iterator[list[tuple]]:
    """The rows of each key; they come sorted by it."""
    held: list[tuple] = []
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns)):
            if held and any(row[i] != held[0][i] for i in key):
                yield held
                held = []
            held.append(row)
    if held:
        yield held


def shared_items(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of the sets ``left`` (rows) with the sets ``right`` (columns); equal lists, or no set in both.

    Items of many sets are counted by a product of incidence tables, a part of the columns at a time, the others pair by pair from the lists
    of sets that have them.
    """
    one = left is right
    owners = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    _, codes, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    order = np.argsort(codes, kind="stable")
    owners, codes = owners[order], codes[order]
    stops = np.cumsum(counts)
    at = np.zeros(len(sets), np.int64)
    at[left], at[right] = np.arange(len(left)), np.arange(len(right))
    of_left = np.zeros(len(sets), bool)
    of_left[left] = True
    out = np.zeros((len(left), len(right)), np.float32)
    many = 16 * counts > len(sets)
    dense = np.flatnonzero(many & (counts > 1))
    column = np.full(len(counts), -1)
    for a in range(0, len(dense), 2048):
        some = dense[a : a + 2048]
        column[:] = -1
        column[some] = np.arange(len(some))
        mine = column[codes]
        has = np.zeros((len(sets), len(some)), np.float32)
        has[owners[mine >= 0], mine[mine >= 0]] = 1
        out += has[left] @ has[right].T
    entry = np.flatnonzero(~many[codes])
    for step in range(1, int(counts[~many].max(initial=1))):
        entry = entry[entry + step < stops[codes[entry]]]
        i, j = owners[entry], owners[entry + step]
        if not one:
            cross = of_left[i] != of_left[j]
            i, j = i[cross], j[cross]
            i, j = np.where(of_left[i], i, j), np.where(of_left[i], j, i)
        np.add.at(out, (at[i], at[j]), 1)
        if one:
            np.add.at(out, (at[j], at[i]), 1)
    return out


def _exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links on full sets that join the components of a task's members: rows of (bucket, x, y, block, node, component, text), sorted by bucket, x and y."""

    def joined(rows: list[tuple]) -> pa.RecordBatch:
        sets = [shingles(r[6].encode()) for r in rows]
        sizes, comps = np.array([len(x) for x in sets], np.float32), np.array([r[5] for r in rows])
        one, side = rows[0][1] == rows[0][2], np.array([r[3] == r[1] for r in rows])
        left = np.arange(len(rows)) if one else np.flatnonzero(side)
        right = left if one else np.flatnonzero(~side)
        up = {c: c for c in comps.tolist()}

        def root(c: int) -> int:
            while up[c] != c:
                up[c] = c = up[up[c]]
            return c

        a, b = [], []
        both = shared_items(sets, left, right)
        for k in range(len(left)):
            i = left[k]
            linked = (100 * both[k] >= PERCENT * (sizes[i] + sizes[right] - both[k])) & (comps[right] != comps[i])
            for j in right[linked].tolist():
                x, y = root(int(comps[i])), root(int(comps[j]))
                if x != y:
                    up[x] = y
                    a.append(rows[i][4])
                    b.append(rows[j][4])
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    yield from map(joined, _tasks(batches, (0, 1, 2)))


def _stacked(rows: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return np.array([r[1] for r in rows], np.int64), np.array([r[2] for r in rows], np.int64), np.frombuffer(b"".join(r[3] for r in rows), "<u4").reshape(-1, HASHES)


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links among (hub, salt, node or null for the hub itself, text), sorted so that a hub's own text comes first."""
    hub, items = None, np.zeros(0, np.uint64)
    for batch in batches:
        found: list[tuple[int, int]] = []
        for h, salt, node, text in zip(*(c.to_pylist() for c in batch.columns)):
            own = shingles((text or "").encode())
            if node is None:
                hub, items = (h, salt), own
            elif hub == (h, salt):
                both = len(np.intersect1d(items, own, assume_unique=True))
                if 100 * both >= PERCENT * (len(items) + len(own) - both):
                    found.append((h, node))
        yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], pa.int64()) for i in (0, 1)], names=["a", "b"])


def verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (hub, node) that are links on their full sets; ``texts`` has node and text of all nodes in them.

    Pairs are dealt by hub; a hub with many members is dealt in shares, each with its own copy of the hub's text.
    """
    shares = pairs.groupBy("hub").agg(F.ceil(F.count("*") / HUB_SHARE).cast("int").alias("shares"))
    hubs = shares.join(texts.withColumnRenamed("node", "hub"), "hub").select("hub", F.explode(F.sequence(F.lit(0), F.col("shares") - 1)).alias("salt"), F.lit(None).cast("long").alias("node"), "text")
    members = pairs.join(shares, "hub").select("hub", F.pmod(F.xxhash64("node"), F.col("shares")).cast("int").alias("salt"), "node").join(texts, "node").select("hub", "salt", "node", "text")
    rows = hubs.unionByName(members).repartition("hub", "salt").sortWithinPartitions("hub", "salt", F.col("node").asc_nulls_first())
    return rows.select("hub", "salt", "node", "text").mapInArrow(_confirm, "a long, b long")


def _bands(classes: DataFrame, carry: list[str]) -> DataFrame:
    """A row for each class and band: ``bucket`` hashes the band's number and rows."""
    band = lambda i: F.xxhash64(i, F.substring(F.col("signature"), i * 4 * ROWS + 1, F.lit(4 * ROWS)))
    return classes.select(*carry, F.explode(F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), band)).alias("bucket"))


def _divided(rows: DataFrame, size: int) -> DataFrame:
    """Buckets of (bucket, node, component, signature) of at most ``size`` members: larger ones are divided by each band of their members.

    Pairs that agree in few bands are lost, so this is for the forest pass alone; what it leaves apart is looked at whole after it.
    """
    for _ in range(BANDS):
        counts = rows.groupBy("bucket").agg(F.count("*").alias("n"))
        large = counts.where(F.col("n") > size)
        if large.isEmpty():
            break
        # the band that made the bucket is the same for all its members and would divide nothing: such a copy is dropped
        parts = rows.join(large.select("bucket", "n"), "bucket")
        band = lambda i: F.xxhash64(F.col("bucket"), i, F.substring(F.col("signature"), i * 4 * ROWS + 1, F.lit(4 * ROWS)))
        parts = parts.select("n", "node", "component", "signature", F.explode(F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), band)).alias("bucket"))
        sizes = parts.groupBy("bucket").agg(F.count("*").alias("m"), F.min("component").alias("c0"), F.max("component").alias("c1"))
        sizes = sizes.where("m > 1 and c0 <> c1").select("bucket", "m")
        parts = parts.join(sizes, "bucket").where("m < n").select("bucket", "node", "component", "signature")
        rows = materialize(rows.join(large.select("bucket"), "bucket", "left_anti").unionByName(parts), "near-buckets")
    return rows


def _blocked(rows: DataFrame, size: int) -> DataFrame:
    """Rows of (bucket, node, component, signature, weight), each once for every task (x, y: two blocks of its bucket) that it is in, with its block.

    A bucket of at most ``size`` weight, which is 1 for a member and more for a long text, is one block.  In a larger one, components that fill a good part of a block have blocks of their
    own and the others are dealt whole.  Every two members of different components meet in exactly one task; two blocks that lie in one
    and the same component have none.  (Two blocks of equal hash are a block: larger, with nothing left out.)
    """
    whole = lambda d: d.select("bucket", "node", "component", "signature", *(F.lit(0).cast("long").alias(x) for x in ("x", "y", "block")))
    large = rows.groupBy("bucket").agg(F.sum("weight").alias("n")).where(F.col("n") > size).select("bucket")
    if large.isEmpty():
        return whole(rows)
    members = rows.join(large, "bucket", "left_semi")
    counts = members.groupBy("bucket", "component").agg(F.sum("weight").alias("own"))
    own = counts.where(F.col("own") * 4 >= size)
    rest = counts.where(F.col("own") * 4 < size).groupBy("bucket").agg(F.sum("own").alias("rest"))
    alone = F.xxhash64("component", F.pmod(F.xxhash64("node"), F.ceil(F.col("own") / size)))
    block = F.when(F.col("own").isNotNull(), alone).otherwise(F.pmod(F.xxhash64("component"), F.ceil(F.col("rest") / size)))
    placed = members.join(own, ["bucket", "component"], "left").join(rest, "bucket", "left").select("bucket", "node", "component", "signature", block.cast("long").alias("block"))
    blocks = placed.groupBy("bucket", "block").agg(F.min("component").alias("c0"), F.max("component").alias("c1"))
    blocks = materialize(blocks, "near-blocks")
    second = blocks.select("bucket", F.col("block").alias("y"), F.col("c0").alias("d0"), F.col("c1").alias("d1"))
    tasks = blocks.withColumnRenamed("block", "x").join(second, "bucket").where("x <= y and least(c0, d0) <> greatest(c1, d1)")
    tasks = tasks.select("bucket", "x", "y", F.explode(F.array_distinct(F.array("x", "y"))).alias("block"))
    cut = placed.join(tasks, ["bucket", "block"]).select("bucket", "node", "component", "signature", "x", "y", "block")
    return whole(rows.join(large, "bucket", "left_anti")).unionByName(cut)


def links(classes: DataFrame, texts_of, bucket: int = BUCKET) -> DataFrame:
    """Verified edges (a, b) that connect all classes (node, signature) which any candidate link connects.

    ``texts_of`` gives (node, text) for a table of nodes.
    """
    members = _bands(classes, ["node"])
    order = F.struct(F.xxhash64("node"), F.col("node"))
    shared = members.groupBy("bucket").agg(F.count("*").alias("n"), F.min(order)["node"].alias("hub")).where("n > 1")
    shared = materialize(shared, "near-shared")
    rows = materialize(members.join(shared, "bucket").select("bucket", "n", "hub", "node"), "near-members")
    pairs = rows.where("hub <> node").select("hub", "node").distinct()
    nodes = rows.select("node").distinct()
    signed = materialize(classes.select("node", "signature").join(nodes, "node"), "near-signatures")
    texts = materialize(texts_of(nodes), "near-texts")

    def confirmed(candidates: DataFrame) -> DataFrame:
        return materialize(verify(candidates, texts), "near-links")

    both = pairs.join(signed.select(F.col("node").alias("hub"), F.col("signature").alias("s1")), "hub").join(signed.withColumnRenamed("signature", "s2"), "node")
    edges = confirmed(materialize(both.select("hub", "node", "s1", "s2").mapInArrow(_prune, "hub long, node long"), "near-pairs"))
    # pairs with the hub have been decided; others are open where a bucket still spans components.  Most of those join by a few
    # very similar pairs, so a forest of these goes first, and every other pair is looked at for what is still apart then
    def still_open() -> DataFrame:
        open_rows = rows.where("n > 2 and hub <> node").join(components(edges), "node", "left").withColumn("component", F.coalesce("component", "node"))
        spans = open_rows.groupBy("bucket").agg(F.min("component").alias("c0"), F.max("component").alias("c1")).where("c0 <> c1")
        return open_rows.join(spans.select("bucket"), "bucket").select("bucket", "node", "component")

    left = materialize(still_open().join(signed, "node").select("bucket", "node", "component", "signature"), "near-open")
    left = _divided(left, bucket).repartition("bucket").sortWithinPartitions("bucket").select("bucket", "node", "component", "signature")
    more = materialize(left.mapInArrow(_forest(HASHES * PERCENT // 100), "hub long, node long").distinct(), "near-pairs")
    if not more.isEmpty():
        edges = edges.unionByName(confirmed(more))
    weights = texts.select("node", (F.ceil(F.octet_length("text") / TEXT_BYTES) + 1).alias("weight"))
    left = materialize(still_open().join(signed, "node").join(weights, "node").select("bucket", "node", "component", "signature", "weight"), "near-open")
    tasks = _blocked(left, bucket).repartition("bucket", "x", "y").sortWithinPartitions("bucket", "x", "y")
    likely_ = materialize(tasks.mapInArrow(_across, "bucket long, x long, y long, block long, node long, component long"), "near-likely")
    if not likely_.isEmpty():
        held = likely_.join(texts, "node").select("bucket", "x", "y", "block", "node", "component", "text")
        held = held.repartition("bucket", "x", "y").sortWithinPartitions("bucket", "x", "y")
        edges = edges.unionByName(materialize(held.mapInArrow(_exact, "a long, b long").distinct(), "near-links"))
    return edges


def near_duplicates(docs: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """doc_id, text_key, n_shingles, component_id and kept of every row."""
    sets = materialize(shingle_sets(docs), "near-sets")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "text_key"))
    classes = sets.where(F.col("set_key").isNotNull()).groupBy("set_key").agg(first.alias("first"), F.first("signature").alias("signature"))
    classes = materialize(classes.select("set_key", "first", "signature", F.monotonically_increasing_id().alias("node")), "near-classes")

    def texts_of(nodes: DataFrame) -> DataFrame:
        wanted = classes.join(nodes, "node").select("node", F.col("first.text_key").alias("text_key"))
        # the digest has every copy meet one row; one text for each node is taken
        found = docs.select(_text_key().alias("text_key"), F.coalesce("text", F.lit("")).alias("text")).join(wanted, "text_key")
        return found.groupBy("node").agg(F.first("text").alias("text"))

    edges = links(classes.select("node", "signature"), texts_of, bucket)
    parts = components(edges)
    known = classes.select("set_key", "first", "node").join(parts, "node", "left").withColumn("component", F.coalesce("component", "node"))
    smallest = known.groupBy("component").agg(F.min("first").alias("smallest"))
    decided = known.join(smallest, "component").select("set_key", "smallest")
    out = sets.select("doc_id", "text_key", "n_shingles", "set_key").join(decided, "set_key", "left")
    # of rows alike in doc_id and text one stays; rows with the empty set are linked with nothing
    own = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "text_key")
    alone = F.col("set_key").isNull()
    component = F.when(alone, F.col("doc_id")).otherwise(F.col("smallest.doc_id"))
    return out.select("doc_id", "text_key", "n_shingles", component.alias("component_id"), (alone | (own == F.col("smallest"))).alias("kept"))


def deduplicate(docs: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """The documents, all columns, that stay: one of each component."""
    from pyspark.sql import Window

    stay = near_duplicates(docs, bucket).where("kept").select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"), (F.col("n_shingles") > 0).alias("_one")).distinct()
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col("doc_id").cast("long").alias("doc_id"), _text_key().alias("text_key"))
    kept = rows.join(stay, (F.col("text_key") == F.col("_key")) & F.col("doc_id").eqNullSafe(F.col("_id")))
    again = Window.partitionBy("text_key", "doc_id").orderBy(F.lit(1))
    return kept.withColumn("nth", F.row_number().over(again)).where("nth = 1 or not _one").select("row.*")
