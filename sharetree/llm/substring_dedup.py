"""Exact substring deduplication of whole texts: repeated byte strings, and repeated word windows.

``repeated_bytes`` is a sparse suffix array: the suffixes that start at shared anchors (see ``anchors``) are sorted deep-shallow
(see ``suffix_sort``), anchor by anchor, both the bytes that follow and, backwards, those that come before; what neighbours share on both
sides together is a repeated string when it has ``LENGTH`` bytes.  All its places lose it.

``repeated_words`` confirms passages in the same way, with documents in the order of doc_id, then compiles them into
Aho-Corasick automata, one after the other for each shard of anchors, and runs all stretches of documents that can hold the shard's passages through them:
the first run finds each passage's first document, the second takes every occurrence in later ones.

Only stretches around shared anchors leave their document.  An anchor with more than ``GROUP`` places is divided before it is sorted
(``_divided``): the windows that it is the anchor of are cut into halves by their offset, again and again, and its stretches dealt by what all windows of a
half have in common; stretches that are equal in a whole half are settled there and one of them goes on.  Each part is sorted, or
run through automata, like a small anchor.

Defined cases: null and empty texts lose nothing; texts shorter than a window lose nothing; copies of a text are judged as separate
documents (rows with equal doc_id too, save that for words only a smaller doc_id counts); a null doc_id comes after all others; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from array import array
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sharetree.llm.anchors import GROUP, LAST, anchors, distinct_texts, shared_anchors, text_key
from sharetree.llm.rolling import windows_hash, word_hashes
from sharetree.llm.storage import join_counted, materialize
from sharetree.llm.suffix_sort import extents

#: Bytes of a repeated string, and of the part that anchors hash.
LENGTH, SEED_BYTES = 400, 64
#: Words of a repeated window, and of the part that anchors hash.
WORDS, SEED_WORDS = 50, 10
#: Characters of passages that one automaton holds.
AUTOMATON_CHARS = 200_000
SPANS = "text_key binary, start int, stop int"
#: Bytes of stretches that wait for one automaton.
HELD_BYTES = 32_000_000
#: A stretch around an anchor: ``places`` are the anchor's positions in the text, ``before`` the units before it.
STRETCHES = "anchor long, large boolean, text_key binary, doc long, places array<int>, before int, stretch binary"
_STRETCH_NAMES = [c.split()[0] for c in STRETCHES.split(", ")]
_STRETCH_KINDS = [pa.int64(), pa.bool_(), pa.binary(), pa.int64(), pa.list_(pa.int32()), pa.int32(), pa.binary()]
_SORTED = ["anchor", "text_key", "doc", "places", "before", "stretch"]
#: A part of a large anchor: the windows that begin ``least`` to ``most`` units before it, where stretches agree in all that these have in common.
PARTS = "anchor long, least int, most int, text_key binary, doc long, places array<int>, before int, stretch binary, size int, kind binary"
_PART_NAMES = [c.split()[0] for c in PARTS.split(", ")]
_PART_KINDS = [pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.int64(), pa.list_(pa.int32()), pa.int32(), pa.binary(), pa.int32(), pa.binary()]


def byte_anchors(length: int = LENGTH, seed: int = SEED_BYTES):
    def find(text: bytes) -> tuple[np.ndarray, np.ndarray]:
        hashes = windows_hash(np.frombuffer(text, np.uint8), seed)
        at = anchors(hashes, length - seed + 1)
        return hashes[at], at

    return find


def word_anchors(length: int = WORDS, seed: int = SEED_WORDS):
    def find(text: bytes) -> tuple[np.ndarray, np.ndarray]:
        words = word_hashes(np.frombuffer(text, np.uint8))
        if len(words) < length:
            return words[:0], np.zeros(0, np.int64)
        # a window of words is hashed by the powers of its places
        n = len(words) - seed + 1
        total = np.zeros(n, np.uint64)
        for i in range(seed):
            total = (total * np.uint64(0x9FB21C651E98DF25)) + words[i : i + n]
        total ^= total >> np.uint64(29)
        total *= np.uint64(0xBF58476D1CE4E5B9)
        total ^= total >> np.uint64(32)
        at = anchors(total, length - seed + 1)
        return total[at], at

    return find


def _cut(words: bool, length: int, seed: int):
    """Stretches of (text_key, text, first, copies, spots)."""
    reach = length - seed

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 200):
                rows: dict[tuple, list[int]] = {}
                for key, text, doc, _, spots in zip(*(c.to_pylist() for c in batch.slice(a, 200).columns)):
                    if not spots:
                        continue
                    data = text.encode()
                    units = data.split() if words else data
                    for spot in spots:
                        at = spot["at"]
                        before = min(at, reach)
                        part = units[at - before : at + length]
                        rows.setdefault((spot["anchor"], spot["large"], key, doc, before, b" ".join(part) if words else part), []).append(at)
                yield _batch([(h, g, k, d, p, b, s) for (h, g, k, d, b, s), p in rows.items()], _STRETCH_KINDS, _STRETCH_NAMES)

    return run


def _batch(rows: list[tuple], kinds: list[pa.DataType], names: list[str]) -> pa.RecordBatch:
    columns = list(zip(*rows)) or [[]] * len(kinds)
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)


def _by_anchor(batches: Iterator[pa.RecordBatch]) -> Iterator[list[list]]:
    """The columns of each anchor's rows, without the anchor; they come sorted by it."""
    last, held = None, []
    for batch in (b.slice(a, 2000) for b in batches for a in range(0, b.num_rows, 2000)):
        at, columns = batch.column(0).to_numpy(), [c.to_pylist() for c in batch.columns[1:]]
        cuts = [0, *(np.flatnonzero(at[1:] != at[:-1]) + 1).tolist(), len(at)]
        for a, b in zip(cuts, cuts[1:]):
            if held and at[a] == last:
                for have, column in zip(held, columns):
                    have += column[a:b]
            else:
                if held:
                    yield held
                last, held = at[a], [c[a:b] for c in columns]
    if held:
        yield held


def _kinds(stretches: list[bytes], befores: list[int]) -> dict[tuple[bytes, int], list[int]]:
    """The rows of each different stretch."""
    out: dict[tuple[bytes, int], list[int]] = {}
    for i, kind in enumerate(zip(stretches, befores)):
        out.setdefault(kind, []).append(i)
    return out


def _span_batch(spans: list[tuple[bytes, int, int]]) -> pa.RecordBatch:
    return _batch(spans, [pa.binary(), pa.int32(), pa.int32()], ["text_key", "start", "stop"])


def _repeated(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spans: list[tuple[bytes, int, int]] = []
        for keys, _, places, befores, stretches in _by_anchor(batches):
            kinds = _kinds(stretches, befores)
            found = extents([s[:b][::-1] for s, b in kinds], [s[b:] for s, b in kinds], None, 1, length) if len(kinds) > 1 else [[]]
            for ((s, b), members), pairs in zip(kinds.items(), found):
                if len(s) >= length and (len(members) > 1 or len(places[members[0]]) > 1):  # the whole stretch stands at two places
                    pairs = [(b, len(s) - b)]
                spans += [(keys[m], at - l, at + r) for m in members for at in places[m] for l, r in pairs]
            if len(spans) > 20_000:
                yield _span_batch(spans)
                spans = []
        yield _span_batch(spans)

    return run


class _Kind:
    """A different stretch of an anchor, with the rows that have it: (doc, text_key, places)."""

    __slots__ = ("stretch", "before", "rows", "first")

    def __init__(self, stretch: bytes, before: int, rows: list[tuple]):
        self.stretch, self.before, self.rows, self.first = stretch, before, rows, min(r[0] for r in rows)


def _passages(length: int, automaton_chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: list[_Kind] = []
        shard: list[str] = []
        chars = held = 0
        for keys, docs, places, befores, stretches in _by_anchor(batches):
            kinds = [_Kind(*kind, [(docs[i], keys[i], places[i]) for i in rows]) for kind, rows in _kinds(stretches, befores).items()]
            passages = sorted(_confirmed(kinds, length))
            own, size = sum(map(len, passages)), sum(len(k.stretch) for k in kinds)
            if not passages:
                continue
            if shard and (chars + own > automaton_chars or held + size > HELD_BYTES):
                yield _span_batch(_occurrences(waiting, shard))
                waiting, shard, chars, held = [], [], 0, 0
            if own > automaton_chars:  # one anchor's passages in several automata, each of which sees all its stretches
                step = max(1, len(passages) * automaton_chars // own)
                for a in range(0, len(passages), step):
                    yield _span_batch(_occurrences(kinds, passages[a : a + step]))
            else:
                waiting += kinds
                shard += passages
                chars, held = chars + own, held + size
        yield _span_batch(_occurrences(waiting, shard) if shard else [])

    return run


def _confirmed(kinds: list[_Kind], length: int) -> set[str]:
    """The passages of at least ``length`` words around the anchor that a stretch shares with one of a smaller doc_id."""
    words = [k.stretch.split(b" ") for k in kinds]
    out = set()
    if len(kinds) > 1:
        if len(kinds) == 2:
            unit, parts = 1, words
        else:
            unit, parts = 8, [word_hashes(np.frombuffer(k.stretch, np.uint8)) for k in kinds]
        lefts, rights = [p[: k.before][::-1] for p, k in zip(parts, kinds)], [p[k.before :] for p, k in zip(parts, kinds)]
        if unit == 8:
            lefts, rights = [x.astype(">u8").tobytes() for x in lefts], [x.astype(">u8").tobytes() for x in rights]
        for k, w, pairs in zip(kinds, words, extents(lefts, rights, [k.first for k in kinds], unit, length)):
            out |= {b" ".join([b"", *w[k.before - l : k.before + r], b""]).decode() for l, r in pairs}
    # a stretch that a second document has is a passage as a whole
    return out | {f" {k.stretch.decode()} " for k, w in zip(kinds, words) if len(w) >= length and len(k.rows) > 1 and max(k.rows)[0] > k.first}


def _occurrences(kinds: list[_Kind], passages: list[str]) -> list[tuple[bytes, int, int]]:
    """Places of the passages in documents after each passage's first, by Aho-Corasick over all the different stretches."""
    import ahocorasick

    automaton, passages = ahocorasick.Automaton(), list(dict.fromkeys(passages))
    for i, p in enumerate(passages):
        automaton.add_word(p, i)
    automaton.make_automaton()
    sizes, words = [len(p) for p in passages], [p.count(" ") - 1 for p in passages]
    first, hits = [LAST] * len(passages), []
    for k in kinds:
        found = array("i")
        for end, i in automaton.iter(f" {k.stretch.decode()} "):
            found.append(end - sizes[i] + 1)
            found.append(i)
            if k.first < first[i]:
                first[i] = k.first
        hits.append(found)
    out = []
    for k, found in zip(kinds, hits):
        if not found:
            continue
        word = np.cumsum(np.frombuffer(f" {k.stretch.decode()} ".encode("utf-32-le"), "<u4") == 32) - 1 - k.before
        spots = [(int(word[at]), int(word[at]) + words[i], first[i]) for at, i in zip(found[::2], found[1::2])]
        earlier = merge([(a, b) for a, b, doc in spots if doc < k.first])
        later = merge([(a, b) for a, b, _ in spots])
        for doc, key, places in k.rows:
            out += [(key, at + a, at + b) for at in places for a, b in (later if doc > k.first else earlier)]
    return out


def _halves(words: bool, length: int, divide: bool):
    """The rows of both halves of each row's offsets (or of all of them, as a first step), cut to what the windows of the half can hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(a, 1000) for b in batches for a in range(0, b.num_rows, 1000)):
            rows = []
            for anchor, low, high, key, doc, places, before, stretch in zip(*(c.to_pylist() for c in batch.columns)):
                units = stretch.split(b" ") if words else stretch
                mid = (low + high) // 2
                for least, most in ((low, mid), (mid + 1, high)) if divide else ((low, high),):
                    left, right = min(before, most), min(len(units) - before, length - least)
                    if least > most or left + right < length:  # no window of the half lies in the stretch
                        continue
                    part, common = units[before - left : before + right], units[before - least : before + length - most]
                    if words:
                        part, common = b" ".join(part), b" ".join(common)
                    name = hashlib.blake2b(b"%d %d %d " % (anchor, least, most) + common, digest_size=8).digest()
                    kind = hashlib.blake2b(b"%d " % left + part, digest_size=16).digest()
                    rows.append((int.from_bytes(name, "little", signed=True) if divide else anchor, least, most, key, doc, places, left, part, left + right, kind))
            yield _batch(rows, _PART_KINDS, _PART_NAMES)

    return run


def _divided(large: DataFrame, words: bool, length: int, reach: int, group: int) -> tuple[DataFrame, DataFrame]:
    """Stretches of large anchors as parts of at most ``group`` different ones, and the spans that were settled on the way.

    Each step halves the offsets of a part that is still larger; a part of one offset has one kind of stretch, so the steps are logarithmic in ``reach``.
    Stretches equal over a whole part share all its windows: all of them (for words: those after the first document) lose the
    stretch, and one goes on to meet the others.
    """
    rows = large.select("anchor", F.lit(0).alias("least"), F.lit(reach).alias("most"), "text_key", "doc", "places", "before", "stretch")
    ready, settled, divide = [], [], False
    while True:
        cut = materialize(rows.mapInArrow(_halves(words, length, divide), PARTS), "anchor-parts")
        place = F.struct("text_key", F.element_at("places", 1).alias("at"))
        kinds = cut.groupBy("anchor", "kind").agg(F.count("*").alias("members"), F.sum(F.size("places")).alias("n"), F.min("doc").alias("first"), F.min(place).alias("chosen"))
        kinds, total = materialize(kinds, "anchor-part-kinds"), cut.count()
        parts = materialize(kinds.groupBy("anchor").agg(F.count("*").alias("kinds"), F.sum("members").alias("members")), "anchor-part-sizes")
        known = join_counted(cut, kinds, ["anchor", "kind"], "members", total).drop("members")
        known = materialize(known.withColumns({"lost": F.col("doc") > F.col("first") if words else F.col("n") > 1, "goes_on": F.col("doc") == F.col("first") if words else place == F.col("chosen")}), "anchor-kinds")
        start = F.explode(F.transform("places", lambda at: at - F.col("before")))
        settled.append(known.where("lost").select("text_key", start.alias("start"), "size").select("text_key", "start", (F.col("start") + F.col("size")).alias("stop")))
        rest = join_counted(known.where("goes_on"), parts.where("kinds > 1"), ["anchor"], "members", total).select("anchor", "least", "most", "text_key", "doc", "places", "before", "stretch", "kinds")
        ready.append(rest.where(F.col("kinds") <= group).select(*_SORTED))
        rows = rest.where(F.col("kinds") > group).drop("kinds")
        if rows.isEmpty():
            return reduce(DataFrame.unionByName, ready), reduce(DataFrame.unionByName, settled)
        divide = True


def _spans(docs: DataFrame, words: bool, length: int, seed: int, group: int, automaton_chars: int) -> DataFrame:
    """Spans (in units) to remove from each distinct text, and the texts themselves."""
    find = word_anchors(length, seed) if words else byte_anchors(length, seed)
    texts = distinct_texts(docs)
    spots = shared_anchors(docs, find, 2 * length - 1 if words else length, not words, group)
    stretches = materialize(texts.join(spots, "text_key", "left").mapInArrow(_cut(words, length, seed), STRETCHES), "stretches")
    sort = _passages(length, automaton_chars) if words else _repeated(length)
    rows, settled = stretches.where("not large").select(*_SORTED), None
    if not stretches.where("large").isEmpty():
        parts, settled = _divided(stretches.where("large"), words, length, length - seed, group)
        rows = rows.unionByName(parts)
    spans = rows.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(sort, SPANS)
    if settled is not None:
        spans = spans.unionByName(settled)
    merged = spans.groupBy("text_key").agg(F.collect_set(F.struct("start", "stop")).alias("spans"))
    return texts.join(merged, "text_key", "left")


def merge(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Maximal runs that the spans cover."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _kept(units, runs: list[tuple[int, int]]) -> list:
    out, at = [], 0
    for a, b in runs:
        out.append(units[at:a])
        at = b
    out.append(units[at:])
    return out


def _judge(words: bool, length: int, digest: bool):
    """What is left of each text: for its first document and for the other ones that have it."""
    names = ["text_key", "first", "n_units", "n_removed", "n_spans", "kept", "all_removed", "all_kept"]
    kinds = [pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_(), pa.string()]
    show = (lambda x: hashlib.sha256(x).hexdigest()) if digest else (lambda x: x.decode("utf-8", "replace"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(a, 500) for b in batches for a in range(0, b.num_rows, 500)):
            rows = []
            for key, text, first, copies, spans in zip(*(c.to_pylist() for c in batch.columns)):
                data = text.encode()
                units = data.split() if words else data
                n = len(units)
                runs = merge([(s["start"], s["stop"]) for s in spans or ()])
                whole = copies > 1 and n >= length
                if whole and not words:
                    runs = [(0, n)]
                parts = _kept(units, runs)
                kept = b" ".join(w for p in parts for w in p) if words else b"".join(parts)
                rest = b"" if whole else b" ".join(units) if words else data
                rows.append((key, first, n, sum(b - a for a, b in runs), len(runs), show(kept), whole, show(rest) if copies > 1 else None))
            yield _batch(rows, kinds, names)

    schema = "text_key binary, first long, n_units long, n_removed long, n_spans long, kept string, all_removed boolean, all_kept string"
    return lambda df: df.mapInArrow(run, schema)


def _answers(docs: DataFrame, words: bool, length: int, seed: int, group: int, automaton_chars: int, digest: bool) -> DataFrame:
    judged = _judge(words, length, digest)(_spans(docs, words, length, seed, group, automaton_chars).select("text_key", "text", "first", "copies", "spans"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("text_key"))
    out = rows.join(judged, "text_key")
    if not words:
        return out
    later = F.coalesce("doc_id", F.lit(LAST)) > F.col("first")
    return out.withColumn("n_removed", F.when(later, F.when(F.col("all_removed"), F.col("n_units")).otherwise(0)).otherwise(F.col("n_removed"))).withColumn("kept", F.when(later, F.col("all_kept")).otherwise(F.col("kept")))


def repeated_bytes(docs: DataFrame, length: int = LENGTH, seed: int = SEED_BYTES, group: int = GROUP, digest: bool = True) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256 (or ``kept``, the text) of every document."""
    out = _answers(docs, False, length, seed, group, 0, digest)
    return out.select("doc_id", F.col("n_units").alias("n_bytes"), "n_removed", "n_spans", F.col("kept").alias("kept_sha256" if digest else "kept"))


def repeated_words(docs: DataFrame, length: int = WORDS, seed: int = SEED_WORDS, group: int = GROUP, automaton_chars: int = AUTOMATON_CHARS, digest: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed and kept_sha256 (or ``kept``, the text) of every document."""
    out = _answers(docs, True, length, seed, group, automaton_chars, digest)
    return out.select("doc_id", F.col("n_units").alias("n_words"), "n_removed", F.col("kept").alias("kept_sha256" if digest else "kept"))


