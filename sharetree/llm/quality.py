"""Quality classifier: a linear-chain conditional random field over the lines of a document.

Every line is labelled good or bad.  The score of a label is linear in the features of the line and of its two neighbours
(shares of byte classes, of words that repeat the word before, length, word shape, lines that come again in the document), plus a weight for each pair of neighbouring labels.  The
field is fitted on a bounded sample of labelled documents whose lines all carry the document's label; a document's score is
the mean, weighted by line length, of the marginal probability that its lines are good.

Features see the text alone.  ``MAX_FIT`` documents of each label are used for fitting, those with the smallest hash of their id
among rows with crc32(doc_id as text) mod ``FOLDS`` other than 0; everything else runs over all documents.

Defined cases: null and empty texts are one empty line, which the field scores like any other; a null doc_id is in no fold; equal texts get equal
scores; without any labelled rows the field is flat and all scores are 1/2; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sharetree.llm.storage import utf8

FOLDS, MAX_FIT, ROUNDS, L2 = 5, 1500, 200, 1e-3
#: Bytes of texts of one label that the fit reads.
MAX_FIT_BYTES = 1 << 25
THRESHOLD = 0.3

#: Byte classes: 0 other control, 1 lower, 2 upper, 3 digit, 4 space, 5 sentence marks, 6 quotes and hyphens, 7 bars and brackets, 8 other signs, 9 beyond ASCII (lead), 10 beyond ASCII (trail).
_CLASS = np.zeros(256, np.uint8)
for _chars, _k in ((b"abcdefghijklmnopqrstuvwxyz", 1), (b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", 2), (b"0123456789", 3), (b" \t\r", 4), (b".,;:?", 5), (b"'\"-", 6), (b"|[]{}()<>\\/=_~^", 7), (b"!#$%&*+@`", 8)):
    _CLASS[list(_chars)] = _k
_CLASS[192:256], _CLASS[128:192] = 9, 10
CLASSES = 11
#: Shares of a line: ten byte classes and words that repeat the word before.
SHARES = 11
#: Bytes of texts whose features are made at once.
BLOCK = 1 << 20
#: Steps that each share is also compared with, so that the linear field can bend.
STEPS = (0.0, 0.05, 0.2, 0.5)


def own_features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features of each line alone, without its neighbours (a row a line), the number of lines of each text, and the length of each line plus one."""
    split = [x.split(b"\n") for x in texts]
    counts = np.array([len(x) for x in split], np.int64)
    n = int(counts.sum())
    lengths = np.fromiter(map(len, (y for x in split for y in x)), np.int64, n)
    data = np.frombuffer(b"".join(y for x in split for y in x), np.uint8)
    line = np.repeat(np.arange(n, dtype=np.int64), lengths)
    by_class = np.bincount(line * CLASSES + _CLASS[data], minlength=n * CLASSES).reshape(n, CLASSES).astype(np.float64)
    chars = np.maximum(by_class.sum(1) - by_class[:, 10], 1)
    again, twice = np.zeros(n), np.zeros(n)
    at = 0
    for lines in split:
        for i, y in enumerate(lines, at):
            w = y.split()
            if len(w) > 1:
                twice[i] = sum(map(eq, w, w[1:])) / (len(w) - 1)
        if len(lines) > 1:
            seen: dict[bytes, int] = {}
            for y in lines:
                seen[y] = seen.get(y, 0) + 1
            if len(seen) < len(lines):
                again[at : at + len(lines)] = [seen[y] > 1 and len(y) > 0 for y in lines]
        at += len(lines)
    share = by_class[:, [1, 2, 3, 4, 5, 6, 7, 8, 0, 9]] / chars[:, None]
    words = by_class[:, 4] + 1
    shape = np.stack([np.log1p(chars) / 8, np.minimum(chars / words, 30) / 30, np.minimum(words, 100) / 100, by_class[:, 2] / words / 4, by_class[:, 8] / words, by_class[:, 7] / words, again, chars <= 1], 1)
    share = np.concatenate([share, twice[:, None]], 1)
    bent = np.concatenate([share > s for s in STEPS], 1)
    return np.concatenate([share, np.minimum(shape, 2), bent], 1), counts, lengths + 1


def line_features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features (a row a line), the number of lines of each text, and the length of each line plus one."""
    own, counts, lengths = own_features(texts)
    n = len(own)
    first = np.concatenate(([0], np.cumsum(counts)))[:-1]
    last = first + counts - 1
    before, after = np.roll(own, 1, 0), np.roll(own, -1, 0)
    before[first], after[last] = 0, 0
    edges = np.zeros((n, 2))
    edges[first, 0], edges[last, 1] = 1, 1
    return np.concatenate([np.ones((n, 1)), own, 0.5 * before, 0.5 * after, edges], 1), counts, lengths


class Lines:
    """The lines of texts for a fit: the features that ``line_features`` gives, as products with weights and residuals, kept in some 200 bytes a line.

    A line's own features are kept once, shares and shape as numbers and the comparisons as bits of a byte; those of its neighbours are the rows beside it.
    """

    def __init__(self, texts: list[bytes]):
        self.blocks: list[tuple[np.ndarray, np.ndarray]] = []
        counts, held, size = [], [], 0
        for i, x in enumerate(texts):
            held.append(x)
            size += len(x)
            if size > BLOCK or i == len(texts) - 1:
                own, some, _ = own_features(held)
                self.width, bits = own.shape[1], len(STEPS) * SHARES
                self.blocks.append((own[:, :-bits].copy(), own[:, -bits:].astype(bool)))
                counts.append(some)
                held, size = [], 0
        self.counts = np.concatenate(counts)
        self.first = np.concatenate(([0], np.cumsum(self.counts)))[:-1]
        self.last = self.first + self.counts - 1

    def _parts(self, weights: np.ndarray) -> tuple[float, list[np.ndarray], np.ndarray]:
        k = self.width
        return weights[0], [weights[1 : 1 + k], 0.5 * weights[1 + k : 1 + 2 * k], 0.5 * weights[1 + 2 * k : 1 + 3 * k]], weights[1 + 3 * k :]

    def scores(self, weights: np.ndarray) -> np.ndarray:
        """Weights times the features of each line."""
        base, ways, edges = self._parts(weights)
        own, before, after = (np.concatenate([np.einsum("ij,j->i", a, w[: a.shape[1]]) + np.einsum("ij,j->i", b, w[a.shape[1] :]) for a, b in self.blocks]) for w in ways)
        before, after = np.roll(before, 1), np.roll(after, -1)
        before[self.first], after[self.last] = 0, 0
        out = base + own + before + after
        out[self.first] += edges[0]
        out[self.last] += edges[1]
        return out

    def sums(self, residuals: np.ndarray) -> np.ndarray:
        """Residuals of the lines times their features: one number a feature."""
        before, after = residuals.copy(), residuals.copy()
        before[self.first], after[self.last] = 0, 0
        # the line before gives its features to this one's residual, so this one's residual goes to the line before
        out, at = [np.zeros(self.width) for _ in range(3)], 0
        ways = [residuals, 0.5 * np.roll(before, -1), 0.5 * np.roll(after, 1)]
        for a, b in self.blocks:
            for total, r in zip(out, ways):
                some = r[at : at + len(a)]
                total += np.concatenate((np.einsum("ij,i->j", a, some), np.einsum("ij,i->j", b, some)))
            at += len(a)
        return np.concatenate([[residuals.sum()], *out, [residuals[self.first].sum(), residuals[self.last].sum()]])


@dataclass
class Field:
    """Weights: of the features for label good against bad, and of pairs of neighbouring labels."""

    weights: np.ndarray
    pairs: np.ndarray

    def marginals(self, x: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """Probability that each line is good, expected counts of label pairs, and the sum of the log partition functions."""
        return self.chains(np.einsum("ij,j->i", x, self.weights), counts)  # not BLAS: its threads would fight the other tasks'

    def chains(self, of_good: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """``marginals`` from the score that each line gives to label good."""
        score = np.zeros((len(of_good), 2))
        score[:, 1] = of_good
        order = np.argsort(-counts, kind="stable")
        lengths = counts[order]
        first = (np.concatenate(([0], np.cumsum(counts)))[:-1])[order]
        top = int(lengths[0])
        active = [int(k) for k in np.searchsorted(-lengths, -np.arange(1, top + 1), side="right")]
        forward, backward, pairs = np.zeros_like(score), np.zeros_like(score), self.pairs
        a = score[first]
        forward[first] = a
        for t in range(1, top):
            k = active[t]
            at = first[:k] + t
            a = np.logaddexp(a[:k, 0, None] + pairs[0], a[:k, 1, None] + pairs[1]) + score[at]
            forward[at] = a
        z = np.logaddexp(*forward[first + lengths - 1].T)
        expected = np.zeros((2, 2))
        for t in range(top - 1, 0, -1):
            k = active[t]
            at = first[:k] + t
            b = backward[at] + score[at]
            joint = forward[at - 1][:, :, None] + pairs[None] + b[:, None, :] - z[:k, None, None]
            expected += np.exp(joint).sum(0)
            backward[at - 1] = np.logaddexp(b[:, 0, None] + pairs[:, 0], b[:, 1, None] + pairs[:, 1])
        each = np.empty(len(counts))
        each[order] = z
        good = np.exp(np.minimum(0.0, forward[:, 1] + backward[:, 1] - np.repeat(each, counts)))
        return good, expected, float(z.sum())

    def scores(self, texts: list[bytes]) -> np.ndarray:
        if not texts:
            return np.zeros(0)
        x, counts, lengths = line_features(texts)
        good, _, _ = self.marginals(x, counts)
        first = np.concatenate(([0], np.cumsum(counts)))[:-1]
        return np.clip(np.add.reduceat(good * lengths, first) / np.add.reduceat(lengths, first), 0.0, 1.0)


def fit(texts: list[bytes], labels: list[int], rounds: int = ROUNDS) -> Field:
    """Maximum likelihood with an L2 penalty, each label with the same total weight of documents, by adaptive gradient steps."""
    field = Field(np.zeros(line_features([b""])[0].shape[1]), np.zeros((2, 2)))
    if len(set(labels)) < 2:
        return field
    # a long document must not outweigh the others: documents of one label and weight form a group of the gradient
    groups = [[x for x, y in zip(texts, labels) if y == v] for v in (0, 1)]
    parts = [(Lines(own), float(v), 0.5 / max(1, len(own))) for v, own in enumerate(groups)]
    m = [np.zeros_like(field.weights), np.zeros((2, 2))]
    s = [np.zeros_like(field.weights), np.zeros((2, 2))]
    for i in range(1, rounds + 1):
        g, h = L2 * field.weights, L2 * field.pairs
        for lines, v, weight in parts:
            pc = lines.counts
            good, expected, _ = field.chains(lines.scores(field.weights), pc)
            per_line = weight / np.repeat(pc, pc)
            g = g - lines.sums((v - good) * per_line)
            seen = np.zeros((2, 2))
            seen[int(v), int(v)] = (pc - 1).sum()
            h = h - (seen - expected) * weight / max(1.0, pc.mean())
        for k, (value, grad) in enumerate(((field.weights, g), (field.pairs, h))):
            m[k] = 0.9 * m[k] + 0.1 * grad
            s[k] = 0.99 * s[k] + 0.01 * grad**2
            value -= 0.1 * (m[k] / (1 - 0.9**i)) / (np.sqrt(s[k] / (1 - 0.99**i)) + 1e-6)
        np.clip(field.pairs, -3, 3, out=field.pairs)
    return field


def fold(doc_id: str | Column) -> Column:
    return F.crc32(F.col(doc_id).cast("string") if isinstance(doc_id, str) else doc_id.cast("string")) % FOLDS


def fit_from(docs: DataFrame, labels: DataFrame, max_fit: int = MAX_FIT, max_bytes: int = MAX_FIT_BYTES) -> Field:
    """Fit on at most ``max_fit`` documents of each label, none of them held out, and of those on the first, in a hashed order, that have ``max_bytes`` together."""
    usable = labels.where(F.col("quality").isin(0, 1) & (fold("doc_id") != 0)).select("doc_id", "quality").distinct()
    some = [usable.where(F.col("quality") == v).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_fit) for v in (0, 1)]
    picked = some[0].unionByName(some[1])  # 2 * max_fit short rows
    order = [F.xxhash64("doc_id"), F.col("doc_id"), F.md5("text")]
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id")
    # ids may repeat: the window is over no more rows than ids were picked
    rows = reduce(DataFrame.unionByName, (rows.where(F.col("quality") == v).orderBy(*order).limit(max_fit) for v in (0, 1)))
    size = F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + 8).over(Window.partitionBy("quality").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    rows = rows.withColumn("size", size).where(F.col("size") <= max_bytes).orderBy("doc_id", "quality", "text").select("quality", utf8("text").alias("text")).collect()
    return fit([bytes(r["text"]) for r in rows], [r["quality"] for r in rows])


def _scorer(field: Field):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(0)
            scores = [np.zeros(0)]
            held: list[bytes] = []
            size = 0
            for x in texts.to_pylist():
                held.append((x or "").encode())
                size += len(held[-1])
                if size > BLOCK:  # bounds what the feature table takes
                    scores.append(field.scores(held))
                    held, size = [], 0
            scores.append(field.scores(held))
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(np.concatenate(scores))], names=[*batch.schema.names[1:], "score"])

    return run


def score(docs: DataFrame, field: Field) -> DataFrame:
    """doc_id, held_out, score and predicted of every document."""
    slim = docs.select(F.coalesce("text", F.lit("")).alias("text"), F.col("doc_id").cast("long").alias("doc_id"))
    scored = slim.mapInArrow(_scorer(field), "doc_id long, score double")
    return scored.select("doc_id", F.coalesce(fold("doc_id") == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, field: Field, threshold: float = THRESHOLD) -> DataFrame:
    """The documents, all columns, that score at least ``threshold``."""
    carried = docs.select(F.coalesce("text", F.lit("")).alias("__scored"), F.struct(*docs.columns).alias("row"))
    from pyspark.sql.types import DoubleType, StructField, StructType

    schema = StructType([carried.schema["row"], StructField("score", DoubleType())])
    return carried.mapInArrow(_scorer(field), schema).where(F.col("score") >= threshold).select("row.*")
