"""Names of subtrees and of sibling lists, for whole batches of trees at once, over arrays.

A name has two words of 64 bits, which don't depend on each other.  A label's is the sum of its bytes, each mixed with its place; an element's mixes its label's
and its child list's; a list's is the sum of its members', each mixed with its place from the end, so that all tails of a list come from one running sum.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

# Odd multipliers, one for each word.
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))
_PLACE = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F))
_LIST = (np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F))
#: Bits of a kept name's second word that hold a tail's flags.
GOES_ON, HAS_KIDS = np.uint32(2), np.uint32(1)


def _mixed(x: np.ndarray) -> np.ndarray:
    """A one-to-one scrambling of words; ``x`` is overwritten."""
    x ^= x >> np.uint64(30)
    x *= _MIX[0]
    x ^= x >> np.uint64(27)
    x *= _MIX[1]
    x ^= x >> np.uint64(31)
    return x


def _labels(labels: pa.Array) -> list[np.ndarray]:
    """The words of each label: sums over its bytes, each mixed with its place; null is a label of its own."""
    coded = labels.dictionary_encode()
    texts = coded.dictionary.cast(pa.large_string())
    _, offsets, data = texts.buffers()
    ends = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    own = np.frombuffer(data, np.uint8)[ends[0] : ends[-1]] if data and ends[-1] else np.zeros(0, np.uint8)
    sizes = np.diff(ends)
    place = np.arange(len(own)) - np.repeat(ends[:-1] - ends[0], sizes)
    placed = ((place + 1) * 256 + own).astype(np.uint64)
    at = pc.fill_null(coded.indices, len(texts)).to_numpy()
    out = []
    for by_place, by_list in zip(_PLACE, _LIST):
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_mixed(placed * by_place))])
        named = _mixed(sums[ends[1:] - ends[0]] - sums[ends[:-1] - ends[0]] + by_list)
        out.append(np.append(named, by_place)[at])
    return out


def pieces(labels: pa.Array, depths: np.ndarray, lengths: np.ndarray) -> tuple[tuple[np.ndarray, ...], tuple[np.ndarray, ...]]:
    """Names of what has edges in trees that follow one another in pre-order, ``lengths`` nodes each.

    The tails of child lists and of the trees' roots (first word, second word with flags), and the elements with children (words, number of children).  A
    name may occur several times.  The second word is cut to 32 bits, of which a tail's flags take two: 96 bits tell names apart.
    """
    at = np.arange(len(depths), dtype=np.int64)
    starts = np.cumsum(lengths)[lengths > 0] - lengths[lengths > 0]
    depths = depths.astype(np.int64)
    depths[starts] = 0
    depths = np.minimum.accumulate(depths - at) + at  # a node is at most one deeper than the one before, as in ``grammar.from_tree``
    most = int(depths.max(initial=0))
    order = np.argsort(depths.astype(np.uint16) if most < 1 << 16 else depths, kind="stable")
    ends = np.cumsum(np.bincount(depths, minlength=1))
    words = _labels(labels)
    tails: list[tuple[np.ndarray, ...]] = []
    elements: list[tuple[np.ndarray, ...]] = []
    of_list: list[np.ndarray] | None = None  # of each node of this level: its child list's words
    number = np.zeros(0, np.int32)
    for level in reversed(range(most + 1 if len(at) else 0)):
        own = order[ends[level - 1] if level else 0 : ends[level]]
        above = order[ends[level - 2] if level > 1 else 0 : ends[level - 1]] if level else starts
        if of_list is None:
            of_list, number = [np.zeros(len(own), np.uint64) for _ in words], np.zeros(len(own), np.int32)
        parent = np.searchsorted(above, own, "right") - 1
        heads = np.flatnonzero(np.concatenate([[True], parent[1:] != parent[:-1]]))
        sizes = np.diff(heads, append=len(own))
        stop = np.repeat(heads + sizes, sizes)
        place = (stop - np.arange(len(own))).astype(np.uint64)  # from the end: the last is 1
        kids = number > 0
        element, tail = [], []
        for w, of, by_list, by_place in zip(words, of_list, _LIST, _PLACE):
            element.append(_mixed(w[own] + of * by_list))
            sums = np.concatenate([np.cumsum(_mixed(element[-1] + place * by_place)[::-1])[::-1], np.zeros(1, np.uint64)])
            tail.append(sums[:-1] - sums[stop])
        flags = (place > 1) * GOES_ON + kids * HAS_KIDS
        some = flags > 0
        tails.append((tail[0][some], ((tail[1][some] >> np.uint64(32)).astype(np.uint32) & ~(GOES_ON | HAS_KIDS)) | flags[some]))
        elements.append((element[0][kids], (element[1][kids] >> np.uint64(32)).astype(np.uint32), number[kids]))
        of_list, number = [np.zeros(len(above), np.uint64) for _ in words], np.zeros(len(above), np.int32)
        for of, x in zip(of_list, tail):
            of[parent[heads]] = x[heads]
        number[parent[heads]] = sizes
    joined = lambda rows, kinds: tuple(np.concatenate([np.zeros(0, k), *(r[i] for r in rows)]) for i, k in enumerate(kinds))
    return joined(tails, (np.uint64, np.uint32)), joined(elements, (np.uint64, np.uint32, np.int32))


def distinct(first: np.ndarray, second: np.ndarray, *more: np.ndarray) -> tuple[np.ndarray, ...]:
    """Each name once, in order of the first word, with what is known of it."""
    order = np.argsort(first)
    a, b = first[order], second[order]
    same = a[1:] == a[:-1]
    if (same & (b[1:] != b[:-1])).any():
        order = np.lexsort((second, first))
        a, b = first[order], second[order]
        same = a[1:] == a[:-1]
    keep = np.concatenate([np.ones(min(1, len(a)), bool), ~(same & (b[1:] == b[:-1]))])
    return a[keep], b[keep], *(x[order[keep]] for x in more)
