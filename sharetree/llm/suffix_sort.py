"""Deep-shallow sorting of byte strings, and what neighbours in the sorted order share.

Multikey quicksort on eight bytes at a time orders strings down to a shallow depth.  Strings that are still together there are ordered by
a blind trie: it is entered by one byte for each node, the one leaf that is met is compared in full, and the common
prefix found tells where the new string branches off, so a long common prefix is compared once for each string, not once for each level.
"""

from __future__ import annotations

from bisect import bisect_left, insort

#: Depth (bytes) down to which multikey quicksort works, and bytes that it takes at once.
SHALLOW, STEP = 96, 8


def common_prefix(a: bytes, b: bytes, start: int = 0) -> int:
    """Length of the longest common prefix; the first ``start`` bytes are known to agree."""
    n = min(len(a), len(b))
    if a[start:n] == b[start:n]:
        return n
    low, high = start, n  # the prefixes of length low agree, those of length high don't
    while high - low > 1:
        mid = (low + high) // 2
        if a[low:mid] == b[low:mid]:
            low = mid
        else:
            high = mid
    return low


class _Node:
    __slots__ = ("depth", "children")

    def __init__(self, depth: int):
        self.depth = depth
        #: By the byte at ``depth`` (-1: the string ends there); a leaf is the list of the positions of equal strings.
        self.children: dict[int, _Node | list[int]] = {}


def _byte(s: bytes, i: int) -> int:
    return s[i] if i < len(s) else -1


def blind_trie(strings: list[bytes], some: list[int], depth: int) -> _Node | list[int]:
    """The trie of the given strings, which agree in their first ``depth`` bytes."""
    root: _Node | list[int] = [some[0]]
    for i in some[1:]:
        s, node = strings[i], root
        while isinstance(node, _Node):
            node = node.children.get(_byte(s, node.depth)) or next(iter(node.children.values()))
        other = strings[node[0]]
        shared = common_prefix(s, other, depth)
        if shared == len(s) == len(other):
            node.append(i)
            continue
        parent, node = None, root
        while isinstance(node, _Node) and node.depth < shared:
            parent, node = node, node.children[_byte(s, node.depth)]
        if isinstance(node, _Node) and node.depth == shared:
            node.children[_byte(s, shared)] = [i]
            continue
        branch = _Node(shared)
        branch.children[_byte(other, shared)] = node
        branch.children[_byte(s, shared)] = [i]
        if parent is None:
            root = branch
        else:
            parent.children[_byte(s, parent.depth)] = branch
    return root


def _emit(root: _Node | list[int], depth: int, order: list[int], shared: list[int], strings: list[bytes]) -> None:
    """Append a trie's leaves in order; ``depth``: what the first of them shares with the one before."""
    stack: list[tuple[_Node | list[int], int]] = [(root, depth)]
    while stack:
        node, lead = stack.pop()
        if isinstance(node, list):
            order.append(node[0])
            shared.append(lead)
            for i in node[1:]:
                order.append(i)
                shared.append(len(strings[i]))
        else:
            keys = sorted(node.children)
            stack += [(node.children[k], node.depth if j else lead) for j, k in reversed(list(enumerate(keys)))]


def deep_shallow(strings: list[bytes], shallow: int = SHALLOW) -> tuple[list[int], list[int]]:
    """The order of the strings, and for each place the common prefix with the place before (0 at the first)."""
    order: list[int] = []
    shared: list[int] = []
    # (members, agreed depth, common prefix of the group's first string with what stands before)
    stack: list[tuple[list[int], int]] = [(list(range(len(strings))), 0)] if strings else []
    while stack:
        some, depth = stack.pop()
        lead = common_prefix(strings[order[-1]], strings[some[0]]) if order else 0
        if len(some) == 1:
            order.append(some[0])
            shared.append(lead)
        elif depth >= shallow:
            root = blind_trie(strings, some, depth)
            at = len(order)
            _emit(root, 0, order, shared, strings)
            shared[at] = common_prefix(strings[order[at - 1]], strings[order[at]]) if at else 0
        else:
            pivot = sorted(strings[some[k]][depth : depth + STEP] for k in (0, len(some) // 2, -1))[1]
            less, same, more = [], [], []
            for i in some:
                piece = strings[i][depth : depth + STEP]
                (less if piece < pivot else same if piece == pivot else more).append(i)
            if more:
                stack.append((more, depth))
            if len(pivot) < STEP:  # these strings end here and are equal
                stack.append((same, max(shallow, depth)))
            else:
                stack.append((same, depth + STEP))
            if less:
                stack.append((less, depth))
    return order, shared


def _groups(order: list[int], shared: list[int]) -> list[tuple[int, int, int]]:
    """(depth, first, last) of each inner node of the suffix tree over the order, deeper ones before those that hold them."""
    out: list[tuple[int, int, int]] = []
    stack: list[tuple[int, int]] = []  # (depth, first place)
    for i in range(1, len(order) + 1):
        depth = shared[i] if i < len(order) else -1
        first = i - 1
        while stack and stack[-1][0] > depth:
            d, first = stack.pop()
            out.append((d, first, i - 1))
        if depth >= 0 and (not stack or stack[-1][0] < depth):
            stack.append((depth, first))
    return out


def extents(lefts: list[bytes], rights: list[bytes], ranks: list[int] | None, unit: int, least: int) -> list[list[tuple[int, int]]]:
    """For each context the maximal (left, right) extents, in units, that it shares with another one.

    A context is what stands before a point (reversed) and what follows.  ``ranks``: only contexts of a smaller rank count as another
    one; None: all do.  Extents of fewer than ``least`` units together are left out, and so are those that another one holds.
    """
    n = len(rights)
    out: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    if n == 2:
        r, l = common_prefix(*rights) // unit, common_prefix(*lefts) // unit
        if r + l >= least:
            for x in (0, 1):
                if ranks is None or ranks[x] > ranks[1 - x]:
                    out[x].append((l, r))
        return out
    order, shared = deep_shallow(rights)
    shared = [s - s % unit for s in shared]
    by_left, _ = deep_shallow(lefts)
    place = [0] * n
    for i, x in enumerate(by_left):
        place[x] = i
    best = [-1] * n
    full = [len(x) // unit for x in lefts]

    def note(x: int, y: int, r: int) -> None:
        if best[x] < full[x]:
            l = common_prefix(lefts[x], lefts[y]) // unit
            if l > best[x]:
                best[x] = l
                if l + r >= least:
                    out[x].append((l, r))

    for depth, first, last in _groups(order, shared):
        r, some = depth // unit, order[first : last + 1]
        if all(best[x] >= full[x] for x in some):
            continue
        if ranks is None:
            some = sorted(some, key=place.__getitem__)
            for x, y in zip(some, some[1:]):
                note(x, y, r)
                note(y, x, r)
            continue
        some = sorted(some, key=ranks.__getitem__)
        seen: list[int] = []  # places in the order of lefts of those with smaller rank
        i = 0
        while i < len(some):
            j = i
            while j < len(some) and ranks[some[j]] == ranks[some[i]]:
                j += 1
            for x in some[i:j]:
                at = bisect_left(seen, place[x])
                for k in (at - 1, at):
                    if 0 <= k < len(seen):
                        note(x, by_left[seen[k]], r)
            for x in some[i:j]:
                insort(seen, place[x])
            i = j
    return out
