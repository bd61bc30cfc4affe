"""Path queries: parsing, and compilation to walkers (deterministic selecting top-down automata over binary trees).

A walker state is the set of steps that wait to be matched.  Reading a label moves to one state for the left child (first child of
the unranked node) and one for the right child (next sibling).  States are made when first asked for, so a query with many
wildcards costs what the data visit, not what the worst case allows.
"""

from __future__ import annotations

import copy
import re
from dataclasses import dataclass, field

CHILD, DESCENDANT, FOLLOWING = "child", "descendant", "following-sibling"
_AXES = {CHILD, DESCENDANT, FOLLOWING}
#: The absent node of the binary form and the default label; neither can be a name.
RESERVED = {"_", "%"}


class QueryError(ValueError):
    pass


class UnsupportedAxis(QueryError):
    pass


@dataclass(frozen=True)
class Step:
    axis: str
    test: str
    probes: tuple[tuple["Step", ...], ...] = ()

    def accepts(self, label: str) -> bool:
        # a label with a constant (``constants``) is still one of its name
        return self.test in ("*", label) or ("=" in label and "=" not in self.test and label.startswith((self.test + "@", self.test + "#")))


@dataclass(frozen=True)
class PathQuery:
    steps: tuple[Step, ...]

    @property
    def probes(self) -> tuple[tuple[Step, ...], ...]:
        """The distinct filter paths, in order."""
        return tuple(dict.fromkeys(p for s in self.steps for p in s.probes))

    @property
    def names(self) -> frozenset[str]:
        return frozenset(s.test for s in self.steps if s.test != "*") | {s.test for p in self.probes for s in p if s.test != "*"}


#: A comparison with an attribute's value, or with an element's own text.
_CONSTANT = re.compile(r"@([A-Za-z][A-Za-z0-9-]*)='([^']*)'|text\(\)='([^']*)'")
_STEP = re.compile(r"(//?)(?:([a-z-]+)::)?(\*|[^/\[\]:]+)")


def _steps(text: str, filters: bool) -> tuple[Step, ...]:
    out, at = [], 0
    while at < len(text):
        m = _STEP.match(text, at)
        if not m:
            raise QueryError(f"can't read {text[at:]!r}")
        slash, axis, test = m.groups()
        if axis and axis not in _AXES:
            raise UnsupportedAxis(axis)
        if slash == "//" and axis not in (None, CHILD, DESCENDANT):
            raise QueryError("// goes with child or descendant")
        if test in RESERVED:
            raise QueryError(f"{test!r} is no name")
        at, probes = m.end(), []
        while at < len(text) and text[at] == "[":
            if not filters:
                raise QueryError("a filter inside a filter")
            end = text.find("]", at)
            inner = text[at + 1 : end]
            if constant := _CONSTANT.fullmatch(inner):
                if test == "*" or "=" in test or probes:
                    raise QueryError("one constant a step, on a name, before its filters")
                test, at = f"{test}@{constant[1]}={constant[2]}" if constant[1] else f"{test}#={constant[3]}", end + 1
                continue
            if end < 0 or not inner.startswith("./"):
                raise QueryError("a filter is [./path] or [.//path]")
            if "[" in inner:
                raise QueryError("a filter inside a filter")
            probes.append(_steps(inner[1:], False))
            at = end + 1
        out.append(Step(DESCENDANT if slash == "//" else axis or CHILD, test, tuple(probes)))
    if not out:
        raise QueryError("an empty query")
    return tuple(out)


def parse(text: str) -> PathQuery:
    return PathQuery(_steps(text.strip(), True))


@dataclass
class Walker:
    """States by number; ``rule(q, label, held)`` gives (selects, left, right); held: bits of the filters that are true at the node."""

    start: int = 0
    names: frozenset[str] = frozenset()
    rules: dict[tuple[int, str | None, int], tuple[bool, int, int]] = field(default_factory=dict)
    dead: int | None = None

    def rule(self, q: int, label: str, held: int = 0) -> tuple[bool, int, int]:
        key = (q, label if label in self.names else None, held)
        got = self.rules.get(key)
        return self._make(key, label) if got is None else got

    def _make(self, key: tuple[int, str | None, int], label: str) -> tuple[bool, int, int]:
        return self.rules[key[0], None, 0]

    def entered(self, q: int) -> "Walker":
        """The same walker, started in another state; rules are shared."""
        out = copy.copy(self)
        out.start = q
        return out

    def close(self, held: tuple[int, ...] = (0,)) -> "Walker":
        """Make all states and rules that can be reached; for tables of a walker."""
        seen, todo = {self.start}, [self.start]
        while todo:
            q = todo.pop()
            for label in [*sorted(self.names), "\0"]:
                for h in held:
                    for p in self.rule(q, label, h)[1:]:
                        if p not in seen:
                            seen.add(p)
                            todo.append(p)
        return self

    @property
    def states(self) -> int:
        return len({q for q, _, _ in self.rules} | {p for r in self.rules.values() for p in r[1:]})

    def rows(self) -> list[tuple[int, str | None, bool, int, int]]:
        return sorted(((q, w, s, a, b) for (q, w, h), (s, a, b) in self.rules.items() if h == 0), key=lambda r: (r[0], r[1] or ""))


class StepWalker(Walker):
    """The walker of a path query.  A state's number is the bit set of the steps that wait, so it is the same in every process."""

    def __init__(self, query: PathQuery, prune: bool = True):
        super().__init__(names=query.names)
        self.query, self.prune = query, prune
        bits = {p: 1 << i for i, p in enumerate(query.probes)}
        self.need = [sum(bits[p] for p in dict.fromkeys(s.probes)) for s in query.steps]
        # nothing follows the root, so a query that begins with a sibling step selects nothing
        self.start = self._number(frozenset() if query.steps[0].axis == FOLLOWING else frozenset([0]))
        self.dead = self._number(frozenset())

    def _number(self, waiting: frozenset[int]) -> int:
        if self.prune:
            # whatever earlier steps could reach lies where the last waiting descendant step waits already
            last = max((i for i in waiting if self.query.steps[i].axis == DESCENDANT), default=-1)
            waiting = frozenset(i for i in waiting if i >= last)
        return sum(1 << i for i in waiting)

    def _make(self, key, label):
        steps = self.query.steps
        waiting = [i for i in range(len(steps)) if key[0] >> i & 1]
        left, right, selects = {i for i in waiting if steps[i].axis == DESCENDANT}, set(waiting), False
        label = "\0" if key[1] is None else label  # one rule for all labels without a name in the query
        for i in waiting:
            if steps[i].accepts(label) and not self.need[i] & ~key[2]:
                if i + 1 == len(steps):
                    selects = True
                else:
                    (right if steps[i + 1].axis == FOLLOWING else left).add(i + 1)
        self.rules[key] = (selects, self._number(frozenset(left)), self._number(frozenset(right)))
        return self.rules[key]


def compile_query(query: PathQuery | str, prune: bool = True) -> StepWalker:
    return StepWalker(parse(query) if isinstance(query, str) else query, prune)


def user_walker(rows: list[tuple[int, str | None, bool, int, int]], start: int = 0) -> Walker:
    """A walker from rules (state, label or None for the default, selects, left, right), validated."""
    rules: dict = {}
    for q, w, s, a, b in rows:
        if (q, w, 0) in rules:
            raise QueryError(f"two rules for state {q} and label {w}")
        rules[q, w, 0] = (s, a, b)
    states = {q for q, *_ in rows} | {p for r in rows for p in r[3:]} | {start}
    if missing := [q for q in sorted(states) if (q, None, 0) not in rules]:
        raise QueryError(f"states without a default rule: {missing}")

    class Given(Walker):
        def _make(self, key, label):
            return self.rules.get((key[0], key[1], 0)) or self.rules[key[0], None, 0]

    return Given(start, frozenset(w for _, w, *_ in rows if w is not None), rules)


def depth_mod(m: int, c: int) -> Walker:
    """Selects the nodes whose number of ancestors is c modulo m."""
    return user_walker([(q, None, q == c % m, (q + 1) % m, q) for q in range(m)])


def constants(query: PathQuery | str) -> frozenset[str]:
    """The labels with constants that a query asks for: ``name@attribute=value`` or ``name#=text``; readers give them to the elements they hold for."""
    return frozenset(x for x in (parse(query) if isinstance(query, str) else query).names if "=" in x)


def path_dfa(query: PathQuery | str) -> dict[tuple[int, str | None], int]:
    """The automaton over label paths for child and descendant steps: (state, label or None) -> state; states ``-1 - q`` accept.

    Subset construction over how many steps a path has matched: step i matches the path's last label if step i - 1 matched the label before it
    (child) or any label before it (descendant).  States are numbered as they are met, from 1; 0 can't match any more.
    """
    query = parse(query) if isinstance(query, str) else query
    steps = query.steps
    if any(s.axis == FOLLOWING for s in steps) or query.probes:
        raise QueryError("a path automaton takes child and descendant steps without filters")
    # a state: the steps that the next label may match
    numbers: dict[frozenset[int], int] = {frozenset(): 0, frozenset([0]): 1}
    rules: dict[tuple[int, str | None], int] = {}
    todo = [frozenset(), frozenset([0])]
    while todo:
        state = todo.pop()
        for label in (*sorted(query.names), None):
            hit = {i for i in state if steps[i].accepts("\0" if label is None else label)}
            after = frozenset({i for i in state if steps[i].axis == DESCENDANT} | {i + 1 for i in hit if i + 1 < len(steps)})
            if after not in numbers:
                numbers[after] = len(numbers)
                todo.append(after)
            rules[numbers[state], label] = -1 - numbers[after] if len(steps) - 1 in hit else numbers[after]
    return rules


def walker_from_dfa(rules: dict[tuple[int, str | None], int], start: int = 1) -> Walker:
    """The walker of a path automaton: the first child goes on in the state after the label, the next sibling in the state before it."""
    return user_walker([(q, w, p < 0, -1 - p if p < 0 else p, q) for (q, w), p in rules.items()], start)


def acceptor(rows: list[tuple[int, str | None, int, int]], reject: int, start: int = 0) -> Walker:
    """A walker that selects the nodes at which a deterministic top-down tree automaton (state, label, left, right) goes into its reject state: a tree is
    accepted if nothing is selected."""
    return user_walker([(q, w, reject in (a, b) and q != reject, a, b) for q, w, a, b in rows], start)


def sibling_walker(names: list[str]) -> StepWalker:
    """The walker of a run of following-sibling steps after a first child step."""
    return compile_query(PathQuery((Step(CHILD, names[0]), *(Step(FOLLOWING, n) for n in names[1:]))))


def minimise(walker: Walker) -> Walker:
    """The smallest walker that selects alike (partition refinement); unreachable states go."""
    walker.close()
    labels = [*sorted(walker.names), None]
    states = sorted({q for q, _, _ in walker.rules})
    rule = lambda q, w: walker.rule(q, "\0" if w is None else w)
    block = {q: tuple(rule(q, w)[0] for w in labels) for q in states}
    while True:
        finer = {q: (block[q], tuple((block[rule(q, w)[1]], block[rule(q, w)[2]]) for w in labels)) for q in states}
        ids = {b: i for i, b in enumerate(dict.fromkeys(finer.values()))}
        now = {q: ids[finer[q]] for q in states}
        if len(set(now.values())) == len(set(block.values())):
            break
        block = now
    seen = {}
    for q in states:
        for w in labels:
            s, a, b = rule(q, w)
            seen[now[q], w] = (now[q], w, s, now[a], now[b])
    return user_walker(list(seen.values()), now[walker.start])


def probe_bits(path: tuple[Step, ...], label: str, left: int, right: int) -> tuple[int, bool]:
    """Bottom-up evaluation of one filter path at a binary node.

    The state packs for each step j two bits: at 2j "step j holds here or at a later sibling", at 2j + 1 "... here, below, or at or
    below a later sibling".  Returns (state, whether the filter holds here).
    """
    bits, need = 0, True
    for j in reversed(range(len(path))):
        hit = path[j].accepts(label) and need
        if hit or right >> 2 * j & 1:
            bits |= 1 << 2 * j
        if hit or (left | right) >> (2 * j + 1) & 1:
            bits |= 1 << (2 * j + 1)
        source, at = {CHILD: (left, 2 * j), DESCENDANT: (left, 2 * j + 1), FOLLOWING: (right, 2 * j)}[path[j].axis]
        need = bool(source >> at & 1)
    return bits, need
