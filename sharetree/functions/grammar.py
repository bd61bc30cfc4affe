"""Template grammars (straight-line linear tree grammars) and what can be computed on them without expanding the tree.

A body is a list of symbols in pre-order (each symbol knows how many arguments follow):
("l", label) a node with two children, ("t", id) a template with as many arguments as its rank, ("y", i) slot i, ("_",) an absent node;
after marking, a selected label is ("m", label).  Templates are kept in an order in which users come before what they use, the start first.
Everything is iterative: sibling chains make binary trees thousands of nodes deep.
"""

from __future__ import annotations

import itertools
from bisect import bisect_right
from collections import Counter, defaultdict
from dataclasses import dataclass

from sharetree.plans.query import CHILD, DESCENDANT, PathQuery, QueryError, Step, Walker, compile_query, probe_bits

NULL = ("_",)
#: Counts are exact up to this; more is an error.
MAX_COUNT = 10**38 - 1


class GrammarError(ValueError):
    pass


@dataclass
class Grammar:
    start: object
    bodies: dict
    ranks: dict

    def arity(self, symbol: tuple) -> int:
        return {"l": 2, "m": 2, "y": 0, "_": 0}.get(symbol[0], 0) if symbol[0] != "t" else self.ranks[symbol[1]]

    def edges(self) -> int:
        """Size: edges of all bodies."""
        return sum(len(b) - 1 for b in self.bodies.values())

    def rank(self) -> int:
        return max(self.ranks.values(), default=0)

    def order(self) -> list:
        """Users before what they use."""
        users = Counter(s[1] for b in self.bodies.values() for s in b if s[0] == "t")
        todo, out = [t for t in self.bodies if not users[t]], []
        while todo:
            t = todo.pop()
            out.append(t)
            for s in self.bodies[t]:
                if s[0] == "t":
                    users[s[1]] -= 1
                    if not users[s[1]]:
                        todo.append(s[1])
        if len(out) != len(self.bodies):
            raise GrammarError("templates use each other in a circle")
        return out


def validate(g: Grammar) -> list[str]:
    """What is wrong with a grammar; empty if nothing is."""
    out = []
    if g.start not in g.bodies:
        return ["no start template"]
    if g.ranks.get(g.start):
        out.append("the start template has slots")
    for t, body in g.bodies.items():
        slots = [s[1] for s in body if s[0] == "y"]
        if slots != list(range(1, g.ranks[t] + 1)):
            out.append(f"{t}: slots {slots} instead of 1 to {g.ranks[t]} in order")
        if any(s[0] == "t" and s[1] not in g.bodies for s in body):
            out.append(f"{t}: uses a template that isn't there")
            continue
        need = 1
        for s in body:
            if need < 1:
                break
            need += g.arity(s) - 1
        if need:
            out.append(f"{t}: the number of arguments is wrong")
    if not out:
        try:
            g.order()
        except GrammarError as e:
            out.append(str(e))
        else:
            if len(trim(g).bodies) < len(g.bodies):
                out.append("templates that the start doesn't reach")
    return out


def trim(g: Grammar) -> Grammar:
    """Without templates that the start doesn't reach."""
    seen, todo = {g.start}, [g.start]
    while todo:
        for s in g.bodies[todo.pop()]:
            if s[0] == "t" and s[1] not in seen:
                seen.add(s[1])
                todo.append(s[1])
    return Grammar(g.start, {t: b for t, b in g.bodies.items() if t in seen}, {t: r for t, r in g.ranks.items() if t in seen})


def expand(g: Grammar, most: int = 10_000_000) -> list[tuple]:
    """The tree as one body."""
    out: list[tuple] = []

    def arguments(body: list, at: int) -> int:
        need = 1
        while need:
            need += g.arity(body[at]) - 1
            at += 1
        return at

    # (body, from, to, environment): an environment holds the arguments, each (body, from, to, environment)
    stack: list[tuple] = [(g.bodies[g.start], 0, len(g.bodies[g.start]), ())]
    while stack:
        body, at, stop, env = stack.pop()
        while at < stop:
            s = body[at]
            if s[0] == "y":
                stack.append((body, at + 1, stop, env))
                stack.append(env[s[1] - 1])
                break
            if s[0] == "t":
                args, a = [], at + 1
                for _ in range(g.ranks[s[1]]):
                    b = arguments(body, a)
                    args.append((body, a, b, env))
                    a = b
                stack.append((body, a, stop, env))
                stack.append((g.bodies[s[1]], 0, len(g.bodies[s[1]]), tuple(args)))
                break
            out.append(s)
            if len(out) > most:
                raise GrammarError("the tree is too large to expand")
            at += 1
    return out


def tree_of(g: Grammar) -> tuple[list[str], list[int]]:
    """Labels and depths of the tree in pre-order."""
    labels, depths, todo = [], [], [0]
    for s in expand(g):
        d = todo.pop()
        if s[0] != "_":
            labels.append(s[1])
            depths.append(d)
            todo += (d, d + 1)
    return labels, depths


# ---- trees and plain grammars


def from_tree(labels: list[str], depths: list[int]) -> tuple[list[list[int]], list[int]]:
    """Children of each node of a forest in pre-order, and its roots."""
    kids: list[list[int]] = [[] for _ in labels]
    roots, way = [], []
    for i, d in enumerate(depths):
        del way[d:]
        (kids[way[-1]] if way else roots).append(i)
        way.append(i)
    return kids, roots


def unranked_dag(labels: list[str], depths: list[int]) -> tuple[list[tuple[str, tuple[int, ...]]], int]:
    """Distinct subtrees (label, children) with children first, and the root's number."""
    kids, roots = from_tree(labels, depths)
    ids: dict[tuple, int] = {}
    of = [0] * len(labels)
    for i in reversed(range(len(labels))):
        of[i] = ids.setdefault((labels[i], tuple(of[k] for k in kids[i])), len(ids))
    return list(ids), of[roots[0]] if roots else -1


def nothing() -> Grammar:
    """The grammar of the empty forest."""
    return Grammar(0, {0: [NULL]}, {0: 0})


def binary_dag(labels: list[str], depths: list[int]) -> Grammar:
    """The minimal DAG of the first-child, next-sibling form: one template for each distinct subtree, one label in each."""
    kids, roots = from_tree(labels, depths)
    if not roots:
        return nothing()
    after = [-1] * len(labels)
    for some in [*kids, roots]:
        for a, b in zip(some, some[1:]):
            after[a] = b
    ids: dict[tuple, int] = {}
    of = [0] * len(labels)
    ref = lambda i: of[i] if i >= 0 else -1
    for i in reversed(range(len(labels))):
        of[i] = ids.setdefault((labels[i], ref(kids[i][0]) if kids[i] else -1, ref(after[i])), len(ids))
    use = lambda k: ("t", k) if k >= 0 else NULL
    return trim(Grammar(of[roots[0]], {k: [("l", w), use(a), use(b)] for (w, a, b), k in ids.items()}, dict.fromkeys(range(len(ids)), 0)))


def hybrid_dag(labels: list[str], depths: list[int]) -> Grammar:
    """The binary DAG of the unranked DAG: each distinct subtree's child list becomes a sibling chain, and chains share their tails.

    For one tree; a forest with several roots has the binary DAG.
    """
    if depths.count(0) != 1:
        return binary_dag(labels, depths)
    nodes, root = unranked_dag(labels, depths)
    bodies: dict = {}
    tails: dict[tuple, object] = {}
    for n, (w, children) in enumerate(nodes):
        tail: object = None
        for k in reversed(children):
            key = (k, tail)
            if key not in tails:
                tails[key] = ("c", len(tails))
                # an element as a sibling: its label, its children's chain, the next sibling
                label, chain = nodes[k][0], bodies[("e", k)][1]
                bodies[tails[key]] = [("l", label), chain, ("t", tail) if tail else NULL]
            tail = tails[key]
        bodies[("e", n)] = [("l", w), ("t", tail) if tail else NULL, NULL]
    g = Grammar(("e", root), bodies, dict.fromkeys(bodies, 0))
    return trim(g)


def hybrid_edges(nodes: list[tuple[str, tuple[int, ...]]]) -> int:
    """Edges of the hybrid DAG: one from each element to its first child, one from each distinct tail of a sibling chain to the next."""
    tails: dict[tuple, int] = {}
    edges = 0
    for _, children in nodes:
        tail = -1
        for k in reversed(children):
            if (k, tail) not in tails:
                edges += tail >= 0
                tails[k, tail] = len(tails)
            tail = tails[k, tail]
        edges += bool(children)
    return edges


def real_edges(g: Grammar) -> int:
    """Edges of a plain grammar, without those to absent nodes."""
    return sum(1 for b in g.bodies.values() for s in b[1:] if s != NULL)


def node_normal(g: Grammar) -> Grammar:
    """A plain grammar with exactly one label in each body."""
    bodies: dict = {}

    def name(t: object, body: list) -> None:
        spans, stack = {}, []
        for i in reversed(range(len(body))):
            ends = [stack.pop() for _ in range(g.arity(body[i]))]
            spans[i] = ends[-1][1] if ends else i + 1
            stack.append((i, spans[i]))
        at = [i for i, s in enumerate(body) if s[0] in "lm"]
        if not at:
            bodies[t] = body
            return
        ids = {i: t if i == 0 else (t, i) for i in at}
        part = lambda i: ("t", ids[i]) if i in ids else body[i]
        for i in at:
            bodies[ids[i]] = [body[i], part(i + 1), part(spans[i + 1])]

    for t, body in g.bodies.items():
        if g.ranks[t]:
            raise GrammarError("only plain grammars have a node normal form")
        name(t, body)
    return Grammar(g.start, bodies, dict.fromkeys(bodies, 0))


def chain(label: str, doublings: int, leaf: str = "e") -> Grammar:
    """label^(2^doublings)(leaf) along first children, by templates that each use the next one twice."""
    if doublings < 1:
        raise GrammarError("at least one doubling")
    bodies: dict = {0: [("t", 1), ("t", 1), ("l", leaf), NULL, NULL]}
    ranks = {0: 0}
    for i in range(1, doublings):
        bodies[i], ranks[i] = [("t", i + 1), ("t", i + 1), ("y", 1)], 1
    bodies[doublings], ranks[doublings] = [("l", label), ("y", 1), NULL], 1
    return Grammar(0, bodies, ranks)


# ---- repeated pairs: grammars of higher rank


def inline_single(g: Grammar) -> Grammar:
    """A plain grammar without templates that are used once."""
    uses = Counter(s[1] for b in g.bodies.values() for s in b if s[0] == "t")
    bodies = {}
    for t in g.bodies:
        if uses[t] != 1:
            out, todo = [], list(reversed(g.bodies[t]))
            while todo:
                s = todo.pop()
                if s[0] == "t" and uses[s[1]] == 1:
                    todo += reversed(g.bodies[s[1]])
                else:
                    out.append(s)
            bodies[t] = out
    return Grammar(g.start, bodies, dict.fromkeys(bodies, 0))


def digrams(g: Grammar, max_rank: int = 4, rounds: int | None = None, least: int = 3) -> Grammar:
    """Replace the most frequent pair of a label or template and one of its arguments by a template, while one occurs ``least`` times.

    Starts from a plain grammar, so repeated subtrees are shared already.  ``rounds``: a bound on the replacements, if any is wanted.
    """
    g = inline_single(g)
    bodies, ranks = {t: list(b) for t, b in g.bodies.items()}, dict(g.ranks)
    work = Grammar(g.start, bodies, ranks)
    for r in itertools.count() if rounds is None else range(rounds):
        count: Counter = Counter()
        parsed = {t: _parsed(work, b) for t, b in bodies.items()}
        for t, (kids, _) in parsed.items():
            used: set[int] = set()
            for i, own in enumerate(kids):
                for j, k in enumerate(own):
                    a, b = bodies[t][i], bodies[t][k]
                    if a[0] in "lt" and b[0] in "lt" and (a != b or i not in used):
                        count[a, j, b] += 1
                        used |= {k} if a == b else set()
        best = next(((p, n) for p, n in sorted(count.items(), key=lambda x: (-x[1], repr(x[0]))) if n >= least and work.arity(p[0]) + work.arity(p[2]) - 1 <= max_rank), None)
        if best is None:
            break
        (a, j, b), _ = best
        fresh, na, nb = ("d", r), work.arity(a), work.arity(b)
        slots = [("y", i + 1) for i in range(na + nb - 1)]
        for t, (kids, _) in parsed.items():
            gone: dict[int, int] = {}  # node of a -> node of b
            taken: set[int] = set()
            for i, own in enumerate(kids):
                if bodies[t][i] == a and i not in taken and j < len(own) and bodies[t][own[j]] == b:
                    gone[i] = own[j]
                    taken |= {i, own[j]}
            if gone:
                bodies[t] = _rewritten(bodies[t], kids, gone, j, ("t", fresh))
        ranks[fresh] = na + nb - 1
        bodies[fresh] = [a, *slots[:j], b, *slots[j : j + nb], *slots[j + nb :]]
    return trim(work)


def _parsed(g: Grammar, body: list) -> tuple[list[list[int]], list[int]]:
    """Argument positions of each symbol, and where each symbol's part ends."""
    kids: list[list[int]] = [[] for _ in body]
    ends, stack = [0] * len(body), []
    for i in reversed(range(len(body))):
        kids[i] = [stack.pop() for _ in range(g.arity(body[i]))]
        ends[i] = ends[kids[i][-1]] if kids[i] else i + 1
        stack.append(i)
    return kids, ends


def _rewritten(body: list, kids: list[list[int]], gone: dict[int, int], j: int, use: tuple) -> list:
    out, stack = [], [0]
    while stack:
        i = stack.pop()
        if i in gone:
            out.append(use)
            stack += reversed([*kids[i][:j], *kids[gone[i]], *kids[i][j + 1 :]])
        else:
            out.append(body[i])
            stack += reversed(kids[i])
    return out


# ---- the three tasks


def run_body(g: Grammar, body: list, walker: Walker, q: int, phi, held=None):
    """One run over a body: (state of each symbol, slot states, count)."""
    states, slots, n, pending = [], [], 0, [q]
    for i, s in enumerate(body):
        q = pending.pop()
        states.append(q)
        kind = s[0]
        if kind == "y":
            slots.append(q)
        elif kind == "t":
            outs, m = phi(s[1], q)
            n += m
            pending += reversed(outs)
        elif kind != "_":
            selects, a, b = walker.rule(q, s[1], s[2] if len(s) > 2 else 0)
            n += selects
            pending += (b, a)
    return states, tuple(slots), n


def behaviours(g: Grammar, walker: Walker, mode: str = "demand", visits: list | None = None) -> dict:
    """(template, state) -> (slot states, count).

    ``full``: every state that can be reached at all, for every template, in reverse order of use.  ``demand``: only pairs that the run from the start
    meets; dependencies are kept on a stack of our own.
    """
    memo: dict = {}
    visited = 0
    if mode == "full":
        walker.close()
        states = sorted({q for q, _, _ in walker.rules})
        for t in reversed(g.order()):
            for q in states:
                _, slots, n = run_body(g, g.bodies[t], walker, q, lambda t, q: memo[t, q])
                visited += len(g.bodies[t])
                memo[t, q] = (slots, n)
    else:
        todo = [(g.start, walker.start)]
        paused: dict = {}
        while todo:
            key = todo[-1]
            if key in memo:
                todo.pop()
                continue
            at, slots, n, pending = paused.pop(key, None) or (0, [], 0, [key[1]])
            body = g.bodies[key[0]]
            while at < len(body):
                s, q = body[at], pending[-1]
                if s[0] == "t":
                    got = memo.get((s[1], q))
                    if got is None:
                        paused[key] = (at, slots, n, pending)
                        todo.append((s[1], q))
                        break
                    pending.pop()
                    n += got[1]
                    pending += reversed(got[0])
                else:
                    pending.pop()
                    if s[0] == "y":
                        slots.append(q)
                    elif s[0] != "_":
                        selects, a, b = walker.rule(q, s[1], s[2] if len(s) > 2 else 0)
                        n += selects
                        pending += (b, a)
                at += 1
                visited += 1
            else:
                memo[key] = (tuple(slots), n)
                todo.pop()
    if visits is not None:
        visits.append(visited)
    return memo


def count(g: Grammar, walker: Walker, mode: str = "demand") -> int:
    n = behaviours(g, walker, mode)[g.start, walker.start][1]
    if n > MAX_COUNT:
        raise OverflowError("a count beyond 38 digits")
    return n


def tree_size(g: Grammar) -> int:
    """Nodes of the tree: a count with a walker that selects everything."""
    from sharetree.plans.query import user_walker

    return count(g, user_walker([(0, None, True, 0, 0)]))


def mark(g: Grammar, walker: Walker, keep: bool = False, stats: dict | None = None) -> Grammar:
    """The grammar of the same tree with selected labels marked; at most one template for each (state, template).

    ``keep``: labels keep the filter bits that they carry.  ``stats`` takes the number of templates before unreachable ones go.
    """
    memo = behaviours(g, walker)
    bodies, ranks = {}, {}
    for (t, q), _ in memo.items():
        states, _, _ = run_body(g, g.bodies[t], walker, q, lambda t, q: memo[t, q])
        body = []
        for s, p in zip(g.bodies[t], states):
            if s[0] == "t":
                s = ("t", (p, s[1]))
            elif s[0] in "lm":
                s = ("m" if walker.rule(p, s[1], s[2] if len(s) > 2 else 0)[0] else "l", s[1], *(s[2:] if keep else ()))
            body.append(s)
        bodies[q, t], ranks[q, t] = body, g.ranks[t]
    if stats is not None:
        stats["made"] = len(bodies)
    return trim(Grammar((walker.start, g.start), bodies, ranks))


def gaps(g: Grammar, weigh=lambda s: 1) -> dict:
    """For each template its stretches before, between and after slots: [(length, marks)]; and where each symbol's own stretches begin.

    Returns template -> (gaps, places): places[i] lists (gap, offset, marks before) for every gap of symbol i.
    """
    out: dict = {}
    for t in reversed(g.order()):
        own, places = [[0, 0]], [[] for _ in g.bodies[t]]
        # what is left to visit: symbols, or (symbol, next gap)
        body, at, stack = g.bodies[t], 0, []

        def visit(i: int, gap: int, own=own, places=places, body=body) -> None:
            s = body[i]
            places[i].append((len(own) - 1, own[-1][0], own[-1][1]))
            if s[0] == "t":
                length, marks = out[s[1]][0][gap]
            else:
                length, marks = (weigh(s), s[0] == "m") if gap == 0 and s[0] in "lm" else (0, 0)
            own[-1][0] += length
            own[-1][1] += marks

        while at < len(body):
            s = body[at]
            if s[0] == "y":
                own.append([0, 0])
            elif s[0] != "_":
                visit(at, 0)
                if g.arity(s):
                    stack.append([at, 1, g.arity(s)])
                    at += 1
                    continue
            at += 1
            while stack:
                top = stack[-1]
                visit(top[0], top[1])
                top[1] += 1
                if top[1] <= top[2]:
                    break
                stack.pop()
        out[t] = ([tuple(x) for x in own], places)
    return out


def locate(g: Grammar, walker: Walker | None = None, limit: int | None = None, offsets: str = "lazy", with_label: bool = False) -> list:
    """Pre-order numbers (from 1) of the selected nodes, in order.  Without a walker, of the marked nodes.

    ``lazy``: lengths bottom-up, then top-down into stretches that hold marks.  ``eager``: offset lists for every template, bottom-up.
    ``limit``: only the first ones; stretches past them aren't entered.  ``with_label``: (number, label) of each.
    """
    of = (lambda u, w: (u, w)) if with_label else (lambda u, w: u)
    marked = g if walker is None else mark(g, walker)
    table = gaps(marked)
    if offsets == "eager":
        lists: dict = {}
        for t in reversed(marked.order()):
            own: list[list[int]] = [[] for _ in table[t][0]]
            for s, places in zip(marked.bodies[t], table[t][1]):
                for j, (gap, off, _) in enumerate(places):
                    if s[0] == "m" and j == 0:
                        own[gap].append((off, s[1]))
                    elif s[0] == "t":
                        own[gap] += [(off + x, w) for x, w in lists[s[1]][j]]
            lists[t] = [sorted(x) for x in own]
        return [of(x + 1, w) for x, w in lists[marked.start][0]][:limit]
    out: list = []
    # (template, first number of each gap, marks that come before each gap)
    todo = [(marked.start, (1,), (0,))]
    while todo:
        t, starts, before = todo.pop()
        for s, places in zip(marked.bodies[t], table[t][1]):
            if s[0] == "m":
                gap, off, seen = places[0]
                if limit is None or before[gap] + seen < limit:
                    out.append(of(starts[gap] + off, s[1]))
            elif s[0] == "t" and any(m for _, m in table[s[1]][0]):
                ranks = tuple(before[gap] + seen for gap, _, seen in places)
                if limit is None or min(r for r, (_, m) in zip(ranks, table[s[1]][0]) if m) < limit:
                    todo.append((s[1], tuple(starts[gap] + off for gap, off, _ in places), ranks))
    return sorted(out)


def node_at(g: Grammar, pre: int, table: dict | None = None) -> tuple[object, str]:
    """The template whose body makes the node with a pre-order number, and its label: one template a step, chosen by its stretches."""
    table = gaps(g) if table is None else table
    t, starts, u = g.start, (0,), pre - 1
    while True:
        for s, places in zip(g.bodies[t], table[t][1]):
            if s[0] in "lm":
                if starts[places[0][0]] + places[0][1] == u:
                    return t, s[1]
            elif s[0] == "t":
                begins = tuple(starts[gap] + off for gap, off, _ in places)
                if any(a <= u < a + n for a, (n, _) in zip(begins, table[s[1]][0])):
                    t, starts = s[1], begins
                    break
        else:
            raise IndexError(pre)


# ---- traversals as string programs


def traversal(g: Grammar) -> dict:
    """A string program of the bracket sequence: (template, gap) -> list of ("<", label), (">", label) or ("r", (template, gap)).

    Closing brackets stand after the left child and before the right child, so the sequence is the unranked tree's XML.  Brackets of
    marked labels have a third entry.
    """
    return {(t, j): x for t in g.order() for j, x in enumerate(_traversed(g, t))}


def _traversed(g: Grammar, t: object) -> list[list[tuple]]:
    """The stretches of one template."""
    body, at, stack = g.bodies[t], 0, []
    own: list[list[tuple]] = [[]]

    def piece(i: int, gap: int) -> None:
        s = body[i]
        if s[0] == "t":
            own[-1].append(("r", (s[1], gap)))
        elif gap < 2:
            own[-1].append(("<" if gap == 0 else ">", s[1], *((True,) if s[0] == "m" else ())))

    while at < len(body):
        s = body[at]
        if s[0] == "y":
            own.append([])
        elif s[0] != "_":
            piece(at, 0)
            if g.arity(s):
                stack.append([at, 1, g.arity(s)])
                at += 1
                continue
        at += 1
        while stack:
            top = stack[-1]
            piece(top[0], top[1])
            top[1] += 1
            if top[1] <= top[2]:
                break
            stack.pop()
    return own


def program_size(p: dict) -> int:
    return sum(map(len, p.values()))


def program_length(p: dict, start) -> int:
    """Tokens of the string, without writing it."""
    return _lengths(p)[start]


def _lengths(p: dict) -> dict:
    out: dict = {}
    for root in p:
        todo = [root]
        while todo:
            k = todo[-1]
            open_ = [x[1] for x in p[k] if x[0] == "r" and x[1] not in out]
            if k in out or not open_:
                out.setdefault(k, sum(out[x[1]] if x[0] == "r" else 1 for x in p[k]))
                todo.pop()
            else:
                todo += open_
    return out


def program_at(p: dict, start, i: int, lengths: dict | None = None) -> tuple:
    """Token i: one part of a rule a step."""
    lengths = _lengths(p) if lengths is None else lengths
    x = ("r", start)
    if not 0 <= i < lengths[start]:
        raise IndexError(i)
    while x[0] == "r":
        for x in p[x[1]]:
            n = lengths[x[1]] if x[0] == "r" else 1
            if i < n:
                break
            i -= n
    return x


def program_tokens(p: dict, start, first: int = 0, last: int | None = None):
    """The tokens from ``first`` to ``last``; parts outside are skipped by their lengths."""
    lengths = _lengths(p)
    last = lengths[start] if last is None else last
    todo, at = [("r", start)], 0
    while todo:
        x = todo.pop()
        n = lengths[x[1]] if x[0] == "r" else 1
        if at + n <= first or at >= last:
            at += n
        elif x[0] == "r":
            todo += reversed(p[x[1]])
        else:
            yield x
            at += 1


def token_text(x: tuple) -> str:
    return f"<{x[1]}>" if x[0] == "<" else f"</{x[1]}>"


def subtree(g: Grammar, pre: int, element_only: bool = True) -> Grammar:
    """A grammar whose tree is the subtree at a pre-order number: a new start body, found by the lengths of the stretches.

    ``element_only``: without the node's later siblings (the right child of the binary form).
    """
    body = subtree_body(g, pre, gaps(g), element_only)
    return trim(Grammar("__at", {**g.bodies, "__at": body}, {**g.ranks, "__at": 0}))


def subtree_body(g: Grammar, pre: int, table: dict, element_only: bool = True) -> list:
    """The body of the new start; ``table`` is ``gaps(g)``."""
    body, u = [("t", g.start)], pre - 1

    def inline(use: list) -> list:
        kids, ends = _parsed(g, use)
        args = [use[k : ends[k]] for k in kids[0]]
        return [y for s in g.bodies[use[0][1]] for y in (args[s[1] - 1] if s[0] == "y" else [s])]

    while True:
        local = gaps_of(g, body, table)
        _, ends = _parsed(g, body)
        hit = next((i for i, s in enumerate(body) if s[0] in "lmt" and any(a <= u < a + n for a, n in local[i])), None)
        if hit is None:
            raise IndexError(pre)
        use = body[hit : ends[hit]]
        if body[hit][0] != "t":
            return [*use[: _parsed(g, use)[0][0][1]], NULL] if element_only else use
        u -= local[hit][0][0]
        body = inline(use)


def gaps_of(g: Grammar, body: list, table: dict) -> list[list[tuple[int, int]]]:
    """(start, own length) of each gap of each symbol in a sentential form."""
    out: list[list[tuple[int, int]]] = [[] for _ in body]
    at, stack, pos = 0, [], 0

    def visit(i: int, gap: int) -> int:
        s = body[i]
        n = table[s[1]][0][gap][0] if s[0] == "t" else int(gap == 0)
        out[i].append((pos, n))
        return n

    while at < len(body):
        s = body[at]
        if s[0] not in ("y", "_"):
            pos += visit(at, 0)
            if g.arity(s):
                stack.append([at, 1, g.arity(s)])
                at += 1
                continue
        at += 1
        while stack:
            top = stack[-1]
            pos += visit(top[0], top[1])
            top[1] += 1
            if top[1] <= top[2]:
                break
            stack.pop()
    return out


def subtrees_program(g: Grammar, numbers: list[int]) -> tuple[dict, object]:
    """One string program for the concatenated subtrees at the given pre-order numbers, any rank: a start body for each."""
    table, refs = gaps(g), []
    program = traversal(g)
    for u in sorted(numbers):
        own = Grammar(("at", u), {("at", u): subtree_body(g, u, table)}, g.ranks | {("at", u): 0})
        program[("at", u), 0] = _traversed(own, ("at", u))[0]
        refs.append(("r", (("at", u), 0)))
    program["__all"] = refs
    return _reached(program, "__all"), "__all"


def _reached(program: dict, start) -> dict:
    """The rules of a string program that its start uses."""
    out, todo = {start: program[start]}, [start]
    while todo:
        for x in program[todo.pop()]:
            if x[0] == "r" and x[1] not in out:
                out[x[1]] = program[x[1]]
                todo.append(x[1])
    return out


def subtrees_program_dag(g: Grammar, numbers: list[int]) -> tuple[dict, object]:
    """The same for a plain grammar, in size O(|G| + |numbers|): elements have symbols of their own, apart from their siblings."""
    g = node_normal(g)
    program: dict = {}
    for t, body in g.bodies.items():
        if body == [NULL]:
            continue
        refs = [("r", ("list", s[1])) if s[0] == "t" else None for s in body[1:]]
        program["element", t] = [("<", body[0][1]), *([refs[0]] if refs[0] else []), (">", body[0][1])]
        program["list", t] = [("r", ("element", t)), *([refs[1]] if refs[1] else [])]
    program["__all"] = [("r", ("element", t)) for t in elements_at(g, numbers)]
    return program, "__all"


def elements_at(g: Grammar, numbers: list[int]) -> list:
    """The templates of the nodes with the given numbers, in order, in a grammar in node normal form.

    All numbers go down together, so a sibling chain is walked once, however many of its nodes are wanted.
    """
    numbers = sorted(numbers)
    sizes = {t: x[0][0][0] for t, x in gaps(g).items()}
    if numbers and not 1 <= numbers[0] <= numbers[-1] <= sizes[g.start]:
        raise IndexError(numbers[-1])
    size = lambda s: sizes[s[1]] if s[0] == "t" else 0
    out: list = [None] * len(numbers)
    todo = [(g.start, 1, 0, len(numbers))] if numbers else []
    while todo:
        t, first, low, high = todo.pop()
        _, left, right = g.bodies[t]
        while low < high and numbers[low] == first:
            out[low], low = t, low + 1
        mid = bisect_right(numbers, first + size(left), low, high)
        if low < mid:
            todo.append((left[1], first + 1, low, mid))
        if mid < high:
            todo.append((right[1], first + 1 + size(left), mid, high))
    return out


class Balanced:
    """Strings as nodes of balanced binary trees that share their parts; joining two costs the difference of their heights."""

    def __init__(self) -> None:
        self.ids: dict[tuple, int] = {}
        self.parts: list[tuple] = []
        #: height, tokens, opening brackets, change of depth, least depth after any token
        self.facts: list[tuple[int, int, int, int, int]] = []

    def _node(self, part: tuple, facts: tuple) -> int:
        got = self.ids.setdefault(part, len(self.parts))
        if got == len(self.parts):
            self.parts.append(part)
            self.facts.append(facts)
        return got

    def leaf(self, token: tuple) -> int:
        step = 1 if token[0] == "<" else -1
        return self._node(token, (0, 1, int(step > 0), step, step))

    def pair(self, a: int, b: int) -> int:
        (h, n, o, d, low), (k, m, p, e, least) = self.facts[a], self.facts[b]
        return self._node((a, b), (max(h, k) + 1, n + m, o + p, d + e, min(low, d + least)))

    def join(self, a: int | None, b: int | None) -> int | None:
        if a is None or b is None:
            return b if a is None else a
        height = lambda x: self.facts[x][0]
        if abs(height(a) - height(b)) < 2:
            return self.pair(a, b)
        if height(a) > height(b):
            left, right = self.parts[a]
            right = self.join(right, b)
            if height(right) < height(left) + 2:
                return self.pair(left, right)
            x, y = self.parts[right]
            if height(x) <= height(y):
                return self.pair(self.pair(left, x), y)
            u, v = self.parts[x]
            return self.pair(self.pair(left, u), self.pair(v, y))
        left, right = self.parts[b]
        left = self.join(a, left)
        if height(left) < height(right) + 2:
            return self.pair(left, right)
        x, y = self.parts[left]
        if height(y) <= height(x):
            return self.pair(x, self.pair(y, right))
        u, v = self.parts[y]
        return self.pair(self.pair(x, u), self.pair(v, right))

    def cut(self, a: int, first: int, last: int) -> int | None:
        """Tokens first to last of a node."""
        n = self.facts[a][1]
        if last <= 0 or first >= n:
            return None
        if first <= 0 and last >= n:
            return a
        left, right = self.parts[a]
        n = self.facts[left][1]
        return self.join(self.cut(left, first, last), self.cut(right, first - n, last - n))

    def opening(self, a: int, u: int) -> int:
        """Where the opening bracket number u (from 1) stands."""
        at = 0
        while self.facts[a][0]:
            left, right = self.parts[a]
            if u <= self.facts[left][2]:
                a = left
            else:
                u, at, a = u - self.facts[left][2], at + self.facts[left][1], right
        return at

    def closing(self, a: int, first: int) -> int:
        """Where the bracket that opens at ``first`` is closed."""
        depth, todo = 0, [(a, 0)]
        while todo:
            x, at = todo.pop()
            height, n, _, step, low = self.facts[x]
            if at + n <= first:
                continue
            if at >= first and depth + low > 0:
                depth += step
            elif not height:
                return at
            else:
                left, right = self.parts[x]
                todo += [(right, at + self.facts[left][1]), (left, at)]
        raise IndexError(first)


def subtrees_program_balanced(g: Grammar, numbers: list[int]) -> tuple[dict, object]:
    """The same by substrings of the whole tree's program, balanced first: O(log) new rules for each number, any rank."""
    strings, program, of = Balanced(), traversal(g), {}
    for t in reversed(g.order()):
        for j in range(g.ranks[t] + 1):
            of[t, j] = None
            for x in program[t, j]:
                of[t, j] = strings.join(of[t, j], of[x[1]] if x[0] == "r" else strings.leaf(x))
    whole, roots = of[g.start, 0], []
    for u in sorted(numbers):
        a = strings.opening(whole, u)
        roots.append(strings.cut(whole, a, strings.closing(whole, a) + 1))
    out: dict = {"__all": [("r", x) for x in roots]}
    todo = list(roots)
    while todo:
        x = todo.pop()
        if x not in out:
            part = strings.parts[x]
            out[x] = [("r", y) for y in part] if strings.facts[x][0] else [part]
            todo += part if strings.facts[x][0] else ()
    return out, "__all"


def serialize_spans(g: Grammar, walker: Walker, nested: bool = True) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """The XML of each outermost selected node, once, with (pre-order number, start, stop) of every selected node in it, in order.

    Only stretches of the marked grammar that hold marks, or lie inside a result, are entered.  ``nested``: False leaves out results inside results.
    """
    marked = mark(g, walker)
    program, facts = traversal(marked), _marks(marked)
    out: list[tuple[str, list[tuple[int, int, int]]]] = []
    parts: list[str] = []
    spans: list[tuple[int, int, int]] = []
    opened: list[tuple[int, int, int]] = []  # number, depth inside, first character
    pre = depth = size = 0
    todo: list[tuple] = [("r", (marked.start, 0))]
    while todo:
        x = todo.pop()
        if x[0] == "r":
            if opened or facts[x[1]][1]:
                todo += reversed(program[x[1]])
            else:  # the brackets outside of results count, their depth doesn't matter
                pre += facts[x[1]][0]
        elif x[0] == "<":
            pre, depth = pre + 1, depth + 1
            if len(x) > 2 and (nested or not opened):
                opened.append((pre, depth, size))
            if opened:
                parts.append(token_text(x))
                size += len(parts[-1])
        else:
            if opened:
                parts.append(token_text(x))
                size += len(parts[-1])
                if depth == opened[-1][1]:
                    u, _, first = opened.pop()
                    spans.append((u, first, size))
                    if not opened:
                        out.append(("".join(parts), sorted(spans)))
                        parts, spans, size = [], [], 0
            depth -= 1
    return out


def _marks(marked: Grammar) -> dict:
    """(nodes, marks) of each stretch."""
    return {(t, j): x for t, (own, _) in gaps(marked).items() for j, x in enumerate(own)}


def serialize(g: Grammar, walker: Walker, nested: bool = True) -> list[tuple[int, str]]:
    """(pre-order number, XML) of every selected node, cut from the texts of the outermost ones."""
    return [(u, text[a:b]) for text, spans in serialize_spans(g, walker, nested) for u, a, b in spans]


def serialized_size(g: Grammar, walker: Walker) -> int:
    """Sum of the sizes (nodes) of all selected subtrees, without writing any.

    A node counts once for each selected node that holds it.  Each stretch of the marked grammar gives its nodes, by how many marked brackets it
    leaves more open, and the sum over its nodes of the marked brackets that are open there; stretches are put together bottom-up.
    """
    marked = mark(g, walker)
    program, facts = traversal(marked), {}
    for t in reversed(marked.order()):
        for j in range(marked.ranks[t] + 1):
            nodes = inside = total = 0
            for x in program[t, j]:
                if x[0] == "r":
                    n, more, own = facts[x[1]]
                    nodes, total, inside = nodes + n, total + own + n * inside, inside + more
                elif x[0] == "<":
                    inside += len(x) > 2
                    nodes, total = nodes + 1, total + inside
                else:
                    inside -= len(x) > 2
            facts[t, j] = (nodes, inside, total)
    return facts[marked.start, 0][2]


# ---- filters


def annotate(g: Grammar, query: PathQuery, mode: str = "table", stats: dict | None = None) -> Grammar:
    """The grammar whose labels carry, as a third entry, the bits of the filters that hold there.

    ``table``: templates specialised by the filter states of their slots, only for tuples that occur.  ``matrix``: the state at a
    template's root is first written as a constant and, for each slot, what each of its bits sets; tuples are specialised from that.
    ``lift``: marks that move up, for filters of child steps.  ``auto``: the cheapest by ``filter_plan``.
    """
    probes = query.probes
    if mode == "auto":
        mode, costs = filter_plan(g, query)
        if stats is not None:
            stats |= {"mode": mode, "costs": costs}
    if mode == "lift":
        return _lifted(g, probes, stats)
    widths = [2 * len(p) for p in probes]

    def node(label: str, left: int, right: int) -> tuple[int, int]:
        state = held = shift = 0
        for i, (p, w) in enumerate(zip(probes, widths)):
            m = (1 << w) - 1
            bits, true = probe_bits(p, label, left >> shift & m, right >> shift & m)
            state |= bits << shift
            held |= true << i
            shift += w
        return state, held

    total = sum(widths)
    roots: dict = {}
    if mode == "matrix":
        # every recurrence is a disjunction of single bits, so a body is affine over "or"
        for t in reversed(g.order()):
            stack: list = []
            for s in reversed(g.bodies[t]):
                if s[0] == "_":
                    stack.append((0, {}))
                elif s[0] == "y":
                    stack.append((0, {(s[1], b): 1 << b for b in range(total)}))
                elif s[0] == "t":
                    args = [stack.pop() for _ in range(g.ranks[s[1]])]
                    const, rows = roots[s[1]]
                    own: dict = {}
                    for (i, b), gives in rows.items():
                        c, r = args[i - 1]
                        if c >> b & 1:
                            const |= gives
                        for key, mask in r.items():
                            if mask >> b & 1:
                                own[key] = own.get(key, 0) | gives
                    stack.append((const, own))
                else:
                    (lc, lr), (rc, rr) = stack.pop(), stack.pop()
                    const = node(s[1], lc, rc)[0]
                    own = {}
                    for key, mask in lr.items():
                        own[key] = own.get(key, 0) | node(s[1], mask, 0)[0]
                    for key, mask in rr.items():
                        own[key] = own.get(key, 0) | node(s[1], 0, mask)[0]
                    base = node(s[1], 0, 0)[0]
                    own = {k: m & ~base for k, m in own.items()}
                    stack.append((const | base, own))
            roots[t] = stack[0]

    def root(t, slots):
        const, rows = roots[t]
        for (i, b), gives in rows.items():
            if slots[i - 1] >> b & 1:
                const |= gives
        return const

    def noted(s: tuple, left: int, right: int) -> tuple[int, tuple]:
        state, held = node(s[1], left, right)
        return state, (s[0], s[1], held)

    out, state = _specialised(g, noted, root if mode == "matrix" else None)
    if stats is not None:
        stats["root"] = state
        by: dict = defaultdict(int)
        for t, _ in out.bodies:
            by[t] += 1
        stats |= {"templates": len(g.bodies), "specialised": len(out.bodies), "most_tuples": max(by.values()), "bits": total}
    return trim(out)


def _specialised(g: Grammar, node, root=None) -> tuple[Grammar, int]:
    """Templates for each tuple of slot states that occurs, and the state at the root: ``node(symbol, left, right)`` gives a state and the new symbol, 0 is the
    state of an absent node.

    ``root(template, slots)``: the state at a template's root where it is known beforehand.
    """
    memo: dict = {}
    bodies: dict = {}
    todo = [(g.start, ())]
    while todo:
        t, slots = key = todo[-1]
        if key in bodies:
            todo.pop()
            continue
        stack, body, wait = [], [], None
        for s in reversed(g.bodies[t]):
            if s[0] == "_":
                stack.append(0)
            elif s[0] == "y":
                stack.append(slots[s[1] - 1])
            elif s[0] == "t":
                args = tuple(stack.pop() for _ in range(g.ranks[s[1]]))
                got = root(s[1], args) if root else memo.get((s[1], args))
                if got is None:
                    wait = (s[1], args)
                    break
                stack.append(got)
                s = ("t", (s[1], args))
            else:
                state, s = node(s, stack.pop(), stack.pop())
                stack.append(state)
            body.append(s)
        if wait:
            todo.append(wait)
            continue
        todo.pop()
        memo[key], bodies[key] = stack[0], body[::-1]
        todo += [s[1] for s in body if s[0] == "t" and s[1] not in bodies]
    return Grammar((g.start, ()), bodies, {(t, s): g.ranks[t] for t, s in bodies}), memo[g.start, ()]


def _lifted(g: Grammar, probes: tuple, stats: dict | None) -> Grammar:
    """Filters of child steps by marks that move up: the last nodes of a filter's path are marked from above, by the path as a query of its own, and marks then
    move to the parents, a step at a time.  A template is copied for those of its slots' sibling chains that have a mark."""
    copies = 0
    for bit, path in enumerate(probes):
        if any(s.axis != CHILD for s in path):
            raise QueryError("lifting takes filters of child steps only")
        g = mark(g, compile_query(PathQuery((Step(DESCENDANT, path[0].test), *path[1:]))), keep=True)
        for k in reversed(range(len(path))):

            def up(s: tuple, left: int, right: int, last: bool = not k, bit: int = bit) -> tuple[int, tuple]:
                held = s[2] if len(s) > 2 else 0
                # the state: this node, or a later sibling, is marked; a parent sees it in its first child's
                return int(s[0] == "m" or right), (("l", s[1], held | left << bit) if last else ("m" if left else "l", s[1], held))

            wide, _ = _specialised(g, up)
            copies += len(wide.bodies) - len({t for t, _ in wide.bodies})
            g = trim(wide)
    if stats is not None:
        stats |= {"copies": copies, "templates": len(g.bodies)}
    return g


def filter_plan(g: Grammar, query: PathQuery) -> tuple[str, dict[str, int]]:
    """The cheapest way to put a query's filters on a grammar, and what each is expected to cost: bounds by size, rank and state bits.

    Tables pay for every tuple of slot states, matrices for the bits of each slot, lifting (child steps only) for one bit a slot and a pass a step.
    """
    bits, k, size = sum(2 * len(p) for p in query.probes), g.rank(), max(1, g.edges())
    costs = {"table": size << min(bits * k, 200), "matrix": size * bits * (k * bits + 1)}
    if all(s.axis == CHILD for p in query.probes for s in p):
        costs["lift"] = (size << k) * sum(len(p) for p in query.probes)
    return min(costs, key=costs.__getitem__), costs


# ---- grammars as arrays


def encode(g: Grammar) -> tuple[list[str], list[int], list[int], list[int]]:
    """Labels, and for each template in order of use (the start first) its rank, its body's length and its symbols.

    A symbol is one number: 0 an absent node, 3 i + 1 label i, 3 i + 2 template i, 3 i slot i (from 1).
    """
    order = [g.start, *(t for t in g.order() if t != g.start)]
    number = {t: i for i, t in enumerate(order)}
    labels: dict[str, int] = {}
    code = {"_": lambda s: 0, "y": lambda s: 3 * s[1], "l": lambda s: 3 * labels.setdefault(s[1], len(labels)) + 1, "t": lambda s: 3 * number[s[1]] + 2}
    symbols = [code[s[0]](s) for t in order for s in g.bodies[t]]
    return list(labels), [g.ranks[t] for t in order], [len(g.bodies[t]) for t in order], symbols


def decode(labels: list[str], ranks: list[int], lengths: list[int], symbols: list[int]) -> Grammar:
    kinds = ([NULL, *(("y", i) for i in range(1, max(ranks, default=0) + 1))], [("l", w) for w in labels], [("t", i) for i in range(len(ranks))])
    body = [kinds[c % 3][c // 3] for c in symbols]
    bodies, at = {}, 0
    for t, n in enumerate(lengths):
        bodies[t], at = body[at : at + n], at + n
    return Grammar(0, bodies, dict(enumerate(ranks)))
