"""Worked examples and random trees: every method on every grammar against a brute-force walk of the tree."""

import random

import pytest

from sharetree.functions import grammar as G
from sharetree.plans import query as Q


def tree(r, depth=5, kids=3, names="abcd"):
    labels, depths = [], []

    def grow(d):
        labels.append(r.choice(names))
        depths.append(d)
        if d < depth:
            for _ in range(r.randint(0, kids)):
                grow(d + 1)

    grow(0)
    return labels, depths


def brute(text, labels, depths):
    """Set-at-a-time evaluation."""
    kids, _ = G.from_tree(labels, depths)
    parent = {k: i for i, own in enumerate(kids) for k in own}
    below = lambda i: [k for c in kids[i] for k in (c, *below(c))]
    later = lambda i: [k for k in kids[parent[i]] if k > i] if i in parent else []

    def walk(steps, now, top):
        for s in steps:
            out = set()
            for i in now:
                if i is None:
                    near = {Q.CHILD: [0], Q.DESCENDANT: range(len(labels)), Q.FOLLOWING: []}[s.axis]
                else:
                    near = kids[i] if s.axis == Q.CHILD else below(i) if s.axis == Q.DESCENDANT else later(i)
                out |= {k for k in near if s.accepts(labels[k]) and all(walk(p, {k}, False) for p in s.probes)}
            now = out
        return now

    return sorted(walk(Q.parse(text).steps, {None}, True))


def random_query(r, filters=True):
    axes = ["/", "//", "/following-sibling::"]
    step = lambda: r.choice(axes) + r.choice("abcd*")
    out = ""
    for _ in range(r.randint(1, 4)):
        out += step()
        if filters and r.random() < 0.3:
            out += "[." + "".join(step() for _ in range(r.randint(1, 2))) + "]"
    return out


def xml(labels, depths, i):
    kids, _ = G.from_tree(labels, depths)
    return f"<{labels[i]}>" + "".join(xml(labels, depths, k) for k in kids[i]) + f"</{labels[i]}>"


@pytest.mark.parametrize("seed", range(60))
def test_all_methods_on_random_trees(seed):
    r = random.Random(seed)
    labels, depths = tree(r)
    plain = G.binary_dag(labels, depths)
    higher = G.digrams(plain, rounds=12, least=2)
    hybrid = G.hybrid_dag(labels, depths)
    dag, _ = G.unranked_dag(labels, depths)
    assert G.hybrid_edges(dag) <= min(G.real_edges(plain), sum(len(k) for _, k in dag))
    assert G.expand(plain) == G.expand(higher) == G.expand(hybrid)
    assert not G.validate(higher) and not G.validate(plain) and not G.validate(hybrid)
    assert G.tree_size(higher) == len(labels)
    for _ in range(6):
        text = random_query(r)
        query, want = Q.parse(text), [i + 1 for i in brute(text, labels, depths)]
        for g in (plain, higher, hybrid):
            lifts = all(s.axis == Q.CHILD for p in query.probes for s in p)
            for mode in ("table", "matrix", "auto", *(["lift"] if lifts else [])):
                noted = G.annotate(g, query, mode) if query.probes else g
                w = Q.compile_query(query)
                assert G.count(noted, w) == len(want)
                assert G.locate(noted, Q.compile_query(query, prune=False)) == want
                assert G.locate(noted, w, offsets="eager") == want
                assert G.locate(noted, w, limit=2) == want[:2]
                assert G.serialize(noted, w) == [(u, xml(labels, depths, u - 1)) for u in want]
            if not query.probes:
                assert G.count(g, Q.compile_query(query), "full") == len(want) == G.count(g, Q.minimise(Q.compile_query(query)))
        size = lambda i: xml(labels, depths, i).count("</")
        noted = G.annotate(higher, query) if query.probes else higher
        assert G.serialized_size(noted, Q.compile_query(query)) == sum(size(u - 1) for u in want)
        some = sorted(r.sample(range(1, len(labels) + 1), min(4, len(labels))))
        for program, start in (G.subtrees_program(higher, some), G.subtrees_program_dag(plain, some), G.subtrees_program_dag(hybrid, some), G.subtrees_program_balanced(higher, some)):
            assert "".join(map(G.token_text, G.program_tokens(program, start))) == "".join(xml(labels, depths, u - 1) for u in some)
    program = G.traversal(higher)
    whole = list(G.program_tokens(program, (higher.start, 0)))
    assert len(whole) == 2 * len(labels) == G.program_length(program, (higher.start, 0))
    assert list(G.program_tokens(program, (higher.start, 0), 3, 9)) == whole[3:9]
    assert [G.program_at(program, (higher.start, 0), i) for i in range(len(whole))] == whole
    for g in (plain, higher, hybrid):
        assert [G.node_at(g, u)[1] for u in range(1, len(labels) + 1)] == labels
        back = G.decode(*G.encode(g))
        assert not G.validate(back) and G.expand(back) == G.expand(plain) and back.edges() == g.edges()
    full = G.digrams(plain)
    assert not G.validate(full) and G.expand(full) == G.expand(plain)
    with pytest.raises(IndexError):
        G.node_at(higher, len(labels) + 1)


def test_the_empty_forest():
    for g in (G.binary_dag([], []), G.hybrid_dag([], []), G.digrams(G.binary_dag([], []))):
        w = Q.compile_query("//a")
        assert not G.validate(g) and G.count(g, w) == G.serialized_size(g, w) == 0 and G.locate(g, w) == G.serialize(g, w) == []
        assert G.annotate(g, Q.parse("//a[./b]")).bodies and G.decode(*G.encode(g)).bodies == {0: [G.NULL]}


def test_several_roots():
    labels, depths = list("abacab"), [0, 1, 0, 1, 0, 1]
    for g in (G.binary_dag(labels, depths), G.hybrid_dag(labels, depths), G.digrams(G.binary_dag(labels, depths), least=2)):
        assert G.tree_size(g) == 6 and G.locate(g, Q.user_walker([(0, None, True, 0, 0)]), with_label=True) == list(enumerate(labels, 1))


def test_serializing_does_not_expand_the_tree():
    g, leaf = G.chain("a", 40), Q.compile_query("//e")
    assert G.serialize(g, leaf) == [(2**40 + 1, "<e></e>")] and G.serialized_size(g, leaf) == 1
    assert G.serialized_size(G.chain("a", 100), Q.compile_query("/a")) == 2**100 + 1
    assert G.node_at(g, 2**40 + 1)[1] == "e"
    program, start = G.subtrees_program_balanced(g, [2**39, 2**40 + 1])
    assert G.program_length(program, start) == 2 * (2**40 + 1 - 2**39 + 1) + 2 and len(program) < 2000


def test_spans_of_nested_results():
    labels, depths = list("abab"), [0, 1, 2, 3]
    ((text, spans),) = G.serialize_spans(G.binary_dag(labels, depths), Q.compile_query("//b"))
    assert text == "<b><a><b></b></a></b>" and [(u, text[a:b]) for u, a, b in spans] == [(2, text), (4, "<b></b>")]
    assert [len(s) for _, s in G.serialize_spans(G.binary_dag(labels, depths), Q.compile_query("//b"), nested=False)] == [1]


def test_subtrees_of_a_long_sibling_chain():
    labels, depths = ["r"] + ["x", "y"] * 3000, [0] + [1] * 6000
    program, start = G.subtrees_program_dag(G.binary_dag(labels, depths), list(range(2, 6002)))
    assert G.program_length(program, start) == 12_000
    assert len(G.serialize(G.binary_dag(labels, depths), Q.compile_query("//x"))) == 3000


def test_the_plan_of_filters():
    r = random.Random(4)
    labels, depths = tree(r, depth=6)
    plain, higher = G.binary_dag(labels, depths), G.digrams(G.binary_dag(labels, depths), least=2)
    query = Q.parse("//a[./b/c/d]/b")
    assert G.filter_plan(plain, query)[0] == "table" and G.filter_plan(higher, query)[0] == "lift" and G.filter_plan(higher, Q.parse("//a[.//b/c/d]/b"))[0] == "matrix"
    stats: dict = {}
    G.annotate(higher, query, "lift", stats)
    assert stats["copies"] >= 0
    with pytest.raises(Q.QueryError):
        G.annotate(higher, Q.parse("//a[.//b]"), "lift")


def library():
    return G.Grammar("S", {"S": [("l", "lib"), ("t", "B"), ("t", "B"), G.NULL, G.NULL], "B": [("l", "book"), ("t", "T"), ("y", 1)], "T": [("l", "title"), G.NULL, ("l", "author"), G.NULL, G.NULL]}, {"S": 0, "B": 1, "T": 0})


def test_library_grammar():
    g = library()
    assert not G.validate(g) and g.edges() == 10 and g.rank() == 1 and G.tree_size(g) == 7
    assert G.locate(g, Q.compile_query("//author")) == [4, 7] and G.locate(g, Q.compile_query("//book")) == [2, 5]
    assert G.gaps(g)["B"][0] == [(3, 0), (0, 0)]


def monadic():
    return Q.user_walker([(0, None, False, 1, 0), (1, None, False, 2, 0), (2, None, True, 0, 0), (0, "e", False, 0, 0), (1, "e", False, 0, 0), (2, "e", False, 0, 0)])


def test_chain_of_sixteen():
    g = G.chain("a", 4)
    # the worked grammar has the doubling in three templates above a pair of labels
    g.bodies[3] = [("l", "a"), ("l", "a"), ("y", 1), G.NULL, G.NULL]
    del g.bodies[4], g.ranks[4]
    w = monadic()
    memo = G.behaviours(g, w, "full")
    assert [memo[3, q] for q in range(3)] == [((2,), 0), ((0,), 1), ((1,), 1)]
    assert [memo[2, q][1] for q in range(3)] == [1, 1, 2] and [memo[1, q][1] for q in range(3)] == [2, 3, 3]
    assert G.count(g, w) == 5 and G.locate(g, w) == [3, 6, 9, 12, 15]
    marked = G.mark(g, w)
    assert len(marked.bodies) == 9
    program = G.traversal(marked)
    used = {k: v for k, v in program.items() if v}
    assert len(used) == 17 and G.program_length(program, (marked.start, 0)) == 34


def test_exponential_compression():
    for n in (10, 40, 100):
        assert G.count(G.chain("a", n), monadic()) == (2**n + 1) // 3
    with pytest.raises(OverflowError):
        G.count(G.chain("a", 130), monadic())


def test_states_and_the_printed_automaton():
    assert [Q.compile_query("//a" + "/*" * k + "/b").close().states for k in range(6)] == [2, 4, 8, 16, 32, 64]
    assert Q.compile_query("/a/following-sibling::b/c").close().states == 4
    ours = Q.compile_query("//a/*/b//c/d").close()
    rows = "0a1 0%0 1a2 1%3 2a2 2b4 2%3 3a2 3b4 3%3 4c5 4%4 5c5 5d6 5%4 6c5 6%4".split()
    printed = Q.user_walker([(int(x[0]), None if x[1] == "%" else x[1], x == "5d6", int(x[2]), int(x[0])) for x in rows])

    def path(walker, names):
        q = walker.start
        for n in names:
            s, q, _ = walker.rule(q, n)
        return s

    assert path(ours, "axbcd") and path(printed, "axbcd")
    assert path(printed, "abxbcd") and not path(ours, "abxbcd")


@pytest.mark.parametrize("text", ["", "a", "//a[b]", "//a[./b[./c]]", "/ancestor::a", "//_", "//a[./b", "//following-sibling::a"])
def test_bad_queries(text):
    with pytest.raises(Q.QueryError):
        Q.parse(text)


def test_bad_grammars():
    n, a = G.NULL, ("l", "a")
    bad = {
        "slot twice": ({"S": [("t", "A"), a, n, n], "A": [a, ("y", 1), ("y", 1)]}, {"S": 0, "A": 1}),
        "slot order": ({"S": [("t", "A"), n, n], "A": [a, ("y", 2), ("y", 1)]}, {"S": 0, "A": 2}),
        "circle": ({"S": [a, ("t", "A"), n], "A": [a, ("t", "A"), n]}, {"S": 0, "A": 0}),
        "unreachable": ({"S": [a, n, n], "A": [a, n, n]}, {"S": 0, "A": 0}),
        "arity": ({"S": [a, n]}, {"S": 0}),
        "start": ({"S": [a, ("y", 1), n]}, {"S": 1}),
        "dangling": ({"S": [a, ("t", "X"), n]}, {"S": 0}),
    }
    for name, (bodies, ranks) in bad.items():
        assert G.validate(G.Grammar("S", bodies, ranks)), name
    for rows in ([(0, None, False, 0, 0), (0, None, True, 0, 0)], [(0, "a", False, 0, 0)]):
        with pytest.raises(Q.QueryError):
            Q.user_walker(rows)
