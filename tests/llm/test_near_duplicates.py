import random

import numpy as np
import pytest

from sharetree.llm.components import components
from sharetree.llm.near_duplicates import HASHES, ROWS, deduplicate, least_matches, links, near_duplicates, signature


def sets_of(text):
    w = (text or "").encode().lower().split()
    k = min(5, len(w))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if k else set()


def brute(rows):
    sets = [sets_of(t) for _, t in rows]
    up = list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 75 * (len(sets[i]) + len(sets[j]) - both):
                up[root(i)] = root(j)
    least = {}
    order = lambda d: (d is None, d or 0)
    for i, (d, _) in enumerate(rows):
        r = root(i)
        least[r] = min(least.get(r, d), d, key=order)
    return [(d, len(sets[i]), least[root(i)] if sets[i] else d) for i, (d, _) in enumerate(rows)]


def corpus(seed):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(3))
    rows = []
    for g in range(12):
        base = [word() for _ in range(r.randint(30, 120))]
        for _ in range(r.randint(1, 14)):
            copy = list(base)
            for _ in range(r.randint(0, 3)):
                copy[r.randrange(len(copy))] = word()
            rows.append((len(rows), " ".join(copy)))
    rows += [(500, "one two"), (501, "ONE  two"), (502, None), (503, ""), (504, " \n"), (505, rows[0][1]), (506, rows[0][1].upper())]
    return rows


@pytest.mark.parametrize("bucket", [4000, 3])
def test_equal_to_brute_force(spark, bucket):
    rows = corpus(5)
    got = near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), bucket)
    assert sorted((r.doc_id, r.n_shingles, r.component_id) for r in got.collect()) == sorted(brute(rows))


def test_whole_table_equals_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    got = near_duplicates(docs).collect()
    assert sorted((r.doc_id, r.n_shingles, r.component_id) for r in got) == sorted(brute([(r.doc_id, r.text) for r in docs.collect()]))


def test_odd_rows(spark, odd):
    got = near_duplicates(odd).collect()
    assert len(got) == odd.count() and near_duplicates(odd.limit(0)).count() == 0
    stay = deduplicate(odd.selectExpr("*", "1 as text_key", "2 as kept"))
    assert stay.columns == [*odd.columns, "text_key", "kept"]
    assert sorted(str(r.text) for r in stay.collect()) == sorted({str(r.text) for r in odd.collect()})


def test_components_of_a_path(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(0, 40)] + [(100, 101), (102, 101), (7, 7)], "a long, b long")
    assert {(r.node, r.component) for r in components(edges).collect()} == {(i, 0) for i in range(41)} | {(100, 100), (101, 100), (102, 100)}
    assert components(edges.limit(0)).count() == 0


def test_few_edges_are_contracted_by_one_task(spark):
    rows = [(i, i + 1) for i in range(40)] + [(101, 100), (102, 100), (100, 101), (7, 7)]
    edges = spark.createDataFrame(rows, "a long, b long")
    want = {(i, 0) for i in range(41)} | {(100, 100), (101, 100), (102, 100)}
    for few in (0, len(rows)):  # 0: by rounds
        got = [(r.node, r.component) for r in components(edges, few=few).collect()]
        assert len(got) == len(want) and set(got) == want
    context = spark.sparkContext
    context.setJobGroup("few-edges", "")
    components(edges).collect()
    context.setJobGroup("other", "")
    assert len(context.statusTracker().getJobIdsForGroup("few-edges")) < 8  # each round alone is several jobs


def test_bounds_and_signatures():
    bounds = least_matches()
    assert len(bounds) == HASHES // 16 and bounds == sorted(bounds) and bounds[-1] < 96
    items = np.unique(np.random.default_rng(1).integers(0, 1 << 63, 2000).astype(np.uint64))
    near = np.concatenate([items[:1800], items[1800:] + np.uint64(1)])
    assert abs((signature(items) == signature(near)).mean() - 1800 / 2200) < 0.15


@pytest.mark.parametrize("bucket", [4000, 8, 3])
def test_a_link_that_shares_only_a_large_bucket(spark, bucket):
    r = np.random.default_rng(3)
    table = r.integers(0, 1 << 32, (30, HASHES)).astype("<u4")
    table[:, :ROWS] = 7  # one bucket of all
    table[1] = table[0]
    table[1, ROWS::ROWS] += 1  # the pair agrees in no other band
    # as many small components, and one that fills blocks of its own
    table[20:] = table[20]
    words = [" ".join(f"w{i}x{j}" for j in range(40)) for i in range(30)]
    words[1] = words[0] + " more"
    words[20:] = [words[20] + " z" * i for i in range(10)]
    classes = spark.createDataFrame([(i, bytearray(table[i].tobytes())) for i in range(30)], "node long, signature binary")
    texts = spark.createDataFrame(list(enumerate(words)), "node long, text string")
    parts = {x.node: x.component for x in components(links(classes, lambda nodes: texts.join(nodes, "node"), bucket)).collect()}
    assert parts == {0: 0, 1: 0} | dict.fromkeys(range(20, 30), 20)
