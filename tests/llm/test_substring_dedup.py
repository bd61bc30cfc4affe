import hashlib
import random
from collections import defaultdict

import pytest

from sharetree.llm.substring_dedup import repeated_bytes, repeated_words
from sharetree.llm.suffix_sort import common_prefix, deep_shallow, extents

sha = lambda b: hashlib.sha256(b).hexdigest()


def brute_bytes(rows, length):
    seen = defaultdict(int)
    data = [(d, (t or "").encode()) for d, t in rows]
    for _, b in data:
        for i in range(len(b) - length + 1):
            seen[hash(b[i : i + length])] += 1
    out = []
    for d, b in data:
        hit = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if seen[hash(b[i : i + length])] > 1:
                hit[i : i + length] = b"\1" * length
        runs = sum(1 for i, x in enumerate(hit) if x and (i == 0 or not hit[i - 1]))
        out.append((d, len(b), sum(hit), runs, sha(bytes(x for x, h in zip(b, hit) if not h))))
    return sorted(out, key=repr)


def brute_words(rows, length):
    first = {}
    data = [(d, (t or "").encode().split()) for d, t in rows]
    order = lambda d: (d is None, d or 0)
    for d, w in data:
        for i in range(len(w) - length + 1):
            k = tuple(w[i : i + length])
            first[k] = min(first.get(k, order(d)), order(d))
    out = []
    for d, w in data:
        hit = [False] * len(w)
        for i in range(len(w) - length + 1):
            if first[tuple(w[i : i + length])] < order(d):
                hit[i : i + length] = [True] * length
        out.append((d, len(w), sum(hit), sha(b" ".join(x for x, h in zip(w, hit) if not h))))
    return sorted(out, key=repr)


def corpus(seed):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abé") for _ in range(r.randint(1, 3)))
    passages = [" ".join(word() for _ in range(r.randint(5, 25))) for _ in range(6)]
    rows = []
    for d in range(60):
        parts = [r.choice(passages) if r.random() < 0.4 else " ".join(word() for _ in range(r.randint(1, 12))) for _ in range(r.randint(0, 6))]
        rows.append((d if r.random() < 0.9 else r.choice([None, 3]), r.choice([" ", "\n", "  "]).join(parts)))
    rows += [rows[4], rows[4], (99, "ab " * 70), (98, "aaaa" * 40), (97, None), (96, ""), (95, rows[7][1])]
    return rows


@pytest.mark.parametrize("group", [4000, 3])
def test_bytes_equal_brute_force(spark, group):
    rows = corpus(1)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(map(tuple, repeated_bytes(docs, 24, 8, group).collect()), key=repr) == brute_bytes(rows, 24)


@pytest.mark.parametrize("group", [4000, 3])
def test_words_equal_brute_force(spark, group):
    rows = corpus(2)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(map(tuple, repeated_words(docs, 8, 3, group, 500).collect()), key=repr) == brute_words(rows, 8)


def test_bytes_with_production_parameters(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    want = brute_bytes(rows, 400)
    assert sorted(map(tuple, repeated_bytes(docs).collect()), key=repr) == want
    assert any(r[2] for r in want)


def test_empty_and_extra_columns(spark, odd):
    assert repeated_bytes(odd.limit(0)).count() == repeated_words(odd.limit(0)).count() == 0
    clash = odd.selectExpr("*", "1 as text_key", "2 as spans", "3 as first")
    assert repeated_bytes(clash).count() == repeated_words(clash).count() == odd.count()
    kept = {r.doc_id: r.kept for r in repeated_words(odd, digest=False).collect()}
    assert kept[2] == "" and kept[5] == "lead and tab end"


def test_sorting_and_extents_equal_brute_force():
    r = random.Random(3)
    for trial in range(300):
        n, letters = r.randint(1, 12), b"ab" if trial % 2 else b"abcd"
        some = lambda most: bytes(r.choice(letters) for _ in range(r.randint(0, most)))
        base = some(30)
        strings = [base[: r.randint(0, 30)] + some(10) for _ in range(n)]
        order, shared = deep_shallow(strings, r.choice([0, 8, 16, 96]))
        assert [strings[i] for i in order] == sorted(strings)
        assert all(shared[i] == common_prefix(strings[order[i - 1]], strings[order[i]]) for i in range(1, n))
        lefts = [some(6) for _ in range(n)]
        for ranks in (None, [r.randint(0, 4) for _ in range(n)]):
            got = extents(lefts, strings, ranks, 1, 5)
            for x in range(n):
                cover = lambda pairs: {(p, q) for a, b in pairs for p in range(a + 1) for q in range(b + 1) if p + q >= 5}
                true = [(common_prefix(lefts[x], lefts[y]), common_prefix(strings[x], strings[y])) for y in range(n) if y != x and (ranks is None or ranks[y] < ranks[x])]
                assert cover(got[x]) == cover(true)
