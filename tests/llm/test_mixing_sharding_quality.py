import hashlib
import math
import zlib
from collections import Counter

import numpy as np

import corpus_pipeline
from sharetree.llm import decontaminate, quality
from sharetree.llm.mixing import mix
from sharetree.llm.sharding import shard, write_shards
from sharetree.llm.storage import scratch_path
from tests.llm.conftest import ODD_ROWS


def test_mixture_meets_its_weights_and_keeps_columns(spark):
    rows = [(i, f"text {i} " * 5, "big" if i % 3 else f"s{i % 4}", i) for i in range(6000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, copy int")
    out = mix(docs, {"big": 1.0, "s0": 1.0, "s1": 1.0, "s2": 1.0, "s3": 1.0}, epochs=1.0)
    assert out.columns == ["doc_id", "text", "source", "copy_in", "copy", "shuffle_key"]
    got = Counter(r.source for r in out.collect())
    assert all(abs(n / sum(got.values()) - 0.2) < 0.02 for n in got.values()) and abs(sum(got.values()) - 6000) < 250
    assert sorted(map(str, out.collect())) == sorted(map(str, mix(docs, {}, epochs=1.0).collect()))
    parts = [[r.shuffle_key for r in p] for p in out.rdd.glom().collect()]
    assert [k for p in parts for k in p] == sorted(k for p in parts for k in p)  # partitions follow each other


def test_large_rates_and_zero_weights(spark):
    docs = spark.createDataFrame([(i, "x" * 92, "a" if i else "b") for i in range(1001)], "doc_id long, text string, source string")
    out = mix(docs, {"a": 0.0, "b": 1.0}, epochs=1.0, shuffle=False)
    assert {r.source for r in out.collect()} == {"b"} and abs(out.count() - 1001) < 6 * math.sqrt(1001)


def test_mixture_of_odd_rows(spark, odd):
    assert mix(odd.limit(0), {}).count() == 0
    assert {r.source for r in mix(odd, {None: 3.0}, epochs=20.0).collect()} == {None, "a", "b", "c"}


def test_shards(spark, odd):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    for df, n in ((docs, 7), (odd, 24), (odd.limit(0), 3)):
        rows = shard(df, n).collect()
        sizes = Counter(r.shard for r in rows)
        assert len(rows) == df.count() and (not rows or max(sizes[i] for i in range(n)) - min(sizes[i] for i in range(n)) <= 1)
        for s, k in sizes.items():
            assert sorted(r.slot for r in rows if r.shard == s) == list(range(k))
    want = sorted((r[0], len((r[1] or "").encode()) + 8, zlib.crc32((r[1] or "").encode())) for r in ODD_ROWS if r[0] is not None)
    assert sorted((r.doc_id, r.size, r.text_crc32) for r in shard(odd, 24).collect() if r.doc_id is not None) == want
    # the definition, by brute force
    key = lambda r: hashlib.md5(f"42:{r.doc_id}:{r.text}".encode()).hexdigest()
    all_rows, order = docs.collect(), []
    for s in {r.source for r in all_rows}:
        own = sorted((r for r in all_rows if r.source == s), key=key)
        order += [((2 * i + 1) / (2 * len(own)), key(r), r.doc_id) for i, r in enumerate(own)]
    got = {r.doc_id: r.position for r in shard(docs, 7).collect()}
    assert [got[d] for _, _, d in sorted(order)] == list(range(len(order)))


def test_written_shards_hold_all_rows(spark, odd):
    path = scratch_path(spark, "shards")
    write_shards(odd, path, 3)
    back = spark.read.parquet(path)
    assert back.count() == odd.count() and sorted(map(str, back.select(*odd.columns).collect())) == sorted(map(str, odd.collect()))


def words(text):
    import re

    return re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", (text or "").translate(str.maketrans(decontaminate.UPPER, decontaminate.LOWER)))


def test_decontamination_equals_brute_force_both_ways(spark):
    rows = [(1, "A b, c d e f g h i J k l m"), (2, "nothing here"), (3, "short ITEM x"), (4, None), (5, ""), (6, "a b c d e f g h i"), (7, "z a b c d e f g h i j a b c d e f g h i j k"), (8, "é e"), (1, "short item")]
    items = [(10, "a b c d e f g h i j"), (11, "short-item"), (12, None), (13, "..."), (14, "b c d e f g h i j k l"), (15, "É e")]
    docs, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    want = []
    for d, t in rows:
        w, hit, found = words(t), set(), set()
        for i, x in items:
            b = words(x)
            n = min(10, len(b))
            for k in range(len(b) - n + 1) if b else ():
                for a in range(len(w) - n + 1):
                    if w[a : a + n] == b[k : k + n]:
                        hit |= set(range(a, a + n))
                        found.add(str(i))
        want.append((d, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    for most in (1000, 0):
        assert sorted(map(tuple, decontaminate.contamination(docs, bench, max_broadcast=most).collect()), key=str) == sorted(want, key=str)
        clean = decontaminate.remove_contaminated(docs.selectExpr("*", "1 as w", "2 as found", "3 as rid"), bench, max_broadcast=most)
        assert sorted(r.doc_id for r in clean.collect()) == [2, 4, 5, 6, 8] and clean.columns == ["doc_id", "text", "w", "found", "rid"]
    left = {(r.doc_id, r.text) for r in decontaminate.remove_spans(docs, bench).collect()}
    assert (1, " m") in left and (3, " x") in left and (2, "nothing here") in left and (4, None) in left
    assert decontaminate.contamination(docs, bench.limit(0)).where("contaminated").count() == 0 and decontaminate.contamination(docs.limit(0), bench).count() == 0


def test_quality_field(spark, odd):
    good = [f"This is a plain line of words number {i}.\nAnother calm sentence, quite long.".encode() for i in range(60)]
    bad = [f"BUY!! NOW!! {i}!!\nWIN### $$$ CASH%%%\nBUY!! NOW!!".encode() for i in range(60)]
    field = quality.fit(good[:50] + bad[:50], [1] * 50 + [0] * 50, 60)
    assert field.scores(good[50:]).min() > 0.9 and field.scores(bad[50:]).max() < 0.1
    # marginals of the chain against all labellings
    x, counts, _ = quality.line_features([bad[0] + b"\n" + good[0]])
    score = np.stack([np.zeros(len(x)), x @ field.weights], 1)
    total = np.zeros(len(x) + 1)
    for bits in range(1 << len(x)):
        y = [bits >> i & 1 for i in range(len(x))]
        p = math.exp(sum(score[i, y[i]] for i in range(len(x))) + sum(field.pairs[a, b] for a, b in zip(y, y[1:])))
        total += p * np.array([1, *y])
    assert np.allclose(field.marginals(x, counts)[0], total[1:] / total[0])
    rows = quality.score(odd, field).collect()
    assert len(rows) == odd.count() and all(0 <= r.score <= 1 for r in rows)
    assert quality.keep_good(odd, field, 0.0).columns == odd.columns and quality.score(odd.limit(0), field).count() == 0
    assert [r.held_out for r in rows if r.doc_id is not None] == [zlib.crc32(str(r.doc_id).encode()) % 5 == 0 for r in rows if r.doc_id is not None]


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    got = quality.score(docs, quality.fit_from(docs, labels)).where("held_out").join(labels, "doc_id").collect()
    assert sum(r.predicted == r.quality for r in got) / len(got) > 0.9


def pairs(df):
    return sorted(((r.doc_id, r.text) for r in df.select("doc_id", "text").collect()), key=repr)


def one_of_each_component(rows):
    from tests.llm.test_near_duplicates import sets_of

    sets, up = [sets_of(t) for _, t in rows], list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                up[root(i)] = root(j)
    order = lambda i: (rows[i][0] is None, rows[i][0] or 0, hashlib.md5((rows[i][1] or "").encode()).hexdigest())
    best = {}
    for i in range(len(rows)):
        k = root(i)
        best[k] = min(best.get(k, i), i, key=order)
    return sorted((rows[i] for i in best.values()), key=repr)


def without_benchmark(rows, items):
    grams = set()
    for x in items:
        w = words(x)
        n = min(10, len(w))
        grams |= {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()
    lengths = {len(g) for g in grams}
    clean = lambda w: not any(tuple(w[i : i + n]) in grams for n in lengths for i in range(len(w) - n + 1))
    return sorted((r for r in rows if clean(words(r[1]))), key=repr)


def mixed(rows, weights, seed):
    size = Counter()
    for _, text, source in rows:
        size[source] += len((text or "").encode()) + 8
    weight = {s: weights.get(s, 1.0) for s in size}
    out = []
    for d, text, s in rows:
        rate = weight[s] / sum(weight.values()) * 1.0 * sum(size.values()) / size[s]
        digest = hashlib.md5(f"{'~' if d is None else d}:{text or ''}".encode()).hexdigest()
        parts = max(1, math.ceil(rate / 200))
        mean, k = rate / parts, 0
        for part in range(1, parts + 1):
            u = int(hashlib.md5(f"{seed}:{part}:{digest}".encode()).hexdigest()[:13], 16) / 2**52
            p = cdf = math.exp(-mean)
            n = 0
            while cdf <= u and n <= math.ceil(mean + 12 * math.sqrt(mean) + 20):
                n += 1
                p *= mean / n
                cdf += p
            k += n
        out += [(d, text)] * k
    return sorted(out, key=repr)


def test_pipeline_stages_equal_brute_force(spark, odd):
    from sharetree.llm.registry import MIX_WEIGHTS, SEED, tokenizer_path
    from sharetree.llm.storage import materialize, table
    from sharetree.llm.token_store import encoder

    sf = "/root/testdata/sf0.001"
    whole = table(spark, sf, "documents")
    # awkward rows, and columns with the names of inner ones
    docs = whole.unionByName(odd.select(*whole.columns)).selectExpr("*", "1 as row", "2 as score", "3 as copy", "4 as text_key", "5 as rid", "6 as kept")
    docs = materialize(docs, "pipeline-test")
    field = quality.fit_from(docs, table(spark, sf, "labels"))
    items = [r.text for r in table(spark, sf, "benchmark").collect()]
    seen = []
    for name, stage in corpus_pipeline.STAGES:
        before = [(r.doc_id, r.text) for r in docs.collect()]
        out = materialize(stage(spark, docs, sf), name)
        seen.append((len(before), out.count()))
        if name == "quality_classifier":
            want = sorted((r for r, x in zip(before, field.scores([(t or "").encode() for _, t in before])) if x >= quality.THRESHOLD), key=repr)
        elif name == "near_dedup":
            want = one_of_each_component(before)
        elif name == "benchmark_decontamination":
            want = without_benchmark(before, items)
        elif name == "target_mixture":
            want = mixed([(r.doc_id, r.text, r.source) for r in docs.collect()], MIX_WEIGHTS, SEED)
        else:
            t = encoder(tokenizer_path()).tokenizer
            ids = [(d, np.array([*t.encode(x or "", add_special_tokens=False).ids, 2], "<u4")) for d, x in before]
            got = out.orderBy("start").collect()
            assert sorted(((r.doc_id, r.n_tokens, r.ids_crc32) for r in got), key=repr) == sorted(((d, len(x), zlib.crc32(x.tobytes())) for d, x in ids), key=repr)
            assert got[0].start == 0 and all(a.start + a.n_tokens == b.start for a, b in zip(got, got[1:]))
            break
        assert pairs(out) == want and out.columns == docs.columns, name
        docs = out
    assert all(b < a for a, b in seen[:3])  # each of the first three found something to remove


def test_pipeline_of_an_empty_table(spark, odd):
    sf, docs = "/root/testdata/sf0.001", odd.limit(0)
    from sharetree.llm.storage import materialize

    for name, stage in corpus_pipeline.STAGES[1:4]:
        docs = materialize(stage(spark, docs, sf), name)
        assert docs.columns == odd.columns and docs.count() == 0


def test_fit_keeps_lines_compactly():
    import tracemalloc

    rng = np.random.default_rng(5)
    words = [b"alpha", b"Beta", b"9", b"||", b"the", b"a,", b"\xc3\xa9t\xc3\xa9"]
    texts = [b"\n".join(b" ".join(words[i] for i in rng.integers(0, 7, 12)) for _ in range(n)) for n in rng.integers(1, 400, 200)]
    labels = [int(i) % 2 for i in range(200)]
    tracemalloc.start()
    quality.fit(texts, labels, 2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 60e6  # for 2 MB of text; all features at once took 196e6
    lines = quality.Lines(texts[:60])
    x, counts, _ = quality.line_features(texts[:60])
    w, r = rng.normal(size=x.shape[1]), rng.normal(size=len(x))
    assert np.allclose(lines.scores(w), x @ w) and np.allclose(lines.sums(r), r @ x) and (lines.counts == counts).all()
