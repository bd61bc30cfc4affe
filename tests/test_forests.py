"""The Spark layer against the grammar functions and against itself."""

import random

import pyarrow as pa
import pyarrow.compute as pc
import pytest
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from sharetree.functions import grammar as G
from sharetree.operators import baseline, compress, evaluate, programs, segments
from sharetree.plans.query import QueryError, constants, depth_mod
from sharetree.sources import forests, stored
from sharetree.sources.forests import FORESTS, Forest, _under_root, binary, edges, html_tree, html_units, nodes, unranked
from sharetree.streaming import streams
from tests.test_grammar import brute, tree


@pytest.fixture(scope="module")
def spark():
    session = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "4g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    return session


@pytest.fixture(scope="module")
def forest(spark):
    r = random.Random(9)
    trees = [tree(r, depth=3) for _ in range(9)]
    trees = [(["a", *w[1:]], d) for w, d in trees] + [(["a"], [0])] * 3
    units = spark.createDataFrame([(i, i // 6 + 1, i % 6, w, d) for i, (w, d) in enumerate(trees)], "unit long, top int, before long, labels array<string>, depths array<int>")
    whole_labels, whole_depths = ["c"], [0]
    for t in (0, 1):
        whole_labels.append("b")
        whole_depths.append(1)
        for w, d in trees[6 * t : 6 * t + 6]:
            whole_labels += w
            whole_depths += [x + 2 for x in d]
    return Forest([(0, None, "c"), (1, 0, "b"), (2, 0, "b")], units), whole_labels, whole_depths


@pytest.mark.parametrize("text", ["//a", "/c/b/a/b", "/c/b/following-sibling::b/a", "//a/following-sibling::a//*", "//b[./a/c]/a[.//d]/*", "//*[.//b/c]", "/c[.//d]//a[./b]", "//c//b//a"])
def test_forest_counts_equal_the_whole_tree(forest, text):
    f, labels, depths = forest
    for options in ({}, {"compress": "digrams", "filters": "matrix"}, {"compress": "tree"}, {"compress": "hybrid"}):
        assert evaluate.count(f, text, **options).first().n == len(brute(text, labels, depths))


def test_user_walker_counts_by_depth(forest):
    f, _, depths = forest
    assert evaluate.count(f, depth_mod(3, 2)).first().n == sum(d % 3 == 2 for d in depths)


def test_sibling_filters_on_top_nodes_are_refused(forest):
    with pytest.raises(QueryError):
        evaluate.count(forest[0], "//b[./following-sibling::b]/a").first()


def test_binary_form_and_back(forest):
    f = forest[0]
    back = {r.unit: (r.labels, r.depths) for r in unranked(binary(nodes(f))).collect()}
    assert back == {r.unit: (r.labels, r.depths) for r in f.units.collect()}


def test_corpus_sharing_equals_one_dictionary(forest):
    f = forest[0]
    kinds = {"unranked": [], "binary": [], "hybrid": []}
    rows = f.units.collect()
    for kind, seen in kinds.items():
        pieces: dict = {}
        for r in rows:
            pieces |= compress.unit_pieces(r.labels, r.depths, kind)
        got = compress.sharing(f, kind).first()
        assert (got.shared_edges, got.shared_nodes) == (sum(pieces.values()), len(pieces))
        seen.append(got.shared_edges)
    assert kinds["hybrid"][0] <= min(kinds["unranked"][0], kinds["binary"][0])
    one = rows[0]
    assert sum(compress.unit_pieces(one.labels, one.depths, "binary").values()) == G.real_edges(G.binary_dag(one.labels, one.depths))
    assert sum(compress.unit_pieces(one.labels, one.depths, "hybrid").values()) == G.hybrid_edges(G.unranked_dag(one.labels, one.depths)[0])


def test_html_rules():
    assert html_tree("<!DOCTYPE html><HTML><p>a<br>b<p>c</html><!-- <i> --><script>if(a<b)'</p>'</script>") == (["html", "p", "br", "p", "script"], [0, 1, 2, 2, 0])
    assert html_tree("</b><a/><b></c></b>") == (["a", "b"], [0, 0])


def test_known_counts_on_the_pages(spark):
    f = FORESTS["pages"](spark, "/root/testdata/sf0.001")
    n = evaluate.count(f, "//p/b").first().n
    assert n == baseline.structural(f, "//p/b").count() == sum(r.n for r in baseline.paths(f, "//p/b").collect()) == evaluate.locate(f, "//p/b").count()
    size = programs.traversal_programs(f).collect()
    assert all(r.size <= 6 * r.edges for r in size)


@pytest.mark.parametrize("text", ["//*", "//b", "/c", "//b[./a/c]", "/c/b/following-sibling::b", "//a", "//b/a"])
def test_locate_and_serialize_take_in_the_nodes_above_units(forest, text):
    f, labels, depths = forest
    hits = [i + 1 for i in brute(text, labels, depths)]
    ends = [next((j for j in range(i + 1, len(depths)) if depths[j] <= depths[i]), len(depths)) for i in range(len(depths))]
    assert evaluate.locate(f, text).count() == len(hits)
    assert evaluate.serialized_size(f, text).first().s == sum(ends[u - 1] - u + 1 for u in hits)
    outer = [u for u in hits if not any(v < u <= ends[v - 1] for v in hits)]
    for nested, wanted in ((True, hits), (False, outer)):
        xml = [evaluate._xml(labels[u - 1 : ends[u - 1]], [d - depths[u - 1] for d in depths[u - 1 : ends[u - 1]]]) for u in wanted]
        assert sorted(r.xml for r in evaluate.serialize(f, text, nested=nested).collect()) == sorted(xml)
    top = {i + 1: w for i, w in enumerate("cbb")}
    assert all(top[r.pre] == r.label for r in evaluate.locate(f, text, with_label=True).where("unit is null").collect())


def test_everything_selected_on_the_pages(spark):
    assert evaluate.serialized_size(FORESTS["pages"](spark, "/root/testdata/sf0.01"), "//*").first().s == 58_219  # SURVEY W4
    assert [(r.unit, r.pre) for r in evaluate.locate(FORESTS["trade"](spark, "/root/testdata/sf0.001"), "/trade").collect()] == [(None, 1)]


@pytest.fixture(scope="module")
def odd_forest(spark):
    """Units without nodes, with several roots, with repeated and null ids, and roots of different labels."""
    trees = [("h", [0]), ("", []), ("dab", [0, 1, 1]), ("hd", [0, 0]), ("hab", [0, 1, 2]), ("", []), ("dh", [0, 1]), ("hab", [0, 1, 2])]
    ids = [1, 2, 2, None, 4, None, 6, 6]
    rows = [(u, 0, i, list(w), d) for i, (u, (w, d)) in enumerate(zip(ids, trees))]
    units = spark.createDataFrame(rows, "unit long, top int, before long, labels array<string>, depths array<int>")
    labels, depths = ["r"], [0]
    for w, d in trees:
        labels += w
        depths += [x + 1 for x in d]
    return Forest([(0, None, "r")], units), labels, depths


ODD_QUERIES = ["//h", "/r/d/following-sibling::h", "/r/h/following-sibling::d", "//a", "//h[./a/b]", "/r/h/following-sibling::h/a", "//*", "/r/d/following-sibling::d/following-sibling::h", "//a/following-sibling::b"]


@pytest.mark.parametrize("chunk", [evaluate.CHUNK, 3])
def test_odd_units_count_as_the_whole_tree(odd_forest, chunk, monkeypatch):
    f, labels, depths = odd_forest
    monkeypatch.setattr(evaluate, "CHUNK", chunk)
    got = {r.query: r.n for r in evaluate.count_many(f, ODD_QUERIES).collect()}
    assert got == {text: len(brute(text, labels, depths)) for text in ODD_QUERIES}
    for text in ODD_QUERIES[:4]:
        for options in ({}, {"compress": "digrams"}, {"compress": "hybrid"}, {"compress": "tree"}):
            assert evaluate.count(f, text, **options).first().n == got[text]


def test_odd_units_through_every_function(odd_forest):
    f, labels, depths = odd_forest
    assert evaluate.exists(f, "//a").count() == 8 and evaluate.exists(f, "//a").where("hit").count() == 3
    assert sorted((str(r.unit), r.pre, r.label) for r in evaluate.locate(f, "//b", with_label=True).collect()) == [("2", 3, "b"), ("4", 3, "b"), ("6", 3, "b")]
    assert evaluate.tree_size(f).first().total == len(labels) and evaluate.selectivity(f, "//b").first().n == 3
    assert [r.xml for r in evaluate.serialize(f, "/r").collect()] == [evaluate._xml(labels, depths)]
    assert evaluate.serialized_size(f, "//*").first().s == sum(d + 1 for d in depths)
    assert baseline.structural(f, "//a").count() == 3 and baseline.structural(f, "//h//b").count() == 2 and sum(r.n for r in baseline.paths(f, "//a").collect()) == 3
    assert nodes(f).count() == len(labels) - 1 and binary(nodes(f, keyed=True)).count() == len(labels) - 1
    for kind in ("unranked", "binary", "hybrid"):
        assert compress.sharing(f, kind).first().shared_nodes > 0
    assert compress.grammar_stats(f, "digrams").count() == 8 and programs.traversal_programs(f).count() == 8
    assert programs.subtree_programs(f, "//a").count() == 8


def test_stored_forest_answers_alike(spark, forest, tmp_path):
    f, labels, depths = forest
    for kind in ("binary", "digrams"):
        stored.save(f, f"file://{tmp_path}/{kind}", kind)
        g = stored.load(spark, f"file://{tmp_path}/{kind}")
        for text in ("//a", "//b[./a/c]", "//*", "/c/b/following-sibling::b"):
            hits = brute(text, labels, depths)
            assert evaluate.count(g, text, compress=kind).first().n == len(hits) == evaluate.locate(g, text, compress=kind).count()
            assert sorted(r.xml for r in evaluate.serialize(g, text, compress=kind).collect()) == sorted(r.xml for r in evaluate.serialize(f, text).collect())
        assert evaluate.count(g, "//a", compress="tree").first().n == len(brute("//a", labels, depths))
    assert {(r.unit, r.pre, r.label) for r in evaluate.node_at(f, nodes(f)).collect()} == {(r.unit, r.pre, r.label) for r in nodes(f).collect()}


def test_filters_lifted_and_planned(forest):
    f, labels, depths = forest
    for text in ("//b[./a/c]/a[./b]", "//a[./b/c]"):
        for options in ({"filters": "lift"}, {"filters": "auto"}, {"compress": "digrams", "filters": "lift"}, {"compress": "tree"}):
            assert evaluate.count(f, text, **options).first().n == len(brute(text, labels, depths))
    with pytest.raises(QueryError):
        evaluate.count(f, "//a" + "[.//b/c/d/a]" * 1 + "".join(f"[./{'a/' * k}b]" for k in range(1, 9))).first()


def test_segments_equal_whole_units(spark):
    r = random.Random(2)
    trees = [tree(r, depth=4) for _ in range(4)]
    trees = [(["u", *w[1:]], d) for w, d in trees]
    bare = Forest([(0, None, "r")], spark.createDataFrame([(i, 0, i, ["u"], [0]) for i in range(4)], "unit long, top int, before long, labels array<string>, depths array<int>"))
    whole = Forest([(0, None, "r")], spark.createDataFrame([(i, 0, i, w, d) for i, (w, d) in enumerate(trees)], "unit long, top int, before long, labels array<string>, depths array<int>"))
    cut = spark.createDataFrame([(i, k, w[5 * k : 5 * k + 5], d[5 * k : 5 * k + 5]) for i, (w, d) in enumerate(trees) for k in range(-(-len(w) // 5))], segments.SEGMENT)
    for text in ("//a/*/b", "/r/u/following-sibling::u//a", "//b/following-sibling::c/d"):
        want = sorted((x.unit, x.pre) for x in evaluate.locate(whole, text, top=False).collect())
        assert sorted((x.unit, x.pre) for x in segments.locate(bare, cut, text, 5).collect()) == want
        assert sum(x.n for x in segments.count_by_unit(bare, cut, text).collect()) == len(want)


def test_empty_pages_and_constants(spark):
    pages = spark.createDataFrame([(1, None), (2, ""), (3, "<p>x</p>"), (3, "<p class='k'>y</p><p><b>y</b></p>"), (None, "<i>")], "page_id long, html string")
    f = _under_root(html_units(pages, "page_id", "html"), "pages")
    assert evaluate.count(f, "//p").first().n == 3 and evaluate.count(f, "/pages/p/following-sibling::p").first().n == 2
    for text, n in (("//p[@class='k']", 1), ("//p[text()='x']", 1), ("//*[./b]", 1), ("//p", 3)):
        g = _under_root(html_units(pages, "page_id", "html", constants(text)), "pages")
        assert evaluate.count(g, text).first().n == n


def test_late_events_are_walked_in_order(spark, tmp_path):
    rows = [(i, i * 60, 1 if i % 3 else 2, ["view", "purchase", "error", "view"][i % 4]) for i in range(60)]
    random.Random(1).shuffle(rows)
    df = spark.createDataFrame(rows, "event_id long, s long, user_id long, event_type string").selectExpr("event_id", "timestamp_seconds(s) as ts", "user_id", "event_type")
    for k, part in enumerate(df.randomSplit([1.0, 1.0, 1.0], 4)):
        part.coalesce(1).write.parquet(f"file://{tmp_path}/in/{k}")
    events = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"file://{tmp_path}/in")
    got = {r.user_id: r.n for r in streams.drain(streams.walk_siblings(events, "//view/following-sibling::purchase", late="2 hours"), "update").groupBy("user_id").max("n").withColumnRenamed("max(n)", "n").collect()}
    want = {}
    for u in (1, 2):
        own = [e for _, _, v, e in sorted(rows) if v == u]
        want[u] = sum(e == "purchase" and "view" in own[:i] for i, e in enumerate(own))
    assert got == want


def test_edges_need_roots_and_may_be_empty(spark):
    links = spark.createDataFrame([("a", None, 1, "x"), ("b", "a", 2, "y"), ("c", "a", 1, "z"), ("d", "b", 1, "w"), ("e", "q", 1, "lost")], "id string, parent string, ord long, label string")
    assert [tuple(r) for r in edges(links).orderBy("pre").collect()] == [("a", 1, 0, 4, "x"), ("c", 2, 1, 1, "z"), ("b", 3, 1, 2, "y"), ("d", 4, 2, 1, "w")]
    assert edges(links.limit(0)).count() == 0


def test_segments_of_many_units_stay_whole_when_a_join_is_planned_anew(spark):
    """Rows of a side that is made smaller or broadcast on the way lie in other parts than the roots': each segment is still one row."""
    rows = spark.range(20_000).select((F.col("id") % 400).alias("user"), "id", F.lit("x" * 50).alias("label"))
    small = {"spark.sql.shuffle.partitions": "20", "spark.sql.adaptive.advisoryPartitionSizeInBytes": "4k", "spark.sql.adaptive.coalescePartitions.parallelismFirst": "false", "spark.sql.autoBroadcastJoinThreshold": "256k"}
    before = {k: spark.conf.get(k, None) for k in small}
    try:
        for k, v in small.items():
            spark.conf.set(k, v)
        cut = segments.sequence(rows, "user", ["id"], "label", "root", 20)
        keys = cut.select("unit", "segment", F.size("labels").alias("n")).collect()
        assert "Union" not in cut._jdf.queryExecution().executedPlan().toString() and cut.inputFiles()
    finally:
        for k, v in before.items():
            spark.conf.set(k, v) if v is not None else spark.conf.unset(k)
    assert len(keys) == len({(r.unit, r.segment) for r in keys}) == 400 * 3
    assert sum(r.n for r in keys) == 20_400


@pytest.mark.parametrize("name", ["cost_walker_rules", "cost_walker_states", "count_depthmod_chain", "udtf_walker_rules"])
def test_measures_take_their_rows_from_a_given_table(spark, name):
    import duckdb

    from sharetree.plans.workloads import ORACLES, QUERIES

    sf_dir, c = "/root/testdata/sf0.001", duckdb.connect()
    for t in ("customer", "orders", "lineitem"):
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    got, want = QUERIES[name](spark, sf_dir), c.sql(ORACLES[name])
    assert got.columns == want.columns
    assert sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, want.fetchall()))
    assert {f.split("/")[-1] for f in got.inputFiles()} & {"orders.parquet", "lineitem.parquet"}


def test_tasks_hold_a_bounded_number_of_nodes():
    import pyarrow as pa

    batch = pa.RecordBatch.from_arrays([pa.array(range(6)), pa.array([["a"] * 3, [], None, ["a"] * 9, ["a"] * 2, ["a"] * 2])], names=["k", "labels"])
    parts = [b.column(0).to_pylist() for b in evaluate.sliced(iter([batch]), 1, 4)]
    assert parts == [[0, 1, 2], [3], [4, 5]]


def test_all_kinds_of_sharing_are_measured_in_one_pass(spark):
    units = spark.createDataFrame([(1, ["a", "b", "c", "b", "c"], [0, 1, 2, 1, 2], 0, 0), (2, ["b", "c"], [0, 1], 0, 1), (3, [], [], 0, 2)], "unit long, labels array<string>, depths array<int>, top int, before long")
    for some in (units, units.where("unit = 3")):
        forest = Forest([(0, None, "t")], some)
        got = compress.ratios(forest)
        assert got._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") == 1
        want = {(k, *compress.sharing(forest, k).select("tree_edges", "shared_edges").first()) for k in compress.KINDS}
        assert {(r.kind, r.tree_edges, r.shared_edges) for r in got.collect()} == want


def test_names_over_arrays_tell_the_same_nodes_apart_as_digests(spark, monkeypatch):
    rng = random.Random(7)
    trees: list[tuple[list, list]] = [([], []), (["a"], [0]), (["a", "é", "é", "", "a"], [0, 0, 1, 1, 0]), (["a"] * 50, list(range(50))), (["a", "b"] * 20, [0, *([1] * 39)]), (["a", "b", "c"], [0, 2, 2])]
    for _ in range(150):
        depths = [0]
        for _ in range(rng.randrange(40)):
            depths.append(rng.randrange(rng.random() < 0.1, depths[-1] + 2))
        trees.append(([rng.choice("ab") for _ in depths], depths))
    want = {kind: {} for kind in compress.KINDS}
    for kind, own in want.items():
        for tree in trees:
            own |= compress.unit_pieces(*tree, kind)
    units = spark.createDataFrame([(i, *t, 0, i) for i, t in enumerate(trees)], "unit long, labels array<string>, depths array<int>, top int, before long")
    for most in (1, 500, 1_000_000):  # slices of one unit, of some, of all
        monkeypatch.setattr(compress, "NODES", most)
        batch = pa.RecordBatch.from_arrays([pa.array([t[0] for t in trees]), pa.array([t[1] for t in trees], pa.list_(pa.int32()))], names=["labels", "depths"])
        packed = pa.Table.from_batches(compress._all_pieces(iter([batch])))
        sums = {kind: 0 for kind in want}
        for bucket in packed["bucket"].unique().to_pylist():
            for kind, n in compress._edges(packed.filter(pc.equal(packed["bucket"], bucket))).to_pylist()[0].items():
                if kind in sums:
                    sums[kind] += n or 0
        assert sums == {kind: sum(own.values()) for kind, own in want.items()}
    got = {r.kind: (r.tree_edges, r.shared_edges) for r in compress.ratios(Forest([(0, None, "t")], units)).collect()}
    assert got == {kind: (sum(max(len(t[0]) - 1, 0) for t in trees), sum(own.values())) for kind, own in want.items()}
    nulls = spark.createDataFrame([([None, "a"], [0, 1]), (["", "a"], [0, 1]), (None, None), ([None, "a"], [0, 1])], "labels array<string>, depths array<int>")
    assert [(r.tree_edges, r.shared_edges) for r in compress.ratios(Forest([(0, None, "t")], nulls)).where("kind = 'unranked'").collect()] == [(3, 2)]


def test_what_needs_no_places_leaves_units_unplaced(spark, tmp_path):
    texts = [(1, None), (2, ""), (None, "x"), (4, " a  b \n\n c\r\n"), (5, "doc line\tq"), (6, "x")]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    forest = forests.prose(spark, str(tmp_path))
    shared = {r.kind: r.shared_edges for r in compress.ratios(forest).collect()}
    assert not forest.has_units
    assert {(r.unit, r.before): (r.labels, r.depths) for r in forest.units.collect()} == {
        (None, 0): (["doc", "line", "x"], [0, 1, 2]), (1, 1): (["doc", "line"], [0, 1]), (2, 2): (["doc", "line"], [0, 1]),
        (4, 3): (["doc", "line", "a", "b", "line", "line", "c\r", "line"], [0, 1, 2, 2, 1, 1, 2, 1]),
        (5, 4): (["doc", "line", "doc", "line\tq"], [0, 1, 2, 2]), (6, 5): (["doc", "line", "x"], [0, 1, 2]),
    }
    assert forest.has_units and shared == {r.kind: r.shared_edges for r in compress.ratios(forest).collect()}
