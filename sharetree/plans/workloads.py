"""More of the registry: stored grammars, several queries at once, measures with their bounds, and the relational surface in full."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sharetree.functions import sql as surface
from sharetree.operators import baseline, compress, evaluate, programs, segments
from sharetree.plans.query import acceptor, compile_query, constants, path_dfa, walker_from_dfa
from sharetree.plans.registry import _CONV, _LOCATE_LOG, _PATHS, _TALK_NODES, _USERS, _W1, LINES, LOG, ORACLES, PAGES, QUERIES, TALK, N, _count, add, of_nodes, on, segment_paths
from sharetree.sources import forests, stored
from sharetree.sources.forests import binary, nodes, opened
from sharetree.sources.scratch import scratch
from sharetree.sources.tables import table
from sharetree.streaming import streams

__all__ = ["ORACLES", "QUERIES"]

# ---- stored grammars: written, read back, queried


def _reloaded(spark: SparkSession, sf_dir: str, name: str, compressor: str = "binary"):
    path = scratch(spark, f"stored-{name}")
    stored.save(opened(spark, sf_dir, name), path, compressor)
    return stored.load(spark, path)


def from_store(name: str, f, *args, **options):
    return lambda spark, sf_dir: f(_reloaded(spark, sf_dir, name, options.get("compress", "binary")), *args, **options)


for _name, _mode in (("w1_trade", "binary"), ("w2_log", "binary"), ("w1_pages", "digrams"), ("w2_pages", "hybrid"), ("filter_w7_trade", "digrams"), ("depthmod_pages", "binary")):
    if _name == "depthmod_pages":
        from sharetree.plans.query import depth_mod

        add("stored_count_depthmod_pages", from_store("pages", evaluate.count, depth_mod(3, 2)), ORACLES["count_depthmod_pages"])
    else:
        _forest, _query, _oracle = _count[_name]
        add(f"stored_count_{_name}", from_store(_forest, evaluate.count, _query, compress=_mode), _oracle)
add("stored_locate_w2_log", from_store("log", evaluate.locate, "//view/following-sibling::purchase"), _LOCATE_LOG)
add("stored_serialize_conv_talk", from_store("talk", evaluate.serialize, "/corpus/conv", compress="digrams"), _CONV)
add("stored_serialize_whole_talk", from_store("talk", evaluate.serialize, "//*", nested=False), ORACLES["serialize_whole_outermost_talk"])
add("grammar_starts_talk", lambda spark, sf_dir: stored.rules(opened(spark, sf_dir, "talk")).where("template = 0").agg(F.count("*").alias("n"), F.max("level").alias("level"), F.max("rank").alias("rank")), "WITH l AS (SELECT list(role ORDER BY turn, role) AS w FROM conversations GROUP BY conv_id) SELECT CAST(count(DISTINCT w) AS BIGINT) AS n, CAST(0 AS INTEGER) AS level, CAST(0 AS INTEGER) AS rank FROM l")
add("grammar_rules_talk", lambda spark, sf_dir: stored.rules(opened(spark, sf_dir, "talk")).groupBy("rank").agg(F.count("*").alias("n")), "WITH l AS (SELECT DISTINCT list(role ORDER BY turn, role) AS w FROM conversations GROUP BY conv_id) SELECT CAST(0 AS INTEGER) AS rank, CAST(sum(len(w) + 1) AS BIGINT) AS n FROM l")


def _source(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "stored-talk")
    stored.save(opened(spark, sf_dir, "talk"), path)
    if not path.startswith(("file:", "/")):  # the data source reads mounted folders only
        return stored.rules(stored.load(spark, path)).groupBy("entry").agg(F.count("*").alias("nodes")).agg(F.count("*").alias("n"), F.sum("nodes").cast("long").alias("nodes"))
    stored.register(spark)
    return spark.read.format("sharetree").load(path).agg(F.count("*").alias("n"), F.sum("nodes").cast("long").alias("nodes"))


add("grammar_source", _source, "WITH l AS (SELECT DISTINCT list(role ORDER BY turn, role) AS w FROM conversations GROUP BY conv_id) SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(len(w) + 1) AS BIGINT) AS nodes FROM l")

# ---- more methods

_MANY = ["//p", "//p/b", "//li/a", "//a/*/b", "/pages"]
add("count_many_pages", on("pages", evaluate.count_many, _MANY), PAGES + "SELECT '//p' AS query, CAST(count(*) AS BIGINT) AS n FROM n WHERE label = 'p' UNION ALL SELECT '//p/b', CAST(count(*) AS BIGINT) FROM n WHERE path LIKE '%/p/b' UNION ALL SELECT '//li/a', CAST(count(*) AS BIGINT) FROM n WHERE path LIKE '%/li/a' UNION ALL SELECT '//a/*/b', CAST(0 AS BIGINT) UNION ALL SELECT '/pages', CAST(1 AS BIGINT)")
add("count_w1_trade_dfa", lambda spark, sf_dir: evaluate.count(opened(spark, sf_dir, "trade"), walker_from_dfa(path_dfa("//region/*/customer//lineitem/R"))), ORACLES["count_w1_trade"])
add("count_w1_pages_dfa", lambda spark, sf_dir: evaluate.count(opened(spark, sf_dir, "pages"), walker_from_dfa(path_dfa("//html/*/nav//li/a"))), ORACLES["count_w1_pages"])
_ATTR = "//a[@href='/The']"
add("count_attr_pages", lambda spark, sf_dir: evaluate.count(forests.pages(spark, sf_dir, constants(_ATTR)), _ATTR), PAGES + "SELECT CAST(sum(len(regexp_extract_all(h, '<a\\b[^>]*href=\"/The\"[^>]*>'))) AS BIGINT) AS n FROM clean")
_TEXT = "//li/a[text()='and']"
add("count_text_pages", lambda spark, sf_dir: evaluate.count(forests.pages(spark, sf_dir, constants(_TEXT)), _TEXT), PAGES + "SELECT CAST(sum(len(regexp_extract_all(h, '<li><a\\b[^>]*>\\s*and\\s*</a>'))) AS BIGINT) AS n FROM clean")
for _name, _mode in (("filter_w8_order", "lift"), ("filter_w8_nation", "lift"), ("filter_two_steps", "lift"), ("filter_w7_pages", "auto"), ("filter_w8_order", "auto"), ("filter_two_steps", "matrix"), ("filter_w8_order", "matrix")):
    _forest, _query, _oracle = _count[_name]
    add(f"count_{_name}_{_mode}", on(_forest, evaluate.count, _query, compress="digrams", filters=_mode), _oracle)
for _name in ("filter_w7_trade", "filter_w7_pages", "filter_w8_order", "filter_two_steps"):
    _forest, _query, _oracle = _count[_name]
    add(f"count_{_name}_tree", on(_forest, evaluate.count, _query, compress="tree"), _oracle)
add("node_at_pages", lambda spark, sf_dir: evaluate.node_at(opened(spark, sf_dir, "pages"), evaluate.locate(opened(spark, sf_dir, "pages"), "//body/*")).drop("template"), ORACLES["locate_labels_pages"])
add("locate_w1_trade", on("trade", evaluate.locate, "//region/*/customer//lineitem/R"), None)
add("locate_depthmod_pages", lambda spark, sf_dir: evaluate.locate(opened(spark, sf_dir, "pages"), depth_mod(3, 2)), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre FROM n WHERE (depth + 1) % 3 = 2")
add("locate_w2_pages", on("pages", evaluate.locate, "//li/following-sibling::li/a"), PAGES + "SELECT CAST(a.page_id AS BIGINT) AS unit, CAST(a.pre AS BIGINT) AS pre FROM n a JOIN n l ON l.page_id = a.page_id AND l.pre = a.parent_pre AND l.label = 'li' WHERE a.label = 'a' AND EXISTS (SELECT 1 FROM n b WHERE b.page_id = l.page_id AND b.parent_pre = l.parent_pre AND b.pre < l.pre AND b.label = 'li')")
add("locate_w2_log_tree", on("log", evaluate.locate, "//view/following-sibling::purchase", compress="tree"), _LOCATE_LOG)
# no user's turn may follow a user's turn: state 0 above, 1 before a turn, 2 after a user's, 9 rejects
_TURNS = [(0, None, 1, 0), (1, None, 1, 1), (1, "user", 1, 2), (2, None, 1, 1), (2, "user", 1, 9), (9, None, 9, 9), (1, "conv", 1, 1)]
add("accepts_turns_talk", lambda spark, sf_dir: evaluate.accepts(opened(spark, sf_dir, "talk"), acceptor(_TURNS, 9)), "SELECT CAST(conv_id AS BIGINT) AS unit, NOT bool_or(role = 'user' AND coalesce(before = 'user', false)) AS accepted FROM (SELECT conv_id, role, lag(role) OVER (PARTITION BY conv_id ORDER BY turn, role) AS before FROM conversations) GROUP BY conv_id")
for _size in (50, 7):
    add(f"segments_count_w2_log_{_size}", lambda spark, sf_dir, k=_size: segments.count_by_unit(*segments.log(spark, sf_dir, k), "//view/following-sibling::purchase").where("n > 0"), ORACLES["count_by_user_w2"])
add("segments_locate_w2_log", lambda spark, sf_dir: segments.locate(*segments.log(spark, sf_dir, 20), "//view/following-sibling::purchase", 20), _LOCATE_LOG)
add("segments_units_log", lambda spark, sf_dir: segments.count_by_unit(*segments.log(spark, sf_dir, 30), "/log/user/following-sibling::user/view").agg(F.sum("n").cast("long").alias("n")), ORACLES["count_units_log"])

# ---- subtrees of pages and of trade, in SQL: stop is the number after a node's last descendant

_STOPS = PAGES + """, e AS (SELECT a.page_id, a.pre, a.parent_pre, a.depth, a.label, coalesce(min(b.pre), (SELECT max(pre) FROM n c WHERE c.page_id = a.page_id) + 1) AS stop
 FROM n a LEFT JOIN n b ON b.page_id = a.page_id AND b.pre > a.pre AND b.depth <= a.depth GROUP BY a.page_id, a.pre, a.parent_pre, a.depth, a.label)
"""
_UL = "x AS (SELECT e.page_id, e.pre, d.pre AS pos, 1 AS kind, 0 AS deep, '<' || d.label || '>' AS token FROM e JOIN e d ON d.page_id = e.page_id AND d.pre >= e.pre AND d.pre < e.stop WHERE e.label = 'ul' UNION ALL SELECT e.page_id, e.pre, d.stop, 0, -d.depth, '</' || d.label || '>' FROM e JOIN e d ON d.page_id = e.page_id AND d.pre >= e.pre AND d.pre < e.stop WHERE e.label = 'ul'), u AS (SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, string_agg(token, '' ORDER BY pos, kind, deep) AS xml FROM x GROUP BY page_id, pre)"
ORACLES["serialize_ul_pages"] = f"{_STOPS}, {_UL} SELECT * FROM u"
add("spans_ul_pages", lambda spark, sf_dir: evaluate.spans(opened(spark, sf_dir, "pages"), "//ul").select("unit", F.explode("results").alias("r"), "xml").select("unit", "r.pre", F.expr("substring(xml, cast(r.start + 1 as int), cast(r.stop - r.start as int))").alias("xml")), ORACLES["serialize_ul_pages"])
add("serialize_ul_pages_digrams", on("pages", evaluate.serialize, "//ul", compress="digrams"), ORACLES["serialize_ul_pages"])
add("serialize_ul_pages_tree", on("pages", evaluate.serialize, "//ul", compress="tree"), ORACLES["serialize_ul_pages"])
add("slp_dag_ul_pages", lambda spark, sf_dir: programs.subtree_programs(opened(spark, sf_dir, "pages"), "/html//ul").select("unit", "r", "length", "text"), f"{_STOPS}, {_UL} SELECT p.page_id::BIGINT AS unit, CAST(count(u.pre) AS BIGINT) AS r, CAST(coalesce(sum(len(regexp_extract_all(u.xml, '<'))), 0) AS BIGINT) AS length, coalesce(string_agg(u.xml, '' ORDER BY u.pre), '') AS text FROM pages p LEFT JOIN u ON u.unit = p.page_id GROUP BY p.page_id")
add("slp_subtrees_balanced_talk", lambda spark, sf_dir: programs.subtree_programs(opened(spark, sf_dir, "talk"), "//user", "balanced", "digrams").select("unit", "r", "length", "text"), _USERS)

_T = """WITH l AS (SELECT l_orderkey, list(l_returnflag ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity, l_extendedprice, l_returnflag) AS f FROM lineitem GROUP BY l_orderkey),
o AS (SELECT o_custkey, o_orderkey, 'status' || o_orderstatus AS st, coalesce(f, []) AS f, 2 + 2 * len(coalesce(f, [])) AS s FROM orders JOIN customer ON o_custkey = c_custkey LEFT JOIN l ON l_orderkey = o_orderkey),
w AS (SELECT *, CAST(3 + coalesce(sum(s) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS pre FROM o),
c AS (SELECT c_custkey, any_value(c_mktsegment) AS seg, coalesce(list(st || '(' || array_to_string(f, ',') || ')' ORDER BY o_orderkey) FILTER (o_orderkey IS NOT NULL), []) AS os, CAST(2 + coalesce(sum(s), 0) AS BIGINT) AS size FROM customer LEFT JOIN o ON o_custkey = c_custkey GROUP BY c_custkey)
"""
add("serialize_order_trade", on("trade", evaluate.serialize, "//order"), _T + "SELECT CAST(o_custkey AS BIGINT) AS unit, pre, '<order><' || st || '></' || st || '>' || array_to_string(list_transform(f, lambda x: '<lineitem><' || x || '></' || x || '></lineitem>'), '') || '</order>' AS xml FROM w")
add("slp_subtrees_order_trade", lambda spark, sf_dir: programs.subtree_programs(opened(spark, sf_dir, "trade"), "/customer/order", text=False).select("unit", "r", "length"), _T + "SELECT CAST(c_custkey AS BIGINT) AS unit, CAST(len(os) AS BIGINT) AS r, 2 * (size - 2) AS length FROM c")
add("slp_traversal_lengths_trade", lambda spark, sf_dir: programs.traversal_programs(opened(spark, sf_dir, "trade"), "digrams").select("unit", "length"), _T + "SELECT CAST(c_custkey AS BIGINT) AS unit, 2 * size AS length FROM c")
add("slp_lengths_pages", lambda spark, sf_dir: programs.traversal_programs(opened(spark, sf_dir, "pages")).select("unit", "length"), PAGES + "SELECT CAST(p.page_id AS BIGINT) AS unit, CAST(2 * count(n.pre) AS BIGINT) AS length FROM pages p LEFT JOIN n ON n.page_id = p.page_id GROUP BY p.page_id")
ORACLES["trade_nodes"] = _T + """SELECT CAST(c_custkey AS BIGINT) AS unit, CAST(1 AS BIGINT) AS pre, CAST(NULL AS BIGINT) AS parent_pre, CAST(0 AS INTEGER) AS depth, size, 'customer' AS label FROM c
UNION ALL SELECT c_custkey, 2, 1, 1, 1, seg FROM c
UNION ALL SELECT o_custkey, pre, 1, 1, s, 'order' FROM w
UNION ALL SELECT o_custkey, pre + 1, pre, 2, 1, st FROM w
UNION ALL SELECT o_custkey, pre + 2 * i, pre, 2, 2, 'lineitem' FROM (SELECT *, unnest(generate_series(1, len(f))) AS i FROM w)
UNION ALL SELECT o_custkey, pre + 2 * i + 1, pre + 2 * i, 3, 1, f[i] FROM (SELECT *, unnest(generate_series(1, len(f))) AS i FROM w)"""

# ---- sharing, in SQL: a node of the binary kinds is a suffix of a child list

_SUBTREES = f"""{_STOPS}, s AS (SELECT e.page_id, e.pre, e.parent_pre, string_agg(d.label || ':' || (d.depth - e.depth), ',' ORDER BY d.pre) AS sig, count(*) FILTER (d.depth = e.depth + 1) AS kids FROM e JOIN n d ON d.page_id = e.page_id AND d.pre >= e.pre AND d.pre < e.stop GROUP BY e.page_id, e.pre, e.parent_pre),
t AS (SELECT e.page_id, e.pre, string_agg(d.label || ':' || (d.depth - e.depth), ',' ORDER BY d.pre) AS suf, bool_or(d.depth = e.depth AND d.pre > e.pre) AS more, bool_or(d.depth = e.depth + 1 AND d.pre < e.stop) AS has FROM e JOIN e p ON p.page_id = e.page_id AND p.pre = e.parent_pre JOIN n d ON d.page_id = e.page_id AND d.pre >= e.pre AND d.pre < p.stop GROUP BY e.page_id, e.pre)
"""
_PAGE_EDGES = "SELECT count(*) - count(DISTINCT page_id) FROM n"
_KINDS = {
    "pages": (_SUBTREES, _PAGE_EDGES, {
        "unranked": "SELECT DISTINCT sig, kids AS edges FROM s",
        "binary": "SELECT DISTINCT suf, CAST(has AS INTEGER) + CAST(more AS INTEGER) AS edges FROM t UNION SELECT sig, CAST(kids > 0 AS INTEGER) FROM s WHERE parent_pre IS NULL",
        "hybrid": "SELECT DISTINCT 'c' || suf, CAST(more AS INTEGER) AS edges FROM t UNION SELECT 'e' || sig, CAST(kids > 0 AS INTEGER) FROM s",
    }),
    "trade": (_T, "SELECT sum(size - 1) FROM c", {
        "unranked": "SELECT DISTINCT seg || array_to_string(os, ';') AS x, 1 + len(os) AS edges FROM c UNION ALL SELECT DISTINCT st || '(' || array_to_string(f, ','), 1 + len(f) FROM o UNION ALL SELECT DISTINCT 'lineitem' || l_returnflag, 1 FROM lineitem UNION ALL SELECT DISTINCT x, 0 FROM (SELECT seg AS x FROM c UNION ALL SELECT st FROM o UNION ALL SELECT l_returnflag FROM lineitem)",
        "binary": "SELECT DISTINCT 'r' || seg || array_to_string(os, ';') AS x, 1 AS edges FROM c UNION ALL SELECT DISTINCT seg || array_to_string(os, ';'), CAST(len(os) > 0 AS INTEGER) FROM c UNION ALL SELECT DISTINCT array_to_string(os[i:], ';'), 1 + CAST(len(os) > i AS INTEGER) FROM (SELECT os, unnest(generate_series(1, len(os))) AS i FROM c) UNION ALL SELECT DISTINCT st || '(' || array_to_string(f, ','), CAST(len(f) > 0 AS INTEGER) FROM o UNION ALL SELECT DISTINCT array_to_string(f[i:], ','), 1 + CAST(len(f) > i AS INTEGER) FROM (SELECT f, unnest(generate_series(1, len(f))) AS i FROM o) UNION ALL SELECT DISTINCT 'flag' || l_returnflag, 0 FROM lineitem",
        "hybrid": "SELECT DISTINCT seg || array_to_string(os, ';') AS x, CAST(len(os) > 0 AS INTEGER) AS edges FROM c UNION ALL SELECT DISTINCT array_to_string(os[i:], ';'), CAST(len(os) > i AS INTEGER) FROM (SELECT os, unnest(generate_series(1, len(os))) AS i FROM c) UNION ALL SELECT DISTINCT st || '(' || array_to_string(f, ','), CAST(len(f) > 0 AS INTEGER) FROM o UNION ALL SELECT DISTINCT array_to_string(f[i:], ','), CAST(len(f) > i AS INTEGER) FROM (SELECT f, unnest(generate_series(1, len(f))) AS i FROM o) UNION ALL SELECT DISTINCT 'flag' || l_returnflag, 0 FROM lineitem UNION ALL SELECT DISTINCT 'r' || seg || array_to_string(os, ';'), 1 FROM c UNION ALL SELECT DISTINCT 'o' || st || '(' || array_to_string(f, ','), 1 FROM o UNION ALL SELECT DISTINCT 'lineitem' || l_returnflag, 1 FROM lineitem UNION ALL SELECT DISTINCT 'leaf' || x, 0 FROM (SELECT seg AS x FROM c UNION ALL SELECT st FROM o UNION ALL SELECT l_returnflag FROM lineitem)",
    }),
}
for _name, (_ctes, _tree, _by_kind) in _KINDS.items():
    for _kind, _sql in _by_kind.items():
        ORACLES[f"{_kind}_stats_{_name}"] = f"{_ctes} SELECT CAST(({_tree}) AS BIGINT) AS tree_edges, CAST(sum(edges) AS BIGINT) AS shared_edges, CAST(count(*) AS BIGINT) AS shared_nodes FROM ({_sql})"
    _rows = " UNION ALL ".join(f"SELECT '{k}' AS kind, CAST(({_tree}) AS BIGINT) AS tree_edges, CAST((SELECT sum(edges) FROM ({q})) AS BIGINT) AS shared_edges" for k, q in _by_kind.items())
    add(f"cost_ratio_{_name}", on(_name, compress.ratios), f"{_ctes} SELECT kind, tree_edges, shared_edges, shared_edges / CAST(tree_edges AS DOUBLE) AS ratio FROM ({_rows})")
_ALL = ["pages", "trade", "log", "talk", "prose", "parts", "bench"]
add("sharing_invariant", lambda spark, sf_dir: reduce(DataFrame.unionByName, (compress.hybrid_is_least(opened(spark, sf_dir, x)).withColumn("forest", F.lit(x)) for x in _ALL)), "SELECT x AS forest, true AS holds FROM (VALUES " + ", ".join(f"('{x}')" for x in _ALL) + ") t(x)")
add("agg_distinct_subtrees", lambda spark, sf_dir: compress.piece_rows(opened(spark, sf_dir, "pages").units, "unranked").agg(F.countDistinct("digest").alias("n")), f"{_SUBTREES} SELECT CAST(count(DISTINCT sig) AS BIGINT) AS n FROM s")
add("digram_top", on("pages", compress.frequent_pairs, 200), PAGES + ", k AS (SELECT *, row_number() OVER (PARTITION BY page_id, parent_pre ORDER BY pre) AS nth, lead(label) OVER (PARTITION BY page_id, parent_pre ORDER BY pre) AS after FROM n), pairs AS (SELECT p.label AS parent, 'first child' AS side, c.label AS child FROM k c JOIN n p ON p.page_id = c.page_id AND p.pre = c.parent_pre WHERE c.nth = 1 UNION ALL SELECT label, 'next sibling', after FROM k WHERE after IS NOT NULL) SELECT parent, side, child, CAST(count(*) AS BIGINT) AS n FROM pairs GROUP BY ALL HAVING count(*) >= 200")

# ---- measures and their bounds


def _within(df: DataFrame, holds) -> DataFrame:
    return df.agg(F.count("*").alias("units"), F.min(holds).alias("holds"))


_OF = {"pages": "pages", "talk": "(SELECT DISTINCT conv_id FROM conversations)", "trade": "customer"}
_QUERY = {"pages": "//html/*/nav//li/a", "talk": "//system/following-sibling::user", "trade": "//customer[./order/lineitem/R]/order"}
for _name in ("pages", "talk"):
    _holds = f"SELECT CAST(count(*) AS BIGINT) AS units, true AS holds FROM {_OF[_name]}"
    for _mode in ("full", "demand"):
        add(f"cost_visits_{_mode}_{_name}", lambda s, d, x=_name, m=_mode: _within(programs.count_work(opened(s, d, x), _QUERY[x], m), F.col("visits") <= F.col("bound")), _holds)
    add(f"cost_marked_{_name}", lambda s, d, x=_name: _within(programs.mark_sizes(opened(s, d, x), _QUERY[x]), (F.col("kept") <= F.col("made")) & (F.col("made") <= F.col("templates") * F.col("states")) & (F.col("marked_edges") <= F.col("edges") * F.col("states"))), _holds)
    for _method, _mode in (("plain", "binary"), ("general", "digrams")):
        add(f"cost_slp_{_method}_{_name}", lambda s, d, x=_name, m=_method, c=_mode: _within(programs.output_sizes(opened(s, d, x), _QUERY[x], m, c), F.col("size") <= F.col("bound")), _holds)
add("cost_output_talk", lambda s, d: programs.output_sizes(opened(s, d, "talk"), "//user").select("unit", "r", "tokens"), _USERS.replace(", repeat(", ", repeat(").replace("AS length", "AS tokens").split(", repeat(")[0] + " FROM conversations GROUP BY conv_id")
add("cost_lift_trade", lambda s, d: _within(programs.lift_costs(opened(s, d, "trade"), _QUERY["trade"]), F.col("copies") >= 0), "SELECT CAST(count(*) AS BIGINT) AS units, true AS holds FROM customer")
_RULES = "(VALUES (0, NULL, false, 0, 0), (0, 'a', false, 0, 0), (0, 'b', false, 0, 0), (0, 'c', false, 0, 0), (1, NULL, false, 0, 1), (1, 'a', false, 0, 3), (1, 'b', false, 0, 1), (1, 'c', false, 0, 1), (3, NULL, false, 0, 3), (3, 'a', false, 0, 3), (3, 'b', false, 4, 3), (3, 'c', false, 0, 3), (4, NULL, false, 0, 4), (4, 'a', false, 0, 4), (4, 'b', false, 0, 4), (4, 'c', true, 0, 4)) t(q, label, selects, a, b)"
ORACLES["cost_walker_rules"] = f"SELECT query, CAST(q AS BIGINT) AS q, CASE t.label WHEN 'a' THEN split_part(query, '/', 2) WHEN 'b' THEN 'order' WHEN 'c' THEN split_part(query, '/', 4) END AS label, selects, CAST(a AS BIGINT) AS q_left, CAST(b AS BIGINT) AS q_right FROM ({_PATHS}), {_RULES}"
_SELECT = "SELECT CAST(count(*) FILTER ({0}) AS BIGINT) AS n, CAST(count(*) + 1 AS BIGINT) AS total, count(*) FILTER ({0}) / CAST(count(*) + 1 AS DOUBLE) AS ratio FROM n"
for _name, _query, _where in (("p", "//p", "label = 'p'"), ("pb", "//p/b", "path LIKE '%/p/b'"), ("lia", "//li/a", "path LIKE '%/li/a'")):
    add(f"selectivity_{_name}_pages", on("pages", evaluate.selectivity, _query), PAGES + _SELECT.format(_where))
add("selectivity_w1_trade", on("trade", evaluate.selectivity, "//region/*/customer//lineitem/R"), f"WITH a AS ({ORACLES['count_all_trade']}), w AS ({ORACLES['count_w1_trade']}) SELECT w.n, a.n AS total, w.n / CAST(a.n AS DOUBLE) AS ratio FROM a, w")
ORACLES["locate_w1_trade"] = _T + "SELECT CAST(o_custkey AS BIGINT) AS unit, pre + 2 * i + 1 AS pre FROM (SELECT *, unnest(generate_series(1, len(f))) AS i FROM w) WHERE f[i] = 'R'"

# ---- baselines

add("baseline_structural_w7", lambda s, d: baseline.structural(opened(s, d, "trade"), "//customer[./BUILDING]/order/lineitem/R").agg(F.count("*").alias("n")), ORACLES["count_w7_part_trade"])
add("baseline_structural_orders", on("trade", baseline.structural, "//order"), ORACLES["locate_orders_trade"])
add("baseline_locate_orders_tree", on("trade", evaluate.locate, "//order", compress="tree"), ORACLES["locate_orders_trade"])
add("baseline_xpath_talk", lambda s, d: evaluate.serialize(opened(s, d, "talk"), "/corpus/conv").select("unit", F.xpath_int("xml", F.lit("count(/conv/user)")).cast("long").alias("n")), "SELECT CAST(conv_id AS BIGINT) AS unit, CAST(count(*) FILTER (role = 'user') AS BIGINT) AS n FROM conversations GROUP BY conv_id")

# ---- sources and sinks

_FLAT = {"region": "r_regionkey, r_name", "nation": "n_nationkey, n_name", "supplier": "s_suppkey, s_nationkey", "part": "p_partkey, p_brand", "benchmark": "item_id", "labels": "doc_id, quality"}
for _name, _columns in _FLAT.items():
    add(f"scan_{_name}", lambda s, d, t=_name, c=_columns: table(s, d, t).select(*c.split(", ")), f"SELECT {_columns} FROM {_name}")
add("trade_orphans", lambda s, d: forests.trade_orphans(s, d), " UNION ALL ".join(f"SELECT '{a}' AS level, CAST(count(*) AS BIGINT) AS n FROM {a} WHERE {x} NOT IN (SELECT {y} FROM {b})" for a, x, b, y in (("nation", "n_regionkey", "region", "r_regionkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("orders", "o_custkey", "customer", "c_custkey"), ("lineitem", "l_orderkey", "orders", "o_orderkey"))))


def _edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    read = lambda t: table(spark, sf_dir, t)
    link = lambda df, id_, parent, key, label: df.select(id_.alias("id"), parent.cast("string").alias("parent"), F.col(key).cast("long").alias("ord"), F.lit(label).alias("label"))
    name = lambda a, c: F.concat(F.lit(a), F.col(c))
    rows = [link(read("region"), name("r", "r_regionkey"), F.lit(None), "r_regionkey", "region"), link(read("nation"), name("n", "n_nationkey"), name("r", "n_regionkey"), "n_nationkey", "nation"), link(read("customer"), name("c", "c_custkey"), name("n", "c_nationkey"), "c_custkey", "customer")]
    return forests.edges(reduce(DataFrame.unionByName, rows))


add("edges_nodes", _edges, "WITH e AS (SELECT 'r' || r_regionkey AS id, r_regionkey AS r, NULL AS n, NULL AS c, 0 AS depth, 'region' AS label FROM region UNION ALL SELECT 'n' || n_nationkey, n_regionkey, n_nationkey, NULL, 1, 'nation' FROM nation UNION ALL SELECT 'c' || c_custkey, n_regionkey, n_nationkey, c_custkey, 2, 'customer' FROM customer JOIN nation ON c_nationkey = n_nationkey) SELECT id, CAST(row_number() OVER (ORDER BY r, n NULLS FIRST, c NULLS FIRST) AS BIGINT) AS pre, depth, CAST(CASE depth WHEN 0 THEN count(*) OVER (PARTITION BY r) WHEN 1 THEN count(*) OVER (PARTITION BY r, n) ELSE 1 END AS BIGINT) AS size, label FROM e")
_LOG_NODES = LOG + ", t AS (SELECT CAST(user_id AS BIGINT) AS unit, CAST(k + 1 AS BIGINT) AS pre, CAST(1 AS BIGINT) AS parent_pre, 1 AS depth, CAST(1 AS BIGINT) AS size, label FROM n UNION ALL SELECT CAST(user_id AS BIGINT), CAST(1 AS BIGINT), NULL, 0, CAST(count(*) + 1 AS BIGINT), 'user' FROM n GROUP BY user_id) "
_slim = lambda d: d.select("unit", "pre", "parent_pre", "depth", "size", "label")
add("log_nodes", of_nodes("log", _slim), _LOG_NODES + "SELECT * FROM t")
add("prose_depth_hist", of_nodes("prose", lambda d: d.groupBy("depth").agg(F.count("*").alias("n"))), "WITH l AS (SELECT unnest(string_split(coalesce(text, ''), chr(10))) AS x FROM documents), w AS (SELECT unnest(string_split(x, ' ')) AS w FROM l) SELECT 0 AS depth, CAST(count(*) AS BIGINT) AS n FROM documents UNION ALL SELECT 1, CAST(count(*) AS BIGINT) FROM l UNION ALL SELECT 2, CAST(count(*) AS BIGINT) FROM w WHERE w <> ''")
add("pages_binary", lambda s, d: binary(nodes(opened(s, d, "pages"), keyed=True)).drop("top", "before"), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, label, CASE WHEN lead(depth) OVER (PARTITION BY page_id ORDER BY pre) = depth + 1 THEN CAST(pre + 1 AS BIGINT) END AS left_pre, CAST(lead(pre) OVER (PARTITION BY page_id, parent_pre ORDER BY pre) AS BIGINT) AS right_pre FROM n")


def _xml(spark: SparkSession, sf_dir: str) -> DataFrame:
    path, units = scratch(spark, "xml"), opened(spark, sf_dir, "talk").units
    units.select(F.col("unit").alias("_unit"), F.expr("slice(labels, 2, size(labels))").alias("turn")).write.format("xml").option("rootTag", "talk").option("rowTag", "conv").save(path)
    rows = spark.read.format("xml").option("rowTag", "conv").schema("_unit long, turn array<string>").load(path)
    return rows.select(F.col("_unit").alias("unit"), F.size(F.filter("turn", lambda x: x == "user")).cast("long").alias("n"))


add("xml_roundtrip", _xml, ORACLES["baseline_xpath_talk"])


def _written(kind: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        path, rows = scratch(spark, f"sink-{kind}"), evaluate.locate(opened(spark, sf_dir, "pages"), "//p/b", with_label=True)
        stored.buckets(rows, "unit", 8).write.partitionBy("bucket").format(kind).save(path)
        return spark.read.schema("unit long, pre long, label string, bucket int").format(kind).load(path).drop("bucket")

    return run


for _kind in ("json", "orc", "csv", "parquet"):
    add(f"sink_{_kind}_roundtrip", _written(_kind), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, label FROM n WHERE path LIKE '%/p/b'")

# ---- projections, predicates, joins

_talk = lambda f: of_nodes("talk", f)
_pages = lambda f: of_nodes("pages", f)
_P = PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, label FROM n WHERE "
add("project_depth_size", _talk(lambda d: d.select("unit", "pre", (F.col("depth") * 100 + F.col("size")).alias("code"), F.upper("label").alias("name"))), _TALK_NODES + "SELECT unit, pre, CAST(depth * 100 + size AS BIGINT) AS code, upper(label) AS name FROM t")
for _name, _cond in (("eq", "label = 'li'"), ("in", "label IN ('nav', 'ul', 'h1')"), ("like", "label LIKE 'h%'"), ("between", "pre BETWEEN 5 AND 9"), ("null", "parent_pre IS NULL")):
    add(f"filter_{_name}_pages", _pages(lambda d, c=_cond: d.where(c).select("unit", "pre", "label")), _P + _cond)
add("filter_rlike_pages", _pages(lambda d: d.where(F.col("label").rlike("^(h1|b|br)$")).select("unit", "pre", "label")), _P + "regexp_matches(label, '^(h1|b|br)$')")


def _rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = programs.walker_rules(spark.createDataFrame([("/conv/user",)], "query string")).drop("query").withColumnRenamed("label", "named")
    return nodes(opened(spark, sf_dir, "talk")).groupBy("label").agg(F.count("*").alias("n")).join(F.broadcast(rules), F.col("label") == F.col("named")).select("label", "q", "selects", "n")


add("join_walker_labels", _rules, _TALK_NODES + ", r AS (SELECT * FROM (VALUES (0, 'conv', false), (0, 'user', false), (1, 'conv', false), (1, 'user', false), (2, 'conv', false), (2, 'user', true)) v(q, named, selects)) SELECT label, CAST(q AS BIGINT) AS q, selects, n FROM (SELECT label, CAST(count(*) AS BIGINT) AS n FROM t GROUP BY label) JOIN r ON label = named")
add("join_theta_depth", _pages(lambda d: (h := d.groupBy("depth").agg(F.count("*").alias("n"))).alias("a").crossJoin(h.alias("b")).where("a.depth < b.depth").groupBy(F.col("a.depth").alias("depth")).agg(F.sum("b.n").alias("deeper"))), PAGES + ", h AS (SELECT depth, count(*) AS n FROM n GROUP BY depth) SELECT a.depth, CAST(sum(b.n) AS BIGINT) AS deeper FROM h a JOIN h b ON a.depth < b.depth GROUP BY a.depth")
_with_r = lambda s, d, how: table(s, d, "orders").join(table(s, d, "lineitem").where("l_returnflag = 'R'"), F.col("o_orderkey") == F.col("l_orderkey"), how).select("o_orderkey")
add("semi_order_with_R", lambda s, d: _with_r(s, d, "left_semi"), "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R')")
add("anti_order_without_R", lambda s, d: _with_r(s, d, "left_anti"), "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R')")


def _outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    hist = lambda x, c: nodes(opened(spark, sf_dir, x)).groupBy("label").agg(F.count("*").alias(c))
    return hist("talk", "talk").join(hist("log", "log"), "label", "full").select("label", F.coalesce("talk", F.lit(0)).alias("talk"), F.coalesce("log", F.lit(0)).alias("log"))


add("outer_label_hist", _outer, "SELECT label, CAST(coalesce(a.n, 0) AS BIGINT) AS talk, CAST(coalesce(b.n, 0) AS BIGINT) AS log FROM (SELECT role AS label, count(*) AS n FROM conversations GROUP BY role UNION ALL SELECT 'conv', count(DISTINCT conv_id) FROM conversations) a FULL JOIN (SELECT event_type AS label, count(*) AS n FROM events GROUP BY event_type UNION ALL SELECT 'user', count(DISTINCT user_id) FROM events) b USING (label)")
add("self_next_sibling", _talk(lambda d: (k := d.where("depth = 1")).alias("a").join(k.alias("b"), (F.col("a.unit") == F.col("b.unit")) & (F.col("b.pre") == F.col("a.pre") + 1)).groupBy(F.col("a.label").alias("label"), F.col("b.label").alias("after")).agg(F.count("*").alias("n"))), TALK + f"SELECT a.label, b.label AS after, {N} FROM n a JOIN n b ON a.conv_id = b.conv_id AND b.k = a.k + 1 GROUP BY ALL")

# ---- aggregates, windows, sorts

add("agg_fanout_percentiles", _pages(lambda d: d.where("parent_pre is not null").groupBy("unit", "parent_pre").agg(F.count("*").alias("n")).agg(F.expr("percentile(n, 0.5)").alias("median"), F.expr("percentile(n, 0.9)").alias("p90"), F.max("n").alias("most"))), PAGES + "SELECT quantile_cont(n, 0.5) AS median, quantile_cont(n, 0.9) AS p90, CAST(max(n) AS BIGINT) AS most FROM (SELECT CAST(count(*) AS DOUBLE) AS n FROM n WHERE parent_pre IS NOT NULL GROUP BY page_id, parent_pre)")
_sold = lambda s, d: table(s, d, "lineitem").join(table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(table(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
add("cube_selected", lambda s, d: _sold(s, d).cube("c_mktsegment", "l_returnflag").agg(F.count("*").alias("n")), f"SELECT c_mktsegment, l_returnflag, {N} FROM {LINES} GROUP BY CUBE (c_mktsegment, l_returnflag)")
add("gsets_selected", lambda s, d: _sold(s, d).groupingSets([["c_mktsegment", "o_orderstatus"], ["l_returnflag"], []], "c_mktsegment", "o_orderstatus", "l_returnflag").agg(F.count("*").alias("n")), f"SELECT c_mktsegment, o_orderstatus, l_returnflag, {N} FROM {LINES} GROUP BY GROUPING SETS ((c_mktsegment, o_orderstatus), (l_returnflag), ())")
add("rollup_region_nation", lambda s, d: table(s, d, "customer").join(table(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n")), f"SELECT r_name, n_name, {N} FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")


def _paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    units = opened(spark, sf_dir, "pages").units
    # the way to a node: labels of the last node at each smaller depth, from an array that is cut and grown along the page
    step = "aggregate(sequence(0, size(labels) - 1), named_struct('w', cast(array() as array<string>), 'p', cast(array() as array<string>)), (a, i) -> named_struct('w', concat(slice(a.w, 1, depths[i]), array(labels[i])), 'p', concat(a.p, array(concat('/', array_join(concat(slice(a.w, 1, depths[i]), array(labels[i])), '/'))))), a -> a.p)"
    return units.where("size(labels) > 0").select(F.explode(F.expr(step)).alias("path")).groupBy("path").agg(F.count("*").alias("n"))


add("path_strings", _paths, PAGES + f"SELECT path, {N} FROM n GROUP BY path")
add("win_top3_pages", _pages(lambda d: d.where("label = 'p'").groupBy("unit").agg(F.count("*").alias("n")).withColumn("place", F.row_number().over(Window.orderBy(F.desc("n"), "unit"))).where("place <= 3").select("unit", "n", F.col("place").cast("long").alias("place"))), PAGES + "SELECT * FROM (SELECT CAST(page_id AS BIGINT) AS unit, CAST(count(*) AS BIGINT) AS n, row_number() OVER (ORDER BY count(*) DESC, page_id) AS place FROM n WHERE label = 'p' GROUP BY page_id) WHERE place <= 3")
add("win_range_hour", lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("n")), "SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS BIGINT) AS n FROM events")
add("win_rank_pages", _pages(lambda d: d.where("label = 'p'").groupBy("unit").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("pages")).select("n", "pages", F.dense_rank().over(Window.orderBy(F.desc("n"))).cast("long").alias("place"), F.ntile(4).over(Window.orderBy("n")).cast("long").alias("quarter"))), PAGES + "SELECT n, pages, dense_rank() OVER (ORDER BY n DESC) AS place, ntile(4) OVER (ORDER BY n) AS quarter FROM (SELECT n, CAST(count(*) AS BIGINT) AS pages FROM (SELECT CAST(count(*) AS BIGINT) AS n FROM n WHERE label = 'p' GROUP BY page_id) GROUP BY n)")
add("topk_first", lambda s, d: evaluate.locate(opened(s, d, "pages"), "//p", limit=10).orderBy("unit", "pre").limit(10), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre FROM n WHERE label = 'p' ORDER BY page_id, pre LIMIT 10")
add("topk_largest_subtrees", _pages(lambda d: d.where("label = 'ul'").select("unit", "pre", "size").orderBy(F.desc("size"), "unit", "pre").limit(5)), _STOPS + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, CAST(stop - pre AS BIGINT) AS size FROM e WHERE label = 'ul' ORDER BY size DESC, unit, pre LIMIT 5")
add("labels_by_year", lambda s, d: table(s, d, "orders").groupBy(F.concat(F.lit("y"), F.date_format("o_orderdate", "yyyy")).alias("label")).agg(F.count("*").alias("n")), f"SELECT 'y' || strftime(o_orderdate, '%Y') AS label, {N} FROM orders GROUP BY ALL")

# ---- functions

add("udf_walk_count", lambda s, d: opened(s, d, "talk").units.select("unit", surface.walk_count("/conv/user")("labels", "depths").alias("n")), ORACLES["baseline_xpath_talk"])


def _walker_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    surface.register(spark)
    segment_paths(spark, sf_dir).createOrReplaceTempView("sharetree_paths")
    return spark.sql("SELECT query, r.q, r.label, r.selects, r.q_left, r.q_right FROM sharetree_paths, LATERAL walker_rules(query) r")


add("udtf_walker_rules", _walker_sql, ORACLES["cost_walker_rules"])


def _rules_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    surface.register(spark)
    table(spark, sf_dir, "pages").createOrReplaceTempView("sharetree_pages")
    return spark.sql("SELECT CAST(page_id AS BIGINT) AS unit, count(*) AS n FROM sharetree_pages, LATERAL grammar_rules(html, 'binary') r GROUP BY page_id")


add("udtf_grammar_rules", _rules_sql, f"{_SUBTREES} SELECT CAST(page_id AS BIGINT) AS unit, CAST(count(DISTINCT x) AS BIGINT) AS n FROM (SELECT page_id, suf AS x FROM t UNION ALL SELECT page_id, sig FROM s WHERE parent_pre IS NULL) GROUP BY page_id")


def _composed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts put together like an aggregate function: each user's events as functions on states, composed group by group."""
    bare, cut = segments.log(spark, sf_dir, 25)
    walker, entered = segments._entered(bare, "//error/following-sibling::error")
    return segments._composed(segments.functions(cut, walker), entered, walker).agg(F.sum("n").cast("long").alias("n"))


add("agg_composed_functions", _composed, ORACLES["count_w2_error_log"])

# ---- streams

ORACLES["stream_sliding"] = "SELECT date_trunc('day', ts) - to_days(CAST(i AS INTEGER)) AS window_start, CAST(count(*) AS BIGINT) AS n FROM events, generate_series(0, 1) g(i) GROUP BY ALL"
add("stream_static_join", lambda s, d: streams.drain(streams.with_customers(streams.stream(s, d, "events"), table(s, d, "customer"))).groupBy("c_mktsegment").agg(F.count("*").alias("n")), f"SELECT c_mktsegment, {N} FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
add("stream_dictionary_pages", lambda s, d: streams.grow_dictionary(streams.stream(s, d, "pages")).agg(F.count("*").alias("n"), F.sum("edges").cast("long").alias("edges")), f"{_SUBTREES} SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(kids) AS BIGINT) AS edges FROM (SELECT DISTINCT sig, kids FROM s)")
