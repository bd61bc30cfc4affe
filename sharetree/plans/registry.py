"""The queries of the path engine and their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sharetree.functions import sql as surface
from sharetree.operators import baseline, compress, evaluate, programs
from sharetree.plans.query import depth_mod
from sharetree.sources.forests import binary, nodes, opened
from sharetree.sources.tables import table
from sharetree.streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, oracle: str | None = None) -> None:
    assert name not in QUERIES, name
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def on(forest: str, f, *args, **options) -> Query:
    return lambda spark, sf_dir: f(opened(spark, sf_dir, forest), *args, **options)


# ---- the trees, in SQL

#: Pages as token stacks: n(page_id, pre, parent_pre, depth, label, path).
PAGES = r"""WITH RECURSIVE clean AS (SELECT page_id, regexp_replace(regexp_replace(html, '<!--.*?-->|<![^>]*>', '', 'gs'), '(<(?:script|style)\b[^>]*>).*?(</(?:script|style)\s*>)', '\1\2', 'gsi') AS h FROM pages),
tok AS (SELECT page_id, regexp_extract_all(h, '</?[A-Za-z][A-Za-z0-9]*[^>]*>') AS t FROM clean),
each AS (SELECT page_id, i, t[i] AS tag, lower(regexp_extract(t[i], '^</?([A-Za-z][A-Za-z0-9]*)', 1)) AS name FROM (SELECT page_id, t, unnest(generate_series(1, len(t))) AS i FROM tok)),
kinds AS (SELECT page_id, i, name, tag[2] = '/' AS ends, (name IN ('area','base','br','col','embed','hr','img','input','link','meta','source','track','wbr') OR tag[-2:] = '/>') AS leaf FROM each),
r AS (SELECT page_id, 0 AS i, CAST([] AS VARCHAR[]) AS st, CAST([] AS INTEGER[]) AS ids, 0 AS pre, CAST(NULL AS VARCHAR) AS label, CAST(NULL AS INTEGER) AS parent_pre, 0 AS depth, '' AS path FROM pages
 UNION ALL
 SELECT r.page_id, k.i,
  CASE WHEN NOT k.ends THEN CASE WHEN k.leaf THEN st ELSE list_append(st, k.name) END WHEN list_contains(st, k.name) THEN st[1 : len(st) - list_position(list_reverse(st), k.name)] ELSE st END,
  CASE WHEN NOT k.ends THEN CASE WHEN k.leaf THEN ids ELSE list_append(ids, pre + 1) END WHEN list_contains(st, k.name) THEN ids[1 : len(st) - list_position(list_reverse(st), k.name)] ELSE ids END,
  CASE WHEN k.ends THEN pre ELSE pre + 1 END, CASE WHEN k.ends THEN NULL ELSE k.name END, ids[-1], len(st),
  '/' || array_to_string(list_append(st, k.name), '/')
 FROM r JOIN kinds k ON k.page_id = r.page_id AND k.i = r.i + 1),
n AS (SELECT page_id, pre, parent_pre, depth, label, path FROM r WHERE label IS NOT NULL)
"""
LOG = "WITH n AS (SELECT user_id, event_type AS label, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events) "
TALK = "WITH n AS (SELECT conv_id, role AS label, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role) AS k FROM conversations) "
LINES = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"
N = "CAST(count(*) AS BIGINT) AS n"

# ---- counts: the paper's queries on the trees, in several modes

COUNTS: list[tuple[str, str, str, str]] = [
    # name, forest, query, oracle
    ("w1_trade", "trade", "//region/*/customer//lineitem/R", f"SELECT {N} FROM {LINES} WHERE l_returnflag = 'R'"),
    ("all_trade", "trade", "//*", f"SELECT CAST(1 + (SELECT count(*) FROM region) + (SELECT count(*) FROM nation) + 2 * (SELECT count(*) FROM customer) + 2 * (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) + 2 * (SELECT count(*) FROM {LINES}) AS BIGINT) AS n"),
    ("top_trade", "trade", "/trade/region/nation", f"SELECT {N} FROM nation"),
    ("w7_part_trade", "trade", "//customer[./BUILDING]/order/lineitem/R", f"SELECT {N} FROM {LINES} WHERE c_mktsegment = 'BUILDING' AND l_returnflag = 'R'"),
    ("filter_w7_trade", "trade", "//customer[.//order/lineitem/R][./BUILDING]/order/lineitem", f"SELECT {N} FROM {LINES} WHERE c_mktsegment = 'BUILDING' AND c_custkey IN (SELECT o_custkey FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE l_returnflag = 'R')"),
    ("filter_w8_nation", "trade", "//nation[./customer/order/statusF]", f"SELECT {N} FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM customer JOIN orders ON o_custkey = c_custkey WHERE o_orderstatus = 'F')"),
    ("filter_w8_order", "trade", "//order[./lineitem/R]", f"SELECT {N} FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R')"),
    ("filter_two_steps", "trade", "//nation[./customer/FURNITURE]/customer[./order/statusP]/order", f"SELECT {N} FROM orders JOIN customer c ON o_custkey = c_custkey WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P') AND c_nationkey IN (SELECT c_nationkey FROM customer WHERE c_mktsegment = 'FURNITURE')"),
    ("w2_log", "log", "//view/following-sibling::purchase", LOG + f"SELECT {N} FROM n a WHERE label = 'purchase' AND EXISTS (SELECT 1 FROM n b WHERE b.user_id = a.user_id AND b.k < a.k AND b.label = 'view')"),
    ("w2_error_log", "log", "//error/following-sibling::error", LOG + f"SELECT {N} FROM n a WHERE label = 'error' AND EXISTS (SELECT 1 FROM n b WHERE b.user_id = a.user_id AND b.k < a.k AND b.label = 'error')"),
    ("w2_chain_log", "log", "/log/user/signup/following-sibling::view/following-sibling::purchase", LOG + f"SELECT {N} FROM n a WHERE label = 'purchase' AND EXISTS (SELECT 1 FROM n b JOIN n c ON b.user_id = c.user_id AND c.k < b.k AND c.label = 'signup' WHERE b.user_id = a.user_id AND b.k < a.k AND b.label = 'view')"),
    ("units_log", "log", "/log/user/following-sibling::user/view", LOG + f"SELECT {N} FROM n WHERE label = 'view' AND user_id > (SELECT min(user_id) FROM events)"),
    ("filter_sibling_log", "log", "//view[./following-sibling::purchase]", LOG + f"SELECT {N} FROM n a WHERE label = 'view' AND EXISTS (SELECT 1 FROM n b WHERE b.user_id = a.user_id AND b.k > a.k AND b.label = 'purchase')"),
    ("w2_talk", "talk", "//system/following-sibling::user/following-sibling::assistant", TALK + f"SELECT {N} FROM n a WHERE label = 'assistant' AND EXISTS (SELECT 1 FROM n b JOIN n c ON b.conv_id = c.conv_id AND c.k < b.k AND c.label = 'system' WHERE b.conv_id = a.conv_id AND b.k < a.k AND b.label = 'user')"),
    ("children_talk", "talk", "//conv/*", f"SELECT {N} FROM conversations"),
    ("words_prose", "prose", "/corpus/doc/line/the", f"SELECT {N} FROM (SELECT unnest(string_split(x, ' ')) AS w FROM (SELECT unnest(string_split(text, chr(10))) AS x FROM documents)) WHERE w = 'the'"),
    ("lines_prose", "prose", "/corpus/doc/line/following-sibling::line", f"SELECT CAST(sum(len(string_split(text, chr(10))) - 1) AS BIGINT) AS n FROM documents"),
    ("parts_words", "parts", "//part/*", f"SELECT CAST(sum(len(string_split(p_name, ' '))) AS BIGINT) AS n FROM part"),
    ("bench_items", "bench", "/bench/item", f"SELECT {N} FROM benchmark"),
    ("empty", "pages", "//a/*/b", f"SELECT CAST(0 AS BIGINT) AS n"),
    ("w1_pages", "pages", "//html/*/nav//li/a", PAGES + f"SELECT {N} FROM n WHERE regexp_matches(path, '/html/[^/]+/nav(/.*)?/li/a$')"),
    ("w1_article_pages", "pages", "//article/*/b//p", PAGES + f"SELECT {N} FROM n WHERE regexp_matches(path, '/article/[^/]+/b(/.*)?/p$')"),
    ("w2_pages", "pages", "//li/following-sibling::li/a", PAGES + f"SELECT {N} FROM n a JOIN n l ON l.page_id = a.page_id AND l.pre = a.parent_pre AND l.label = 'li' WHERE a.label = 'a' AND EXISTS (SELECT 1 FROM n b WHERE b.page_id = l.page_id AND b.parent_pre = l.parent_pre AND b.pre < l.pre AND b.label = 'li')"),
    ("w11_third_li", "pages", "//ul/li/following-sibling::li/following-sibling::li", PAGES + f"SELECT {N} FROM n l JOIN n u ON u.page_id = l.page_id AND u.pre = l.parent_pre AND u.label = 'ul' WHERE l.label = 'li' AND (SELECT count(*) FROM n b WHERE b.page_id = l.page_id AND b.parent_pre = l.parent_pre AND b.pre < l.pre AND b.label = 'li') >= 2"),
    ("w11_title", "pages", "//head/meta/following-sibling::title", PAGES + f"SELECT {N} FROM n t WHERE label = 'title' AND path LIKE '%/head/title' AND EXISTS (SELECT 1 FROM n b WHERE b.page_id = t.page_id AND b.parent_pre = t.parent_pre AND b.pre < t.pre AND b.label = 'meta')"),
    ("filter_w7_pages", "pages", "//body[.//ul/li/a][./article/h1]/nav/ul", PAGES + f"SELECT {N} FROM n u WHERE path LIKE '%/body/nav/ul' AND EXISTS (SELECT 1 FROM n b WHERE b.page_id = u.page_id AND b.path LIKE '%/body/%ul/li/a') AND EXISTS (SELECT 1 FROM n b WHERE b.page_id = u.page_id AND b.path LIKE '%/body/article/h1')"),
]
for _name, _query, _like in (("p", "//p", ".*/p"), ("pb", "//p/b", ".*/p/b"), ("lia", "//li/a", ".*/li/a"), ("li_any", "//li//*", "(/[^/]+)*/li(/[^/]+)+"), ("body_any", "/pages/html/body/*", "/html/body/[^/]+"), ("article_pb", "//article/*/b/p", ".*/article/[^/]+/b/p")):
    COUNTS.append((f"w11_{_name}", "pages", _query, PAGES + f"SELECT {N} FROM n WHERE regexp_full_match(path, '{_like}')"))
for _name, _forest, _query, _oracle in COUNTS:
    add(f"count_{_name}", on(_forest, evaluate.count, _query), _oracle)

_count = {name: (forest, query, oracle) for name, forest, query, oracle in COUNTS}
for _name in ("w1_trade", "w2_log", "w2_talk", "w1_pages", "w2_pages"):
    _forest, _query, _oracle = _count[_name]
    for _mode in ("hybrid", "digrams", "tree"):
        add(f"count_{_name}_{_mode}", on(_forest, evaluate.count, _query, compress=_mode), _oracle)
    add(f"count_{_name}_full", on(_forest, evaluate.count, _query, mode="full"), _oracle)
for _name in ("filter_w7_trade", "filter_w7_pages", "filter_sibling_log"):
    _forest, _query, _oracle = _count[_name]
    for _mode in ("table", "matrix"):
        add(f"count_{_name}_{_mode}", on(_forest, evaluate.count, _query, compress="digrams", filters=_mode), _oracle)
add("count_depthmod_pages", on("pages", evaluate.count, depth_mod(3, 2)), PAGES + f"SELECT {N} FROM n WHERE (depth + 1) % 3 = 2")
add("count_depthmod_trade", on("trade", evaluate.count, depth_mod(3, 2)), f"SELECT CAST((SELECT count(*) FROM nation) + (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) + (SELECT count(*) FROM {LINES}) AS BIGINT) AS n")
# a chain for each quantity of a line: twice as many doublings
add("count_depthmod_chain", lambda spark, sf_dir: programs.chain_counts(table(spark, sf_dir, "lineitem").where("l_quantity >= 0").select((2 * F.col("l_quantity")).cast("long").alias("doublings")).distinct()), "SELECT doublings, CAST(((CAST(1 AS HUGEINT) << CAST(doublings AS INTEGER)) + 1) // 3 AS VARCHAR) AS n FROM (SELECT DISTINCT CAST(2 * l_quantity AS BIGINT) AS doublings FROM lineitem WHERE l_quantity >= 0)")

# ---- per unit, existence, selectivity

BY_PAGE = "SELECT CAST(page_id AS BIGINT) AS unit, CAST(count(*) AS BIGINT) AS n FROM n WHERE {} GROUP BY page_id"
for _name, _query, _where in (("p", "//p", "label = 'p'"), ("pb", "//p/b", "path LIKE '%/p/b'"), ("lia", "//li/a", "path LIKE '%/li/a'")):
    add(f"count_by_page_{_name}", on("pages", evaluate.count_by_unit, _query), PAGES + BY_PAGE.format(_where))
add("count_by_customer", on("trade", evaluate.count_by_unit, "//lineitem/R"), f"SELECT CAST(c_custkey AS BIGINT) AS unit, CAST(count(*) AS BIGINT) AS n FROM {LINES} WHERE l_returnflag = 'R' GROUP BY c_custkey")
add("count_by_user_w2", on("log", evaluate.count_by_unit, "//view/following-sibling::purchase"), LOG + "SELECT CAST(user_id AS BIGINT) AS unit, CAST(count(*) AS BIGINT) AS n FROM n a WHERE label = 'purchase' AND EXISTS (SELECT 1 FROM n b WHERE b.user_id = a.user_id AND b.k < a.k AND b.label = 'view') GROUP BY user_id")
add("exists_R_by_customer", on("trade", evaluate.exists, "//lineitem/R"), f"SELECT CAST(c.c_custkey AS BIGINT) AS unit, c.c_custkey IN (SELECT c_custkey FROM {LINES} WHERE l_returnflag = 'R') AS hit FROM customer c")
add("exists_system_by_conv", on("talk", evaluate.exists, "//system"), "SELECT CAST(conv_id AS BIGINT) AS unit, bool_or(role = 'system') AS hit FROM conversations GROUP BY conv_id")
add("selectivity_talk", on("talk", evaluate.selectivity, "//user"), "SELECT CAST(sum(CASE WHEN role = 'user' THEN 1 ELSE 0 END) AS BIGINT) AS n, CAST(count(*) + count(DISTINCT conv_id) + 1 AS BIGINT) AS total, sum(CASE WHEN role = 'user' THEN 1 ELSE 0 END) / CAST(count(*) + count(DISTINCT conv_id) + 1 AS DOUBLE) AS ratio FROM conversations")

# ---- locate and serialize

_LOCATE_LOG = LOG + "SELECT CAST(user_id AS BIGINT) AS unit, CAST(k + 1 AS BIGINT) AS pre FROM n a WHERE label = 'purchase' AND EXISTS (SELECT 1 FROM n b WHERE b.user_id = a.user_id AND b.k < a.k AND b.label = 'view')"
for _mode, _options in (("", {}), ("_eager", {"offsets": "eager"}), ("_digrams", {"compress": "digrams"}), ("_hybrid", {"compress": "hybrid"})):
    add(f"locate_w2_log{_mode}", on("log", evaluate.locate, "//view/following-sibling::purchase", **_options), _LOCATE_LOG)
add("locate_pb_pages", on("pages", evaluate.locate, "//p/b"), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre FROM n WHERE path LIKE '%/p/b'")
add("locate_labels_pages", on("pages", evaluate.locate, "//body/*", with_label=True), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, label FROM n WHERE regexp_matches(path, '/body/[^/]+$')")
add("locate_first3_p", on("pages", evaluate.locate, "//p", limit=3), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre FROM n WHERE label = 'p' QUALIFY row_number() OVER (PARTITION BY page_id ORDER BY pre) <= 3")
add("locate_depthmod_talk", on("talk", evaluate.locate, depth_mod(3, 2)), TALK + "SELECT CAST(conv_id AS BIGINT) AS unit, CAST(k + 1 AS BIGINT) AS pre FROM n")
add("locate_orders_trade", on("trade", evaluate.locate, "//order"), "WITH l AS (SELECT o_custkey, o_orderkey, 2 + 2 * (SELECT count(*) FROM lineitem WHERE l_orderkey = o_orderkey) AS s FROM orders JOIN customer ON o_custkey = c_custkey) SELECT CAST(o_custkey AS BIGINT) AS unit, CAST(3 + coalesce(sum(s) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS pre FROM l")
_CONV = TALK + "SELECT CAST(conv_id AS BIGINT) AS unit, CAST(1 AS BIGINT) AS pre, '<conv>' || string_agg('<' || label || '></' || label || '>', '' ORDER BY k) || '</conv>' AS xml FROM n GROUP BY conv_id"
add("serialize_conv_talk", on("talk", evaluate.serialize, "/corpus/conv"), _CONV)
add("serialize_outermost_talk", on("talk", evaluate.serialize, "//*", top=False, nested=False), _CONV)
add("serialize_user_log", on("log", evaluate.serialize, "//user"), LOG + "SELECT CAST(user_id AS BIGINT) AS unit, CAST(1 AS BIGINT) AS pre, '<user>' || string_agg('<' || label || '></' || label || '>', '' ORDER BY k) || '</user>' AS xml FROM n GROUP BY user_id")
add("serialize_ul_pages", on("pages", evaluate.serialize, "//ul"))
add("serialized_size_talk", on("talk", evaluate.serialized_size, "//*", top=False), "SELECT CAST(2 * count(*) + count(DISTINCT conv_id) AS BIGINT) AS s FROM conversations")
add("serialized_size_pages", on("pages", evaluate.serialized_size, "//*", top=False), PAGES + "SELECT CAST(sum(depth + 1) AS BIGINT) AS s FROM n")
# the same over the whole tree, nodes above units included (those above look at the units alone, as their oracles do)
add("serialize_whole_outermost_talk", on("talk", evaluate.serialize, "//*", nested=False), f"WITH c AS ({_CONV}) SELECT CAST(NULL AS BIGINT) AS unit, CAST(1 AS BIGINT) AS pre, '<corpus>' || string_agg(xml, '' ORDER BY unit) || '</corpus>' AS xml FROM c")
add("serialized_size_whole_talk", on("talk", evaluate.serialized_size, "//*"), "SELECT CAST(3 * count(*) + 2 * count(DISTINCT conv_id) + 1 AS BIGINT) AS s FROM conversations")
add("serialized_size_whole_pages", on("pages", evaluate.serialized_size, "//*"), PAGES + "SELECT CAST(sum(depth + 2) + 1 AS BIGINT) AS s FROM n")
add("serialized_size_whole_trade", on("trade", evaluate.serialized_size, "//*"), f"SELECT CAST(1 + 2 * (SELECT count(*) FROM region) + 3 * (SELECT count(*) FROM nation) + 9 * (SELECT count(*) FROM customer) + 11 * (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) + 13 * (SELECT count(*) FROM {LINES}) AS BIGINT) AS s")
add("locate_nation_trade", on("trade", evaluate.locate, "//nation"), "SELECT CAST(NULL AS BIGINT) AS unit, CAST(1 + row_number() OVER (ORDER BY n_regionkey, n_nationkey) + dense_rank() OVER (ORDER BY n_regionkey) AS BIGINT) AS pre FROM nation JOIN region ON n_regionkey = r_regionkey")

# ---- string programs

_USERS = "SELECT CAST(conv_id AS BIGINT) AS unit, CAST(sum(CASE WHEN role = 'user' THEN 1 ELSE 0 END) AS BIGINT) AS r, CAST(2 * sum(CASE WHEN role = 'user' THEN 1 ELSE 0 END) AS BIGINT) AS length, repeat('<user></user>', CAST(sum(CASE WHEN role = 'user' THEN 1 ELSE 0 END) AS BIGINT)) AS text FROM conversations GROUP BY conv_id"
for _name, _options in (("dag", {}), ("general", {"method": "general", "compress": "digrams"}), ("hybrid", {"compress": "hybrid"})):
    add(f"slp_subtrees_{_name}_talk", lambda spark, sf_dir, o=_options: programs.subtree_programs(opened(spark, sf_dir, "talk"), "//user", **o).select("unit", "r", "length", "text"), _USERS)
add("slp_sizes_pages", on("pages", programs.subtree_programs, "//ul", text=False))
add("slp_traversal_talk", lambda spark, sf_dir: programs.traversal_programs(opened(spark, sf_dir, "talk")).select("unit", "length"), "SELECT CAST(conv_id AS BIGINT) AS unit, CAST(2 * count(*) + 2 AS BIGINT) AS length FROM conversations GROUP BY conv_id")
add("slp_traversal_sizes_trade", on("trade", programs.traversal_programs))

# ---- compression

_LISTS = {
    "talk": "WITH l AS (SELECT conv_id AS u, list(role ORDER BY turn, role) AS w FROM conversations GROUP BY conv_id)",
    "log": "WITH l AS (SELECT user_id AS u, list(event_type ORDER BY ts, event_id) AS w FROM events GROUP BY user_id)",
}
for _name, _lists in _LISTS.items():
    _suffixes = "t AS (SELECT DISTINCT w[i : ] AS x FROM (SELECT w, unnest(generate_series(1, len(w))) AS i FROM l))"
    _tree = "CAST((SELECT sum(len(w)) FROM l) AS BIGINT) AS tree_edges"
    add(f"dag_stats_{_name}", on(_name, compress.sharing, "unranked"), f"{_lists} SELECT {_tree}, CAST((SELECT sum(len(w)) FROM (SELECT DISTINCT w FROM l)) AS BIGINT) AS shared_edges, CAST((SELECT count(DISTINCT w) FROM l) + (SELECT count(DISTINCT x) FROM (SELECT unnest(w) AS x FROM l)) AS BIGINT) AS shared_nodes")
    _edges = "CAST((SELECT count(DISTINCT w) FROM l) + (SELECT count(*) FROM t WHERE len(x) > 1) AS BIGINT) AS shared_edges"
    add(f"binary_dag_stats_{_name}", on(_name, compress.sharing, "binary"), f"{_lists}, {_suffixes} SELECT {_tree}, {_edges}, CAST((SELECT count(DISTINCT w) FROM l) + (SELECT count(*) FROM t) AS BIGINT) AS shared_nodes")
    add(f"hybrid_stats_{_name}", on(_name, compress.sharing, "hybrid"), f"{_lists}, {_suffixes} SELECT {_tree}, {_edges}, CAST((SELECT count(DISTINCT w) FROM l) + (SELECT count(*) FROM t) + (SELECT count(DISTINCT x) FROM (SELECT unnest(w) AS x FROM l)) AS BIGINT) AS shared_nodes")
for _name in ("pages", "trade"):
    for _kind in ("unranked", "binary", "hybrid"):
        add(f"{_kind}_stats_{_name}", on(_name, compress.sharing, _kind))
    add(f"digram_stats_{_name}", on(_name, compress.grammar_stats, "digrams"))

# ---- baselines

_W1 = f"SELECT CAST(c_custkey AS BIGINT) AS unit, CAST(count(*) AS BIGINT) AS n FROM {LINES} WHERE l_returnflag = 'R' GROUP BY c_custkey"
add("baseline_paths_w1", on("trade", baseline.paths, "//order//lineitem/R"), _W1)
add("baseline_structural_w1", lambda spark, sf_dir: baseline.structural(opened(spark, sf_dir, "trade"), "//order//lineitem/R").groupBy("unit").agg(F.count("*").alias("n")), _W1)
add("baseline_structural_w2_log", on("log", baseline.structural, "//view/following-sibling::purchase"), _LOCATE_LOG)
add("baseline_lift_w8", lambda spark, sf_dir: baseline.structural(opened(spark, sf_dir, "trade"), "//order[./lineitem/R]").agg(F.count("*").alias("n")), _count["filter_w8_order"][2])

# ---- measures

# as many wildcards as lines that stand before a line in its order
_ENDS = "SELECT DISTINCT 'order' AS ancestor, CAST(l_linenumber - 1 AS BIGINT) AS wildcards, l_returnflag AS label FROM lineitem WHERE l_linenumber > 0 AND l_returnflag IS NOT NULL"
#: Of each market segment and order status that meet: a customer's first child is the segment, its orders follow.
_PATHS = "SELECT DISTINCT concat('/', c_mktsegment, '/following-sibling::order/status', o_orderstatus) AS query FROM customer JOIN orders ON c_custkey = o_custkey WHERE c_mktsegment IS NOT NULL AND o_orderstatus IS NOT NULL"


def segment_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """query: the path from each market segment to the orders of each status that its customers have."""
    both = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey")).where("c_mktsegment is not null and o_orderstatus is not null")
    return both.select("c_mktsegment", "o_orderstatus").distinct().select(F.concat(F.lit("/"), "c_mktsegment", F.lit("/following-sibling::order/status"), "o_orderstatus").alias("query"))


def _walker_ends(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem").where("l_linenumber > 0 and l_returnflag is not null")
    return rows.select(F.lit("order").alias("ancestor"), (F.col("l_linenumber") - 1).cast("long").alias("wildcards"), F.col("l_returnflag").alias("label")).distinct()


add("cost_walker_states", lambda spark, sf_dir: programs.walker_states(_walker_ends(spark, sf_dir)), f"SELECT ancestor, wildcards, label, CAST(pow(2, wildcards + 1) AS BIGINT) AS states FROM ({_ENDS})")
add("cost_walker_rules", lambda spark, sf_dir: programs.walker_rules(segment_paths(spark, sf_dir)))
add("cost_filters_table", on("trade", programs.filter_costs, "//customer[.//order/lineitem/R][./BUILDING]/order/lineitem", "table"))
add("cost_filters_matrix", on("trade", programs.filter_costs, "//customer[.//order/lineitem/R][./BUILDING]/order/lineitem", "matrix"))

# ---- nodes and the relational surface over them


def of_nodes(forest: str, f: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, sf_dir: f(nodes(opened(spark, sf_dir, forest)))


_TALK_NODES = TALK + ", t AS (SELECT CAST(conv_id AS BIGINT) AS unit, CAST(k + 1 AS BIGINT) AS pre, CAST(1 AS BIGINT) AS parent_pre, 1 AS depth, CAST(1 AS BIGINT) AS size, label FROM n UNION ALL SELECT CAST(conv_id AS BIGINT), CAST(1 AS BIGINT), NULL, 0, CAST(count(*) + 1 AS BIGINT), 'conv' FROM n GROUP BY conv_id) "
_slim = lambda d: d.select("unit", "pre", "parent_pre", "depth", "size", "label")
add("talk_nodes", of_nodes("talk", _slim), _TALK_NODES + "SELECT * FROM t")
add("pages_nodes", of_nodes("pages", lambda d: d.select("unit", "pre", "parent_pre", "depth", "label")), PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, CAST(parent_pre AS BIGINT) AS parent_pre, depth, label FROM n")
add("trade_nodes", of_nodes("trade", _slim))
add("talk_binary", of_nodes("talk", binary), _TALK_NODES + "SELECT unit, pre, label, CASE WHEN depth = 0 THEN CAST(2 AS BIGINT) END AS left_pre, CASE WHEN depth = 1 THEN lead(pre) OVER (PARTITION BY unit, parent_pre ORDER BY pre) END AS right_pre FROM t")
add("agg_label_hist", of_nodes("pages", lambda d: d.groupBy("label").agg(F.count("*").alias("n"))), PAGES + f"SELECT label, {N} FROM n GROUP BY label")
add("pages_depth_hist", of_nodes("pages", lambda d: d.groupBy("depth").agg(F.count("*").alias("n"))), PAGES + f"SELECT depth, {N} FROM n GROUP BY depth")
add("agg_shape_stats", of_nodes("talk", lambda d: d.agg(F.max("depth").alias("deepest"), F.max("size").alias("largest"), F.avg("size").alias("mean_size"))), _TALK_NODES + "SELECT max(depth) AS deepest, max(size) AS largest, avg(size) AS mean_size FROM t")
add("agg_having_frequent", of_nodes("talk", lambda d: d.groupBy("label").agg(F.count("*").alias("n")).where("n > 100")), _TALK_NODES + f"SELECT label, {N} FROM t GROUP BY label HAVING count(*) > 100")
add("cube_label_depth", of_nodes("talk", lambda d: d.cube("label", "depth").agg(F.count("*").alias("n"))), _TALK_NODES + f"SELECT label, depth, {N} FROM t GROUP BY CUBE (label, depth)")
add("rollup_depth_label", of_nodes("talk", lambda d: d.rollup("depth", "label").agg(F.count("*").alias("n"))), _TALK_NODES + f"SELECT depth, label, {N} FROM t GROUP BY ROLLUP (depth, label)")
add("pivot_label_depth", of_nodes("talk", lambda d: d.groupBy("label").pivot("depth", [0, 1]).agg(F.count(F.lit(1))).select("label", F.col("0").alias("d0"), F.col("1").alias("d1"))), _TALK_NODES + "SELECT label, CAST(nullif(count(*) FILTER (depth = 0), 0) AS BIGINT) AS d0, CAST(nullif(count(*) FILTER (depth = 1), 0) AS BIGINT) AS d1 FROM t GROUP BY label")
add("agg_child_signature", of_nodes("talk", lambda d: d.where("depth = 1").groupBy("unit").agg(F.array_join(F.sort_array(F.collect_list(F.struct("pre", "label")))["label"], ",").alias("children"))), _TALK_NODES + "SELECT unit, string_agg(label, ',' ORDER BY pre) AS children FROM t WHERE depth = 1 GROUP BY unit")
add("win_sibling_ord", of_nodes("talk", lambda d: d.where("depth = 1").select("unit", "pre", F.row_number().over(Window.partitionBy("unit", "parent_pre", "label").orderBy("pre")).alias("nth"))), _TALK_NODES + "SELECT unit, pre, CAST(row_number() OVER (PARTITION BY unit, parent_pre, label ORDER BY pre) AS INTEGER) AS nth FROM t WHERE depth = 1")
add("win_next_sibling", of_nodes("talk", lambda d: d.where("depth = 1").select("unit", "pre", F.lead("label").over(Window.partitionBy("unit", "parent_pre").orderBy("pre")).alias("next_label"))), _TALK_NODES + "SELECT unit, pre, lead(label) OVER (PARTITION BY unit, parent_pre ORDER BY pre) AS next_label FROM t WHERE depth = 1")
add("win_prefix_sizes", of_nodes("talk", lambda d: d.select("unit", "pre", F.sum("size").over(Window.partitionBy("unit").orderBy("pre")).alias("so_far"))), _TALK_NODES + "SELECT unit, pre, CAST(sum(size) OVER (PARTITION BY unit ORDER BY pre) AS BIGINT) AS so_far FROM t")
add("win_top3_units", of_nodes("talk", lambda d: d.where("depth = 0").select("unit", "size").orderBy(F.desc("size"), "unit").limit(3)), _TALK_NODES + "SELECT unit, size FROM t WHERE depth = 0 ORDER BY size DESC, unit LIMIT 3")
add("join_parent_child", of_nodes("pages", lambda d: d.alias("c").join(d.alias("p"), (F.col("c.unit") == F.col("p.unit")) & (F.col("c.parent_pre") == F.col("p.pre"))).groupBy(F.col("p.label").alias("parent"), F.col("c.label").alias("child")).agg(F.count("*").alias("n"))), PAGES + f"SELECT p.label AS parent, c.label AS child, {N} FROM n c JOIN n p ON c.page_id = p.page_id AND c.parent_pre = p.pre GROUP BY ALL")
add("join_ancestor_desc", on("pages", lambda f: baseline.structural(f, "//article//b").agg(F.count("*").alias("n"))), PAGES + f"SELECT {N} FROM n WHERE regexp_matches(path, '/article/(.*/)?b$')")
add("asof_prev_view", lambda spark, sf_dir: table(spark, sf_dir, "events").select("event_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)).alias("view_id")), "SELECT event_id, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events")
_li = lambda q: (lambda spark, sf_dir: evaluate.locate(opened(spark, sf_dir, "pages"), q))
_SET = PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre FROM n WHERE "
add("set_union", lambda s, d: _li("//p")(s, d).union(_li("//li//a")(s, d)).distinct(), _SET + "label = 'p' OR regexp_matches(path, '/li/(.*/)?a$')")
add("set_intersect", lambda s, d: _li("//p")(s, d).intersect(_li("//article//*")(s, d)), _SET + "label = 'p' AND regexp_matches(path, '/article/')")
add("set_except", lambda s, d: _li("//article//*")(s, d).exceptAll(_li("//p")(s, d)), _SET + "label <> 'p' AND regexp_matches(path, '/article/')")
add("props_nodes", lambda spark, sf_dir: table(spark, sf_dir, "events").select("event_id", F.explode(F.from_json("props", "map<string,int>")).alias("label", "value_of")), "SELECT event_id, 'k' AS label, CAST(json_extract(props, '$.k') AS INTEGER) AS value_of FROM events")


def _udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    surface.register(spark)
    table(spark, sf_dir, "pages").createOrReplaceTempView("sharetree_pages")
    return spark.sql("SELECT CAST(page_id AS BIGINT) AS unit, s.pre, s.label FROM sharetree_pages, LATERAL path_select(html, '//p/b') s")


add("udtf_path_select", _udtf, PAGES + "SELECT CAST(page_id AS BIGINT) AS unit, CAST(pre AS BIGINT) AS pre, label FROM n WHERE path LIKE '%/p/b'")

# ---- streams, drained over what is there


def _stream(name: str, f, mode: str = "append") -> Query:
    return lambda spark, sf_dir: streams.drain(f(streams.stream(spark, sf_dir, name)), mode)


add("stream_count_pages", lambda s, d: _stream("pages", lambda x: streams.count_pages(x, "//p"))(s, d).select(F.col("page_id").alias("unit"), "n"), PAGES + BY_PAGE.format("label = 'p'"))
add("stream_w2_log", lambda s, d: _stream("events", lambda x: streams.walk_siblings(x, "//view/following-sibling::purchase"), "update")(s, d).groupBy("user_id").agg(F.max("n").alias("n")), LOG + "SELECT CAST(user_id AS BIGINT) AS user_id, CAST(count(*) FILTER (label = 'purchase' AND EXISTS (SELECT 1 FROM n b WHERE b.user_id = a.user_id AND b.k < a.k AND b.label = 'view')) AS BIGINT) AS n FROM n a GROUP BY user_id")
add("stream_tumbling", _stream("events", streams.tumbling, "complete"), f"SELECT date_trunc('day', ts) AS window_start, event_type, {N} FROM events GROUP BY ALL")
add("stream_sliding", _stream("events", streams.sliding, "complete"))
add("stream_session", _stream("events", streams.sessions, "complete"), "WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS session_start, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY user_id, k")
add("stream_dedup", lambda s, d: _stream("events", streams.deduplicated)(s, d).groupBy("event_type").agg(F.count("*").alias("n")), f"SELECT event_type, {N} FROM events GROUP BY event_type")
add("stream_interval_join", _stream("events", streams.view_then_purchase), "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR WHERE v.event_type = 'view' AND p.event_type = 'purchase'")
