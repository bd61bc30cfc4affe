"""Forests over the given tables.

A forest is a small top tree, held by the driver, and units: one row a page, customer, user, conversation or document, with the unit's
whole tree as arrays of labels and depths in pre-order.  Units are the grain of distribution; a unit hangs under a top node, after
``before`` sibling units.  A unit may have no root (an empty page) or several.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sharetree.sources.scratch import scratch
from sharetree.sources.tables import ranked, table

#: Nodes that a top tree may have; it is held by the driver.
MAX_TOP = 100_000
#: Bytes of text (or one text) that a task splits at once.
TEXT_BYTES = 1_000_000
# Elements that never have content.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
_ATTRIBUTE = re.compile(r"""([A-Za-z][A-Za-z0-9-]*)\s*=\s*("[^"]*"|'[^']*')""")
UNIT = "unit long, labels array<string>, depths array<int>"
Reader = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]
Read = tuple[DataFrame, Reader]


@dataclass
class Forest:
    #: (id, parent id or None, label) in pre-order; siblings in order.
    top: list[tuple[int, int | None, str]]
    #: ``units``, or what places them when they are first asked for
    placed: DataFrame | Callable[[], DataFrame]
    #: What has been built of it so far, on disk: dictionary and grammars.
    built: dict = field(default_factory=dict, repr=False, compare=False)
    #: the units before they are placed: unit, labels, depths, or (rows, function that reads such units from their batches)
    unplaced: DataFrame | Read | None = field(default=None, repr=False, compare=False)

    @property
    def units(self) -> DataFrame:
        """unit, top, before, labels, depths; (top, before) is a unit's key: unit ids may be null or repeat"""
        if not self.has_units:
            self.placed = self.placed()
        return self.placed

    @property
    def has_units(self) -> bool:
        return isinstance(self.placed, DataFrame)

    def over_trees(self, run: Reader, schema: str) -> DataFrame:
        """What a function makes of batches of labels and depths of the units, whose places it doesn't need; units that Python reads go on in the same task."""
        if self.has_units or self.unplaced is None:
            return self.units.select("labels", "depths").mapInArrow(run, schema)
        if isinstance(self.unplaced, DataFrame):
            return self.unplaced.select("labels", "depths").mapInArrow(run, schema)
        rows, read = self.unplaced
        return rows.mapInArrow(lambda batches: run(b.select(["labels", "depths"]) for b in read(batches)), schema)


def html_tree(html: str, constants: frozenset[str] = frozenset()) -> tuple[list[str], list[int]]:
    """Labels and depths of the elements of a page, however malformed.

    ``constants``: labels ``name@attribute=value`` or ``name#=text`` that elements get for which they hold.

    Comments, declarations and the content of script and style go; names are lower-cased; void and self-closed elements are leaves; an end
    tag closes the nearest open element of its name and what is open inside, or is ignored; the end of input closes the rest.
    """
    html = re.sub(r"<!--.*?-->|<![^>]*>", "", html, flags=re.S)
    html = re.sub(r"(<(script|style)\b[^>]*>).*?(</\2\s*>)", r"\1\3", html, flags=re.S | re.I)
    labels, depths, way = [], [], []
    texts: dict[int, str] = {}  # an element's own text, if a constant asks for texts
    numbers: list[int] = []
    at = 0
    by_text = any("#=" in c for c in constants)
    for m in re.finditer(r"<(/?)([A-Za-z][A-Za-z0-9]*)([^>]*)>", html):
        name = m[2].lower()
        if by_text and numbers:
            texts[numbers[-1]] = texts.get(numbers[-1], "") + html[at : m.start()]
        at = m.end()
        if m[1]:
            if name in way:
                n = len(way) - 1 - way[::-1].index(name)
                del way[n:], numbers[n:]
        else:
            hold = [c for k, v in _ATTRIBUTE.findall(m[3]) if (c := f"{name}@{k.lower()}={v[1:-1]}") in constants] if constants else ()
            labels.append(hold[0] if hold else name)
            depths.append(len(way))
            if name not in VOID and not m[3].endswith("/"):
                way.append(name)
                numbers.append(len(labels) - 1)
    for i, text in texts.items():
        if f"{labels[i]}#={text.strip()}" in constants:
            labels[i] = f"{labels[i]}#={text.strip()}"
    return labels, depths


def _html_read(pages: DataFrame, id_col: str, html_col: str, constants: frozenset[str] = frozenset()) -> Read:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            trees = [html_tree(x or "", constants) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t[0] for t in trees], pa.list_(pa.string())), pa.array([t[1] for t in trees], pa.list_(pa.int32()))], names=["unit", "labels", "depths"])

    return pages.select(F.col(id_col).cast("long"), html_col), run


def html_units(pages: DataFrame, id_col: str, html_col: str, constants: frozenset[str] = frozenset()) -> DataFrame:
    rows, read = _html_read(pages, id_col, html_col, constants)
    return rows.mapInArrow(read, UNIT)


def _under_root(units: DataFrame | Read, root: str) -> Forest:
    made = lambda: units if isinstance(units, DataFrame) else units[0].mapInArrow(units[1], UNIT)
    return Forest([(0, None, root)], lambda: ranked(made(), "unit", name="before").withColumn("top", F.lit(0)), unplaced=units)


def pages(spark: SparkSession, sf_dir: str, constants: frozenset[str] = frozenset()) -> Forest:
    """pages > html > ...; a null or empty page is a unit without nodes."""
    return _under_root(_html_read(table(spark, sf_dir, "pages"), "page_id", "html", constants), "pages")


def trade(spark: SparkSession, sf_dir: str) -> Forest:
    """trade > region > nation > customer > (market segment, order > (status, lineitem > return flag)).

    The tree is what can be reached from a region: rows whose key is null or leads nowhere have no place in it (``trade_orphans`` counts them).
    """
    read = lambda name: table(spark, sf_dir, name)
    line = F.struct("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice", "l_returnflag")
    lines = read("lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_list(line))["l_returnflag"].alias("flags"))
    orders = read("orders").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    text = lambda *parts: F.concat(*(F.lit(p) if isinstance(p, str) else p for p in parts))
    order = F.struct("o_orderkey", F.coalesce("flags", F.expr("cast(array() as array<string>)")).alias("flags"), text("status", F.col("o_orderstatus")).alias("status"))
    by_customer = orders.groupBy("o_custkey").agg(F.sort_array(F.collect_list(order)).alias("orders"))
    rows = read("customer").join(by_customer, F.col("c_custkey") == F.col("o_custkey"), "left")
    own = F.coalesce("orders", F.expr("cast(array() as array<struct<o_orderkey:bigint,flags:array<string>,status:string>>)"))
    labels = F.flatten(F.transform(own, lambda o: F.concat(F.array(F.lit("order"), o["status"]), F.flatten(F.transform(o["flags"], lambda f: F.array(F.lit("lineitem"), f))))))
    depths = F.flatten(F.transform(own, lambda o: F.concat(F.array(F.lit(1), F.lit(2)), F.flatten(F.transform(o["flags"], lambda f: F.array(F.lit(2), F.lit(3)))))))
    units = rows.select(
        F.col("c_custkey").cast("long").alias("unit"), F.col("c_nationkey").alias("nation"),
        F.concat(F.array(F.lit("customer"), F.col("c_mktsegment")), labels).alias("labels"), F.concat(F.array(F.lit(0), F.lit(1)), depths).alias("depths"),
    )
    top: list[tuple[int, int | None, str]] = [(0, None, "trade")]
    nations: dict[int, int] = {}
    joined = read("nation").join(read("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_regionkey", "n_nationkey").orderBy("n_regionkey", "n_nationkey")
    regions: dict[int, int] = {}
    for row in joined.limit(MAX_TOP + 1).collect():
        if row["n_regionkey"] not in regions:
            regions[row["n_regionkey"]] = len(top)
            top.append((len(top), 0, "region"))
        nations[row["n_nationkey"]] = len(top)
        top.append((len(top), regions[row["n_regionkey"]], "nation"))
    if len(top) > MAX_TOP:
        raise ValueError("the top tree is too large for the driver")
    keys = spark.createDataFrame([(k, v) for k, v in nations.items()], "nation int, top int")
    under = units.join(F.broadcast(keys), "nation").drop("nation")

    def put() -> DataFrame:
        placed = ranked(under, "top", "unit")
        first = placed.groupBy("top").agg(F.min("place").alias("first"))  # a row a top node
        return placed.join(F.broadcast(first), "top").withColumn("before", F.col("place") - F.col("first")).drop("place", "first")

    return Forest(top, put, unplaced=under)


def trade_orphans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """level and n: rows of each table that hang under no row of the level above."""
    read = lambda name: table(spark, sf_dir, name)
    levels = [("nation", "n_regionkey", "region", "r_regionkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("orders", "o_custkey", "customer", "c_custkey"), ("lineitem", "l_orderkey", "orders", "o_orderkey")]
    counts = [read(a).join(read(b), F.col(x) == F.col(y), "left_anti").agg(F.lit(a).alias("level"), F.count("*").alias("n")) for a, x, b, y in levels]
    return reduce(DataFrame.unionByName, counts)


def _sequence(df: DataFrame, unit: str, order: list[str], label: str, root: str) -> DataFrame:
    """A unit for each value of ``unit``: a root and one leaf for each row, in order."""
    rows = df.groupBy(F.col(unit).cast("long").alias("unit")).agg(F.sort_array(F.collect_list(F.struct(*order, F.col(label).alias("label"))))["label"].alias("own"))
    return rows.select("unit", F.concat(F.array(F.lit(root)), "own").alias("labels"), F.concat(F.array(F.lit(0)), F.transform("own", lambda _: F.lit(1))).alias("depths"))


def log(spark: SparkSession, sf_dir: str) -> Forest:
    """log > user > event type."""
    return _under_root(_sequence(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "event_type", "user"), "log")


def talk(spark: SparkSession, sf_dir: str) -> Forest:
    """corpus > conv > role."""
    return _under_root(_sequence(table(spark, sf_dir, "conversations"), "conv_id", ["turn"], "role", "conv"), "corpus")


def _lines_and_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """doc > line > word of texts: marks, which no word can be, stand for the document and its lines while the text is split."""
    for batch in batches:
        ends = pc.cumulative_sum(pc.fill_null(pc.binary_length(batch.column(1)), 0).cast(pa.int64())).to_numpy()
        a = 0
        while a < batch.num_rows:
            b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + TEXT_BYTES, "right")))
            texts = pc.replace_substring(pc.fill_null(batch.column(1).slice(a, b - a), ""), "\n", " \n ")
            words = pc.split_pattern(pc.binary_join_element_wise("\n\n \n ", texts, ""), " ")
            own, of = words.flatten(), pc.list_parent_indices(words)
            some = pc.not_equal(own, "")
            own, of = own.filter(some), of.filter(some).to_numpy()
            doc, line = pc.equal(own, "\n\n"), pc.equal(own, "\n")
            labels = pc.if_else(doc, "doc", pc.if_else(line, "line", own)).cast(pa.string())
            depths = pc.subtract(pa.scalar(2, pa.int32()), pc.add(line.cast(pa.int32()), pc.multiply(doc.cast(pa.int32()), pa.scalar(2, pa.int32()))))
            at = pa.array(np.concatenate([[0], np.cumsum(np.bincount(of, minlength=b - a))]).astype(np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.ListArray.from_arrays(at, labels), pa.ListArray.from_arrays(at, depths)], names=["unit", "labels", "depths"])
            a = b


def prose(spark: SparkSession, sf_dir: str) -> Forest:
    """corpus > doc > line > word."""
    rows = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long"), "text")
    return _under_root((rows, _lines_and_words), "corpus")


def parts(spark: SparkSession, sf_dir: str) -> Forest:
    """parts > type > part > words of its name."""
    part = table(spark, sf_dir, "part")
    each = part.select("p_type", F.col("p_partkey").alias("k"), F.split("p_name", " ").alias("w"))
    one = lambda x: F.concat(F.array(F.lit("part")), x["w"])
    deep = lambda x: F.concat(F.array(F.lit(1)), F.transform(x["w"], lambda _: F.lit(2)))
    rows = each.groupBy("p_type").agg(F.sort_array(F.collect_list(F.struct("k", "w"))).alias("own"))
    units = rows.select(F.dense_rank().over(Window.orderBy("p_type")).cast("long").alias("unit"), F.concat(F.array(F.lit("type")), F.flatten(F.transform("own", one))).alias("labels"), F.concat(F.array(F.lit(0)), F.flatten(F.transform("own", deep))).alias("depths"))
    return _under_root(units, "parts")


def bench(spark: SparkSession, sf_dir: str) -> Forest:
    """bench > item > word."""
    words = F.filter(F.split(F.translate(F.coalesce("text", F.lit("")), "\n", " "), " "), lambda w: w != "")
    units = table(spark, sf_dir, "benchmark").select(F.col("item_id").cast("long").alias("unit"), F.concat(F.array(F.lit("item")), words).alias("labels"), F.concat(F.array(F.lit(0)), F.transform(words, lambda _: F.lit(1))).alias("depths"))
    return _under_root(units, "bench")


_open: dict[tuple, Forest] = {}


def opened(spark: SparkSession, sf_dir: str, name: str) -> Forest:
    """A forest over the given tables that this session builds once: later queries find its units, dictionary and grammars on disk.

    It is built anew when the tables' files have changed, or its own files have gone.
    """
    path = spark._jvm.org.apache.hadoop.fs.Path
    conf = spark._jsc.hadoopConfiguration()
    found = path(f"{sf_dir}/*.parquet")
    files = tuple(sorted((f.getPath().getName(), f.getModificationTime(), f.getLen()) for f in found.getFileSystem(conf).globStatus(found) or ()))
    key = (spark.sparkContext.applicationId, sf_dir, name)
    have = _open.get(key)
    if have and have.built["files"] == files and all(path(p).getFileSystem(conf).exists(path(p)) for p in [*(have.units.inputFiles() if have.has_units else ()), *have.built.get("paths", ())]):
        return have
    _open[key] = FORESTS[name](spark, sf_dir)
    _open[key].built["files"] = files
    return _open[key]


FORESTS: dict[str, Callable[[SparkSession, str], Forest]] = {"pages": pages, "trade": trade, "log": log, "talk": talk, "prose": prose, "parts": parts, "bench": bench}


def _nodes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["unit", "top", "before", "pre", "post", "parent_pre", "ord", "depth", "size", "label"]
    kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.string()]
    for batch in batches:
        for unit, top, before, labels, depths in zip(*(c.to_pylist() for c in batch.columns)):
            n, way = len(labels), []
            parent, order, kids, size, post = [None] * n, [0] * n, [0] * n, [1] * n, [0] * n
            done = 0
            for i, d in enumerate([*depths, 0]):
                while len(way) > d or (i == n and way):
                    k = way.pop()
                    done += 1
                    post[k] = done
                    size[k] = i - k
                if i < n:
                    if way:
                        parent[i] = way[-1] + 1
                        kids[way[-1]] += 1
                        order[i] = kids[way[-1]] - 1
                    way.append(i)
            columns = [[unit] * n, [top] * n, [before] * n, list(range(1, n + 1)), post, parent, order, depths, size, labels]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)


def nodes(forest: Forest, keyed: bool = False) -> DataFrame:
    """A row for each node of the units: unit, pre (from 1), post, parent_pre, ord, depth, size, label; ``keyed``: and the unit's key (top, before)."""
    units = forest.units.select("unit", F.col("top").cast("int").alias("top"), F.col("before").cast("long").alias("before"), "labels", "depths")
    rows = units.mapInArrow(_nodes, "unit long, top int, before long, pre long, post long, parent_pre long, ord int, depth int, size long, label string")
    return rows if keyed else rows.drop("top", "before")


def binary(tree: DataFrame) -> DataFrame:
    """First child and next sibling of every node, by windows over siblings; a unit is told apart by (top, before) if the rows have them, else by its id."""
    key = [c for c in ("top", "before") if c in tree.columns] or ["unit"]
    kids = tree.where("parent_pre is not null").groupBy(*key, "parent_pre").agg(F.min("pre").alias("left_pre"))
    kids = kids.select(*(F.col(c).alias(f"{c}_of") for c in key), F.col("parent_pre").alias("pre_of"), "left_pre")
    after = F.lead("pre").over(Window.partitionBy(*key, "parent_pre").orderBy("ord"))
    same = reduce(lambda a, b: a & b, (F.col(c).eqNullSafe(F.col(f"{c}_of")) for c in [*key, "pre"]))
    return tree.withColumn("right_pre", after).join(kids, same, "left").select("unit", *(c for c in key if c != "unit"), "pre", "label", "left_pre", "right_pre")


def edges(links: DataFrame, most: int = 1_000) -> DataFrame:
    """id, pre, depth, size and label of the nodes of a tree or forest given as rows (id, parent or null, ord, label), siblings in order of (ord, id).

    A level a round, each written before the next; a node's way from its root orders it, and counts for the size of each node on it.  Rows that no root
    leads to are left out; more than ``most`` levels are an error.
    """
    spark = links.sparkSession

    def put(df: DataFrame) -> DataFrame:
        path = scratch(spark, "levels")
        df.write.parquet(path)
        return spark.read.schema(df.schema).parquet(path)

    step = F.array(F.struct(F.col("ord").cast("long").alias("ord"), F.col("id").alias("id")))
    level = put(links.where("parent is null").select("id", "label", step.alias("way")))
    levels = []
    while not level.isEmpty():
        levels.append(level)
        if len(levels) > most:
            raise ValueError("too many levels, or a circle")
        up = level.select(F.col("id").alias("parent"), F.col("way").alias("above"))
        level = put(links.join(up, "parent").select("id", "label", F.concat("above", step).alias("way")))
    if not levels:
        return links.select("id", F.lit(0).cast("long").alias("pre"), F.lit(0).alias("depth"), F.lit(0).cast("long").alias("size"), "label").where("false")
    rows = ranked(reduce(DataFrame.unionByName, levels), "way")
    sizes = rows.select(F.explode("way.id").alias("id")).groupBy("id").agg(F.count("*").alias("size"))
    return rows.join(sizes, "id").select("id", (F.col("place") + 1).cast("long").alias("pre"), (F.size("way") - 1).alias("depth"), "size", "label")


def unranked(pairs: DataFrame) -> DataFrame:
    """The inverse of ``binary``: labels and depths in pre-order, by a walk inside each unit."""

    def run(batches):
        for batch in batches:
            rows = []
            for unit, own in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                by = {x["pre"]: x for x in own}
                labels, depths, todo = [], [], [(min(by), 0)] if by else []
                while todo:
                    at, d = todo.pop()
                    labels.append(by[at]["label"])
                    depths.append(d)
                    if by[at]["right_pre"]:
                        todo.append((by[at]["right_pre"], d))
                    if by[at]["left_pre"]:
                        todo.append((by[at]["left_pre"], d + 1))
                rows.append((unit, labels, depths))
            kinds = (pa.int64(), pa.list_(pa.string()), pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=["unit", "labels", "depths"])

    return pairs.groupBy("unit").agg(F.collect_list(F.struct("pre", "label", "left_pre", "right_pre")).alias("own")).mapInArrow(run, UNIT)
