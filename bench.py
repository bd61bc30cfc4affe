"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

One small query warms the session up, untimed.  Building a forest (reading, units, dictionary, grammars) is timed apart from the queries on it; every
method answers the same question from what is on disk.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sharetree.operators import baseline, compress, evaluate, programs
from sharetree.sources.forests import Forest, opened

R, W7, ORDER, W2 = "//order//lineitem/R", "//customer[.//order/lineitem/R][./BUILDING]/order/lineitem", "//order", "//view/following-sibling::purchase"
FORESTS = {"trade": ["binary"], "log": ["binary"], "pages": ["binary", "hybrid", "digrams"], "talk": ["binary"]}
#: name -> forest, what it asks of it
HEADLINE = {
    "count_R_trade": ("trade", lambda f: evaluate.count(f, R)),
    "count_R_trade_tree": ("trade", lambda f: evaluate.count(f, R, compress="tree")),
    "count_R_trade_structural": ("trade", lambda f: baseline.structural(f, R).agg(F.count("*"))),
    "count_R_trade_paths": ("trade", lambda f: baseline.paths(f, R).agg(F.sum("n"))),
    "count_w7_trade": ("trade", lambda f: evaluate.count(f, W7)),
    "count_w7_trade_tree": ("trade", lambda f: evaluate.count(f, W7, compress="tree")),
    "locate_orders_trade": ("trade", lambda f: evaluate.locate(f, ORDER)),
    "locate_orders_trade_tree": ("trade", lambda f: evaluate.locate(f, ORDER, compress="tree")),
    "locate_orders_trade_structural": ("trade", lambda f: baseline.structural(f, ORDER)),
    "count_w2_log": ("log", lambda f: evaluate.count(f, W2)),
    "count_w2_log_tree": ("log", lambda f: evaluate.count(f, W2, compress="tree")),
    "count_w2_log_structural": ("log", lambda f: baseline.structural(f, W2).agg(F.count("*"))),
    "count_w1_pages": ("pages", lambda f: evaluate.count(f, "//html/*/nav//li/a")),
    "count_w1_pages_hybrid": ("pages", lambda f: evaluate.count(f, "//html/*/nav//li/a", compress="hybrid")),
    "count_w1_pages_digrams": ("pages", lambda f: evaluate.count(f, "//html/*/nav//li/a", compress="digrams")),
    "count_w1_pages_tree": ("pages", lambda f: evaluate.count(f, "//html/*/nav//li/a", compress="tree")),
    "count_three_pages": ("pages", lambda f: evaluate.count_many(f, ["//p", "//p/b", "//li/a"])),
    "locate_pb_pages": ("pages", lambda f: evaluate.locate(f, "//p/b")),
    "serialize_ul_pages": ("pages", lambda f: evaluate.serialize(f, "//ul")),
    "serialized_size_pages": ("pages", lambda f: evaluate.serialized_size(f, "//*")),
    "sharing_unranked_pages": ("pages", lambda f: compress.sharing(f, "unranked")),
    "sharing_binary_pages": ("pages", lambda f: compress.sharing(f, "binary")),
    "sharing_hybrid_pages": ("pages", lambda f: compress.sharing(f, "hybrid")),
    "slp_subtrees_dag_talk": ("talk", lambda f: programs.subtree_programs(f, "//user")),
    "slp_subtrees_general_talk": ("talk", lambda f: programs.subtree_programs(f, "//user", "general", "digrams")),
}


def run(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def timed(f) -> float:
    began = time.time()
    f()
    return round(time.time() - began, 3)


def build(spark: SparkSession, sf_dir: str, name: str) -> Forest:
    forest = opened(spark, sf_dir, name)
    for kind in FORESTS[name]:
        evaluate.grammars(forest, kind)
    return forest


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    warm = opened(spark, "/root/testdata/sf0.001" if os.path.isdir("/root/testdata/sf0.001") else sf_dir, "talk")
    run(evaluate.count(warm, "//user"))
    times = {f"build_{name}": timed(lambda n=name: build(spark, sf_dir, n)) for name in FORESTS}
    for name, (forest, ask) in HEADLINE.items():
        times[name] = timed(lambda: run(ask(opened(spark, sf_dir, forest))))
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    main()
