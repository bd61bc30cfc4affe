"""Structured Streaming: pages counted as they come, walkers along each user's events, windows, and deduplication.

Each function takes a streaming frame and gives one; ``drain`` runs a stream over all that is available and returns what it wrote.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sharetree.plans.query import compile_query
from sharetree.sources.scratch import scratch
from sharetree.sources.tables import table


def stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    rows = spark.readStream.schema(table(spark, sf_dir, name).schema).option("pathGlobFilter", f"{name}.parquet*").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows  # watermarks need an instant


def drain(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run to the end of what is there and read back what was written: append mode by the file sink, the others a folder a micro-batch.

    Complete mode gives the last batch's table, update mode the rows of all batches.  A batch that runs again replaces its folder.
    """
    spark = df.sparkSession
    path, writer = scratch(spark, "stream-out"), df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", scratch(spark, "stream"))
    if mode == "append":
        writer.format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(path)
    done: list[int] = []

    def put(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{i}")
        done.append(i)

    writer.foreachBatch(put).start().awaitTermination()
    if not done:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*(f"{path}/{i}" for i in (sorted(set(done))[-1:] if mode == "complete" else sorted(set(done)))))


def count_pages(pages: DataFrame, query: str) -> DataFrame:
    """page_id and n for each arriving page; no state."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sharetree.functions.grammar import binary_dag, count
        from sharetree.sources.forests import html_tree

        walker = compile_query(query)
        for batch in batches:
            counts = []
            for html in batch.column(1).to_pylist():
                labels, depths = html_tree(html or "")
                roots = [i for i, d in enumerate(depths) if d == 0] + [len(labels)]
                counts.append(sum(count(binary_dag(labels[a:b], depths[a:b]), walker) for a, b in zip(roots, roots[1:])))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64())], names=["page_id", "n"])

    return pages.select(F.col("page_id").cast("long"), "html").mapInArrow(run, "page_id long, n long")


def walk_siblings(events: DataFrame, query: str, root: str = "log", unit: str = "user", late: str = "1 hour", forget: str | None = None) -> DataFrame:
    """user_id and n: the walker's state along each user's events is kept, so an event costs one rule.

    Events wait until the watermark has passed them, and are walked in order of (ts, event_id), so the order in which they come doesn't matter; n counts
    those that still wait, too, as they stand.  An event that comes more than ``late`` behind is left out once later ones have been walked.  ``forget``: a user
    without events for so long (in event time) loses its state; None keeps it.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    walker = compile_query(query)
    start = walker.rule(walker.rule(walker.start, root)[1], unit)
    first = walker.rule(start[2], unit)[1]
    keep = None if forget is None else int(pd.Timedelta(forget).total_seconds() * 1000)

    def along(q: int, n: int, rows: list[tuple]) -> tuple[int, int]:
        for _, _, label in rows:
            hit, _, q = walker.rule(q, label)
            n += bool(hit)
        return q, n

    def step(key, frames, state: GroupState):
        q, n, walked, ts, ids, labels = state.get if state.exists else (first, 0, -1, [], [], [])
        if state.hasTimedOut and not ts:
            state.remove()
            return
        waiting = list(zip(ts, ids, labels))
        for frame in frames:
            waiting += [x for x in zip(frame["micros"].tolist(), frame["event_id"].tolist(), frame["event_type"].tolist()) if x[0] > walked]
        waiting.sort()
        mark = state.getCurrentWatermarkMs() * 1000
        passed = [x for x in waiting if x[0] <= mark]
        waiting = waiting[len(passed) :]
        if passed:
            (q, n), walked = along(q, n, passed), passed[-1][0]
        state.update((q, n, walked, [x[0] for x in waiting], [x[1] for x in waiting], [x[2] for x in waiting]))
        if waiting:
            state.setTimeoutTimestamp(max(waiting[0][0], mark) // 1000 + 1)
        elif keep is not None:
            state.setTimeoutTimestamp(max(walked, mark) // 1000 + keep + 1)
        yield pd.DataFrame({"user_id": [key[0]], "n": [along(q, n, waiting)[1]]})

    kept = "q long, n long, walked long, ts array<long>, ids array<long>, labels array<string>"
    rows = events.withWatermark("ts", late).select("user_id", "ts", F.unix_micros("ts").alias("micros"), "event_id", "event_type")
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long", kept, "update", GroupStateTimeout.EventTimeTimeout)


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Arriving events with their customer's market segment: a join of a stream with a table."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "user_id", "event_type", "c_mktsegment")


def grow_dictionary(pages: DataFrame, kind: str = "unranked") -> DataFrame:
    """Run a stream of pages to its end, adding the distinct nodes that are new to a dictionary on disk; returns the dictionary (digest, edges).

    Each micro-batch's nodes are matched against what earlier batches wrote, and go into a folder of its own, which a repeated batch replaces.
    """
    from sharetree.operators.compress import PIECES, dictionary_update, piece_rows
    from sharetree.sources.forests import html_units

    spark, path = pages.sparkSession, scratch(pages.sparkSession, "dictionary")
    done: list[int] = []

    def put(batch: DataFrame, i: int) -> None:
        before = [f"{path}/{k}" for k in done if k != i]
        known = spark.read.schema(PIECES).parquet(*before) if before else spark.createDataFrame([], PIECES)
        dictionary_update(known, piece_rows(html_units(batch, "page_id", "html"), kind)).write.mode("overwrite").parquet(f"{path}/{i}")
        done.append(i)

    pages.writeStream.trigger(availableNow=True).option("checkpointLocation", scratch(spark, "stream")).foreachBatch(put).start().awaitTermination()
    return spark.read.schema(PIECES).parquet(*(f"{path}/{k}" for k in sorted(set(done)))) if done else spark.createDataFrame([], PIECES)


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, slide)).agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    rows = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return rows.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("session_start"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def view_then_purchase(events: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Pairs of a view and a purchase of the same user at most so much later."""
    kind = lambda name, a: events.where(F.col("event_type") == name).withWatermark("ts", late).select(F.col("user_id").alias(f"{a}_user"), F.col("ts").alias(f"{a}_ts"), F.col("event_id").alias(f"{a}_id"))
    near = F.expr(f"v_user = p_user and p_ts >= v_ts and p_ts <= v_ts + interval {within}")
    return kind("view", "v").join(kind("purchase", "p"), near).select(F.col("v_id").alias("view_id"), F.col("p_id").alias("purchase_id"))
