"""Scans of the given tables, and orders that don't need one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sharetree.sources.scratch import scratch


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ranked(df: DataFrame, *keys: str | Column, name: str = "place") -> DataFrame:
    """Place (from 0) of each row in the order of the keys.

    A range exchange sorts the rows; the place inside a partition comes from the row id, the partition's first place from counts
    with one row a partition.  No window holds more than that.
    """
    rows = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_id", F.monotonically_increasing_id())
    rows = rows.withColumns({"_part": F.shiftright("_id", 33), "_in": F.col("_id").bitwiseAND((1 << 33) - 1)})
    # bounds of a range exchange are drawn anew each time it runs, so the rows are written once and both readers see the same parts
    path = scratch(df.sparkSession, "ranked")
    rows.drop("_id").write.parquet(path)
    rows = df.sparkSession.read.parquet(path)
    counts = rows.groupBy("_part").agg(F.count("*").alias("_n"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    firsts = counts.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_first"))
    return rows.join(firsts, "_part").withColumn(name, F.col("_first") + F.col("_in")).drop("_part", "_in", "_first")
