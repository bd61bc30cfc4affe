"""Sharding by proportional stratified interleaving.

Rows are ranked within their source in a seeded random order; row r of a source of n rows gets the fractional rank
(r + 1/2) / n.  In the order of fractional ranks every stretch holds the sources in their proportions, so cutting that order
into runs of equal length gives shards that all match the mixture.  Law ``rows``: counts of the shards differ by at most one.

Neither ranking needs a source, or the whole, in one task: the random order is that of a digest, so a source is first
dealt into digest ranges, and the global order into ranges of the fractional rank; counts of the ranges, summed up over a
table with one row a range, give each range its first rank.

Only (doc_id, size, text digest, source) is moved, never a text.  Defined cases: a null source is a source of its own; a null
text has no bytes; equal rows are ordered by their digest and then stand side by side; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sharetree.llm.storage import materialize, utf8

#: Rows that a range should hold; ranges are the unit of ranking.
ROWS_PER_RANGE = 50_000
PER_ROW_BYTES = 8


def ranges_for(n_rows: int) -> int:
    return max(256, -(-n_rows // ROWS_PER_RANGE))


def _first_ranks(rows: DataFrame, group: list[str], bucket: str) -> DataFrame:
    """Rows of the group in earlier buckets, one row for each (group, bucket)."""
    counts = rows.groupBy(*group, bucket).agg(F.count("*").alias("in_bucket"))
    window = Window.partitionBy(*group) if group else Window.partitionBy(F.lit(1))
    before = window.orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn("first", F.coalesce(F.sum("in_bucket").over(before), F.lit(0)))


def _part(digest: Column, ranges: int) -> Column:
    """The range of a hexadecimal digest, by its first 32 bits."""
    return F.floor(F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") * F.lit(ranges) / F.lit(1 << 32)).cast("int")


def shard(docs: DataFrame, shards: int, seed: int = 42) -> DataFrame:
    """doc_id, size, text_crc32, source, position (in the interleaved order), shard and slot of every row."""
    slim = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce("source", F.lit("")).alias("source"),
        F.col("source").isNull().alias("no_source"),
        (F.coalesce(F.octet_length("text"), F.lit(0)) + PER_ROW_BYTES).cast("long").alias("size"),
        F.crc32(utf8("text")).alias("text_crc32"),
        F.md5(F.concat_ws(":", F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("~")), F.coalesce("text", F.lit("")))).alias("digest"),
    )
    slim = materialize(slim, "shard-rows")  # three passes follow over some 60 bytes a row
    n = slim.count()
    ranges, source = ranges_for(n), ["source", "no_source"]
    slim = slim.withColumn("range", _part(F.col("digest"), ranges))
    sizes = slim.groupBy(*source).agg(F.count("*").alias("of_source"))
    firsts = _first_ranks(slim, source, "range").join(sizes, source).drop("in_bucket")
    within = Window.partitionBy(*source, "range").orderBy("digest")
    ranked = slim.withColumn("in_range", F.row_number().over(within) - 1).join(firsts, [*source, "range"])
    # one division of integers: equal fractions give the same double, and it keeps their order
    fraction = (2 * (F.col("first") + F.col("in_range")) + 1) / (2 * F.col("of_source"))
    placed = ranked.select("doc_id", "source", "no_source", "size", "text_crc32", "digest", fraction.alias("fraction"))
    placed = placed.withColumn("range", F.least(F.floor(F.col("fraction") * ranges), F.lit(ranges - 1)).cast("int"))
    placed = materialize(placed, "shard-fractions")
    order = Window.partitionBy("range").orderBy("fraction", "digest", "source", "no_source")
    ordered = placed.withColumn("in_range", F.row_number().over(order) - 1).join(_first_ranks(placed, [], "range").drop("in_bucket"), "range")
    position = (F.col("first") + F.col("in_range")).cast("long")
    shard_of = F.floor(F.col("position") * shards / F.lit(max(n, 1))).cast("int") if n * shards < 1 << 52 else F.expr(f"cast(position * {shards} div {n} as int)")
    cut = F.expr(f"cast((cast(shard as bigint) * {n} + {shards} - 1) div {shards} as bigint)")
    out = ordered.withColumn("position", position).withColumn("shard", shard_of).withColumn("slot", F.col("position") - cut)
    return out.select("doc_id", "size", "text_crc32", F.when(~F.col("no_source"), F.col("source")).alias("source"), "position", "shard", "slot")


def write_shards(docs: DataFrame, path: str, shards: int, seed: int = 42) -> None:
    """The documents themselves, one folder a shard, in the order of their slots."""
    keys = shard(docs, shards, seed).select("doc_id", F.col("text_crc32").alias("_crc"), F.col("size").alias("_size"), "shard", "slot")
    again = Window.partitionBy("doc_id", "_crc", "_size").orderBy("slot")
    nth = Window.partitionBy("doc_id", "_crc", "_size").orderBy(F.lit(1))
    left = docs.withColumns({"_crc": F.crc32(utf8("text")), "_size": (F.coalesce(F.octet_length("text"), F.lit(0)) + PER_ROW_BYTES).cast("long")}).withColumn("_nth", F.row_number().over(nth))
    right = keys.withColumn("_nth", F.row_number().over(again)).withColumnRenamed("doc_id", "_doc_id")
    same = F.col("doc_id").eqNullSafe(F.col("_doc_id")) & (left["_crc"] == right["_crc"]) & (left["_size"] == right["_size"]) & (left["_nth"] == right["_nth"])
    rows = left.join(right, same).select(*docs.columns, "shard", "slot")
    rows.repartition("shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
