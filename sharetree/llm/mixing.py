"""Mixing sources to target weights by Poisson replication, in DataFrame functions only.

Each source gets a mean repetition rate: its share of the target weights times the target size, over what it has.  A document
is repeated as often as the inverse Poisson distribution says for a uniform number hashed from seed and document, so the
draw needs no state, is the same on every run, and a lost task draws it again alike.  The copies are then dealt to
partitions by a hash of their own and sorted by it: a global shuffle without sampled range bounds.

Defined cases: a null source is a source of its own, with the weight ``weights[None]`` or ``default_weight``; null and empty texts
count ``per_row`` bytes, so they are drawn like others; a source of weight 0 goes; rows that are alike in doc_id and text are
drawn alike; an empty table gives an empty table; other columns, whatever their names, stay as they are (struct column
inside).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sharetree.llm.storage import materialize

#: Poisson rates above this are drawn as a sum of equal parts, for exp(-rate) must not vanish.
PART_RATE = 200.0
#: Sources whose distributions (some kilobytes each at most) may be broadcast.
MAX_BROADCAST_SOURCES = 10_000


def uniform(*parts: Column) -> Column:
    """A number in [0, 1) from the first 52 bits of the MD5 digest of the parts, joined by colons."""
    digest = F.md5(F.concat_ws(":", *(p.cast("string") for p in parts)))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


def rates(docs: DataFrame, weights: dict[str | None, float], default_weight: float, epochs: float, per_row: int) -> DataFrame:
    """One row a source: its size (UTF-8 bytes plus ``per_row``), mean repetition rate, and the cumulated Poisson distribution of a part of it."""
    size = F.coalesce(F.octet_length("text"), F.lit(0)) + F.lit(per_row)
    named = [(k, float(v)) for k, v in weights.items() if k is not None]
    weight = F.lit(float(default_weight))
    if named:
        table = F.create_map(*(F.lit(x) for pair in named for x in pair))
        weight = F.coalesce(table[F.col("source")], weight)
    if None in weights:
        weight = F.when(F.col("source").isNull(), F.lit(float(weights[None]))).otherwise(weight)
    sizes = docs.groupBy("source").agg(F.sum(size).alias("bytes")).withColumn("weight", weight)
    every = Window.partitionBy(F.lit(1))  # over a row a source
    share = F.col("weight") / F.sum("weight").over(every)
    rate = (share * F.lit(float(epochs)) * F.sum("bytes").over(every) / F.col("bytes")).alias("rate")
    rated = sizes.select("source", "bytes", rate).where("rate > 0")
    rated = rated.withColumn("parts", F.greatest(F.lit(1), F.ceil(F.col("rate") / PART_RATE)).cast("int"))
    mean = F.col("rate") / F.col("parts")
    # the tail past 12 deviations has no mass in doubles
    most = F.ceil(mean + 12 * F.sqrt(mean) + 20).cast("int")
    start = F.struct(F.exp(-mean).alias("p"), F.array(F.exp(-mean)).alias("cdf"))

    def step(s: Column, k: Column) -> Column:
        p = s["p"] * mean / k
        return F.struct(p.alias("p"), F.concat(s["cdf"], F.array(F.element_at(s["cdf"], -1) + p)).alias("cdf"))

    return rated.withColumn("cdf", F.aggregate(F.sequence(F.lit(1), most), start, step)["cdf"])


def poisson(cdf: Column, parts: Column, seed: int, *key: Column) -> Column:
    """The Poisson number that hashed uniform numbers, one for each part of the rate, invert to."""
    drawn = F.transform(F.sequence(F.lit(1), parts), lambda part: uniform(F.lit(seed), part, *key))
    return F.aggregate(drawn, F.lit(0), lambda total, u: total + F.size(F.filter(cdf, lambda c: c <= u)))


def mix(docs: DataFrame, weights: dict[str | None, float], default_weight: float = 1.0, epochs: float = 1.0, seed: int = 42, per_row: int = 8, shuffle: bool = True) -> DataFrame:
    """All columns of ``docs``, repeated to the target weights, with ``copy`` (0 first) and ``shuffle_key`` beside them."""
    spark = docs.sparkSession
    rows = docs.select(F.struct("*").alias("row"), F.col("source").alias("source"))
    rated = materialize(rates(docs, weights, default_weight, epochs, per_row).select(F.col("source").alias("of"), "parts", "cdf"), "mix-rates")
    # a row a source; counted before it is sent out, joined by shuffle beyond the bound
    if rated.count() <= MAX_BROADCAST_SOURCES:
        rated = F.broadcast(rated)
    rated = rows.join(rated, F.col("source").eqNullSafe(F.col("of")))
    rated = rated.withColumn("digest", F.md5(F.concat_ws(":", F.coalesce(F.col("row.doc_id").cast("string"), F.lit("~")), F.coalesce("row.text", F.lit("")))))
    drawn = rated.withColumn("times", poisson(F.col("cdf"), F.col("parts"), seed, F.col("digest"))).where("times > 0")
    copies = drawn.select("row", "digest", F.explode(F.sequence(F.lit(0), F.col("times") - 1)).alias("copy"))
    copies = copies.withColumn("shuffle_key", F.md5(F.concat_ws(":", F.lit(seed + 1), "digest", F.col("copy"))))
    if shuffle:
        # the key is uniform, so bounds are known without sampling
        n = int(spark.conf.get("spark.sql.shuffle.partitions"))
        slot = F.floor(F.conv(F.substring("shuffle_key", 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32)) * n).cast("int")
        copies = copies.repartitionById(n, slot).sortWithinPartitions("shuffle_key")
    taken = {"copy", "shuffle_key"}
    own = [F.col("row")[c].alias(c if c not in taken else f"{c}_in") for c in docs.columns]
    return copies.select(*own, "copy", "shuffle_key")
