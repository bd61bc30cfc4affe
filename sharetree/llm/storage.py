"""Shared scratch space and schema helpers of the llm operators.

Everything that more than one executor has to see goes below the folder that the cluster names in
``spark.checkpoint.dir``.  Only where that setting is absent (tests, a laptop) a folder of our own is made and kept
for the life of the session.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_own_folder: dict[str, str] = {}


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _own_folder:
        _own_folder[app] = "file://" + tempfile.mkdtemp(prefix="sharetree-")
    return _own_folder[app]


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path for one table; unique, so that a repeated call never overwrites what a lazy frame still reads."""
    return f"{shared_folder(spark)}/llm/{name}-{uuid.uuid4().hex[:12]}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet below the shared folder and read it back: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def utf8(text: str | Column) -> Column:
    """The text's UTF-8 bytes; null counts as empty."""
    return F.encode(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), "UTF-8")


#: Keys that may each have more than one row in this many.
HEAVY = 1000


def join_counted(rows: DataFrame, counts: DataFrame, on: list[str], n: str, total: int) -> DataFrame:
    """``rows`` joined with the row that ``counts`` has for a key; a key has at most ``counts[n]`` of the ``total`` rows.

    The counts of all keys add up to ``total`` at most, so fewer than ``HEAVY`` keys exceed its ``HEAVY``th part: these are broadcast and
    their rows stay where they are.  All other keys are shuffled.  Both frames are read twice: give stored ones.
    """
    heavy = F.broadcast(counts.where(F.col(n) > total // HEAVY))
    light = rows.join(heavy.select(*on), on, "left_anti").join(counts.where(F.col(n) <= total // HEAVY), on)
    return light.unionByName(rows.join(heavy, on))
