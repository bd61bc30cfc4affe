"""Forests kept compressed: written once, read and queried without the trees.

Layout of a folder: ``top`` (id, parent, label, in order of n), ``units`` (unit, top, before, entry), ``entries`` (entry, roots, nodes) and
``grammars`` (entry, labels, ranks, lengths, symbols; ``grammar.encode``), with the compressor's name in ``about``; all Parquet.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from sharetree.functions import grammar as G
from sharetree.operators import evaluate
from sharetree.sources.forests import Forest


def save(forest: Forest, path: str, compress: str = "binary", mode: str = "errorifexists") -> None:
    """Write a forest's grammars and what places them."""
    entries, units = evaluate.dictionary(forest)
    spark = entries.sparkSession
    tables = {
        "top": spark.createDataFrame([(n, *x) for n, x in enumerate(forest.top)], "n int, id int, parent int, label string").coalesce(1),
        "about": spark.createDataFrame([(compress,)], "compress string").coalesce(1),
        "units": units,
        "entries": entries.select("entry", "roots", "nodes"),
        "grammars": evaluate.grammars(forest, compress),
    }
    for name, df in tables.items():
        df.write.mode(mode).parquet(f"{path}/{name}")


def _expanded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        trees = [G.tree_of(g) for g in evaluate._decoded(batch, 1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t[0] for t in trees], pa.list_(pa.string())), pa.array([t[1] for t in trees], pa.list_(pa.int32()))], names=["entry", "labels", "depths"])


def load(spark: SparkSession, path: str) -> Forest:
    """The forest of a folder; its trees are expanded only by what asks for them (node tables, the uncompressed baselines, XML of nodes above units)."""
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    top = [(r["id"], r["parent"], r["label"]) for r in read("top").orderBy("n").collect()]  # its size was checked when it was made
    kept = read("grammars")
    trees = kept.mapInArrow(_expanded, "entry string, labels array<string>, depths array<int>")
    entries, units = read("entries").join(trees, "entry"), read("units")
    built = {"dictionary": (entries.select("entry", "roots", "nodes", "labels", "depths"), units), read("about").first()[0]: kept}
    return Forest(top, units.join(trees, "entry").select("unit", "top", "before", "labels", "depths"), built)


def rules(forest: Forest, compress: str = "binary") -> DataFrame:
    """entry, template, rank, level (longest way up to the start), size (edges) and body (in pre-order, as text) of every template."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = {"l": str, "t": "<{}>".format, "y": "${}".format}
        for batch in batches:
            rows = []
            for entry, g in zip(batch.column(0).to_pylist(), evaluate._decoded(batch, 1)):
                level = dict.fromkeys(g.bodies, 0)
                for t in g.order():
                    for s in g.bodies[t]:
                        if s[0] == "t":
                            level[s[1]] = max(level[s[1]], level[t] + 1)
                rows += [(entry, t, g.ranks[t], level[t], len(b) - 1, [names[s[0]](s[1]) if len(s) > 1 else "_" for s in b]) for t, b in g.bodies.items()]
            kinds = [pa.string(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.string())]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=["entry", "template", "rank", "level", "size", "body"])

    return evaluate.grammars(forest, compress).mapInArrow(run, "entry string, template long, rank int, level int, size int, body array<string>")


class _Part(InputPartition):
    def __init__(self, file: str):
        self.file = file


class GrammarReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"].removeprefix("file://")

    def partitions(self) -> list[_Part]:
        from pyarrow import fs

        found = fs.FileSelector(f"{self.path}/grammars")
        return [_Part(f.path) for f in fs.LocalFileSystem().get_file_info(found) if f.path.endswith(".parquet")]

    def read(self, partition: _Part):
        import pyarrow.parquet as pq

        for batch in pq.ParquetFile(partition.file).iter_batches(columns=["entry", "labels", "ranks", "lengths", "symbols"]):
            for entry, g in zip(batch.column(0).to_pylist(), evaluate._decoded(batch, 1)):
                yield entry, len(g.bodies), g.edges(), g.rank(), G.tree_size(g)


class GrammarSource(DataSource):
    """``spark.read.format("sharetree").load(folder)``: a row a stored grammar, by its measures.  For folders on a file system that executors mount; ``load`` reads any."""

    @classmethod
    def name(cls) -> str:
        return "sharetree"

    def schema(self) -> str:
        return "entry string, templates long, edges long, rank long, nodes long"

    def reader(self, schema) -> GrammarReader:
        return GrammarReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GrammarSource)


def buckets(df: DataFrame, key: str, n: int = 64) -> DataFrame:
    """A result with a bucket column, for ``write.partitionBy("bucket")``: rewriting a bucket replaces it whole."""
    return df.withColumn("bucket", F.pmod(F.xxhash64(key), F.lit(n)).cast("int"))
