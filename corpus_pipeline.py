"""A corpus pipeline: quality, near duplicates, benchmark decontamination, mixture, token ids.

Each stage takes (spark, docs, sf_dir) and returns a frame that is written as Parquet and read again as the next stage's
documents.  All but the last return the columns of ``documents``, whatever other ones there are and whatever they are called.

Defined cases, by stage: ``quality_classifier`` scores null and empty texts like any other text, and keeps a row for each input row that it
keeps; ``near_dedup`` leaves rows without words alone, of rows alike in doc_id and text one stays, and a null doc_id comes last in its
component; ``benchmark_decontamination`` keeps rows without words; ``target_mixture`` takes a null source for a source of its own and draws rows that are alike
alike; ``token_output`` gives null and empty texts the end id alone.  An empty table goes through all stages as an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sharetree.llm import decontaminate, mixing, near_duplicates, quality, token_store
from sharetree.llm.registry import MIX_WEIGHTS, SEED, tokenizer_path
from sharetree.llm.storage import materialize, table


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line field rejects go."""
    return quality.keep_good(docs, quality.fit_from(docs, table(spark, sf_dir, "labels")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate component stays."""
    return near_duplicates.deduplicate(docs)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a benchmark window go."""
    return decontaminate.remove_contaminated(docs, table(spark, sf_dir, "benchmark"))


def target_mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are repeated to the target weights and shuffled; the order of the files is the order of the mixture."""
    mixed = mixing.mix(docs, MIX_WEIGHTS, seed=SEED)
    taken = {"copy", "shuffle_key"}
    return mixed.select(*(F.col(f"{c}_in" if c in taken else c).alias(c) for c in docs.columns))


def token_output(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids, in the order of the mixture, as directly addressable codes; a row a document as read back."""
    return token_store.token_documents(docs, tokenizer_path(), order="stored")


STAGES = [
    ("quality_classifier", quality_classifier),
    ("near_dedup", near_dedup),
    ("benchmark_decontamination", benchmark_decontamination),
    ("target_mixture", target_mixture),
    ("token_output", token_output),
]

#: The first stage is a fitted model, which SQL can't express; tests hold the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
