"""The corpus pipeline: five stages over `documents`, each stage's result written and read again by the next.

Every stage works on all rows that its predecessor kept. All but the last return the columns they got."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tracedex.llm import contamination, near, packing, private, quality
from tracedex.llm.binary import shared_folder
from tracedex.llm.common import table

#: Documents that score below are rejected.
KEEP_FROM = 0.3


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the rule ensemble, trained on this stage's rows with labels, rejects."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.accepted(docs, model, KEEP_FROM)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps of each near-duplicate class the document of least id.

    Documents without text link to nothing and stay. Rows that share an id but not their text are documents of their own; rows without an
    id come last in their class; of rows equal in id and text one stays."""
    return near.keep_one(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops contaminated documents."""
    return contamination.clean(docs, table(spark, sf_dir, "benchmark"))


def without_private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data by surrogates."""
    return private.pseudonymise(docs, entities=False)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences."""
    return packing.pack(docs)


STAGES = [("quality", keep_quality), ("near_duplicates", one_of_each), ("decontamination", without_benchmark), ("private_data", without_private), ("packing", packed)]
#: SQL has no rule ensemble, MinHash join or packing; the tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; between stages a table in the shared folder, which survives lost executors."""
    docs, at = table(spark, sf_dir, "documents"), shared_folder(spark, "pipeline")
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.mode("overwrite").parquet(f"{at}/{name}")
        docs = spark.read.parquet(f"{at}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
