"""A training corpus from raw documents: five stages, each written as Parquet and read again.

1. toxicity: documents that the classifier rejects go;
2. near duplicates: of each class one document stays;
3. decontamination: documents that hold a passage of the benchmark go;
4. mixing: sources are brought to their target weights, repeats as repeated rows;
5. token codes: the ids of all that is left, written and read back.

Every stage works on all that the one before kept. An empty table passes
through as an empty table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from clipforge.llm import common, leak_windows, shingle_forest, source_mix, token_codes, toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.train(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "labels"))
    return toxicity.filter_toxic(docs, model)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return shingle_forest.keep_one(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return leak_windows.drop_leaks(docs, common.table(spark, sf_dir, "benchmark"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return source_mix.mix_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return token_codes.token_codes(docs)


STAGES = [("toxicity", drop_toxic), ("near_duplicates", drop_copies), ("decontamination", drop_leaks), ("mix", mix), ("token_codes", encode)]

#: SQL cannot express the classifier or the tokenizer; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's rows are a table in the shared folder, which goes when the next one is written."""
    docs, last = common.table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        path = common.scratch_path(spark, f"pipeline-{name}")
        with common.scratch_scope(spark):
            out = stage(spark, docs, sf_dir)
            out.write.parquet(path)
        docs = spark.read.schema(out.schema).parquet(path)
        if last:
            common.remove(spark, last)
        last = path
    return docs
