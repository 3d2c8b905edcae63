"""A corpus pipeline of the training-data operators, over whole documents at every stage.

Stages: language ID drops documents without a letter (`und`) and those whose language is ambiguous; toxicity drops scores
of 0.7 and more; SimHash near-dedup keeps the document with the least id of each group; decontamination drops documents
that hold a benchmark passage; BPE replaces the texts by token ids and counts, with the digest of the decoded text.
Models learn from the whole given tables by the operators' own folds and documented bounds, not from what is left. The
near-copy stage is op2's search (4-word shingles, 4 of 64 bits); what share of near copies that radius finds is in the README.

Defined results: null, empty and letterless texts are `und` and go in the first stage; documents with a null id are judged like
others but link nothing and all stay in the near-copy stage; of a group the row with the least id stays, and of its rows the
least text hash; repeated rows are copies of each other; without labels nothing is toxic, without a benchmark nothing is
contaminated, and an empty table gives no rows; other columns are carried along up to the last stage, whatever their
names. A stage's scratch data is deleted once its result is written.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bandloom.llm import bpe, decontaminate, langid, simhash, toxicity
from bandloom.runtime import delete, scratch, scratch_paths, table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    got = langid.identified(docs, langid.fit(table(spark, sf_dir, "documents")), "__lid_")
    return got.where((F.col("__lid_lang_pred") != langid.UND) & ~F.col("__lid_ambiguous")).select(*docs.columns)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.fit(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return toxicity.scored(docs, model, "__toxicity").where(F.col("__toxicity") < toxicity.THRESHOLD).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.one_of_each(docs)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.bpe_encode(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("language_id", identify_language),
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_copies),
    ("benchmark_decontamination", decontaminated),
    ("bpe", encode),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, last = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        path, before = scratch(spark, f"stage-{name}"), scratch_paths()
        out = stage(spark, docs, sf_dir)
        out.write.parquet(path)
        for done in [p for p in scratch_paths() if p not in before] + ([last] if last else []):
            delete(spark, done)
        docs, last = spark.read.schema(out.schema).parquet(path), path
    return docs
