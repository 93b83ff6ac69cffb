"""Corpus preparation as five stages over `documents`.

toxicity: rejected documents go; near_duplicates: the smallest document of each group stays
(five-word shingles, similarity 0.8); substring_dedup: passages of 50 words that a smaller
document has are cut out; source_mix: sources are mixed to their targets along the curriculum,
documents beyond a target go and short sources repeat; packing: token pieces in sequences.

Every stage but the last returns the columns of `documents`.  Repeated passages are judged after
near duplicates are gone, so a passage stays in the smallest document that is left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmatch.llm import near_duplicates, packing, source_mix, substring_dedup, toxicity
from gridmatch.llm.common import WRITTEN, cut, remove, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, model, docs.columns)
    return scored.filter(F.col("score") < toxicity.THRESHOLD).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = near_duplicates.near_duplicates(docs)
    gone = found.filter("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return substring_dedup.deduplicated(docs).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return source_mix.training_order(docs).select(*docs.columns)


def pack_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, packing.public_vocabulary())


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("substring_dedup", cut_repeats),
    ("source_mix", mix_sources),
    ("packing", pack_tokens),
]

#: Trees, sketches and tokens are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; a stage's own tables, and the one before, go once its result is written."""
    docs = table(spark, sf_dir, "documents")
    held = len(WRITTEN)
    for _, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir))
        remove(spark, WRITTEN[held:-1])
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracles() -> dict:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
