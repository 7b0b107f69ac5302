"""The corpus pipeline: five stages over ``documents``, each on all that the one before it kept.

1. toxicity: documents that the classifier rejects go (labels of the held-out fold are never learned).
2. line dedup: lines that have an earlier similar line go; a document whose lines all go stays with an empty text.
3. near-dedup: documents whose sets of five-word shingles have a similarity of 0.8 or more link, each link proven on the
   sets; of each group one row stays, the one of the least doc_id.
4. benchmark decontamination: documents with a twentieth or more of their words in benchmark windows go.
5. best-fit packing: the rest in sequences of 2048 tokens.

Defined results: an empty table stays empty in every stage; a null text counts as empty, is not toxic, has no lines and no
benchmark words, and all empty texts are copies of each other; rows without an id and different texts under one id are
documents of their own in every stage; a repeated row is one document to the line stage and a copy to the near-copy stage,
where of equal ids and texts one row stays; extra columns are kept up to packing, which returns one row a piece.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathwindow.llm import decontaminate, lines, packing, shingles, toxicity
from pathwindow.llm.common import load, written

SHINGLE, SIMILARITY = 5, 0.8


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.fit(docs, load(spark, sf_dir, "labels"), held_out=toxicity.held_out("doc_id"))
    return toxicity.keep_clean(docs, model)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    left = lines.rewrite(docs, lines.removed_lines(docs))
    return left.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else left


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return shingles.keep_first(docs, shingles.near_duplicates(docs, shingle=SHINGLE, threshold=SIMILARITY))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.keep_clean(docs, load(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [("toxicity", drop_toxic), ("line dedup", drop_lines), ("near-dedup", drop_near_copies), ("decontamination", drop_contaminated), ("packing", pack)]

# Learned scores, fingerprints and BPE ids are beyond SQL; tests hold the stages against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), "pipeline")
    return STAGES[-1][1](spark, docs, sf_dir)
