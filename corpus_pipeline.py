"""From raw documents to packed training sequences, in five stages.

Each stage takes (spark, docs, sf_dir) and returns a frame that is written before the next one reads it. All but the last
return the columns of `documents`. Every stage gives a defined result for an empty table, null and empty texts, ties, repeated
rows and extra columns: the operators' own texts in blockflow/llm say which.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockflow.llm import mixing, toxicity
from blockflow.llm.neardup import NearDupConfig, keep_representatives
from blockflow.llm.packing import pack_documents
from blockflow.llm.substrings import remove_repeats
from blockflow.llm.tables import table
from blockflow.session import materialize

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
TOXIC = 0.5
#: The stage's own threshold: five-word shingle sets that share four fifths of their union are near-duplicates.
NEAR = NearDupConfig(share=80)
#: Rare domains gain by the mixing, but toxic text isn't to: these hold its share about where it was.
EMPHASIS = {"q0_t1": 0.2, "q1_t1": 0.2}


def _documents(df: DataFrame) -> DataFrame:
    return df.select(*COLUMNS)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, fitted on the labelled ones, doesn't score as toxic."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return _documents(toxicity.score(_documents(docs), model, keep_text=True).where(F.col("toxicity") < TOXIC))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: the one with the smallest doc_id."""
    return _documents(keep_representatives(_documents(docs), NEAR))


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without the byte strings of 100 and more that occurred earlier; n_chars follows the text."""
    cut = remove_repeats(_documents(docs), with_text=True)
    return cut.select("doc_id", F.col("kept_text").alias("text"), "lang", "source", F.length("kept_text").cast("long").alias("n_chars"))


def mix_domains(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, those of a domain that should weigh more repeated as its rates say; none is left out."""
    labels = table(spark, sf_dir, "labels", "doc_id", "quality", "toxic")
    config = mixing.MixConfig(floor=1.0, grow=True)
    rated, _, _ = mixing.mix(_documents(docs).select("doc_id", "text"), labels, emphasis=EMPHASIS, config=config)
    more = rated.select("doc_id", mixing.copies(F.col("rate"), F.col("doc_id")).alias("mix_copies")).groupBy("doc_id").agg(F.max("mix_copies").alias("mix_copies"))
    joined = _documents(docs).join(more, "doc_id", "left")
    return _documents(joined.withColumn("mix_copy", F.explode(F.expr("sequence(1, greatest(1, coalesce(mix_copies, 1)))"))))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences of 2048 tokens."""
    import public_tokenizers

    return pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), end_id=1)


STAGES = [
    ("toxicity", drop_toxic),
    ("near-dedup", drop_near_duplicates),
    ("suffix-dedup", cut_repeats),
    ("mixing", mix_domains),
    ("packing", pack),
]

#: Hashing, classifiers and a tokenizer library are beyond SQL; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
