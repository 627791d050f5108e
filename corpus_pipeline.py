"""The corpus pipeline: stages applied to ``documents``, each on all that the stage before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cloudlattice.llm import mixing, packing, shingle_join, suffix_dedup, toxicity
from cloudlattice.llm.work import load, written

#: Near duplicates: word shingles of five words, similarity of 0.8 or more.
WORDS, PERCENT = 5, 80
#: Repeated passages: of over 50 words, or of 400 bytes, whichever a passage has.
PASSAGE = 51


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression-distance model does not call toxic."""
    return toxicity.kept(docs, load(spark, sf_dir, "labels"))


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates."""
    return shingle_join.representatives(docs, PERCENT, WORDS)


def unrepeated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without passages of over 50 words or of 400 bytes that start anywhere else too."""
    return suffix_dedup.deduplicated(docs, words=PASSAGE)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at their target weights; documents repeat or stay out as the mix says."""
    return mixing.mixed(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 tokens with their places in sequences."""
    return packing.pack_documents(docs, packing.default_tokenizer())


STAGES = [("toxicity", clean), ("near duplicates", distinct), ("suffix deduplication", unrepeated), ("mixing", mix), ("packing", pack)]

#: Compression lengths, byte-level spans and byte-pair ids have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = written(docs, name.replace(" ", "-"))
    return docs
