"""A corpus pipeline of five operators, each reading what the one before it wrote.

Documents in no learned language go; of equal texts the one with the largest id stays; of near
copies the one with the smallest id stays; sources are mixed to their target weights; what is left is
packed into sequences.

Defined results: every stage reads all rows that its predecessor kept, and all but the last return the columns of the documents, whatever
further columns there are. A null text, or one without a letter, is in no language and goes. Of repeated rows one stays, then the mix may
repeat it. A null id is an id like others, the largest none and the smallest none. A null source is a source. Documents without words are
in no language, so none reaches the mix. An empty table gives an empty result. Each stage is written to the shared folder,
and the stage before it is removed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ordering_engine.llm import exact_dedup, language_id, packing, parity_join, source_mix
from ordering_engine.llm.queries import vocabulary
from ordering_engine.llm.shared import settled, table
from ordering_engine.storage import remove


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language_id.known_language(docs)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.drop_copies(docs, keep="max")


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return parity_join.one_per_class(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return source_mix.mixed_documents(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs, vocabulary())


STAGES = [
    ("language_id", keep_known_languages),
    ("exact_dedup", drop_exact_copies),
    ("near_copies", keep_one_of_near_copies),
    ("source_mix", mix_sources),
    ("packing", pack_sequences),
]

#: Language models, hashes of 64 bits and a tokenizer are beyond SQL; the tests hold ``run`` against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        docs = settled(spark, lambda stage=stage, docs=docs: stage(spark, docs, sf_dir), f"pipeline-{name}")
        if before:
            remove(before)
        before = docs.staged_at
    return STAGES[-1][1](spark, docs, sf_dir)
