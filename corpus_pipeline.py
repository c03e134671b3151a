"""A training-data pipeline of five stages over documents.

Every stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept; its result is
written as Parquet to the shared folder and read again for the next one.

Defined cases, for all stages: a null text counts as empty, and a null id is a document like others; an
empty text is not toxic unless empty texts are learned to be, equals other empty texts, is near only to
them, holds no benchmark item and is never drawn by the mix; of equal texts, and of each group of near copies,
the least id stays, null last; repeated rows are one document to the second stage; empty tables give empty
results, and an empty benchmark or table of labels drops nothing; columns beyond those of documents are kept,
whatever their names, but for those the last stage adds (size, source_size, target, taken, copy, shard).

This module needs posterior_patterns.llm and is deleted with it.
"""

from __future__ import annotations

from posterior_patterns.llm import decontaminate, exact_dedup, mixing, near_copies, toxicity
from posterior_patterns.plans.durable import Durable


def drop_toxic(spark, docs, sf_dir):
    """Documents that the classifier rejects go."""
    return toxicity.keep_clean(docs, spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic"))


def drop_copies(spark, docs, sf_dir):
    """Of equal texts the one with the smallest id stays."""
    return exact_dedup.distinct_documents(docs, keep="smallest")


def drop_near_copies(spark, docs, sf_dir):
    """Of every group of near copies the document with the smallest id stays."""
    return near_copies.one_of_each(docs)


def drop_leaks(spark, docs, sf_dir):
    """Documents that hold a benchmark item go."""
    return decontaminate.keep_uncontaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark, docs, sf_dir):
    """One row for each copy of a document that the mix draws, dealt to output shards and shuffled inside them; documents it doesn't draw stay without a shard."""
    return mixing.mix_shards(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact dedup", drop_copies),
    ("near dedup", drop_near_copies),
    ("decontamination", drop_leaks),
    ("mixing", mix_sources),
]

#: The classifier, the fingerprints and the tiling have no SQL form.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs, store = spark.read.parquet(f"{sf_dir}/documents.parquet"), Durable(spark, "pipeline")
    for i, (_, stage) in enumerate(STAGES):
        docs = store.save(stage(spark, docs, sf_dir), f"stage{i}")
    return docs
