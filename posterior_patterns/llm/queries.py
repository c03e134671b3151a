"""Queries over whole tables, with production parameters."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.durable import Durable
from . import brown_lm, decontaminate, exact_dedup, mixing, pii, secrets, simhash, token_counts, toxicity, warc

#: Key of the surrogates in the registered query; a production run passes its own.
DEMO_KEY = "demonstration key"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash_near_dedup(spark, sf_dir):
    found = simhash.near_duplicate_groups(_table(spark, sf_dir, "documents").select("doc_id", "text"), shingle_words=3, radius=2)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op2_token_counts(spark, sf_dir):
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return token_counts.token_counts(docs, public_tokenizers.path("byte_bpe_50k.json"), Durable(spark, "tokens").path("cache"))


def op3_exact_dedup(spark, sf_dir):
    return exact_dedup.duplicate_groups(_table(spark, sf_dir, "documents").select("doc_id", "text"), keep="largest")


def op4_mixing(spark, sf_dir):
    return mixing.assign(_table(spark, sf_dir, "documents").select("doc_id", "source", "text"))


def op5_decontamination(spark, sf_dir):
    return decontaminate.decontaminate(_table(spark, sf_dir, "documents").select("doc_id", "text"), _table(spark, sf_dir, "benchmark"))


def op6_brown_lm(spark, sf_dir):
    return brown_lm.score(_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_secret_scan(spark, sf_dir):
    found = secrets.scan(_table(spark, sf_dir, "documents").select("doc_id", "text"), Durable(spark, "secrets").path("ledger"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "blob")


def op8_pii_surrogates(spark, sf_dir):
    return pii.pseudonymise(_table(spark, sf_dir, "documents").select("doc_id", "text"), DEMO_KEY)


def op9_toxicity(spark, sf_dir):
    return toxicity.toxicity(_table(spark, sf_dir, "documents").select("doc_id", "text"), _table(spark, sf_dir, "labels").select("doc_id", "toxic"))


def op10_warc(spark, sf_dir):
    return warc.round_trip(_table(spark, sf_dir, "pages").select("page_id", "url", "html"), Durable(spark, "warc").path("archives"), 0)


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries():
    found = (op1_simhash_near_dedup, op2_token_counts, op3_exact_dedup, op4_mixing, op5_decontamination, op6_brown_lm, op7_secret_scan, op8_pii_surrogates, op9_toxicity, op10_warc, pipeline)
    return {f.__name__: f for f in found}


OP3_SQL = """
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256
FROM d JOIN g USING (t)
"""


def oracle_sql():
    return {"op3_exact_dedup": OP3_SQL}
