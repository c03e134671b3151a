"""Token counts through a digest cache.

The cache is a Parquet table (content digest, tokenizer digest, count).  Documents are reduced to
distinct contents, those already counted by the same tokenizer version are joined out, only the
misses are encoded, and their counts are appended.  The counts come back to all documents by a join
of narrow rows.

For byte-level BPE files without a normalizer, a text is cut where the pre-tokenizer must cut too
(before a space that opens a run of other characters, and around white space), so pieces are encoded
once per worker and remembered in a bounded table; the library itself counts each piece.  Texts that
hold one of the tokenizer's added tokens, and all other kinds of tokenizers, are encoded whole.

Defined cases: null texts count as empty and have 0 bytes and 0 tokens; copies share one cache row;
repeated rows and ids keep one result row each; an empty table gives an empty result and leaves the
cache as it was; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import os
import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import arrow_map, blob, one_of_each_new, with_class

CACHE_SCHEMA = "content string, version string, n_tokens long"
#: Pieces remembered by one worker at most.
REMEMBERED = 400_000
_SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
_PIECE = re.compile(f" ?[^{_SPACE}]+|[{_SPACE}]+(?![^{_SPACE}])|[{_SPACE}]+")
_LOADED: dict[str, "Counter"] = {}


def tokenizer_version(path: str) -> str:
    """Digest of a tokenizer file."""
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


class Counter:
    """Counts tokens of texts with the library that reads the file."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self.pieces: dict[str, int] | None = None
        if path.endswith(".model"):
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_file=path)
            self.encode = lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
            return
        from tokenizers import Tokenizer

        model = Tokenizer.from_file(path)
        model.no_truncation()
        model.no_padding()
        self.encode = lambda texts: [len(x.ids) for x in model.encode_batch(texts, add_special_tokens=False)]
        with open(path) as f:
            spec = json.load(f)
        pre = spec.get("pre_tokenizer") or {}
        self.added = [x["content"] for x in spec.get("added_tokens", [])]
        if spec.get("normalizer") is None and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and spec["model"]["type"] == "BPE":
            self.pieces = {}

    def __call__(self, texts: list[str]) -> list[int]:
        if self.pieces is None:
            return self.encode(texts)
        return [self.whole(t) if any(a in t for a in self.added) else self.cut(t) for t in texts]

    def whole(self, text: str) -> int:
        return self.encode([text])[0]

    def cut(self, text: str) -> int:
        known, found = self.pieces, _PIECE.findall(text)
        try:
            return sum(map(known.__getitem__, found))
        except KeyError:
            new = list({p for p in found if p not in known})
        if len(known) + len(new) > REMEMBERED:
            known.clear()
            new = list(set(found))
        known.update(zip(new, self.encode(new), strict=True))
        return sum(map(known.__getitem__, found))


def _counts(path: str, texts: list[str]) -> list[int]:
    if path not in _LOADED:
        _LOADED[path] = Counter(path)
    return _LOADED[path](texts)


def _stored(spark: SparkSession, cache: str) -> DataFrame:
    at = spark._jvm.org.apache.hadoop.fs.Path(cache)
    if not at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at):
        return spark.createDataFrame([], CACHE_SCHEMA)
    return spark.read.schema(CACHE_SCHEMA).parquet(cache)


def token_counts(docs: DataFrame, tokenizer: str, cache: str, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) for every row; cache is extended by the contents it lacked."""
    spark, version = docs.sparkSession, tokenizer_version(tokenizer)
    store, data = Durable(spark, "token-contents"), blob(F.col(text_col))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.sha2(data, 256).alias("content"), F.octet_length(data).cast("long").alias("n_bytes"), data.alias("data"))
    held = store.save(rows.drop("data"), "rows")
    contents = store.save(held.groupBy("content").agg(F.count("*").alias("rows")), "contents")
    known = _stored(spark, cache).filter(F.col("version") == version)
    new = store.save(contents.select("content").join(known.select("content"), "content", "left_anti"), "new")
    misses = one_of_each_new(rows.select("content", "data"), new, "content")
    counted = arrow_map(misses, lambda content, found: (content, [version] * len(content), _counts(tokenizer, [d.decode("utf-8", "replace") for d in found])), CACHE_SCHEMA)
    counted.write.mode("append").parquet(cache)
    known = _stored(spark, cache).filter(F.col("version") == version).groupBy("content").agg(F.max("n_tokens").alias("n_tokens"))
    found = store.save(contents.join(known, "content"), "found")
    met = with_class(held, found, "content", "rows", "doc_id")
    return met.select("doc_id", "n_bytes", "class.n_tokens", (F.col("class.n_tokens") > limit).alias("over_limit"))
