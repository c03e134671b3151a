"""Exact duplicates: grouping by a 128-bit content hash together with the bytes themselves.

The grouping key is (MD5, text), so a hash only sorts and spreads the rows: texts that share one and
differ in a byte are different keys.  Copies collapse in the map tasks before the shuffle, hence a
hot group sends one row per task.  Documents then find their class by (MD5, SHA-256) over narrow rows, in a
join that spreads the rows of hot classes.

Defined cases: null texts count as empty and equal each other; ties don't arise, the least (or
greatest) id stays; rows that repeat the kept id are all marked kept, while distinct_documents
returns one of them; null ids stay only in classes without another; an empty table gives an empty result;
further columns, whatever their names, don't matter to the grouping, and distinct_documents keeps them.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import blob, digest, with_class


def duplicate_groups(docs: DataFrame, keep: str = "smallest", id_col: str = "doc_id", text_col: str = "text", content_hash: Callable[[Column], Column] = digest) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) for every row."""
    best, store = {"smallest": F.min, "largest": F.max}[keep], Durable(docs.sparkSession, "exact")
    data = blob(F.col(text_col))
    rows = docs.select(F.col(id_col).alias("doc_id"), content_hash(F.col(text_col)).alias("h"), data.alias("data"))
    named = F.concat("h", F.unhex(F.sha2("data", 256))).alias("name")
    classes = rows.groupBy("h", "data").agg(best("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    classes = store.save(classes.select(named, "keep_id", "group_size"), "classes")
    met = with_class(rows.select("doc_id", named), classes, "name", "group_size", "doc_id")
    kept = F.coalesce(F.col("doc_id") == F.col("class.keep_id"), F.col("class.keep_id").isNull())
    return met.select("doc_id", "class.keep_id", "class.group_size", kept.alias("kept"), F.lower(F.hex(F.substring("name", -32, 32))).alias("text_sha256"))


def distinct_documents(docs: DataFrame, keep: str = "smallest", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One whole row of docs for each distinct text, that with the least (greatest) id."""
    pick = {"smallest": F.min_by, "largest": F.max_by}[keep]
    row, order = F.struct(*(F.col(f"`{c}`") for c in docs.columns)), F.col(id_col)
    order = F.struct(order.isNull(), order) if keep == "smallest" else F.struct(order.isNotNull(), order)
    return docs.groupBy(digest(F.col(text_col)), blob(F.col(text_col))).agg(pick(row, order).alias("the row")).select("`the row`.*")
