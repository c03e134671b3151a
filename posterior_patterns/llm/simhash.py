"""SimHash near-duplicates through covering locality-sensitive hashing.

A 64-bit fingerprint keeps a bit where more than half of a text's shingle hashes have it.
For a radius r every bit position gets a non-zero label of r+1 bits; mask number v keeps the
positions whose label has odd parity with v.  At most r differing positions can't span all
r+1 dimensions, so some mask avoids all of them: every pair within the radius shares a key in
at least one of the 2^(r+1)-1 tables, with certainty.

Buckets of distinct fingerprints are compared pairwise up to HOT members.  Members of larger
buckets go another exact way: each is listed under all fingerprints within r/2 flips of it.  Two
fingerprints are within r exactly if some listing holds both, and all fingerprints of a listing
are within r of each other, so linking a listing's members to its least one loses nothing; a
listing never holds more than the number of such flips.

Defined cases: null texts count as empty; an empty text has fingerprint 0 and is linked like any
other; fewer words than a shingle make one shingle; repeated rows and ids are kept, one result row
for each row; a null id gets a fingerprint and the least other id reachable, if any; an empty table
gives an empty result; further columns are ignored, whatever their names.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .graph import components
from .text import arrow_map, blob, words

BITS = 64
#: Buckets with more distinct fingerprints than this take the exact way by listings.
HOT = 48
_CHUNK = 1 << 16


def shingles(data: bytes, k: int) -> list[bytes]:
    """Space-joined runs of k words, repeats included; a shorter text is one shingle."""
    w = words(data)
    if len(w) <= k:
        return [b" ".join(w)] if w else []
    return list(map(b" ".join, zip(*(w[i:] for i in range(k)), strict=False)))


def fingerprint(data: bytes, k: int, seed: int = 42) -> int:
    """The fingerprint as a signed 64-bit integer."""
    found = shingles(data, k)
    if not found:
        return 0
    counts = np.zeros(BITS, dtype=np.int64)
    for i in range(0, len(found), _CHUNK):
        part = found[i : i + _CHUNK]
        hashes = np.fromiter((xxhash.xxh64_intdigest(s, seed) for s in part), dtype="<u8", count=len(part))
        counts += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > len(found), bitorder="little").view("<i8")[0])


def masks(radius: int) -> list[int]:
    """The covering masks of a radius, as signed 64-bit integers."""
    top = 1 << (radius + 1)
    labels = [1 + i % (top - 1) for i in range(BITS)]
    made = [sum(1 << i for i, label in enumerate(labels) if (label & v).bit_count() % 2) for v in range(1, top)]
    return [m - (1 << 64) if m >> 63 else m for m in made]


def fingerprints(docs: DataFrame, shingle_words: int = 5, id_col: str = "doc_id", text_col: str = "text", seed: int = 42) -> DataFrame:
    """(doc_id, fp) for every row."""
    kind = dict(docs.dtypes)[id_col]
    return arrow_map(
        docs.select(F.col(id_col).alias("doc_id"), blob(F.col(text_col)).alias("data")),
        lambda ids, data: (ids, [fingerprint(d, shingle_words, seed) for d in data]),
        f"doc_id {kind}, fp long",
    )


def _keys(fp: Column, radius: int) -> Column:
    return F.array(*(F.struct(F.lit(n).alias("n"), fp.bitwiseAND(F.lit(m)).alias("key")) for n, m in enumerate(masks(radius))))


def _flips(radius: int) -> list[int]:
    sets = [()] + [c for r in range(1, radius // 2 + 1) for c in combinations(range(BITS), r)]
    made = [sum(1 << i for i in c) for c in sets]
    return [m - (1 << 64) if m >> 63 else m for m in made]


def links(distinct: DataFrame, radius: int, store: Durable, hot: int = HOT) -> DataFrame:
    """distinct(fp) -> links (a, b) whose closure joins exactly the fingerprints within the radius, step by step."""
    if radius % 2:
        raise ValueError("the radius must be even, so that listings of half of it are exact")
    tabled = distinct.select("fp", F.explode(_keys(F.col("fp"), radius)).alias("t")).select("t.n", "t.key", "fp")
    crowded = tabled.groupBy("n", "key").agg(F.count("*").alias("members")).filter("members > 1")
    shared = store.save(tabled.join(crowded, ["n", "key"]), "shared")
    near = shared.filter(F.col("members") <= hot)
    pairs = (
        near.select("n", "key", F.col("fp").alias("a"))
        .join(near.select("n", "key", F.col("fp").alias("b")), ["n", "key"])
        .filter((F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius))
        .select("a", "b")
    )
    listed = (
        shared.filter(F.col("members") > hot).select("fp").distinct()
        .select("fp", F.explode(F.array(*(F.col("fp").bitwiseXOR(F.lit(m)) for m in _flips(radius)))).alias("centre"))
        .groupBy("centre").agg(F.collect_set("fp").alias("all"))  # at most as many as there are flips
        .filter(F.size("all") > 1)
        .select(F.array_min("all").alias("a"), F.explode("all").alias("b")).filter("a <> b")
    )
    return pairs.unionByName(listed).distinct()


def near_duplicate_groups(docs: DataFrame, shingle_words: int = 5, radius: int = 2, id_col: str = "doc_id", text_col: str = "text", seed: int = 42) -> DataFrame:
    """(doc_id, fp, component_id) for every row; component_id is the least id reachable over links within the radius."""
    store = Durable(docs.sparkSession, "simhash")
    marked = store.save(fingerprints(docs, shingle_words, id_col, text_col, seed), "marked")
    distinct = store.save(marked.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    roots = store.save(components(links(distinct.select("fp"), radius, store), store), "roots")
    named = distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    leader = named.groupBy("root").agg(F.min("least").alias("component_id"))
    return marked.join(named.select("fp", "root").join(leader, "root").select("fp", "component_id"), "fp", "left").select("doc_id", "fp", "component_id")
