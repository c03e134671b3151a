"""Benchmark decontamination by greedy string tiling.

Words are runs of letters and digits, lower-cased and named by 64-bit hashes.  Seeds are runs of MIN_MATCH words
(all words of a shorter item).  Documents and items that share a seed are joined; each pair is tiled: a rolling
hash finds the longest common run of words not yet covered, all runs of that length are marked first come
first served without overlap, and the search goes on with shorter runs down to a seed.  Sentences in another
order are therefore covered too.  An item is leaked into a document if marked words make up at least COVERAGE
of the item.

An item covered that far shares a known least number of its seeds, so as many but one of those most common in
the benchmark need not be looked for: boilerplate makes no pairs.  Documents pass a bit table of all seeds, of
bounded size, before anything is shuffled; what moves then are hits, pairs, and texts with a hit.  Hot seeds are
split by salt, hot items and hot copies are broadcast (see text.with_class), equal texts are tiled once.

Defined cases: null texts count as empty; items and documents without words never match; equal items
tie, the least id is reported; items with a null id match like others and are reported as null, after
all ids at a tie; ids may be of any orderable type; repeated rows are decided alike; an empty benchmark leaks
nothing; an empty table gives an empty result; further columns, whatever their names, are ignored, or kept by
the filter.  Coverage is reported for items met through a seed; of others it is 0.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import arrow_map, blob, bound_batches, digest, free_name, powers, with_class

MIN_MATCH, COVERAGE = 5, 0.5
#: Binary digits of the number of bits in the seed table: 512 bits for a seed, two of them set, within these bounds (16 MB at most).
TABLE_BITS = (22, 27)
#: Parts into which the hits of a seed are split that has more than one in a thousand of all hits.
SALTS = 64
#: Leaked texts of which a broadcast may list the digests.
BROADCAST_LEAKS = 100_000
#: Words remembered by a worker at most.
REMEMBERED = 500_000
_TOKEN = re.compile(r"[^\W_]+")
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


class _Ids(dict):
    def __missing__(self, word: str) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        made = self[word] = xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))
        return made


_IDS = _Ids()


def word_ids(text: str) -> np.ndarray:
    found = _TOKEN.findall(text.lower())
    return np.fromiter(map(_IDS.__getitem__, found), dtype=np.uint64, count=len(found))


def _running(ids: np.ndarray) -> np.ndarray:
    """Sums of id * base^place, from which the hash of any run follows."""
    return np.concatenate((np.zeros(1, dtype=np.uint64), np.cumsum(ids * powers(_BASE, len(ids))[: len(ids)], dtype=np.uint64)))


def _runs(running: np.ndarray, size: int) -> np.ndarray:
    """Hash of every run of `size` ids, the same wherever the run starts."""
    n = len(running) - size
    return (running[size:] - running[:n]) * powers(_INVERSE, n)[:n] if n > 0 else np.zeros(0, dtype=np.uint64)


def seeds(ids: np.ndarray, size: int) -> np.ndarray:
    return _runs(_running(ids), size)


def _free(marked: np.ndarray, size: int) -> np.ndarray:
    """Starts of runs of `size` without a mark."""
    total = np.concatenate(([0], np.cumsum(marked)))
    return np.flatnonzero(total[size:] == total[: max(0, len(total) - size)])


def _near_seeds(item: np.ndarray, text: np.ndarray, least: int) -> np.ndarray:
    """Places of the text that lie in a run of `least` words that the item holds too."""
    met = np.flatnonzero(np.isin(seeds(text, least), seeds(item, least)))
    edge = np.zeros(len(text) + 1, dtype=np.int64)
    np.add.at(edge, met, 1)
    np.add.at(edge, met + least, -1)
    return np.flatnonzero(np.cumsum(edge[:-1]) > 0)


def tiles(item: np.ndarray, text: np.ndarray, least: int = MIN_MATCH) -> list[tuple[int, int, int]]:
    """Tiles (item start, text start, length) of greedy tiling: longest first, then by item start and text start."""
    near = _near_seeds(item, text, least)
    if not len(near):
        return []
    # of the text only places near seeds matter; a mark between their stretches keeps runs from crossing
    gaps = np.flatnonzero(np.diff(near) > 1) + 1
    place = np.insert(near, gaps, -1)
    done_i, done_t = np.zeros(len(item), dtype=bool), place < 0
    short = np.where(done_t, np.uint64(0), text[np.maximum(place, 0)])
    run_i, run_t = _running(item), _running(short)
    made: list[tuple[int, int, int]] = []

    def common(size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        at_i, at_t = _free(done_i, size), _free(done_t, size)
        hash_i, hash_t = _runs(run_i, size)[at_i], _runs(run_t, size)[at_t]
        in_i = np.isin(hash_i, hash_t)
        in_t = np.isin(hash_t, hash_i[in_i])
        return at_i[in_i], hash_i[in_i], at_t[in_t], hash_t[in_t]

    most = min(len(item), len(short))
    while True:
        low, high, found = least - 1, most, None
        while low < high:  # a common run of some length has common runs of all smaller ones
            size = (low + high + 1) // 2
            here = common(size)
            if len(here[0]):
                low, found = size, here
            else:
                high = size - 1
        if found is None:
            return made
        starts: dict[int, list[int]] = {}
        for t, h in zip(found[2][::-1].tolist(), found[3][::-1].tolist(), strict=True):
            starts.setdefault(h, []).append(t)  # the next one is the last
        for i, h in zip(found[0].tolist(), found[1].tolist(), strict=True):
            if done_i[i : i + low].any():
                continue
            waiting = starts[h]
            while waiting and (done_t[waiting[-1]] or done_t[waiting[-1] + low - 1]):
                waiting.pop()  # marked runs are at least as long, so an overlap covers an end
            if waiting and np.array_equal(item[i : i + low], short[waiting[-1] : waiting[-1] + low]):
                t = waiting.pop()
                done_i[i : i + low] = done_t[t : t + low] = True
                made.append((i, int(place[t]), low))
        most = low - 1


def benchmark_items(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(item, item_id, data): a number of its own for every row, as a string."""
    data = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    return benchmark.select(F.monotonically_increasing_id().cast("string").alias("item"), F.col(id_col).alias("item_id"), data.alias("data"))


def item_seeds(items: DataFrame, least: int, coverage: float) -> DataFrame:
    """(seed, item, size): the seeds by which an item must be met if it is covered that far; size is their length.

    Tiles of n >= least words hold n - least + 1 >= n / least seeds, hence the least number shared.
    """

    def cut(keys, data):
        made, sizes, need = [], [], []
        for d in data:
            ids = word_ids(d.decode("utf-8", "replace"))
            size = min(least, len(ids))
            made.append(seeds(ids, size).view(np.int64).tolist() if size else [])
            sizes.append(size)
            need.append(max(1, math.ceil(coverage * len(ids) / least - 1e-9)) if size == least else 1)
        return keys, made, sizes, need

    found = arrow_map(items.select("item", "data"), cut, "item string, seeds array<long>, size int, need int")
    listed = found.select("item", "size", "need", F.size("seeds").alias("n"), F.explode("seeds").alias("seed"))
    common = listed.groupBy("seed").agg(F.count("*").alias("held"))
    rank = F.row_number().over(Window.partitionBy("item").orderBy("held", "seed"))  # of one item
    kept = listed.join(common, "seed").withColumn("rank", rank).filter(F.col("rank") <= F.col("n") - F.col("need") + 1)
    return kept.select("seed", "item", "size").distinct()


def seed_table(wanted: DataFrame) -> tuple[np.ndarray, int]:
    """Two bits for every seed hash, as 64-bit words, and the number of bits in binary digits: bounded by TABLE_BITS."""
    bits = min(max(int(512 * max(1, wanted.count())).bit_length(), TABLE_BITS[0]), TABLE_BITS[1])
    places = F.array(F.shiftrightunsigned("seed", 64 - bits), F.col("seed").bitwiseAND(F.lit((1 << bits) - 1)))
    one = F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col("place") % 64).cast("int"))
    set_ = wanted.select(F.explode(places).alias("place")).groupBy((F.col("place") / 64).cast("bigint").alias("word")).agg(F.bit_or(one).alias("bits"))
    got = set_.toArrow()  # at most 2^(bits - 6) rows
    table = np.zeros(1 << (bits - 6), dtype=np.int64)
    table[got.column("word").to_numpy()] = got.column("bits").to_numpy()
    return table.view(np.uint64), bits


def seed_hits(docs: DataFrame, table: np.ndarray, bits: int, sizes: list[int]) -> DataFrame:
    """docs(name, data) -> (name, data, seeds): texts that may hold a wanted seed, with these."""
    shared = docs.sparkSession.sparkContext.broadcast(table)  # bounded by TABLE_BITS

    def held(place: np.ndarray) -> np.ndarray:
        return ((shared.value[place >> np.uint64(6)] >> (place & np.uint64(63))) & np.uint64(1)).astype(bool)

    def find(text: str) -> list[int]:
        ids, found = word_ids(text), []
        for size in sizes:
            h = seeds(ids, size)
            h = h[held(h >> np.uint64(64 - bits))]
            found.append(np.unique(h[held(h & np.uint64((1 << bits) - 1))]))
        return np.concatenate(found).view(np.int64).tolist() if found else []

    def hits(names, data):
        rows = [(n, d, s) for n, d in zip(names, data, strict=True) if (s := find(d.decode("utf-8", "replace")))]
        return tuple(map(list, zip(*rows, strict=True))) if rows else ([], [], [])

    return arrow_map(docs, hits, "name binary, data binary, seeds array<long>")


def _pairs(hits: DataFrame, wanted: DataFrame) -> DataFrame:
    """(name, item) of every text and item that share a seed."""
    met = hits.select("name", F.explode("seeds").alias("seed"))
    counted = met.groupBy("seed").agg(F.count("*").alias("n"))
    total = counted.agg(F.sum("n").alias("n")).first().n or 0
    hot = F.broadcast(counted.filter(F.col("n") * 1000 > total).select(F.col("seed").alias("hot")))  # under a thousand
    met = met.join(hot, F.col("seed") == F.col("hot"), "left").withColumn("salt", F.when(F.col("hot").isNotNull(), F.pmod(F.xxhash64("name"), F.lit(SALTS))).otherwise(0))
    salts = F.when(F.col("hot").isNotNull(), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    spread = wanted.join(hot, F.col("seed") == F.col("hot"), "left").select("seed", "item", F.explode(salts).alias("salt"))
    return met.withColumn("salt", F.col("salt").cast("int")).join(spread, ["seed", "salt"]).select("name", "item").distinct()


def _tiled(rows: DataFrame, least: int) -> DataFrame:
    """rows(name, text, item, body) in order of name -> (name, item, coverage)."""

    def run(batches):
        last, ids = None, None
        for batch in batches:
            names, items, covered = batch.column(0), batch.column(2), []
            for name, text, body in zip(names.to_pylist(), batch.column(1).to_pylist(), batch.column(3).to_pylist(), strict=True):
                if name != last:
                    last, ids = name, word_ids(text.decode("utf-8", "replace"))
                item = word_ids(body.decode("utf-8", "replace"))
                covered.append(sum(n for *_, n in tiles(item, ids, min(least, len(item)))) / len(item))
            yield pa.RecordBatch.from_arrays([names, items, pa.array(covered, pa.float64())], names=["name", "item", "coverage"])

    bound_batches(rows)
    return rows.mapInArrow(run, "name binary, item string, coverage double")


def verdicts(docs: DataFrame, benchmark: DataFrame, least: int = MIN_MATCH, coverage: float = COVERAGE, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(name, rows, coverage, item_id, items) of the distinct texts that share a seed with an item: the best item, and how many were met."""
    store = Durable(docs.sparkSession, "leaks")
    items = store.save(benchmark_items(benchmark, id_col), "items")
    wanted = store.save(item_seeds(items, least, coverage), "seeds")
    sizes = sorted(r.size for r in wanted.select(F.col("size")).distinct().collect())  # at most `least` values
    texts = docs.select(digest(F.col(text_col)).alias("name"), blob(F.col(text_col)).alias("data"))
    hits = store.save(seed_hits(texts, *seed_table(wanted), sizes), "hits")
    held = hits.groupBy("name").agg(F.count("*").alias("rows"))
    pairs = store.save(_pairs(hits.select("name", "seeds").dropDuplicates(["name"]), wanted.select("seed", "item")), "pairs")
    met = store.save(items.join(pairs.groupBy("item").agg(F.count("*").alias("n")), "item"), "met")
    bodies = with_class(pairs, met.select("item", "n", F.col("data").alias("body")), "item", "n", "name").select("name", "item", "class.body")
    once = hits.groupBy("name").agg(F.first("data").alias("text"))
    tiled = store.save(_tiled(bodies.join(once, "name").select("name", "text", "item", "body").sortWithinPartitions("name"), least), "tiled")
    named = with_class(tiled, met.select("item", "n", "item_id"), "item", "n", "name").select("name", "coverage", "class.item_id")
    order = F.struct((-F.col("coverage")).alias("c"), F.col("item_id").isNull().alias("none"), F.col("item_id").alias("id"))
    best = named.filter("coverage > 0").groupBy("name").agg(F.min(order).alias("best"), F.count("*").alias("items"))
    return store.save(best.join(held, "name").select("name", "rows", (-F.col("best.c")).alias("coverage"), F.col("best.id").alias("item_id"), "items"), "verdicts")


def decontaminate(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, least: int = MIN_MATCH, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id") -> DataFrame:
    """(doc_id, contaminated, item_id, coverage, items) for every row of docs."""
    found = verdicts(docs, benchmark, least, coverage, item_col, text_col)
    rows = docs.select(F.col(id_col).alias("doc_id"), digest(F.col(text_col)).alias("name"))
    met, share = with_class(rows, found, "name", "rows", "doc_id"), F.coalesce(F.col("class.coverage"), F.lit(0.0))
    return met.select("doc_id", (share >= coverage).alias("contaminated"), "class.item_id", F.round(share, 6).alias("coverage"), F.coalesce("class.items", F.lit(0)).cast("long").alias("items"))


def keep_uncontaminated(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, least: int = MIN_MATCH, text_col: str = "text", item_col: str = "item_id") -> DataFrame:
    """docs without those that hold a benchmark item; all columns stay."""
    name = free_name(docs, "leaked")
    leaked = verdicts(docs, benchmark, least, coverage, item_col, text_col).filter(F.col("coverage") >= coverage).select(F.col("name").alias(name))
    if leaked.count() <= BROADCAST_LEAKS:
        leaked = F.broadcast(leaked)
    return docs.join(leaked, digest(F.col(text_col)) == F.col(name), "left_anti")
