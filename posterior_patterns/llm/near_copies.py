"""Near-duplicate texts: SimHash covering tables and a prefix filter find candidates, exact shingle similarity decides.

Two texts are linked if the Jaccard similarity of their 5-word shingle sets (64-bit shingle hashes) is
at least 0.8, and a group is a connected set of linked texts.  Groups are exact.

First every text meets the least of those that SimHash's covering tables join it to (fingerprints of the same
shingles, radius 2), which finds most copies.  A pair at 0.8 may differ in more bits than covering tables
can reach, so a prefix filter finds the rest: a set of n shingles lies within 0.8 of another only if all but
n // 5 of its shingles are in both, so in any one order of all shingles two such sets share l of their
first n // 5 + l, for any l; here l = 1 + n // 20.  The order puts shingles common in a sample last, which keeps
buckets small; it has no influence on the result.

A bucket holds the texts that share such a shingle.  Texts already in one group needn't be compared again:
in a few turns, more while they find links, each text meets one text of another group, the one it shares most
buckets with, and buckets whose texts have become one group are done.  Then one text of each group of a bucket meets those
of the others, so that what is left of a large group of copies joins it without all its pairs.  The last turn compares all
pairs of different groups that share as many buckets as they must.  No turn compares pairs whose set sizes or parities of
shingle classes rule out the similarity.

Defined cases: null texts count as empty; texts without words are alike; fewer than five words make
one shingle; ids may be null or repeat, every row is judged by its own text; rows equal in id and text stand
or go together; of a group the least id stays, null last, ties by text; an empty table gives an empty
result; other columns, whatever their names, are kept by one_of_each and don't matter.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .graph import components
from .simhash import links
from .text import arrow_map, blob, bound_batches, digest, free_name, mixed, word_hashes

SHINGLE_WORDS, SIMILARITY, RADIUS = 5, 0.8, 2
#: Texts, about, from which common shingles are counted; the least count, and the most shingles, to be called common.
SAMPLE, SEEN, COMMON = 4096, 3, 100_000
#: Parity classes of a sketch: the power of 2 from the set's size on, this at least; and of the one that goes along with bucket rows.
LEAST_PARITIES, FEW_PARITIES = 256, 512
#: Turns in which a text meets one other, before groups and then all pairs left are compared: these at least, then more while
#: one pair in FRUITFUL that a turn compares is linked, as each link spares the pairs of two whole groups.
TURNS, FRUITFUL, MOST_TURNS = 2, 2, 12
#: Links that are joined to groups on the driver, 16 bytes each.
FEW_LINKS = 100_000
#: Rows of a table of ids or digests that may be broadcast, 24 bytes each.
BROADCAST_ROWS = 300_000
_EMPTY = np.array([0], dtype=np.int64)  # the bucket of texts without words
_BASE = np.uint64(0x9E3779B97F4A7C15)


def _hashes(data: bytes, k: int = SHINGLE_WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles: polynomials of word hashes, mixed."""
    ids = word_hashes(data)
    k = min(k, len(ids))
    if not k:
        return np.zeros(0, dtype=np.int64)
    h = np.full(len(ids) - k + 1, np.uint64(k))
    for i in range(k):
        h = h * _BASE + ids[i : len(ids) - k + 1 + i]
    return np.unique(mixed(h).view(np.int64))


def shingle_set(data: bytes) -> list[int]:
    """Sorted distinct 64-bit hashes of the 5-word shingles."""
    return _hashes(data).tolist()


def parities(found: np.ndarray, classes: int | None = None) -> np.ndarray:
    """Whether each class of shingles has an odd number in the set, 64 to a word.  Halves of a sketch add up to the next smaller one."""
    classes = classes or max(LEAST_PARITIES, 1 << (len(found) - 1).bit_length() if len(found) else 0)
    odd = np.bincount(found & (classes - 1), minlength=classes) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view("<i8")


def fingerprint(found: np.ndarray) -> int:
    """SimHash of a set of shingle hashes."""
    counts = np.zeros(64, dtype=np.int64)
    for i in range(0, len(found), 1 << 16):
        part = found[i : i + (1 << 16)]
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > len(found), bitorder="little").view("<i8")[0])


def prefix(found: np.ndarray, common: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The first n // 5 + 1 + n // 20 of n sorted shingles: rare ones by hash, then common ones (sorted, with their ranks) by rank."""
    if not len(found):
        return _EMPTY
    place = np.zeros(len(found), dtype=np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, found), len(common) - 1)
        place = np.where(common[at] == found, rank[at], 0)
    return found[np.argsort(place, kind="stable")[: len(found) // 5 + 1 + len(found) // 20]]


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 5 * both >= 4 * (len(a) + len(b) - both)


def common_shingles(texts: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The shingles that a sample of texts(d, data) holds most often, sorted, and their ranks from 1, the most common last."""
    share = max(1, texts.count() // SAMPLE)
    sample = texts.filter(F.pmod(F.xxhash64(F.lit(11), "d"), F.lit(share)) == 0)
    held = arrow_map(sample.select("data"), lambda data: ([_hashes(d) for d in data],), "shingles array<long>")
    counted = held.select(F.explode("shingles").alias("token")).groupBy("token").agg(F.count("*").alias("n")).filter(F.col("n") >= SEEN)
    got = counted.orderBy(F.col("n").desc(), "token").limit(COMMON).toArrow()  # bounded by COMMON
    tokens = got.column("token").to_numpy()
    order = np.argsort(tokens)
    return tokens[order], (len(tokens) - np.arange(len(tokens)))[order]


def marked(texts: DataFrame) -> DataFrame:
    """texts(rec, d, data) -> (row, rec, d, n, shape, fp, few, odd, tokens): a number, the size, digest, fingerprint, parities and prefix of each shingle set."""
    shared = texts.sparkSession.sparkContext.broadcast(common_shingles(texts))  # bounded by COMMON

    def mark(recs, digests, data):
        found = [_hashes(x) for x in data]
        shapes = [hashlib.md5(h.tobytes()).digest() for h in found]
        sketches = [parities(h, FEW_PARITIES) for h in found], [parities(h) for h in found]
        return recs, digests, [len(h) for h in found], shapes, [fingerprint(h) for h in found], *sketches, [prefix(h, *shared.value) for h in found]

    made = arrow_map(texts, mark, "rec binary, d binary, n int, shape binary, fp long, few array<long>, odd array<long>, tokens array<long>")
    return made.select(F.monotonically_increasing_id().alias("row"), "*")


def _small(df: DataFrame) -> DataFrame:
    """A stored table, broadcast if it is within BROADCAST_ROWS."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def buckets(rows: DataFrame) -> DataFrame:
    """rows(row, tokens) -> (token, row): every prefix shingle that two or more rows have, with all of them."""
    same = Window.partitionBy("token")
    tabled = rows.select(F.explode("tokens").alias("token"), "row")
    return tabled.select("token", "row", F.min("row").over(same).alias("x"), F.max("row").over(same).alias("y")).filter("x <> y").select("token", "row")


def still_open(rows: DataFrame) -> DataFrame:
    """The rows(token, row, root) in buckets with two or more groups."""
    same = Window.partitionBy("token")
    left = rows.withColumn("x", F.min("root").over(same)).withColumn("y", F.max("root").over(same)).filter("x <> y")
    return left.select("token", "row", "root")


def similar(pairs: DataFrame, nodes: DataFrame, texts: DataFrame, store: Durable, name: str) -> DataFrame:
    """The pairs (a, b) of rows whose texts are alike enough, stored; only texts of the pairs are moved."""
    wanted = store.save(pairs.select(F.explode(F.array("a", "b")).alias("row")).distinct().join(nodes, "row").select("row", F.col("d").alias("wd")), f"{name}-rows")
    held = texts.join(_small(wanted), F.col("d") == F.col("wd")).groupBy("row").agg(F.first("data").alias("data"))
    both = pairs.join(held.select(F.col("row").alias("a"), F.col("data").alias("x")), "a").join(held.select(F.col("row").alias("b"), F.col("data").alias("y")), "b")

    def test(batches):
        for batch in batches:
            x, y = (batch.column(i).to_pylist() for i in (2, 3))
            keep = pa.array([alike(_hashes(s), _hashes(t)) for s, t in zip(x, y, strict=True)], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], names=["a", "b"])

    bound_batches(pairs)
    return store.save(both.select("a", "b", "x", "y").mapInArrow(test, "a long, b long"), f"{name}-linked")


_SIZES = "5 * na >= 4 * nb and 5 * nb >= 4 * na"


def _few_fit() -> str:
    """Sizes na, nb and parities of both sides allow the similarity: every class whose parities differ holds a
    shingle of one set only, of which there are at most a ninth of both sizes."""
    differ = " + ".join(f"bit_count(fewa[{i}] ^ fewb[{i}])" for i in range(FEW_PARITIES // 64))
    return f"{_SIZES} and 9 * ({differ}) <= na + nb"


def _passing(pairs: DataFrame, sketches: DataFrame) -> DataFrame:
    """pairs(a, b, ...) that may be alike by all parities; sizes so near differ by one halving of a sketch at most."""
    side = lambda c: sketches.select(F.col("row").alias(c), F.col("n").alias(f"n{c}"), F.col("odd").alias(f"odd{c}"))
    xor = lambda x, y: x.bitwiseXOR(y)
    met = pairs.join(side("a"), "a").join(side("b"), "b").filter(_SIZES)
    words = F.least(F.size("odda"), F.size("oddb"))
    folded = lambda c: F.when(F.size(c) > words, F.zip_with(F.slice(c, 1, words), F.slice(c, words + 1, words), xor)).otherwise(F.col(c))
    differ = F.aggregate(F.zip_with(folded("odda"), folded("oddb"), xor), F.lit(0), lambda t, w: t + F.bit_count(w))
    return met.filter(9 * differ <= F.col("na") + F.col("nb")).select(*pairs.columns)


def _ordered(a: str, b: str) -> list:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def with_one(open_: DataFrame, sketches: DataFrame, tested: DataFrame, turn: int) -> DataFrame:
    """(a, b), a < b, that may be alike: each row of open_(token, row, root) with one of another group, of the buckets' least
    (greatest, then any) the one it shares most buckets with.  A row that can't be alike is not met in another's place."""
    order = [] if turn < 2 else [F.xxhash64(F.lit(turn), "root").alias("any")]
    pick = (F.min, F.max)[turn % 2](F.struct(*order, "root", "row"))
    chosen = open_.groupBy("token").agg(pick.alias("p")).select("token", F.col("p.row").alias("o"), F.col("p.root").alias("other"))
    met = open_.join(chosen, "token").filter("root <> other").groupBy("row", "o").agg(F.count("*").alias("shared"))
    size = lambda row, n: sketches.select(F.col("row").alias(row), F.col("n").alias(n))
    met = met.join(size("row", "na"), "row").join(size("o", "nb"), "o").filter(f"{_SIZES} and shared > least(na, nb) div 20")
    met = met.select("row", "o", "shared", *_ordered("row", "o")).join(tested, ["a", "b"], "left_anti")
    best = _passing(met, sketches).groupBy("row").agg(F.max(F.struct("shared", (-F.col("o")).alias("o"))).alias("m"))
    return best.select(*_ordered("row", F.negative("m.o"))).distinct()


def with_all(open_: DataFrame, sketches: DataFrame, tested: DataFrame) -> DataFrame:
    """(a, b), a < b, that may be alike: all rows in different groups that share as many buckets as alike sets do."""
    sized = open_.join(sketches.select("row", "n", "few"), "row")
    side = lambda c: sized.select("token", F.col("row").alias(c), F.col("root").alias(f"r{c}"), F.col("n").alias(f"n{c}"), F.col("few").alias(f"few{c}"))
    met = side("a").join(side("b"), "token").filter(f"a < b and ra <> rb and {_few_fit()}")
    shared = met.groupBy("a", "b").agg(F.count("*").alias("shared"), F.min(F.least("na", "nb")).alias("n"))
    return shared.filter("shared > n div 20").select("a", "b").join(tested, ["a", "b"], "left_anti")


def one_a_group(open_: DataFrame) -> DataFrame:
    """(token, row, root): of each group in a bucket one row, the same in as many buckets as it can be."""
    chosen = open_.groupBy("token", "root").agg(F.min(F.struct(F.xxhash64("row").alias("any"), "row")).alias("p"))
    return chosen.select("token", "p.row", "root")


class _Groups:
    """(row, root) of the rows linked so far; new links join whole groups."""

    def __init__(self, store: Durable):
        self.store, self.turn, self.table = store, 0, store.save(store.spark.createDataFrame([], "row long, root long"), "groups0")

    def rooted(self, rows: DataFrame) -> DataFrame:
        """rows(row, ...) with their root."""
        return rows.join(self.table, "row", "left").withColumn("root", F.coalesce("root", "row"))

    def add(self, links_: DataFrame) -> None:
        self.turn += 1
        if links_.isEmpty():
            return
        for c in "ab":
            at = self.table.select(F.col("row").alias(c), F.col("root").alias(f"r{c}"))
            links_ = links_.join(at, c, "left").withColumn(f"r{c}", F.coalesce(f"r{c}", c))
        moved = components(links_.select(F.col("ra").alias("a"), F.col("rb").alias("b")), self.store, f"cc{self.turn}-", few=FEW_LINKS)
        moved = self.store.save(moved.select("node", F.col("root").alias("to")), f"moved{self.turn}")
        old = self.table.join(moved, self.table.root == moved.node, "left").select("row", F.coalesce("to", "root").alias("root"))
        new = moved.join(self.table.select("root").distinct(), moved.node == F.col("root"), "left_anti").select(F.col("node").alias("row"), F.col("to").alias("root"))
        self.table = self.store.save(old.unionByName(new).unionByName(moved.select(F.col("to").alias("row"), F.col("to").alias("root"))).distinct(), f"groups{self.turn}")


def _records(docs: DataFrame, id_col: str, text_col: str):
    """Name of a row: a digest of its id and text."""
    named = F.coalesce(F.concat(F.lit("i"), F.col(id_col).cast("string")), F.lit("none"))
    return F.unhex(F.md5(F.concat(digest(F.col(text_col)), named.cast("binary"))))


def near_copy_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(rec, group_rec, doc_id, group_id) of every row in a group of two or more; group_rec names the row that stays."""
    store = Durable(docs.sparkSession, "nearcopies")
    texts = docs.select(_records(docs, id_col, text_col).alias("rec"), digest(F.col(text_col)).alias("d"), blob(F.col(text_col)).alias("data"))
    rows = store.save(marked(texts), "marked")
    texts, nodes = texts.select("d", "data"), rows.select("row", "d")
    groups = _Groups(store)
    # rows with equal sets: all but the least are linked to it and leave the search
    least = rows.groupBy("shape").agg(F.min("row").alias("a"), F.count("*").alias("k")).filter("k > 1")
    twins = store.save(rows.select("shape", F.col("row").alias("b")).join(_small(store.save(least, "repeated")), "shape").filter("a <> b").select("a", "b"), "twins")
    groups.add(twins)
    live = rows.join(_small(twins.select(F.col("b").alias("row"))), "row", "left_anti")
    # SimHash: the least row of all that the covering tables join
    prints = store.save(live.groupBy("fp").agg(F.min("row").alias("first"), F.count("*").alias("k")), "prints")
    roots = store.save(components(links(prints.select("fp"), RADIUS, store), store, "fp", few=FEW_LINKS), "roots")
    homes = prints.join(roots, prints.fp == roots.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    heads = homes.join(homes.groupBy("root").agg(F.min("first").alias("head"), F.count("*").alias("f")), "root").join(prints.select("fp", "k"), "fp").filter("k > 1 or f > 1")
    sketches = rows.select("row", "n", "odd")
    near = live.select("row", "fp").join(_small(store.save(heads.select("fp", "head"), "heads")), "fp").filter("row <> head").select(*_ordered("row", "head"))
    tested = store.save(_passing(near, sketches), "pairs")
    groups.add(similar(tested, nodes, texts, store, "simhash"))
    # prefix filter
    shared = store.save(buckets(live.select("row", "tokens")), "buckets")
    fruitful, grouped, done = True, False, False
    for turn in range(MOST_TURNS + 2):
        open_ = store.save(still_open(groups.rooted(shared.select("token", "row"))), f"open{turn}")
        if open_.isEmpty():
            break
        if turn < TURNS or fruitful and turn < MOST_TURNS and not grouped:
            pairs = with_one(open_, sketches, tested, turn)
        else:
            pairs = _passing(with_all(open_ if grouped else one_a_group(open_), rows.select("row", "n", "few"), tested), sketches)
            grouped, done = True, grouped
        pairs = store.save(pairs, f"pairs{turn}")
        linked = similar(pairs, nodes, texts, store, f"turn{turn}")
        groups.add(linked)
        if done:
            break
        fruitful = linked.count() * FRUITFUL > pairs.count()
        tested, shared = tested.unionByName(pairs), open_
    ids = docs.select(_records(docs, id_col, text_col).alias("rec"), F.col(id_col).alias("doc_id"))
    named = store.save(groups.table.join(rows.select("row", "rec"), "row").select("rec", "root").distinct(), "named")
    named = store.save(ids.join(_small(named), "rec").distinct(), "members")
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("rec").alias("rec"))
    stays = named.groupBy("root").agg(F.min(order).alias("s"))
    return named.join(stays, "root").select("rec", F.col("s.rec").alias("group_rec"), "doc_id", F.col("s.id").alias("group_id"))


def near_copy_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, group_id) of every row in a group of two or more, equal rows once; group_id is the least id of the group."""
    return near_copy_rows(docs, id_col, text_col).select("doc_id", "group_id")


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the texts that are near copies of one with a smaller id; all columns stay."""
    store = Durable(docs.sparkSession, "nearcopies-gone")
    name = free_name(docs, "gone")
    gone = near_copy_rows(docs, id_col, text_col).filter("rec <> group_rec").select(F.col("rec").alias(name)).distinct()
    return docs.join(_small(store.save(gone, "gone")), _records(docs, id_col, text_col) == F.col(name), "left_anti")
