"""Class-based bigram language model: every word of the learning documents has a class of its own bigrams.

Training counts every token of the learning documents.  Exchange clustering moves the UNITS most frequent words
between classes while the class-bigram likelihood of the corpus grows; all other words are one unit that stays
where it is.  Then every other word of the vocabulary, however rare, is put into the class in which its own
neighbours are likeliest, by one pass over all bigrams.  With these classes all learning tokens are read again
for the class bigrams.  A token's probability is

    MIX * P(class | previous class) * (c + 0.1) / (N_class + 0.1 V_class) + (1 - MIX) * (c + 0.1) / (N + 0.1 (V + 1))

where words never seen form one more class, which comes as often as words seen once do; for every previous
class the probabilities of all words seen and of one unseen word sum to 1.  Texts begin and end with the end token.

What is gathered grows with the corpus: the table of words with their classes and counts is stored, and tokens
beyond a dictionary of the DICTIONARY most frequent words, whose counts and classes tasks hold, meet it in a join.
A text's classes are then stored, one byte a token, so texts aren't read again.

Defined cases: null texts count as empty; an empty text is its end token; without learning documents
every count is 0 and scores are finite; repeated rows are scored alike and learned from each time; rows with a
null id are learned from; an empty table gives an empty result; further columns, whatever their names, are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import arrow_map, blob, bound_batches, words

UNITS, CLASSES, SWEEPS, MIX, ADD = 2000, 48, 6, 0.95, 0.1
#: Words, of at most WORD_BYTES bytes each, whose counts and classes are sent to every task.
DICTIONARY, WORD_BYTES = 150_000, 64
#: Distinct words, or words with their neighbours' classes, that a counting task holds before it hands them on.
HELD = 300_000
#: Weight of a class's share of all tokens in its share after another class.
BACKOFF = 5.0
END = b""  # no word is empty


def learning(doc_id: Column) -> Column:
    """Rows one may learn from."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 10 != 0, F.lit(True))


def vocabulary(texts: DataFrame) -> DataFrame:
    """texts(data) -> (word, n), the end token included."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_pydict({"word": pa.array(list(held), pa.binary()), "n": pa.array(list(held.values()), pa.int64())})

        for batch in batches:
            for data in batch.column(0).to_pylist():
                held.update(words(data))
                held[END] += 1
                if len(held) >= HELD:
                    yield out()
                    held.clear()
        yield out()

    return texts.mapInArrow(count, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def frequent(vocab: DataFrame, most: int = DICTIONARY) -> list[tuple[bytes, int]]:
    """The most frequent words, at most `most`: all above the least count that keeps within it."""
    level = F.floor(F.log2("n") * 4).cast("int")
    short = vocab.filter(F.octet_length("word") <= WORD_BYTES)
    sizes = sorted(((r.l, r.c) for r in short.groupBy(level.alias("l")).agg(F.count("*").alias("c")).collect()), reverse=True)  # a few hundred levels
    total, least = 0, None
    for value, n in sizes:
        if total + n > most:
            break
        total, least = total + n, value
    if least is None:
        return []
    rows = short.filter(level >= least).collect()  # at most `most` rows of WORD_BYTES
    return sorted(((bytes(r.word), r.n) for r in rows), key=lambda x: (-x[1], x[0]))


def _x_log_x(a: np.ndarray) -> np.ndarray:
    return a * np.log(np.maximum(a, 1.0))


def exchange(pairs: np.ndarray, n_classes: int = CLASSES, sweeps: int = SWEEPS) -> np.ndarray:
    """Classes of units from their bigram counts.  Unit 0, the end token, keeps class 0 and the last unit, all words
    that aren't units, the last class, each to itself."""
    units = len(pairs)
    size = pairs.sum(1) + pairs.sum(0)
    order = 1 + np.argsort(-size[1:-1], kind="stable")
    at = np.zeros(units, dtype=np.int64)
    at[order] = 1 + np.arange(units - 2) % max(1, n_classes - 2)
    at[-1] = n_classes - 1
    member = np.zeros((units, n_classes))
    member[np.arange(units), at] = 1
    grid = member.T @ pairs @ member
    out_u, in_u = pairs.sum(1), pairs.sum(0)
    every = np.arange(n_classes)
    for _ in range(sweeps):
        moved = 0
        for u in order:
            if not size[u]:
                continue
            own, old = pairs[u, u], at[u]
            right, left = np.bincount(at, pairs[u], n_classes), np.bincount(at, pairs[:, u], n_classes)
            right[old] -= own
            left[old] -= own
            grid[old] -= right
            grid[:, old] -= left
            grid[old, old] -= own
            rows, cols = grid.sum(1), grid.sum(0)
            gain = (_x_log_x(grid + right) - _x_log_x(grid)).sum(1) + (_x_log_x(grid + left[:, None]) - _x_log_x(grid)).sum(0)
            diagonal = grid[every, every]
            gain += _x_log_x(diagonal + right + left + own) - _x_log_x(diagonal + right) - _x_log_x(diagonal + left) + _x_log_x(diagonal)
            gain -= _x_log_x(rows + out_u[u]) - _x_log_x(rows) + _x_log_x(cols + in_u[u]) - _x_log_x(cols)
            gain[0] = gain[-1] = -np.inf
            new = int(gain.argmax())
            if gain[new] <= gain[old] + 1e-9:
                new = int(old)
            at[u] = new
            moved += new != old
            grid[new] += right
            grid[:, new] += left
            grid[new, new] += own
        if not moved:
            break
    return at


def unit_pairs(texts: DataFrame, table: dict[bytes, int], units: int) -> np.ndarray:
    """Bigram counts of units over all texts; the last unit is any word that isn't in the table."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(units * units, dtype=np.int32)

        def out() -> pa.RecordBatch:
            found = np.flatnonzero(held)
            return pa.RecordBatch.from_pydict({"pair": pa.array(found, pa.int64()), "n": pa.array(held[found].astype(np.int64), pa.int64())})

        done = 0
        for batch in batches:
            for data in batch.column(0).to_pylist():
                w = words(data)
                seq = np.zeros(len(w) + 2, dtype=np.int64)
                seq[1:-1] = np.fromiter(map(table.get, w, repeat(units - 1)), dtype=np.int64, count=len(w))
                np.add.at(held, seq[:-1] * units + seq[1:], 1)
                done += len(seq)
                if done > 1 << 30:  # counts stay within their type
                    yield out()
                    held[:], done = 0, 0
        yield out()

    summed = texts.mapInArrow(count, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n"))
    got = summed.toArrow()  # at most units squared rows
    pairs = np.zeros(units * units)
    pairs[got.column("pair").to_numpy()] = got.column("n").to_numpy()
    return pairs.reshape(units, units)


#: A class pair and how often, as a word's row holds them.
TOLD = np.dtype([("around", "<u2"), ("n", "<u4")])
#: Places of words that aren't units that a counting task holds before it hands them on.
PLACES = 1 << 21
#: Entries of TOLD that are weighed against all classes at once.
PIECE = 1 << 16


def neighbour_counts(texts: DataFrame, table: dict[bytes, int], unit_class: np.ndarray) -> DataFrame:
    """(word, told) of all words that aren't units: how often they stand between words of two classes,
    one of which at least is a unit.  told is an array of TOLD; a word may have several rows.

    around = class before * classes + class after; the last class stands for words that aren't units.
    """
    classes, other = int(unit_class[-1]) + 1, len(unit_class) - 1
    square = classes * classes

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names: dict[bytes, int] = {}
        held: list[np.ndarray] = []
        size = 0

        def out() -> pa.RecordBatch:
            keys, n = np.unique(np.concatenate(held) if held else np.zeros(0, dtype=np.int64), return_counts=True)
            told = np.empty(len(keys), dtype=TOLD)
            told["around"], told["n"] = keys % square, n
            ends = np.searchsorted(keys, np.arange(len(names) + 1) * square) * TOLD.itemsize
            packed = pa.BinaryArray.from_buffers(pa.binary(), len(names), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(told.tobytes())])
            return pa.RecordBatch.from_arrays([pa.array(list(names), pa.binary()), packed], names=["word", "told"])

        for batch in batches:
            for data in batch.column(0).to_pylist():
                w = words(data)
                seq = np.zeros(len(w) + 2, dtype=np.int64)
                seq[1:-1] = np.fromiter(map(table.get, w, repeat(other)), dtype=np.int64, count=len(w))
                c = unit_class[seq]
                at = np.flatnonzero(seq == other)
                around = c[at - 1] * classes + c[at + 1]
                told = around < square - 1  # a neighbour is a unit
                at, around = at[told], around[told]
                ids = np.fromiter((names.setdefault(w[i], len(names)) for i in (at - 1).tolist()), dtype=np.int64, count=len(at))
                held.append(ids * square + around)
                size += len(at)
                if size >= PLACES or len(names) >= HELD:
                    yield out()
                    names, held, size = {}, [], 0
        yield out()

    return texts.mapInArrow(count, "word binary, told binary")


def likelihoods(grid: np.ndarray) -> np.ndarray:
    """[around, class]: log-likelihood of a class between two classes; neighbours in the last class tell nothing."""
    classes = len(grid)
    after = np.log((grid + 0.5) / (grid.sum(1, keepdims=True) + 0.5 * classes))  # [class, next]
    size = grid.sum(1) + 1.0
    before = np.log((grid + 0.5) / (grid.sum(0, keepdims=True) + 0.5 * classes))  # [previous, class], per token of the class
    made = np.zeros((classes, classes, classes))
    made[: classes - 1] += before[: classes - 1, None, :]
    made[:, : classes - 1] += after.T[None, : classes - 1, :]
    made[:, :, 0] = made[:, :, -1] = -np.inf  # the end token and the pseudo class take no words
    made[:, :, size <= 1.0] = -np.inf
    return made.reshape(classes * classes, classes)


#: Class of words whose neighbours tell nothing.
NEUTRAL = 1


def weighed(table: np.ndarray, told: np.ndarray, firsts: np.ndarray) -> np.ndarray:
    """Sums of table[around] * n for rows of entries, none empty, that start at `firsts`."""
    rows, ends, low = np.empty((len(firsts), table.shape[1])), np.append(firsts[1:], len(told)), 0
    while low < len(firsts):
        high = max(low + 1, int(np.searchsorted(ends, firsts[low] + PIECE, "right")))
        part = told[firsts[low] : ends[high - 1]]
        rows[low:high] = np.add.reduceat(table[part["around"]] * part["n"][:, None], firsts[low:high] - firsts[low], axis=0)
        low = high
    return rows


def insert_words(counts: DataFrame, scores: np.ndarray) -> DataFrame:
    """neighbour_counts -> (word, class): the class in which a word's neighbours are likeliest.

    Rows of a word come one after the other, so a task holds one batch and one word's sums.
    """
    shared = counts.sparkSession.sparkContext.broadcast(np.nan_to_num(scores, neginf=-1e9))

    def best(names: list[bytes], sums: np.ndarray) -> pa.RecordBatch:
        at = np.where(sums.max(1) > -1e8, sums.argmax(1), NEUTRAL)
        return pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(at, pa.int32())], names=["word", "class"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, last, total = shared.value, None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            names, packed = (c.to_pylist() for c in batch.columns)
            told = np.frombuffer(b"".join(packed), dtype=TOLD)
            firsts = np.concatenate(([0], np.cumsum([len(x) for x in packed])[:-1])) // TOLD.itemsize
            starts = [0] + [i for i in range(1, len(names)) if names[i] != names[i - 1]]
            sums = np.add.reduceat(weighed(table, told, firsts), starts, axis=0)
            keys = [names[i] for i in starts]
            if last is not None:
                if keys[0] == last:
                    sums[0] += total
                else:
                    yield best([last], total[None])
            if len(keys) > 1:
                yield best(keys[:-1], sums[:-1])
            last, total = keys[-1], sums[-1].copy()
        if last is not None:
            yield best([last], total[None])

    together = counts.repartition("word").sortWithinPartitions("word")
    return together.mapInArrow(run, "word binary, class int")


@dataclass
class Dictionary:
    """The most frequent words with their counts and classes; at most DICTIONARY of WORD_BYTES bytes."""

    index: dict[bytes, int]
    counts: np.ndarray
    at: np.ndarray

    def __post_init__(self):
        self.log_counts = np.log10(self.counts + ADD)


#: Class byte of a token that the dictionary lacks, until its word is looked up.
OPEN = 255

CODED = "row long, doc_id {id}, held_out boolean, n_tokens long, n_known long, s double, classes binary, places array<int>, rare array<binary>"


def coded(docs: DataFrame, dictionary: Dictionary) -> DataFrame:
    """docs(doc_id, held_out, data) -> CODED: classes and log counts of the dictionary's words; the other words with their places."""
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = CODED.format(id=dict(docs.dtypes)["doc_id"])
    arrow = to_arrow_schema(docs.sparkSession.createDataFrame([], schema).schema)
    shared = docs.sparkSession.sparkContext.broadcast(dictionary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        d, row = shared.value, TaskContext.get().partitionId() << 36
        at = np.append(d.at, OPEN).astype(np.uint8)
        for batch in batches:
            made: list[tuple] = []
            for doc_id, held_out, data in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                w = words(data)
                w.append(END)
                places = np.fromiter(map(d.index.get, w, repeat(-1)), dtype=np.int64, count=len(w))
                open_ = np.flatnonzero(places < 0)
                known = places[places >= 0]
                made.append((row, doc_id, held_out, len(w), len(known), float(d.log_counts[known].sum()), at[places].tobytes(), open_.astype(np.int32), [w[i] for i in open_.tolist()]))
                row += 1
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*made, strict=True) if made else [[]] * len(arrow), arrow, strict=True)], schema=arrow)

    return docs.mapInArrow(run, schema)


def filled(mine: DataFrame, vocab: DataFrame, unseen: int) -> DataFrame:
    """CODED and vocabulary(word, n, class) -> (row, doc_id, held_out, n_tokens, n_known, s, classes) with the looked-up words put in."""
    rare = mine.select("row", F.explode(F.arrays_zip("places", "rare")).alias("t")).select("row", F.col("t.places").alias("place"), F.col("t.rare").alias("word"))
    met = rare.join(vocab, "word", "left").select("row", "place", F.coalesce("class", F.lit(unseen)).alias("c"), F.coalesce("n", F.lit(0)).alias("n"))
    per_row = met.groupBy("row").agg(F.collect_list(F.struct("place", "c")).alias("found"), F.sum(F.log10(F.col("n") + F.lit(ADD))).alias("s_rare"), F.sum(F.when(F.col("n") > 0, 1).otherwise(0)).alias("k_rare"))  # rare words of one text
    both = mine.drop("places", "rare").join(per_row, "row", "left")
    both = both.select("row", "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("k_rare", F.lit(0))).alias("n_known"), (F.col("s") + F.coalesce("s_rare", F.lit(0.0))).alias("s"), "classes", F.col("found.place").alias("places"), F.col("found.c").alias("new"))

    def put(row, doc_id, held_out, n_tokens, n_known, s, classes, places, new):
        made = []
        for c, p, v in zip(classes, places, new, strict=True):
            if p:
                seq = np.frombuffer(c, dtype=np.uint8).copy()
                seq[p] = v
                c = seq.tobytes()
            made.append(c)
        return row, doc_id, held_out, n_tokens, n_known, s, made

    return arrow_map(both, put, f"row long, doc_id {dict(mine.dtypes)['doc_id']}, held_out boolean, n_tokens long, n_known long, s double, classes binary")


def class_bigrams(texts: DataFrame, classes: int) -> np.ndarray:
    """Counts of class pairs of all learning texts(held_out, classes), from the end token to the end token."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(classes * classes, dtype=np.int64)
        for batch in batches:
            for c in batch.column(0).to_pylist():
                seq = np.concatenate(([0], np.frombuffer(c, dtype=np.uint8))).astype(np.int64)
                held += np.bincount(seq[:-1] * classes + seq[1:], minlength=classes * classes)
        found = np.flatnonzero(held)
        yield pa.RecordBatch.from_pydict({"pair": pa.array(found, pa.int64()), "n": pa.array(held[found], pa.int64())})

    got = texts.filter(~F.col("held_out")).select("classes").mapInArrow(count, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")).toArrow()  # classes squared rows
    grid = np.zeros(classes * classes)
    grid[got.column("pair").to_numpy()] = got.column("n").to_numpy()
    return grid.reshape(classes, classes)


def step_logs(grid: np.ndarray, tokens: np.ndarray, types: np.ndarray, seen_once: int) -> np.ndarray:
    """[previous class, class]: log10 of a token's probability without its factor c + 0.1; the last class is that of unseen words."""
    seen, n, v = len(grid) - 1, tokens.sum(), types.sum()
    share = (tokens[:seen] + ADD) / (tokens[:seen] + ADD).sum() if seen else tokens[:0]
    share = np.where(types[:seen] > 0, share, 0.0)
    share = share / share.sum() if share.sum() else share
    unseen = (seen_once + 0.5) / (n + 1.0) if n else 1.0
    step = np.zeros_like(grid)
    step[:, :seen] = (1 - unseen) * (grid[:, :seen] + BACKOFF * share) / (grid[:, :seen].sum(1, keepdims=True) + BACKOFF)
    step[:, seen] = unseen
    mass = np.append(np.maximum(tokens[:seen] + ADD * types[:seen], ADD), ADD)
    return np.log10(MIX * step / mass + (1 - MIX) / (n + ADD * (v + 1)))


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = DICTIONARY, units: int = UNITS, classes: int = CLASSES) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row."""
    bound_batches(docs)
    store = Durable(docs.sparkSession, "brown")
    rows = docs.select(F.col(id_col).alias("doc_id"), (~learning(F.col(id_col))).alias("held_out"), blob(F.col(text_col)).alias("data"))
    texts = rows.filter(~F.col("held_out")).select("data")
    counts = store.save(vocabulary(texts), "counts")
    whole = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count("*").alias("v"), F.count_if(F.col("n") == 1).alias("once")).first()
    listed = frequent(counts, most)
    # exchange over the most frequent words, insertion of all others
    own = [w for w, _ in listed if w != END][:units]
    table = {END: 0} | {w: i + 1 for i, w in enumerate(own)}
    pairs = unit_pairs(texts, table, len(table) + 1)
    unit_class = exchange(pairs, classes)
    member = np.eye(classes)[unit_class]
    scores = likelihoods(member.T @ pairs @ member)
    put = insert_words(neighbour_counts(texts, table, unit_class), scores)
    core = docs.sparkSession.createDataFrame([(bytearray(w), int(unit_class[i])) for w, i in table.items()], "word binary, class int")  # at most units + 1 rows
    unseen = classes - 1  # no word seen is in it
    at = store.save(put.unionByName(core), "classes")
    vocab = store.save(counts.join(at, "word", "left").select("word", "n", F.coalesce("class", F.lit(NEUTRAL)).alias("class")), "vocabulary")
    classed = {bytes(r.word): r["class"] for r in vocab.join(F.broadcast(_words(docs, listed)), "word", "left_semi").select("word", "class").collect()}  # of the dictionary
    dictionary = Dictionary({w: i for i, (w, _) in enumerate(listed)}, np.array([n for _, n in listed], dtype=float), np.array([classed[w] for w, _ in listed], dtype=np.int64))
    done = store.save(filled(store.save(coded(rows, dictionary), "coded"), vocab, unseen), "filled")
    per_class = vocab.groupBy("class").agg(F.sum("n").alias("n"), F.count("*").alias("v")).collect()  # a row for each class
    tokens, types = np.zeros(classes), np.zeros(classes)
    for r in per_class:
        tokens[r["class"]], types[r["class"]] = r.n, r.v
    logs = docs.sparkSession.sparkContext.broadcast(step_logs(class_bigrams(done, classes), tokens, types, whole.once))

    def steps(doc_id, held_out, n_tokens, n_known, s, found):
        seqs = [np.concatenate(([0], np.frombuffer(c, dtype=np.uint8))) for c in found]
        return doc_id, held_out, n_tokens, n_known, s, [float(logs.value[q[:-1], q[1:]].sum()) for q in seqs]

    made = arrow_map(done.select("doc_id", "held_out", "n_tokens", "n_known", "s", "classes"), steps, f"doc_id {dict(rows.dtypes)['doc_id']}, held_out boolean, n_tokens long, n_known long, s double, steps double")
    base = float(np.log10(whole.n + ADD * (whole.v + 1)))
    return made.select(
        "doc_id", "held_out", "n_tokens", "n_known", F.lit(int(whole.n)).cast("long").alias("train_tokens"),
        (F.col("s") - F.col("n_tokens") * F.lit(base)).alias("base_score"), (F.col("s") + F.col("steps")).alias("score"),
    )


def _words(docs: DataFrame, listed: list[tuple[bytes, int]]) -> DataFrame:
    """A bounded dictionary's words as a table."""
    from pyspark.sql.types import BinaryType, StructField, StructType

    return docs.sparkSession.createDataFrame(pa.table({"word": pa.array([w for w, _ in listed], pa.binary())}), StructType([StructField("word", BinaryType())]))
