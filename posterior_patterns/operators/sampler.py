"""Markov chains over decomposable families, run as Spark tasks.

A step proposes one of the d(M) legal merges and splits uniformly and accepts it with probability
min(1, exp(change of BIC weight) * d(M) / d(M')).  Chains start at the family of single items, are pure
functions of (seed, chain id), and so come out the same for any partitioning and after any lost task.

Where entropies come from depends on the size of the pattern table:
  patterns    a table within BROADCAST_BYTES is shipped to the tasks as arrays; they compute and remember entropies;
  entropies   entropies of all itemsets of up to three items are computed in one pass before the chains start;
              a chain that needs another goes on in supersteps;
  supersteps  each chain runs until it lacks an entropy, and asks for those of all moves open to it; the distinct
              itemsets asked for are computed in one batch pass over the patterns and joined back to the chains.
States with their entropies are stored after every superstep, so nothing grows on the driver.  All tiers give the
same chains and the same draws.
"""

from __future__ import annotations

import math
from collections import ChainMap
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .bic import log_bic, log_n
from .entropy import EntropyCache, EntropyTable, entropy, wide_entropy
from .family import bits
from .patterns import WORD_BITS, total
from .state import ChainState

BROADCAST_BYTES = 200 << 20
_MASK = (1 << 64) - 1


class Numbers:
    """A splitmix64 stream; its state is one integer."""

    __slots__ = ("state",)

    def __init__(self, seed: int):
        self.state = seed & _MASK

    def next(self) -> int:
        self.state = (self.state + 0x9E3779B97F4A7C15) & _MASK
        z = self.state
        z = ((z ^ (z >> 30)) * 0xBF58476D1CE4E5B9) & _MASK
        z = ((z ^ (z >> 27)) * 0x94D049BB133111EB) & _MASK
        return z ^ (z >> 31)

    def below(self, n: int) -> int:
        return (self.next() * n) >> 64

    def unit(self) -> float:
        """In (0, 1]."""
        return ((self.next() >> 11) + 1) * 2.0**-53


def chain_seed(seed: int, chain_id: int) -> int:
    return Numbers(seed * 0x5851F42D4C957F2D + chain_id).next()


def default_steps(k: int) -> int:
    """ceil(100 K ln K); one item has no move."""
    return math.ceil(100 * k * math.log(k)) if k > 1 else 0


@dataclass
class Chain:
    """One chain; run() goes on until `steps` are done."""

    k: int
    n: float
    rng: Numbers
    rebuild: bool = False
    proposal: str = "legal"
    max_clique: int | None = None
    maxs: list[int] | None = None
    done: int = 0
    accepted: int = 0
    trace: list | None = None
    state: ChainState = field(init=False)

    def __post_init__(self):
        self.state = ChainState(self.k, self.maxs, self.rebuild)

    def run(self, h: Callable[[int], float], steps: int) -> None:
        if self.proposal == "flip":
            return self._run_flips(h, steps)
        state, rng, n, half_log = self.state, self.rng, self.n, log_n(self.n)
        known: dict[tuple[int, int], float] = {}
        while self.done < steps:
            before, d = rng.state, state.degree
            if not d:
                self.done = steps
                return
            is_merge, s, x, y = state.move(rng.below(d))
            whole, pair = s | x | y, x | y
            if is_merge and self.max_clique and whole.bit_count() > self.max_clique:  # refused whatever its weight
                rng.unit()
                self.done += 1
                if self.trace is not None:
                    self.trace.append((self.done, "merge", s, x, y, None, d, None, False))
                continue
            change = known.get((whole, pair))
            if change is None:
                try:
                    change = n * (h(whole) - h(s | x) - h(s | y) + h(s)) + half_log * 2.0 ** (whole.bit_count() - 3)
                except EntropyTable.Missing:
                    rng.state = before
                    raise
                known[whole, pair] = change
            delta = -change if is_merge else change
            limit = math.log(rng.unit())
            taken, deg_new = False, None
            # the new degree is at least 1, so most moves can be refused before they are made
            if limit <= delta + math.log(d):
                (state.merge if is_merge else state.split)(s, x, y)
                deg_new = state.degree
                taken = limit <= delta + math.log(d) - math.log(deg_new)
                if not taken:
                    (state.split if is_merge else state.merge)(s, x, y)
            self.done += 1
            self.accepted += taken
            if self.trace is not None:
                self.trace.append((self.done, "merge" if is_merge else "split", s, x, y, delta, d, deg_new, taken))

    def _run_flips(self, h: Callable[[int], float], steps: int) -> None:
        """Propose any pair of items; an illegal change leaves the family as it is.  Same stationary law."""
        from .family import cliques, neighbours

        rng, n, half_log, k = self.rng, self.n, log_n(self.n), self.k
        near = {1 << i: 0 for i in range(k)} | neighbours(self.state.maxs)
        pairs = [(1 << i, 1 << j) for i in range(k) for j in range(i)]
        while self.done < steps and pairs:
            before = rng.state
            x, y = pairs[rng.below(len(pairs))]
            limit, s, linked = math.log(rng.unit()), near[x] & near[y], bool(near[x] & y)
            self.done += 1
            if linked:
                legal = all(s & ~near[b] & ~b == 0 for b in bits(s))
            else:  # s must lie on every way from x to y
                seen = edge = x
                while edge:
                    new = 0
                    for b in bits(edge):
                        new |= near[b]
                    edge = new & ~seen & ~s
                    seen |= edge
                legal = not seen & y
            if not legal:
                continue
            whole = s | x | y
            if not linked and self.max_clique and whole.bit_count() > self.max_clique:
                continue
            try:
                change = n * (h(whole) - h(s | x) - h(s | y) + h(s)) + half_log * 2.0 ** (whole.bit_count() - 3)
            except EntropyTable.Missing:
                rng.state, self.done = before, self.done - 1
                self.state = ChainState(k, cliques(near))
                raise
            if limit <= (change if linked else -change):
                near[x] ^= y
                near[y] ^= x
                self.accepted += 1
        self.state = ChainState(k, cliques(near))


def _options(k, n, rebuild, proposal, max_clique):
    return {"k": k, "n": n, "rebuild": rebuild, "proposal": proposal, "max_clique": max_clique}


def run_chain(h: Callable[[int], float], k: int, n: float, steps: int, seed: int, *, rebuild=False, proposal="legal", max_clique=None, trace=None, thin=None) -> tuple[list, Chain]:
    """(families, chain): the last family, or every thin-th one."""
    chain = Chain(**_options(k, n, rebuild, proposal, max_clique), rng=Numbers(seed), trace=trace)
    made = []
    for mark in _marks(steps, thin):
        chain.run(h, mark)
        made.append(sorted(chain.state.maxs))
    return made, chain


def _marks(steps: int, thin: int | None) -> list[int]:
    """Steps after which a family is drawn."""
    return list(range(thin, steps + 1, thin)) if thin else [steps]


def _collect_patterns(patterns: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Patterns on the driver as arrays, wide ones with a row for each; callers have checked their size."""
    got = patterns.toArrow()
    counts = got.column("n").to_numpy()
    if "mask" in got.column_names:
        return got.column("mask").to_numpy(), counts
    flat = got.column("words").combine_chunks().flatten().to_numpy()
    return flat.reshape(len(counts), -1) if len(counts) else np.zeros((0, 1), dtype=np.int64), counts


def plan(patterns: DataFrame, k: int) -> str:
    """The tier for a pattern table."""
    rows = patterns.count()
    if rows * (8 * -(-k // 62) + 8) <= BROADCAST_BYTES:
        return "patterns"
    return "supersteps"


_ROW = "chain_id long, draw int, maximal array<string>, log_bic double, steps long, accepted long, entropies long"
_TRACE = "chain_id long, step int, op string, s string, x int, y int, delta double, deg long, deg_new long, accepted boolean"


def _chains(spark: SparkSession, restarts: int, partitions: int | None, first: int = 0) -> DataFrame:
    return spark.range(first, first + restarts, 1, partitions or max(1, min(restarts, spark.sparkContext.defaultParallelism * 4)))


def sample_models(
    patterns: DataFrame, k: int, restarts: int = 5000, steps: int | None = None, seed: int = 0, *, rebuild: bool = False, proposal: str = "legal",
    max_clique: int | None = None, thin: int | None = None, partitions: int | None = None, tier: str | None = None,
) -> DataFrame:
    """(chain_id, draw, maximal, log_bic, steps, accepted, entropies), stored: the last family of each chain, or every
    thin-th one, masks as decimal strings.  The chains run once, however often the result is read.
    """
    spark, steps = patterns.sparkSession, default_steps(k) if steps is None else steps
    store = Durable(spark, "models")
    tier = tier or plan(patterns, k)
    if tier in SIZES:
        return _supersteps(patterns, k, restarts, steps, seed, rebuild, proposal, max_clique, thin, partitions, store, SIZES[tier])
    if tier != "patterns":
        raise ValueError(f"no such tier: {tier}")
    shared = spark.sparkContext.broadcast(_collect_patterns(patterns))  # within BROADCAST_BYTES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        h = _source(shared)
        for batch in batches:
            made = []
            for chain_id in batch.column(0).to_pylist():
                families, chain = run_chain(h, k, h.n, steps, chain_seed(seed, chain_id), rebuild=rebuild, proposal=proposal, max_clique=max_clique, thin=thin)
                for draw, maxs in enumerate(families):
                    made.append({"chain_id": chain_id, "draw": draw, "maximal": [str(m) for m in maxs], "log_bic": log_bic(maxs, h, h.n), "steps": chain.done, "accepted": chain.accepted, "entropies": h.misses})
            yield pa.RecordBatch.from_pylist(made, schema=_arrow(_ROW))

    models = store.save(_chains(spark, restarts, partitions).mapInArrow(run, _ROW), "models")
    shared.unpersist()
    return models


def trace_chains(patterns: DataFrame, k: int, restarts: int, steps: int, seed: int = 0, *, rebuild: bool = False, partitions: int | None = None) -> DataFrame:
    """Every step of every chain, for pattern tables that may be shipped."""
    spark = patterns.sparkSession
    if plan(patterns, k) != "patterns":
        raise ValueError("traces are written where patterns fit the tasks")
    shared = spark.sparkContext.broadcast(_collect_patterns(patterns))  # within BROADCAST_BYTES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        h = _source(shared)
        for batch in batches:
            for chain_id in batch.column(0).to_pylist():
                rows: list = []
                run_chain(h, k, h.n, steps, chain_seed(seed, chain_id), rebuild=rebuild, trace=rows)
                made = [{"chain_id": chain_id, "step": t, "op": op, "s": str(s), "x": x.bit_length(), "y": y.bit_length(), "delta": delta, "deg": d, "deg_new": new, "accepted": taken} for t, op, s, x, y, delta, d, new, taken in rows]
                yield pa.RecordBatch.from_pylist(made, schema=_arrow(_TRACE))

    return _chains(spark, restarts, partitions).mapInArrow(run, _TRACE)


_HELD: dict[str, object] = {"value": None}


def _source(shared):
    """The entropies of a broadcast, kept by a worker between its tasks."""
    value = shared.value
    if _HELD["value"] is not value:
        _HELD.update(value=value, source=EntropyCache(*value))
    return _HELD["source"]


def _arrow(ddl: str) -> pa.Schema:
    kinds = {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "boolean": pa.bool_(), "array<string>": pa.list_(pa.string()), "array<double>": pa.list_(pa.float64()), "binary": pa.binary()}
    return pa.schema([(name, kinds[kind]) for name, kind in (x.split(" ") for x in ddl.split(", "))])


#: Items of the itemsets whose entropies are computed before the chains start, by tier.
SIZES = {"entropies": 3, "supersteps": 2}


def precomputed(patterns: DataFrame, k: int, size: int = 3) -> DataFrame:
    """(m, h): entropies of all itemsets of up to `size` items in one pass, masks as decimal strings."""
    from itertools import combinations

    wanted = [(str(sum(1 << i for i in c)),) for r in range(1, min(size, k) + 1) for c in combinations(range(k), r)]
    return entropies_of(patterns, patterns.sparkSession.createDataFrame(wanted, "m string"), k)


def entropies_of(patterns: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """wanted(m), masks of any width as decimal strings -> (m, h)."""
    if "mask" in patterns.columns:
        sets = wanted.select(F.col("m").cast("bigint").alias("mask")).withColumn("size", F.bit_count("mask").cast("int"))
        return entropy(patterns, sets).select(F.col("mask").cast("string").alias("m"), "h")
    return wide_entropy(patterns, wanted, -(-k // WORD_BITS))


_STATE = "chain_id long, rng string, maxs array<string>, done long, accepted long, draws array<string>, missing array<string>"


def _open_sets(state: ChainState) -> set[int]:
    """Itemsets whose entropies decide the moves that a family has open."""
    made: set[int] = set()
    for pair in state.once:
        whole = next(m for m in state.maxs if m & pair == pair)
        x = pair & -pair
        made |= {whole, whole & ~x, whole & ~(pair ^ x), whole & ~pair}
    for s, parts in state.parts.items():
        made.add(s)
        for i, v in enumerate(parts):
            for w in parts[:i]:
                for x in bits(v):
                    made.add(s | x)
                    for y in bits(w):
                        made |= {s | x | y, s | y}
    return made - {0}


def _supersteps(patterns, k, restarts, steps, seed, rebuild, proposal, max_clique, thin, partitions, store, size, max_rounds: int = 100_000) -> DataFrame:
    """Chains whose entropies are computed as they are asked for.  A state row holds the chain's own entropies."""
    spark, n, marks = patterns.sparkSession, float(total(patterns)), _marks(steps, thin)
    first = store.save(precomputed(patterns, k, size), "h")  # at most K^size / 6 rows, whatever the data
    known = {int(r.m): r.h for r in first.collect()}
    shared = spark.sparkContext.broadcast(known)
    kind = _STATE + ", sets array<string>, h array<double>"

    def begin(batches):
        for batch in batches:
            made = [{"chain_id": i, "rng": str(Numbers(chain_seed(seed, i)).state), "maxs": [str(1 << j) for j in range(k)], "done": 0, "accepted": 0, "draws": [], "missing": [], "sets": [], "h": []} for i in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_pylist(made, schema=_arrow(kind))

    def advance(batches):
        for batch in batches:
            made = []
            for row in batch.to_pylist():
                chain = Chain(**_options(k, n, rebuild, proposal, max_clique), rng=Numbers(int(row["rng"])), maxs=[int(m) for m in row["maxs"]], done=row["done"], accepted=row["accepted"])
                own, missing, draws = dict(zip(map(int, row["sets"]), row["h"], strict=True)), set(), row["draws"]
                h = EntropyTable(ChainMap(own, shared.value), n)
                try:
                    for mark in marks[len(draws) :]:
                        chain.run(h, mark)
                        maxs = sorted(chain.state.maxs)
                        draws.append(f"{log_bic(maxs, h, n)!r} " + " ".join(map(str, maxs)))
                except EntropyTable.Missing as e:
                    missing = {m for m in _open_sets(chain.state) if m not in own and m not in shared.value} | {e.args[0]}
                made.append(row | {"rng": str(chain.rng.state), "maxs": [str(m) for m in sorted(chain.state.maxs)], "done": chain.done, "accepted": chain.accepted, "draws": draws, "missing": sorted(map(str, missing))})
            yield pa.RecordBatch.from_pylist(made, schema=_arrow(kind))

    states = _chains(spark, restarts, partitions).mapInArrow(begin, kind)
    for i in range(max_rounds):
        states = store.save(states.mapInArrow(advance, kind), f"states{i}")
        if i:
            store.drop(f"states{i - 1}")
            store.drop(f"h{i - 1}")
        asked = states.select("chain_id", F.explode("missing").alias("m"))
        if asked.isEmpty():
            break
        found = store.save(entropies_of(patterns, asked.select("m").distinct(), k), f"h{i}")
        got = asked.join(found, "m").groupBy("chain_id").agg(F.collect_list(F.struct("m", F.col("h").alias("v"))).alias("got"))  # what one chain asked for
        new = lambda c: F.concat("sets" if c == "m" else "h", F.coalesce(F.transform("got", lambda g: g[c]), F.array().cast("array<string>" if c == "m" else "array<double>")))
        states = states.join(got, "chain_id", "left").withColumn("more", new("m")).withColumn("h", new("v")).withColumn("sets", F.col("more")).drop("more", "got")
    else:
        raise RuntimeError(f"chains were not done after {max_rounds} supersteps")
    drawn = states.select("chain_id", F.posexplode("draws").alias("draw", "text"), "done", "accepted", (F.size("sets") + F.lit(len(known))).cast("long").alias("entropies"))
    parts = F.split("text", " ")
    cut = drawn.select("chain_id", "draw", F.slice(parts, 2, F.size(parts)).alias("maximal"), F.get(parts, F.lit(0)).cast("double").alias("log_bic"), F.col("done").alias("steps"), "accepted", "entropies")
    return store.save(cut, "models")


def diagnostics(models: DataFrame) -> DataFrame:
    """One row: chains, steps, share of accepted moves, spread of the weight between chains.  Thinned chains count once."""
    models = models.groupBy("chain_id").agg(F.max("steps").alias("steps"), F.max("accepted").alias("accepted"), F.max_by("log_bic", "draw").alias("log_bic"), F.max("entropies").alias("entropies"))
    return models.agg(
        F.count("*").alias("chains"), F.sum("steps").alias("steps"), (F.sum("accepted") / F.sum("steps")).alias("acceptance"),
        F.avg("log_bic").alias("mean_log_bic"), F.stddev_samp("log_bic").alias("sd_log_bic"), F.max("entropies").alias("entropies"),
    )
