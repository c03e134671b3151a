"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

Targets: sources in code-point order (null last) weigh 5, 2, 1, repeating, and share a budget of words;
no source gets more than twice its own size, the excess going to the others by weight.

Each source's documents fall into blocks by a keyed hash, at least BLOCKS of them and as many as keep a
block at about BLOCK_WORDS words.  A source whose target is e full passes and a rest has a quota of draws:
all its blocks e times and, in the order of a keyed permutation, as many more as the rest takes.  The
quotas form one vector over the sources.  A binary tree splits it: at every node the left child's share of
each source is a hypergeometric draw conditional on the sources before it, so halves have exact sizes and a
leaf (an output shard) holds the mix that random dealing would give.  Each leaf draws a run of its own of
each source's permuted blocks, so draws are disjoint; what the mix takes of a document follows from the
draws of its block that the leaves were dealt.  In the block where the rest ends, documents are taken in
hash order, and the one at the cut in part, so a source's taken words equal its rounded target.  Inside a
shard rows are ordered by a keyed hash.

Everything is DataFrame functions.  Aggregates follow the numbers of sources and blocks, never the
documents, and a hot source is spread over its blocks.

Defined cases: null texts have size 0 and are never taken; a null source is a source of its own;
a source without words has target 0; rows that agree in id, source and size are treated alike; an
empty table gives an empty result; columns of the input other than the three named are ignored by
assign() and kept by mix_documents(), whose own columns replace ones of the same name; any other column
name is left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import WORD

WEIGHTS, BUDGET, MOST_PASSES = (5, 2, 1), 1.5, 2
BLOCKS, BLOCK_WORDS, DEPTH, SEED = 256, 1 << 24, 4, 20250101
#: Words, about, of an output shard of a large mix.
SHARD_WORDS = 1 << 26
#: Rows of the source or block table up to which it may be broadcast (each is under 300 bytes).
BROADCAST_ROWS = 100_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text.cast("string"), F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(totals: DataFrame, weights=WEIGHTS, budget: float = BUDGET, most: int = MOST_PASSES) -> DataFrame:
    """totals(source, source_size) -> the same with rank, weight and target."""
    by_name = Window.orderBy(F.col("source").isNull(), "source")
    cycle = F.element_at(F.array(*map(F.lit, weights)), ((F.col("rank") - 1) % len(weights) + 1).cast("int"))
    by_ratio = Window.orderBy("ratio", "rank")
    everything = Window.partitionBy()
    ranked = totals.withColumn("rank", F.row_number().over(by_name)).withColumn("weight", cycle).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    ranked = ranked.withColumn("ratio", F.col("cap") / F.col("weight")).withColumn("words", F.sum("source_size").over(everything) * F.lit(budget))
    ranked = ranked.withColumn("caps", F.sum("cap").over(by_ratio.rowsBetween(Window.unboundedPreceding, -1))).withColumn("shares", F.sum("weight").over(by_ratio.rowsBetween(0, Window.unboundedFollowing)))
    ranked = ranked.withColumn("full", F.col("ratio") <= (F.col("words") - F.coalesce("caps", F.lit(0.0))) / F.col("shares"))
    level = (F.col("words") - F.coalesce(F.sum(F.when(F.col("full"), F.col("cap"))).over(everything), F.lit(0.0))) / F.sum(F.when(~F.col("full"), F.col("weight"))).over(everything)
    return ranked.withColumn("target", F.when(F.col("full"), F.col("cap")).otherwise(level * F.col("weight"))).select("source", "source_size", "rank", "weight", "target")


def _log_factorial(n: Column) -> Column:
    """Stirling's series from 10 on, by the product below that."""
    small = F.element_at(F.array(*(F.lit(x) for x in (0.0, 0.0, 0.6931471805599453, 1.791759469228055, 3.1780538303479458, 4.787491742782046, 6.579251212010101, 8.525161361065415, 10.60460290274525, 12.801827480081469))), (n + 1).cast("int"))
    x = n.cast("double")
    series = (x + 0.5) * F.log(x) - x + 0.9189385332046727 + 1 / (12 * x) - 1 / (360 * x * x * x) + 1 / (1260 * x * x * x * x * x)
    return F.when(n < 10, small).otherwise(series)


def _hypergeometric(population: Column, marked: Column, drawn: Column, u: Column) -> Column:
    """How many of `drawn` are marked: the inverse of the distribution function at u."""
    low, high = F.greatest(F.lit(0).cast("long"), drawn - (population - marked)), F.least(marked, drawn)
    lf = _log_factorial
    fixed = lf(marked) + lf(population - marked) + lf(drawn) + lf(population - drawn) - lf(population)

    def weight(x: Column) -> Column:
        return F.exp(fixed - lf(x) - lf(marked - x) - lf(drawn - x) - lf(population - marked - drawn + x))

    start = F.struct(F.lit(0.0).alias("mass"), low.alias("x"))
    step = lambda a, x: F.struct((a.mass + weight(x)).alias("mass"), F.when(a.mass < u, x).otherwise(a.x).alias("x"))
    return F.when(low >= high, low).otherwise(F.aggregate(F.sequence(low, high), start, step, lambda a: a.x))


def _uniform(*parts: Column) -> Column:
    return F.pmod(F.xxhash64(*parts), F.lit(1 << 52)).cast("double") / F.lit(float(1 << 52))


def splitting_tree(quotas: DataFrame, depth: int = DEPTH, seed: int = SEED) -> DataFrame:
    """quotas(rank, draws) -> (shard, rank, draws) for 2^depth shards."""
    zero = F.lit(0).cast("long")
    nodes = quotas.agg(F.sort_array(F.collect_list(F.struct("rank", F.col("draws").cast("long").alias("draws")))).alias("q")).select(F.lit(1).cast("long").alias("node"), "q")
    for _ in range(depth):
        all_ = F.aggregate("q", zero, lambda a, x: a + x.draws)
        half = F.floor((all_ + F.when(_uniform(F.lit(seed), F.col("node")) < 0.5, F.lit(1)).otherwise(F.lit(0))) / 2).cast("long")
        start = F.struct(all_.alias("population"), half.alias("drawn"), F.expr("cast(array() as array<bigint>)").alias("got"))

        def draw(a: Column, x: Column) -> Column:
            n = _hypergeometric(a.population, x.draws, a.drawn, _uniform(F.lit(seed + 1), F.col("node"), x["rank"]))
            return F.struct((a.population - x.draws).alias("population"), (a.drawn - n).alias("drawn"), F.concat(a.got, F.array(n)).alias("got"))

        split = nodes.withColumn("left", F.aggregate("q", start, draw, lambda a: a.got))
        child = lambda k, n: F.struct((F.col("node") * 2 + k).alias("node"), F.zip_with("q", "left", lambda x, y: F.struct(x["rank"].alias("rank"), n(x, y).cast("long").alias("draws"))).alias("q"))
        nodes = split.select(F.explode(F.array(child(0, lambda x, y: y), child(1, lambda x, y: x.draws - y))).alias("c")).select("c.node", "c.q")
    return nodes.select((F.col("node") - (1 << depth)).alias("shard"), F.explode("q").alias("x")).select("shard", "x.rank", "x.draws")


def _block(id_: Column, size: Column, blocks: Column, seed: int) -> Column:
    return F.pmod(F.xxhash64(F.lit(seed), id_, size), blocks)


def _place(id_: Column, size: Column, seed: int) -> Column:
    """Order of documents inside a block."""
    return F.struct(F.xxhash64(F.lit(seed + 7), id_, size).alias("h"), id_.alias("id"))


def _few(df: DataFrame) -> DataFrame:
    """A stored table, broadcast if it is within BROADCAST_ROWS."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def _in_blocks(rows: DataFrame, sources: DataFrame, seed: int) -> DataFrame:
    """rows(id, source, size, ...) -> with rank, source_size, target and block."""
    at = _few(sources).select(F.col("source").alias("at_source"), "rank", "source_size", "target", "blocks")
    met = rows.join(at, F.col("source").eqNullSafe(F.col("at_source")))
    return met.withColumn("block", _block(F.col("id"), F.col("size"), F.col("blocks"), seed)).drop("at_source", "blocks")


def _dealt(turned: DataFrame, leaves: DataFrame) -> DataFrame:
    """(rank, block, draws): which leaf draws each block in each pass.

    Leaves and draws of a source are put on one line; a draw belongs to the last leaf that starts at or before it.
    """
    run = Window.partitionBy("rank").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    starts = leaves.filter("draws > 0").withColumn("position", F.coalesce(F.sum("draws").over(run), F.lit(0)))
    starts = starts.select("rank", "position", F.lit(0).alias("what"), "shard", F.lit(None).cast("long").alias("block"), F.lit(None).cast("long").alias("epoch"))
    drawn = turned.select("rank", "block", "place", F.explode(F.expr("filter(sequence(0L, passes), e -> e < passes or extra = 1)")).alias("epoch"))
    drawn = drawn.withColumn("position", F.row_number().over(Window.partitionBy("rank").orderBy("epoch", "place")).cast("long") - 1)
    drawn = drawn.select("rank", "position", F.lit(1).alias("what"), F.lit(None).cast("long").alias("shard"), "block", "epoch")
    line = Window.partitionBy("rank").orderBy("position", "what").rowsBetween(Window.unboundedPreceding, 0)
    owned = starts.unionByName(drawn).withColumn("shard", F.last("shard", ignorenulls=True).over(line)).filter("what = 1")
    return owned.groupBy("rank", "block").agg(F.sort_array(F.collect_list(F.struct("epoch", "shard"))).alias("draws"))  # one for each pass


def block_plan(rows: DataFrame, store: Durable, depth: int = DEPTH, seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """rows(id, source, size) -> (sources, plan): targets and numbers of blocks; for each block its leaves' draws and, where the rest ends, the cut."""
    totals = rows.groupBy("source").agg(F.sum("size").alias("source_size"))
    passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    count = F.greatest(F.lit(BLOCKS).cast("long"), F.ceil(F.col("source_size") / F.lit(BLOCK_WORDS)).cast("long"))
    sources = source_targets(totals).withColumn("passes", passes).withColumn("blocks", count)
    sources = store.save(sources.withColumn("rest", F.round(F.col("target") - F.col("passes") * F.col("source_size")).cast("long")), "sources")
    rows = _in_blocks(rows, sources, seed)
    blocks = store.save(rows.groupBy("rank", "block").agg(F.sum("size").alias("words")), "blocks")
    order = Window.partitionBy("rank").orderBy("turn", "block")
    turned = blocks.join(_few(sources.select("rank", "passes", "rest")), "rank").withColumn("turn", F.xxhash64(F.lit(seed + 3), "rank", "block"))
    turned = turned.withColumn("place", F.row_number().over(order)).withColumn("before", F.coalesce(F.sum("words").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    room = F.col("rest") - F.col("before")
    turned = turned.withColumn("part", F.when(room <= 0, F.lit(0).cast("long")).otherwise(F.least(room, F.col("words"))))
    turned = store.save(turned.withColumn("extra", F.when(F.col("part") > 0, 1).otherwise(0)), "turned")
    # the block in which the rest ends, and the document at the cut
    ends = turned.filter("part > 0 and part < words").select("rank", "block", "part")  # one of each source at most
    inside = Window.partitionBy("rank", "block").orderBy("p", "size")
    met = rows.join(_few(ends), ["rank", "block"]).select("rank", "block", "size", "part", _place(F.col("id"), F.col("size"), seed).alias("p"))
    met = met.withColumn("before", F.coalesce(F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    cuts = met.filter("before < part and before + size >= part").select("rank", "block", F.col("p").alias("cut"), (F.col("part") - F.col("before")).alias("cut_words"))
    quotas = turned.groupBy("rank").agg(F.sum(F.col("passes") + F.col("extra")).alias("draws"))
    leaves = store.save(splitting_tree(quotas, depth, seed), "leaves")
    plan = turned.join(_dealt(turned, leaves), ["rank", "block"], "left").join(cuts, ["rank", "block"], "left")
    return sources, store.save(plan.select("rank", "block", "passes", "words", "part", "cut", "cut_words", "draws"), "plan")


def _with_draws(rows: DataFrame, sources: DataFrame, plan: DataFrame, seed: int) -> DataFrame:
    """rows(id, source, size, ...) -> with source_size, target, taken and shards, both from the draws of the row's block."""
    met = _in_blocks(rows, sources, seed).join(_few(plan), ["rank", "block"]).withColumn("place", _place(F.col("id"), F.col("size"), seed))
    none = F.lit(0).cast("long")
    last = (
        F.when(F.col("part") >= F.col("words"), F.col("size"))
        .when(F.col("place") < F.col("cut"), F.col("size"))
        .when(F.col("place") == F.col("cut"), F.least(F.col("cut_words"), F.col("size")))
        .otherwise(none)
    )
    of_draw = F.transform(F.coalesce("draws", F.expr("cast(array() as array<struct<epoch:bigint,shard:bigint>>)")), lambda d: F.struct(d.shard.alias("shard"), F.when(d.epoch < F.col("passes"), F.col("size")).otherwise(F.col("last")).alias("words")))
    met = met.withColumn("last", last).withColumn("used", F.filter(of_draw, lambda d: d.words > 0))
    return met.withColumn("taken", F.aggregate("used", none, lambda a, d: a + d.words)).withColumn("shards", F.transform("used", lambda d: d.shard))


def _sized(docs: DataFrame, id_col: str, text_col: str, source_col: str, *more: Column) -> DataFrame:
    return docs.select(*more, F.col(id_col).alias("id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size"))


def assign(docs: DataFrame, depth: int = DEPTH, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(doc_id, size, source_size, target, taken, shards) for every row."""
    store = Durable(docs.sparkSession, "mixing")
    rows = store.save(_sized(docs, id_col, text_col, source_col), "sizes")
    done = _with_draws(rows, *block_plan(rows, store, depth, seed), seed)
    return done.select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken", F.concat_ws(",", "shards").alias("shards"))


def depth_for(words: float, shard_words: int = SHARD_WORDS) -> int:
    """Depth of a tree whose shards hold about shard_words words each, DEPTH at least."""
    return max(DEPTH, (int(words) // shard_words).bit_length())


def shard_rows(mixed: DataFrame, depth: int = DEPTH, seed: int = SEED, id_col: str = "doc_id", with_rest: bool = False) -> DataFrame:
    """One row for each drawn copy, with its number and shard (`copy`, `shard`), shuffled inside the shard by a keyed hash.

    A shard lies in one partition.  Documents that the mix doesn't take have no row, or with_rest one without a shard.
    """
    kept = [F.col(f"`{c}`") for c in mixed.columns if c not in ("shards", "copy", "shard")]
    copies = mixed.select(*kept, (F.posexplode_outer if with_rest else F.posexplode)("shards").alias("copy", "shard"))
    order = F.xxhash64(F.lit(seed + 11), F.col(id_col), F.col("copy"))
    home = F.coalesce(F.col("shard"), F.pmod(order, F.lit(1 << depth)))  # those without a shard are spread
    return copies.repartition(1 << depth, home).sortWithinPartitions("shard", order)


def mix_documents(docs: DataFrame, depth: int = DEPTH, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """docs with size, source_size, target, taken and shards; documents the mix doesn't take stay with taken = 0."""
    return _mixed(docs, depth, seed, id_col, text_col, source_col)[0]


def mix_shards(docs: DataFrame, depth: int | None = None, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix itself: shard_rows() of mix_documents(), with as many shards as its words need if no depth is given.

    Documents that it doesn't take stay, without a shard.
    """
    mixed, depth = _mixed(docs, depth, seed, id_col, text_col, source_col)
    return shard_rows(mixed, depth, seed, id_col, with_rest=True)


def _mixed(docs, depth, seed, id_col, text_col, source_col) -> tuple[DataFrame, int]:
    store = Durable(docs.sparkSession, "mixing")
    sizes = store.save(_sized(docs, id_col, text_col, source_col), "sizes")
    if depth is None:
        depth = depth_for(BUDGET * (sizes.agg(F.sum("size").alias("n")).first().n or 0))
    plan = block_plan(sizes, store, depth, seed)
    mine = ("size", "source_size", "target", "taken", "shards")
    whole = F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("caller")
    done = _with_draws(_sized(docs, id_col, text_col, source_col, whole), *plan, seed)
    return done.select(*(F.col(f"caller.`{c}`") for c in docs.columns if c not in mine), *mine), depth
