"""The registered queries of the scoring engine, each with the SQL that must give the same rows where there is one.

Sampled results are turned into verdicts that don't depend on a seed.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from itertools import combinations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from . import workloads as W
from .operators import baselines, bic, catalogue, entropy, expmodel, family, measures, moves, patterns, sampler, score
from .operators.family import mask_of
from .plans.durable import Durable
from .sources import encode
from .sources.encode import SPECS, to_baskets
from .sources.tables import example, load
from .streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

#: Chains in the registered queries; a full run takes 5,000.
CHAINS = 64
PAIRS5 = [1 << i | 1 << j for i in range(5) for j in range(i)]
ALL5 = list(range(1, 32))
F1, F2, F3 = ([mask_of(s) for s in f] for f in (((1, 2), (2, 3), (2, 4), (4, 5)), ((1, 2), (2, 3, 4), (4, 5)), ((1, 2), (2, 3, 4), (3, 4, 5))))
#: Literal families that stand for sampled models where a result must be fixed.
FIXED = [F1, F1, F2, F3, family.singletons(5), [mask_of((1, 2, 3)), mask_of((4, 5))], [mask_of((1, 2, 3)), mask_of((3, 4)), mask_of((4, 5))], F2, F1, family.saturated(5)]


def query(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            SQL[key] = sql
        return f

    return add


def _rows(spark, rows, ddl):
    return spark.createDataFrame(rows, ddl)


def _values(rows: list[tuple], columns: str, casts: str) -> str:
    def one(v):
        return "NULL" if v is None else str(v).upper() if isinstance(v, bool) else f"'{v}'" if isinstance(v, str) else str(v)

    return f"SELECT {casts} FROM (VALUES {', '.join('(' + ', '.join(map(one, r)) + ')' for r in rows)}) AS t({columns})"


def _named(df: DataFrame, *more: str, k: int = 16) -> DataFrame:
    return df.select(patterns.label("mask", k).alias("itemset"), F.col("size").cast("int").alias("size"), *more)


# -- encodings ------------------------------------------------------------------------------------

for _name in ("line", "thermo", "cust", "userday", "userday_all", "word5", "word5_en", "ord5", "doclabel", "sign", "tag", "role", "brand", "custsize"):
    query(O.patterns_sql(_name), f"enc_{_name}_patterns")(lambda spark, d, n=_name: W.patterns_of(spark, d, n))
for _name in ("ind_100", "ind_1000", "ind_10000", "path_100", "path_1000", "path_10000"):
    query(O.patterns_sql(_name), f"synth_{_name}_patterns")(lambda spark, d, n=_name: W.patterns_of(spark, d, n))


def _item_freq(spark, d, name):
    k = SPECS[name].k
    found = patterns.frequency(W.patterns_of(spark, d, name), patterns.itemset_table(spark, [1 << i for i in range(k)]))
    return found.select(patterns.label("mask", k).alias("itemset"), "support", F.round("fr", 6).alias("fr"))


for _name in ("custsize", "size", "hour", "brand"):
    query(O.item_freq_sql(_name), f"enc_{_name}_item_freq")(lambda spark, d, n=_name: _item_freq(spark, d, n))

_TOKENS = "SELECT label, CAST(count(*) AS BIGINT) AS n_docs FROM (SELECT unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]{{4,}}'))) AS label FROM {t}) AS u GROUP BY label ORDER BY n_docs DESC, label LIMIT {k}"


@query(_TOKENS.format(t="documents", k=15))
def enc_word_catalog(spark, d):
    return encode.words_catalog(load(spark, d, "documents"), 15).select("label", "n_docs")


@query(_TOKENS.format(t="benchmark", k=15))
def enc_bench_item_freq(spark, d):
    return encode.words_catalog(load(spark, d, "benchmark"), 15).select("label", "n_docs")


@query(f"""WITH top AS (SELECT label, row_number() OVER (ORDER BY n_docs DESC, label) - 1 AS o FROM ({_TOKENS.format(t='documents', k=15)}) AS c),
tok AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]{{4,}}'))) AS label FROM documents),
b AS (SELECT doc_id, bit_or(CAST(1 << CAST(o AS INT) AS BIGINT)) AS mask FROM tok JOIN top USING (label) GROUP BY doc_id)
SELECT mask, CAST(count(*) AS BIGINT) AS n FROM b GROUP BY mask""")
def enc_word15_patterns(spark, d):
    return patterns.compress(encode.word_baskets(load(spark, d, "documents"), 15))


@query(f"""WITH top AS (SELECT label FROM ({_TOKENS.format(t='documents', k=90)}) AS c),
tok AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]{{4,}}'))) AS label FROM documents),
b AS (SELECT doc_id, count(*) AS items FROM tok JOIN top USING (label) GROUP BY doc_id)
SELECT CAST(items AS BIGINT) AS items, CAST(count(*) AS BIGINT) AS n FROM b GROUP BY items""")
def enc_word90_wide_sizes(spark, d):
    wide = encode.word_baskets(load(spark, d, "documents"), 90)
    return wide.select(F.aggregate("words", F.lit(0), lambda a, w: a + F.bit_count(w)).cast("bigint").alias("items")).groupBy("items").agg(F.count("*").alias("n"))


@query("""WITH b AS (%s) SELECT CAST(i AS INT) AS pair, round(avg(CASE WHEN ((mask >> (i - 1)) & 1) = ((mask >> i) & 1) THEN 1.0 ELSE 0.0 END), 6) AS agreement
FROM b, (SELECT unnest(range(1, 15)) AS i) AS r GROUP BY i""" % SPECS["path_10000"].duckdb())
def synth_path_agreement(spark, d):
    pairs = spark.range(1, 15).select(F.col("id").cast("int").alias("pair"))
    same = F.getbit("mask", F.col("pair") - 1) == F.getbit("mask", F.col("pair"))
    p = W.patterns_of(spark, d, "path_10000").crossJoin(F.broadcast(pairs))
    return p.groupBy("pair").agg(F.round(F.sum(F.when(same, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias("agreement"))


# -- counts and entropies ---------------------------------------------------------------------------

_SETS8 = [m for m in range(1, 256) if m.bit_count() <= 3]


@query(f"WITH {O.patterns_cte('line')}, {O.itemsets_cte(_SETS8)}, {O.SUPPORT} SELECT itemset, size, support FROM s")
def itemset_support(spark, d):
    return _named(patterns.support(W.patterns_of(spark, d, "line"), patterns.itemset_table(spark, _SETS8)), "support")


@query(f"WITH {O.patterns_cte('cust')}, {O.itemsets_cte(_SETS8)}, {O.SUPPORT} SELECT itemset, size, support, round(support / total, 6) AS fr FROM s")
def itemset_frequency(spark, d):
    return _named(patterns.frequency(W.patterns_of(spark, d, "cust"), patterns.itemset_table(spark, _SETS8)), "support", F.round("fr", 6).alias("fr"))


_CELL_SQL = f"WITH {O.patterns_cte('word5')}, {O.itemsets_cte(ALL5)}, {O.CELLS} SELECT itemset, cell, n FROM cells"


@query(_CELL_SQL)
def projection_cells(spark, d):
    return patterns.cells(W.patterns_of(spark, d, "word5"), patterns.itemset_table(spark, ALL5)).select(patterns.label("x", 5).alias("itemset"), "cell", "n")


@query(_CELL_SQL)
def cells_by_inclusion_exclusion(spark, d):
    s = patterns.support(W.patterns_of(spark, d, "word5"), patterns.itemset_table(spark, [0, *ALL5]))
    return patterns.cells_from_frequencies(s, 5).select(patterns.label("x", 5).alias("itemset"), "cell", "n")


@query(f"WITH {O.patterns_cte('word5')} SELECT CAST(x AS BIGINT) AS x, mask & x AS cell, CAST(sum(n) AS BIGINT) AS n FROM p, (SELECT unnest(range(0, 32)) AS x) AS r GROUP BY 1, 2")
def cells_by_cube(spark, d):
    p = W.patterns_of(spark, d, "word5").select("n", *(F.getbit("mask", F.lit(i)).cast("bigint").alias(f"a{i}") for i in range(5)))
    c = p.cube(*(f"a{i}" for i in range(5))).agg(F.sum("n").alias("n"), F.grouping_id().alias("gid"))
    x = sum((F.when(F.getbit("gid", F.lit(4 - i)) == 0, F.lit(1 << i)).otherwise(F.lit(0)) for i in range(5)), F.lit(0))
    cell = sum((F.coalesce(F.col(f"a{i}"), F.lit(0)) * (1 << i) for i in range(5)), F.lit(0))
    return c.select(x.cast("bigint").alias("x"), cell.cast("bigint").alias("cell"), "n")


@query(f"WITH {O.patterns_cte('line5')}, total AS (SELECT sum(n) AS n FROM p) SELECT CAST(r.m AS BIGINT) AS mask, round(coalesce(p.n, 0) / total.n * 0.99 + 0.01 / 32, 6) AS p FROM (SELECT unnest(range(0, 32)) AS m) AS r LEFT JOIN p ON p.mask = r.m CROSS JOIN total")
def smoothed_cells(spark, d):
    return patterns.smooth(W.patterns_of(spark, d, "line5"), 5, 0.01).select("mask", F.round("p", 6).alias("p"))


_ENTROPY_SQL = O.entropy_sql(O.patterns_cte("word5"), ALL5)
for _name, _method in (("entropy_hash", "hash_agg"), ("entropy_sort_scan", "sort_scan"), ("entropy_batch", "batch"), ("entropy_from_support", "from_support")):
    query(_ENTROPY_SQL, _name)(lambda spark, d, m=_method: _named(entropy.entropy(W.patterns_of(spark, d, "word5"), patterns.itemset_table(spark, ALL5), m, 5), (F.round("h", 6) + 0.0).alias("h")))


def _mi_sql(name: str, k: int) -> str:
    masks = [1 << i for i in range(k)] + [1 << i | 1 << j for i in range(k) for j in range(i)]
    return f"""WITH {O.patterns_cte(name)}, {O.itemsets_cte(masks)}, {O.CELLS}, {O.ENTROPY}
SELECT CAST(a.itemset AS INT) AS x, CAST(b.itemset AS INT) AS y, round(abs(a.h + b.h - c.h), 6) AS mi FROM h AS a JOIN h AS b ON a.size = 1 AND b.size = 1 AND a.x < b.x JOIN h AS c ON c.x = (a.x | b.x)"""


@query(_mi_sql("line", 8))
def mutual_information_pairs(spark, d):
    return baselines.pair_information(W.patterns_of(spark, d, "line"), 8).select("x", "y", F.round("mi", 6).alias("mi"))


_TRIPLES = [1 << a | 1 << b | 1 << c for a, b, c in combinations(range(5), 3)]


@query(f"""WITH {O.patterns_cte('word5')}, {O.itemsets_cte(ALL5)}, {O.CELLS}, {O.ENTROPY}, total AS (SELECT sum(n) AS n FROM p)
SELECT t.itemset, i.itemset || ',' || j.itemset AS pair, round(total.n * (t.h - a.h - b.h + c.h), 4) + 0.0 AS gain
FROM h AS t JOIN h AS i ON t.size = 3 AND i.size = 1 AND i.x & t.x = i.x JOIN h AS j ON j.size = 1 AND j.x & t.x = j.x AND i.x < j.x
JOIN h AS a ON a.x = xor(t.x, i.x) JOIN h AS b ON b.x = xor(t.x, j.x) JOIN h AS c ON c.x = xor(xor(t.x, i.x), j.x) CROSS JOIN total""")
def gain_triples(spark, d):
    p = W.patterns_of(spark, d, "word5")
    n = patterns.total(p)
    h = entropy.entropy(p, patterns.itemset_table(spark, ALL5)).select("mask", "h")
    rows = [(t, x, y) for t in _TRIPLES for x, y in combinations(family.bits(t), 2)]
    want = _rows(spark, [(family.canonical(t), f"{x.bit_length()},{y.bit_length()}", t, t ^ x, t ^ y, t ^ x ^ y) for t, x, y in rows], "itemset string, pair string, t bigint, a bigint, b bigint, c bigint")
    for c in "tabc":
        want = want.join(F.broadcast(h.select(F.col("mask").alias(c), F.col("h").alias(f"h{c}"))), c)
    return want.select("itemset", "pair", (F.round(n * (F.col("ht") - F.col("ha") - F.col("hb") + F.col("hc")), 4) + 0.0).alias("gain"))


# -- families and moves -----------------------------------------------------------------------------

_FAMILIES = {1: F1, 2: F2, 3: F3}


def _family_values() -> str:
    return ", ".join(f"({i}, {m})" for i, f in _FAMILIES.items() for m in f)


#: What a customer orders in a year is a basket of five priorities; the baskets of a customer span a family.
_YEARS = f"SELECT o_custkey AS model_id, CAST(bit_or(CASE substr(o_orderpriority, 1, 1) {' '.join(f"WHEN '{i + 1}' THEN {1 << i}" for i in range(5))} ELSE 0 END) AS BIGINT) AS m FROM {{orders}} GROUP BY o_custkey, year(o_orderdate)"
_YEARS_CTE = f"y AS ({_YEARS.format(orders='orders')})"


def customer_families(spark, d):
    """(model_id, maximal) of every customer; sets that lie in another one are among them."""
    years = spark.sql(_YEARS, orders=load(spark, d, "orders"))
    return years.groupBy("model_id").agg(F.collect_set("m").alias("maximal"))


@query(f"WITH {_YEARS_CTE} SELECT DISTINCT CAST(model_id AS BIGINT) AS model_id, CAST(x AS BIGINT) AS mask FROM y, (SELECT unnest(range(1, 32)) AS x) AS r WHERE m & x = x")
def closure_members(spark, d):
    """Members of the family that each customer's years span."""
    return bic.members(customer_families(spark, d), 5)


@query(f"SELECT CAST(model_id AS BIGINT) AS model_id, CAST(m AS BIGINT) AS mask FROM (VALUES {_family_values()}) AS t(model_id, m)")
def maximal_sets(spark, d):
    every = bic.members(bic.model_rows(spark, _FAMILIES), 5)
    above = every.select(F.col("model_id").alias("other"), F.col("mask").alias("m"))
    return every.join(above, (F.col("model_id") == F.col("other")) & (F.col("mask").bitwiseAND(F.col("m")) == F.col("mask")) & (F.col("m") != F.col("mask")), "left_anti")


@query(f"""WITH {_YEARS_CTE}, b AS (SELECT DISTINCT model_id, m FROM y), gaps AS (SELECT b.model_id, xor(b.m, i.i) AS m FROM b, (VALUES (1), (2), (4), (8), (16)) AS i(i) WHERE b.m & i.i <> 0 AND b.m <> i.i)
SELECT CAST(b.model_id AS BIGINT) AS model_id, TRUE AS closed, b.model_id NOT IN (SELECT model_id FROM (SELECT * FROM gaps EXCEPT SELECT * FROM b) AS g) AS baskets_closed FROM b GROUP BY b.model_id""")
def downward_closed_check(spark, d):
    """Whether the family that a customer's years span is downward closed, and whether the baskets alone are."""

    @F.pandas_udf("closed boolean, baskets_closed boolean")
    def check(sets: pd.Series) -> pd.DataFrame:
        made = [(family.is_downward_closed(family.closure(map(int, f))), family.is_downward_closed(map(int, f))) for f in sets]
        return pd.DataFrame(made, columns=["closed", "baskets_closed"])

    found = customer_families(spark, d).select("model_id", check("maximal").alias("c"))
    return found.select("model_id", "c.closed", "c.baskets_closed")


@query(f"WITH m AS (SELECT * FROM (VALUES {_family_values()}) AS t(model_id, m)) SELECT CAST(model_id AS BIGINT) AS model_id, CAST(count(DISTINCT x) AS BIGINT) AS family_size FROM m, (SELECT unnest(range(0, 32)) AS x) AS r WHERE m & x = x GROUP BY model_id")
def family_size(spark, d):
    from .functions.udfs import family_size as size

    return bic.model_rows(spark, _FAMILIES).select("model_id", size("maximal").alias("family_size"))


@query(_values([(1, mask_of(s)) for s in ((2,), (2,), (4,))] + [(2, mask_of((2,))), (2, mask_of((4,))), (3, mask_of((2,))), (3, mask_of((3, 4)))], "model_id, separator", "CAST(model_id AS BIGINT) AS model_id, CAST(separator AS BIGINT) AS separator"))
def junction_separators(spark, d):
    return bic.model_rows(spark, _FAMILIES).select("model_id", F.explode("separators").alias("separator"))


def _customer_graph(k: int) -> str:
    """SELECT of (model_id, g) from y: pairs of the first k items that a customer has in one year, as a graph number."""
    bits = " + ".join(f"max(CASE WHEN m & {1 << i | 1 << j} = {1 << i | 1 << j} THEN {1 << n} ELSE 0 END)" for n, (i, j) in enumerate(catalogue.pair_list(k)))
    return f"SELECT model_id, CAST({bits} AS BIGINT) AS g FROM y GROUP BY model_id"


def customer_graphs(spark, d, k):
    """(g, customers): how many customers have a graph."""
    found = spark.sql(f"WITH y AS ({_YEARS}) {_customer_graph(k)}", orders=load(spark, d, "orders"))
    return found.groupBy("g").agg(F.count("*").alias("customers"))


def _catalogue_sql(k: int) -> str:
    return f"""WITH {O._graphs(k)}, {_YEARS_CTE}, c AS (SELECT g, count(*) AS n FROM ({_customer_graph(k)}) AS t GROUP BY g)
SELECT CAST(bit_count(g.g) AS INT) AS pairs, CAST(count(*) AS BIGINT) AS families, CAST(count(c.g) AS BIGINT) AS met, CAST(coalesce(sum(c.n), 0) AS BIGINT) AS customers FROM g LEFT JOIN c ON c.g = g.g GROUP BY 1"""


def _catalogue(spark, d, k):
    """Decomposable families by number of pairs: all, those that some customer has, and how many customers have one."""
    both = catalogue.graphs(spark, k).join(customer_graphs(spark, d, k), "g", "left")
    return both.groupBy(F.bit_count("g").cast("int").alias("pairs")).agg(F.count("*").alias("families"), F.count("customers").alias("met"), F.coalesce(F.sum("customers"), F.lit(0)).alias("customers"))


for _k in (3, 4, 5):
    query(_catalogue_sql(_k), f"decomposable_catalogue_k{_k}")(lambda spark, d, k=_k: _catalogue(spark, d, k))

def _legal_sql(k: int, drop: bool) -> str:
    """Graphs and pairs whose change keeps the graph free of chordless cycles."""
    op = "g.g & e <> 0" if drop else "g.g & e = 0"
    pairs = ", ".join(f"({1 << i})" for i in range(len(catalogue.pair_list(k))))
    return f"""WITH {O._graphs(k)} SELECT CAST(g.g AS BIGINT) AS g, CAST(count(*) AS BIGINT) AS moves FROM g, (VALUES {pairs}) AS t(e)
WHERE {op} AND xor(g.g, e) IN (SELECT g FROM g) GROUP BY g.g"""


def _graph_number(maxs: list[int], k: int) -> int:
    g = 0
    for m in maxs:
        g |= catalogue.edge_mask(m, k)
    return g


def _legal(spark, k, count):
    rows = [(_graph_number(f, k), count(f)) for f in catalogue.decomposable(k)]
    return _rows(spark, [r for r in rows if r[1]], "g bigint, moves bigint")


query(_legal_sql(4, True), "split_legality_k4")(lambda spark, d: _legal(spark, 4, lambda f: len(moves.legal_splits(f))))
query(_legal_sql(4, False), "merge_legality_k4")(lambda spark, d: _legal(spark, 4, lambda f: len(moves.legal_merges(f))))


_CUSTOMER_GRAPHS = f"""WITH {O._graphs(5)}, {_YEARS_CTE}, c AS (SELECT g, count(*) AS n FROM ({_customer_graph(5)}) AS t GROUP BY g), e AS (SELECT * FROM (VALUES {', '.join(f'({1 << i})' for i in range(10))}) AS t(e))"""


def _of_graphs(found: DataFrame, fn: Callable[[list[int]], int], name: str) -> DataFrame:
    """found(g, customers) with fn of the family of each decomposable graph of five items; the others go."""

    @F.pandas_udf("bigint")
    def value(g: pd.Series) -> pd.Series:
        made = []
        for n in map(int, g):
            near = {1 << i: 0 for i in range(5)}
            for at, (i, j) in enumerate(catalogue.pair_list(5)):
                if n >> at & 1:
                    near[1 << i] |= 1 << j
                    near[1 << j] |= 1 << i
            made.append(fn(family.cliques(near)) if family.is_chordal(near) else None)
        return pd.Series(made, dtype="Int64")

    return found.withColumn(name, value("g")).filter(F.col(name).isNotNull())


@query(f"{_CUSTOMER_GRAPHS} SELECT CAST(c.g AS BIGINT) AS g, CAST(c.n AS BIGINT) AS customers, CAST(count(*) AS BIGINT) AS degree FROM c, e WHERE c.g IN (SELECT g FROM g) AND xor(c.g, e.e) IN (SELECT g FROM g) GROUP BY c.g, c.n")
def degree_equals_edge_flips(spark, d):
    """Legal moves of every decomposable family that customers have."""
    return _of_graphs(customer_graphs(spark, d, 5), lambda f: moves.degrees(f)[2], "degree").select("g", "customers", "degree")


@query(f"""WITH m AS (SELECT * FROM (VALUES {_family_values()}) AS t(model_id, m)), i AS (SELECT unnest(range(0, 5)) AS i)
SELECT CAST(model_id AS BIGINT) AS model_id, CAST(a.i + 1 AS INT) AS x, CAST(b.i + 1 AS INT) AS y, CAST(count(*) AS BIGINT) AS n FROM m, i AS a, i AS b
WHERE a.i < b.i AND (m >> CAST(a.i AS INT)) & 1 = 1 AND (m >> CAST(b.i AS INT)) & 1 = 1 GROUP BY 1, 2, 3""")
def occurrence_table(spark, d):
    sets = bic.model_rows(spark, _FAMILIES).select("model_id", F.explode("maximal").alias("m"))
    items = F.filter(F.sequence(F.lit(1), F.lit(5)), lambda i: F.getbit("m", i - 1) == 1)
    pairs = sets.select("model_id", items.alias("all"), F.explode(items).alias("x")).select("model_id", "x", F.explode("all").alias("y")).filter("x < y")
    return pairs.groupBy("model_id", "x", "y").agg(F.count("*").alias("n"))


_REDUCED = [(1, "2", "1"), (1, "2", "3"), (1, "2", "4"), (1, "4", "2"), (1, "4", "5"), (2, "2", "1"), (2, "2", "3-4"), (2, "4", "2-3"), (2, "4", "5"), (3, "2", "1"), (3, "2", "3-4"), (3, "3-4", "2"), (3, "3-4", "5")]
_ASKED = [(1, 2), (1, 8), (2, 2), (2, 8), (3, 2), (3, 12)]


@query(_values(_REDUCED, "model_id, s, part", "CAST(model_id AS BIGINT) AS model_id, s, part"))
def reduced_family_toy(spark, d):
    return _rows(spark, [(i, family.canonical(s), family.canonical(p)) for i, s in _ASKED for p in moves.reduced_family(_FAMILIES[i], s)], "model_id bigint, s string, part string")


@query(_values([(0, "1-2 2-3 2-4 4-5"), (1, "1-2 2-3-4 4-5"), (2, "1-2 2-3-4 3-4-5"), (3, "1-2 2-3-4 4-5"), (4, "1-2 2-3 2-4 4-5")], "step, family", "CAST(step AS INT) AS step, family"))
def toy_move_path(spark, d):
    now, made = F1, []
    path = [("merge", 2, 4, 8), ("merge", 8, 4, 16), ("split", mask_of((3, 4, 5)), 4, 16), ("split", mask_of((2, 3, 4)), 4, 8)]
    for i in range(len(path) + 1):
        made.append((i, " ".join(sorted(map(family.canonical, now)))))
        if i < len(path):
            op, s, x, y = path[i]
            now = (moves.merge if op == "merge" else moves.split)(now, s, x, y)
    return _rows(spark, made, "step int, family string")


@query(_values([(3, True), (4, True), (5, True)], "k, ok", "CAST(k AS INT) AS k, ok"))
def paths_to_independence(spark, d):
    """Every family reaches the single items by splits, and has at most K maximal sets and K - 1 joints."""

    def fine(f, k):
        now = f
        for step in moves.path_to_independence(f):
            now = moves.split(now, *step)
        outcomes = [tuple(moves.merge(f, *m)) for m in moves.legal_merges(f)]
        return now == family.singletons(k) and len(f) <= k and len(moves.joints(f)) <= k - 1 and len(set(outcomes)) == len(outcomes)

    return _rows(spark, [(k, all(fine(f, k) for f in catalogue.decomposable(k))) for k in (3, 4, 5)], "k int, ok boolean")


# -- models -----------------------------------------------------------------------------------------

_TWO = {0: W.EXAMPLE_TREE, 1: family.singletons(5)}


def _two_values() -> str:
    return ", ".join(f"({i}, {x})" for i, f in _TWO.items() for x in sorted(family.closure(f)) if x)


def _two_bic(cte: str) -> str:
    return f"""WITH {cte}, {O._weights(5)}, m AS (SELECT * FROM (VALUES {_two_values()}) AS t(model_id, x)),
b AS (SELECT model_id, sum(w) AS b, count(*) AS c FROM m JOIN w USING (x) GROUP BY model_id)"""


@query(f"""{_two_bic(O.example_cte())}, e AS (SELECT model_id, exp(b - (SELECT max(b) FROM b)) AS e FROM b)
SELECT xs.itemset, xs.size, round(coalesce(sum(e.e) / (SELECT sum(e) FROM e), 0), 6) + 0.0 AS score FROM xs LEFT JOIN m USING (x) LEFT JOIN e USING (model_id) GROUP BY xs.itemset, xs.size""")
def two_model_example(spark, d):
    return _named(W.two_model_example(spark), (F.round("score", 6) + 0.0).alias("score"))


def _fixed_bic(p, spark, models):
    return bic.score_models(bic.model_rows(spark, models), entropy.entropy(p, bic.required(bic.model_rows(spark, models))), patterns.total(p))


@query(f"{_two_bic(O.patterns_cte('word5_en'))} SELECT CAST(model_id AS BIGINT) AS model_id, round(b + 0.5 * ln(total.n) * c, 4) AS log_lik FROM b, total")
def loglik_tree_vs_independence(spark, d):
    return _fixed_bic(W.patterns_of(spark, d, "word5_en"), spark, _TWO).select("model_id", F.round("log_lik", 4).alias("log_lik"))


@query(f"{_two_bic(O.patterns_cte('word5'))} SELECT CAST(model_id AS BIGINT) AS model_id, round(b, 4) AS log_bic FROM b")
def loglik_mobius_equals_tree(spark, d):
    """Weights summed over members, in Spark too; the same as by junction trees."""
    p = W.patterns_of(spark, d, "word5")
    w = entropy.mobius_weights(entropy.entropy(p, patterns.itemset_table(spark, ALL5)), patterns.total(p), 5)
    return bic.log_bic_by_members(bic.model_rows(spark, _TWO), w, 5).select("model_id", F.round("log_bic", 4).alias("log_bic"))


@query(f"""{_two_bic(O.patterns_cte('cust5'))}, s AS (SELECT 'saturated' AS name, sum(w) AS b FROM w), i AS (SELECT 'independence' AS name, sum(w) AS b FROM w WHERE size = 1)
SELECT name, round(b, 4) AS log_bic FROM s UNION ALL SELECT name, round(b, 4) AS log_bic FROM i""")
def bic_fixed_models(spark, d):
    return baselines.fixed_models(W.patterns_of(spark, d, "cust5"), 5).filter("name <> 'tree'").select("name", F.round("log_bic", 4).alias("log_bic"))


@query(_values([(f"{i}-{i + 1}",) for i in range(1, 15)], "edge", "edge"))
def best_tree_edges(spark, d):
    """The tree of greatest pair information of the chained synthetic set is its chain."""
    found = {(r.x, r.y): r.mi for r in baselines.pair_information(W.patterns_of(spark, d, "path_10000"), 15).collect()}
    return _rows(spark, [(f"{a}-{b}",) for a, b in family.best_tree(found, 15)], "edge string")


@query(f"""WITH {O.patterns_cte('word5')}, total AS (SELECT sum(n) AS n FROM p), m AS (SELECT p.mask, p.n, f.m, f.sign FROM p, (VALUES (3, 1), (6, 1), (10, 1), (24, 1), (2, -1), (2, -1), (8, -1)) AS f(m, sign)),
c AS (SELECT f.m, p.mask & f.m AS cell, sum(p.n) AS cn FROM p, (VALUES (3), (6), (10), (24), (2), (8)) AS f(m) GROUP BY 1, 2),
d AS (SELECT m.mask, any_value(m.n) AS n, exp(sum(m.sign * ln(c.cn / total.n))) AS p FROM m JOIN c ON c.m = m.m AND c.cell = m.mask & m.m CROSS JOIN total GROUP BY m.mask)
SELECT mask, n, round(p, 6) AS p FROM d""")
def decomposable_density(spark, d):
    return expmodel.decomposable_density(W.patterns_of(spark, d, "word5"), W.EXAMPLE_TREE).select("mask", "n", F.round("p", 6).alias("p"))


@query(f"""WITH {O.patterns_cte('line5')}, total AS (SELECT sum(n) AS n FROM p), f AS (SELECT i, sum(CASE WHEN mask & i = i THEN n ELSE 0 END) / (SELECT n FROM total) AS f FROM p, (VALUES (1), (2), (4), (8), (16)) AS t(i) GROUP BY i),
q AS (SELECT mask, any_value(p.n) / (SELECT n FROM total) AS a, sum(ln(CASE WHEN mask & i = i THEN f ELSE 1 - f END)) AS lb FROM p, f GROUP BY mask)
SELECT round(sum(a * (ln(a) - lb)), 6) AS kl FROM q""")
def kl_independence(spark, d):
    p = W.patterns_of(spark, d, "line5")
    n = patterns.total(p)
    q = expmodel.decomposable_density(p, family.singletons(5)).select("mask", "p")
    return expmodel.kl(p.select("mask", (F.col("n") / n).alias("p")), q).select(F.round("kl", 6).alias("kl"))


@query(_values([("tree", True), ("triples", True), ("independence", True)], "model, ok", "model, ok"))
def ipf_equals_closed_form(spark, d):
    q = expmodel.empirical(W.patterns_of(spark, d, "word5"), 5)
    made = []
    for name, f in (("tree", W.EXAMPLE_TREE), ("triples", F3), ("independence", family.singletons(5))):
        p, _ = expmodel.fit_ipf(q, f)
        same = abs(p - expmodel.closed_form(q, f)).max() < 1e-6
        margins = all(abs(expmodel.marginal(p, m) - expmodel.marginal(q, m)).max() < 1e-6 for m in f)
        made.append((name, bool(same and margins)))
    return _rows(spark, made, "model string, ok boolean")


@query(_values([(f, True) for f in ("sums_to_one", "monotone", "singletons")], "check_, ok", "check_ AS \"check\", ok"))
def general_vs_decomposable_k3(spark, d):
    rows = {r.mask: r for r in W.general_and_decomposable(spark, 3).collect()}
    mono = all(rows[a].general + 1e-9 >= rows[b].general for a in rows for b in rows if a & b == a)
    single = all(abs(rows[1 << i].general - 1) < 1e-9 for i in range(3))
    return _rows(spark, [("sums_to_one", all(0 <= r.general <= 1 + 1e-9 for r in rows.values())), ("monotone", mono), ("singletons", single)], "check string, ok boolean")


@query("SELECT CAST(m AS BIGINT) AS mask, round(exp(s) / sum(exp(s)) OVER (), 6) AS p FROM (SELECT m, CASE WHEN m & 1 = 1 THEN 0.5 ELSE 0 END + CASE WHEN m & 3 = 3 THEN -1.25 ELSE 0 END + CASE WHEN m & 12 = 12 THEN 2 ELSE 0 END AS s FROM (SELECT unnest(range(0, 16)) AS m) AS r) AS t")
def exponential_density(spark, d):
    return expmodel.density(spark, 4, {1: 0.5, 3: -1.25, 12: 2.0}).select("mask", F.round("p", 6).alias("p"))


# -- exact scores -----------------------------------------------------------------------------------


def _exact(spark, p):
    return score.named(score.exact_decomposable(p, 5), 5)


#: The worked example's job on orders of lines; the nine rows themselves are in the tests.
query(O.exact_score_sql(O.patterns_cte("lines5"), 5), "exact_score_ex9")(lambda spark, d: _exact(spark, W.patterns_of(spark, d, "lines5")))
for _name in ("word5", "word5_en", "line5", "cust5", "ord5", "userday_all"):
    query(O.exact_score_sql(O.patterns_cte(_name), 5), f"exact_score_{_name}")(lambda spark, d, n=_name: _exact(spark, W.patterns_of(spark, d, n)))


@query("SELECT CAST(0 AS BIGINT) AS x, CAST(0 AS BIGINT) AS y WHERE FALSE")
def exact_score_monotone(spark, d):
    return score.monotone_violations(score.exact_decomposable(W.patterns_of(spark, d, "word5"), 5)).select("x", "y")


# -- sampling ---------------------------------------------------------------------------------------


def _verdict(spark, p, chains=400, steps=805):
    """Sampled scores within four standard errors (and a little) of the exact ones."""
    exact = score.exact_decomposable(p, 5)
    found = score.estimate(sampler.sample_models(p, 5, chains, steps, 11), 5).select("mask", F.col("score").alias("s"))
    se = F.sqrt(F.col("score") * (1 - F.col("score")) / chains)
    return exact.join(found, "mask", "left").select(patterns.label("mask", 5).alias("itemset"), (F.abs(F.col("score") - F.coalesce("s", F.lit(0.0))) <= 4 * se + 0.01).alias("ok"))


query(O.verdict_sql(O.patterns_cte("word5_en"), 5), "mcmc_vs_exact_word5_en")(lambda spark, d: _verdict(spark, W.patterns_of(spark, d, "word5_en")))
query(O.verdict_sql(O.patterns_cte("cust5"), 5), "mcmc_vs_exact_cust5")(lambda spark, d: _verdict(spark, W.patterns_of(spark, d, "cust5")))
query(O.verdict_sql(O.example_cte(), 5), "mcmc_vs_exact_ex9")(lambda spark, d: _verdict(spark, patterns.compress(example(spark))))


def _ideal(spark, d, name, sigma=0.2):
    """Itemsets above sigma, which must be the family the set was made from."""
    found = score.estimate(W.sampled(spark, d, name, CHAINS), SPECS[name].k)
    return found.filter(F.col("score") > sigma).select(patterns.label("mask", 16).alias("itemset"), F.lit(True).alias("ok"))


for _name, _query in (("ind_10000", "mcmc_ind_ideal"), ("path_10000", "mcmc_path_ideal"), ("thermo", "mcmc_thermo_chain"), ("planted_10000", "mcmc_planted_pair")):
    query(_values([(family.canonical(m), True) for m in W.ideal_family(_name)], "itemset, ok", "itemset, ok"), _query)(lambda spark, d, n=_name: _ideal(spark, d, n))


@query(_values([("path_100", 0), ("line", 0)], "name, differing", "name, CAST(differing AS BIGINT) AS differing"))
def mcmc_incremental_equals_rebuild(spark, d):
    """Models of chains with structures kept up to date and with structures built afresh."""
    made = None
    for name in ("path_100", "line"):
        a, b = (W.sampled(spark, d, name, 8, 600, rebuild=r).select("chain_id", F.col("maximal").cast("string").alias("m")) for r in (False, True))
        one = a.exceptAll(b).agg(F.count("*").alias("differing")).select(F.lit(name).alias("name"), "differing")
        made = one if made is None else made.unionByName(one)
    return made


@query(_values([(4, 0), (16, 0)], "partitions, differing", "CAST(partitions AS INT) AS partitions, CAST(differing AS BIGINT) AS differing"))
def mcmc_partition_invariance(spark, d):
    pick = lambda parts: W.sampled(spark, d, "word5", 32, 400, partitions=parts).select("chain_id", F.col("maximal").cast("string").alias("m"))
    made = None
    for parts in (4, 16):
        one = pick(1).exceptAll(pick(parts)).agg(F.count("*").alias("differing")).select(F.lit(parts).alias("partitions"), "differing")
        made = one if made is None else made.unionByName(one)
    return made


@query(_values([(t, n, 0) for t in ("supersteps", "entropies") for n in ("last", "thinned", "bounded")], "tier, draws, differing", "tier, draws, CAST(differing AS BIGINT) AS differing"))
def mcmc_tiers_agree(spark, d):
    """The same chains and draws whether tasks hold patterns, computed entropies, or ask for them in supersteps; eight items."""
    p, made = patterns.compress(to_baskets(spark, d, SPECS["line"])).persist(), None
    for name, options in (("last", {}), ("thinned", {"thin": 40}), ("bounded", {"max_clique": 3})):
        base, *others = (sampler.sample_models(p, 8, 12, 200, 1, tier=t, **options).select("chain_id", "draw", F.col("maximal").cast("string").alias("m")) for t in ("patterns", "supersteps", "entropies"))
        for tier, other in zip(("supersteps", "entropies"), others, strict=True):
            one = base.exceptAll(other).unionByName(other.exceptAll(base)).agg(F.count("*").alias("differing")).select(F.lit(tier).alias("tier"), F.lit(name).alias("draws"), "differing")
            made = one if made is None else made.unionByName(one)
    return made


@query()
def mcmc_diagnostics(spark, d):
    return sampler.diagnostics(W.sampled(spark, d, "path_1000", CHAINS))


@query()
def mcmc_trace_summary(spark, d):
    t = sampler.trace_chains(W.patterns_of(spark, d, "line"), 8, 8, 400, 1)
    return t.groupBy("chain_id").agg(F.count("*").alias("steps"), F.sum(F.col("accepted").cast("int")).alias("accepted"), F.max("deg").alias("max_degree"))


@query(_values([("flip", True), ("thinned", True)], "variant, ok", "variant, ok"))
def mcmc_variants(spark, d):
    """The flip proposal and a thinned long chain estimate the exact scores too."""
    p = patterns.compress(example(spark)).persist()
    exact = {r.mask: r.score for r in score.exact_decomposable(p, 5).collect()}
    made = []
    for name, models in (("flip", sampler.sample_models(p, 5, 400, 805, 5, proposal="flip")), ("thinned", sampler.sample_models(p, 5, 8, 20_000, 5, thin=100))):
        found = {r.mask: r.score for r in score.estimate(models, 5).collect()}
        made.append((name, all(abs(s - found.get(m, 0.0)) < 0.12 for m, s in exact.items())))
    return _rows(spark, made, "variant string, ok boolean")


@query(_values([("singletons", True), ("monotone", True)], "check_, ok", "check_ AS \"check\", ok"))
def mcmc_wide_words(spark, d):
    """90 items, beyond one word of bits: every item scores 1, and no pair less than a triple that holds it."""
    p = patterns.compress(encode.word_baskets(load(spark, d, "documents"), 90))
    found = {tuple(map(int, r.itemset.split("-"))): r.score for r in score.estimate_wide(sampler.sample_models(p, 90, 4, 1500, 3)).collect()}
    single = all(found.get((i,), 0) == 1 for i in range(1, 91))
    mono = all(found[s[:i] + s[i + 1 :]] >= v for s, v in found.items() if len(s) > 1 for i in range(len(s)))
    return _rows(spark, [("singletons", single), ("monotone", mono)], "check string, ok boolean")


@query(_values([("ex9_k3", True)], "space, ok", "space, ok"))
def mcmc_tv_to_exact(spark, d):
    """Total variation between sampled and exact model posteriors over the eight families of three items."""
    p = patterns.compress(example(spark).select(F.col("mask").bitwiseAND(7).alias("mask")))
    families = catalogue.decomposable(3)
    models = bic.model_rows(spark, dict(enumerate(families)))
    exact = score.posterior(bic.score_models(models, entropy.entropy(p, bic.required(models)), patterns.total(p)).select("model_id", "log_bic"))
    keys = _rows(spark, [(i, ",".join(map(str, sorted(f)))) for i, f in enumerate(families)], "model_id bigint, family string")
    found = sampler.sample_models(p, 3, 600, 330, 7).select(F.array_join(F.array_sort(F.transform("maximal", lambda m: m.cast("bigint"))), ",").alias("family"))
    return measures.tv_to_exact(found, exact.join(keys, "model_id").select("family", "p")).select(F.lit("ex9_k3").alias("space"), (F.col("tv") < 0.08).alias("ok"))


# -- mining and measures ----------------------------------------------------------------------------


def fixed_models(spark):
    return _rows(spark, [(i, 0, [str(m) for m in f]) for i, f in enumerate(FIXED)], "chain_id bigint, draw int, maximal array<string>")


_FIXED_SQL = f"""WITH m AS (SELECT * FROM (VALUES {', '.join(f'({i}, {m})' for i, f in enumerate(FIXED) for m in f)}) AS t(id, m)), {O.itemsets_cte(ALL5)},
f AS (SELECT x, size, itemset, CAST(count(DISTINCT id) AS BIGINT) AS hits FROM m, xs WHERE m & x = x GROUP BY ALL), s AS (SELECT *, hits / {len(FIXED)}.0 AS score FROM f)"""


@query(f"{_FIXED_SQL} SELECT itemset, size, hits, round(score, 6) AS score FROM s")
def score_estimate_fixed_models(spark, d):
    return _named(score.estimate(fixed_models(spark), 5), "hits", F.round("score", 6).alias("score"))


@query(f"{_FIXED_SQL} SELECT itemset, round(sqrt(score * (1 - score) / {len(FIXED)}), 6) + 0.0 AS se FROM s")
def score_standard_error(spark, d):
    return score.estimate(fixed_models(spark), 5).select(patterns.label("mask", 5).alias("itemset"), (F.round("se", 6) + 0.0).alias("se"))


for _name, _mine in (("mine_dfs_fixed_models", score.mine_dfs), ("mine_levelwise_fixed_models", score.mine_levelwise), ("mine_explode_fixed_models", score.mine_explode)):
    query(f"{_FIXED_SQL} SELECT itemset, size, hits FROM s WHERE score > 0.3", _name)(lambda spark, d, f=_mine: _named(f(fixed_models(spark), 5, 0.3), "hits", k=5))


@query(f"{O.exact_cte(O.patterns_cte('cust5'), 5)} SELECT xs.itemset, xs.size, round(score, 6) + 0.0 AS score FROM score JOIN xs USING (x) WHERE size = 2 ORDER BY round(score, 6) DESC, itemset LIMIT 4")
def top4_pairs(spark, d):
    return score.top_k(_exact(spark, W.patterns_of(spark, d, "cust5")), 2, 4)


#: Customers' families in place of sampled models: the score of an itemset is the share of customers whose family holds it.
_CUSTOMER_SCORES = f"""WITH {_YEARS_CTE}, {O.itemsets_cte(ALL5)}, f AS (SELECT x, size, itemset, CAST(count(DISTINCT model_id) AS BIGINT) AS hits FROM y, xs WHERE m & x = x GROUP BY ALL),
s AS (SELECT *, hits / (SELECT count(DISTINCT model_id) FROM y) AS score FROM f)"""


def customer_scores(spark, d):
    models = Durable(spark, "customers").save(customer_families(spark, d).select(F.col("model_id").alias("chain_id"), F.lit(0).alias("draw"), "maximal"), "families")
    return score.estimate(models, 5)


@query(f"{_CUSTOMER_SCORES} SELECT CAST(g AS DOUBLE) AS sigma, CAST(count(itemset) AS BIGINT) AS n_itemsets FROM (VALUES (0.05), (0.15), (0.25), (0.45), (0.65), (0.95)) AS t(g) LEFT JOIN s ON score > g GROUP BY g")
def curve_fixed_models(spark, d):
    """The curve of fixed models, which are the customers' families."""
    return measures.curve(customer_scores(spark, d), [0.05, 0.15, 0.25, 0.45, 0.65, 0.95])


@query(f"""{O.exact_cte(O.patterns_cte('word5'), 5)}, k AS (SELECT score.x, xs.size, score.score FROM score JOIN xs USING (x) WHERE size >= 2 AND score >= 0.05),
f AS (SELECT k.x, sum(CASE WHEN mask & k.x = k.x THEN n ELSE 0 END) / sum(n) AS fr FROM p, k GROUP BY k.x)
SELECT CAST(count(*) AS BIGINT) AS n, round(corr(k.score, f.fr), 4) AS corr_fr, round(corr(k.score, h.h), 4) AS corr_h FROM k JOIN f USING (x) JOIN h USING (x)""")
def correlations_exact_word5(spark, d):
    p = W.patterns_of(spark, d, "word5")
    s = score.exact_decomposable(p, 5).withColumn("size", F.bit_count("mask"))
    return measures.correlations(measures.scatter(s, p)).select("n", F.round("corr_fr", 4).alias("corr_fr"), F.round("corr_h", 4).alias("corr_h"))


@query(f"""{_CUSTOMER_SCORES}, i AS (SELECT * FROM (VALUES (3), (6), (10), (24), (1), (2), (4), (8), (16)) AS t(x)), b AS (SELECT i.x AS w, s.x AS f FROM i FULL OUTER JOIN (SELECT x FROM s WHERE score > 0.3) AS s USING (x))
SELECT CAST(count(*) FILTER (w IS NOT NULL AND f IS NOT NULL) AS BIGINT) AS hits, CAST(count(*) FILTER (f IS NULL) AS BIGINT) AS misses, CAST(count(*) FILTER (w IS NULL) AS BIGINT) AS extras FROM b""")
def against_ideal(spark, d):
    """Itemsets in more than 0.3 of the customers' families against the worked example's tree."""
    ideal = [m for m in family.closure(W.EXAMPLE_TREE) if m]
    return measures.against_ideal(customer_scores(spark, d), ideal, 0.3).select("hits", "misses", "extras")


@query(f"{_FIXED_SQL} SELECT itemset, CAST(floor(log2(x)) - floor(log2(x & -x)) AS INT) AS gap FROM s WHERE size = 2")
def index_gap_pairs(spark, d):
    return score.estimate(fixed_models(spark), 5).filter("size = 2").select(patterns.label("mask", 5).alias("itemset"), baselines.index_gap(F.col("mask")).alias("gap"))


@query(f"""{_CUSTOMER_GRAPHS}, x AS (SELECT c.g, c.n, count(*) FILTER (c.g & e.e = 0 AND xor(c.g, e.e) IN (SELECT g FROM g)) AS extensions FROM c, e WHERE c.g IN (SELECT g FROM g) GROUP BY c.g, c.n)
SELECT CAST(extensions AS BIGINT) AS extensions, CAST(count(*) AS BIGINT) AS families, CAST(sum(n) AS BIGINT) AS customers FROM x GROUP BY extensions""")
def candidate_extensions(spark, d):
    """How many itemsets can extend the decomposable families that customers have."""
    found = _of_graphs(customer_graphs(spark, d, 5), measures.candidate_extensions, "extensions")
    return found.groupBy("extensions").agg(F.count("*").alias("families"), F.sum("customers").alias("customers"))


@query("""SELECT CAST(k AS INT) AS k, CAST(ceil(100 * k * ln(k)) AS BIGINT) AS steps, CAST(count(*) AS BIGINT) AS customers
FROM (SELECT count(DISTINCT CAST(o_orderdate AS DATE)) AS k FROM orders GROUP BY o_custkey) AS c GROUP BY k""")
def default_steps(spark, d):
    """Steps of a chain over the days on which a customer orders, by their number."""

    @F.pandas_udf("bigint")
    def steps(k: pd.Series) -> pd.Series:
        return k.map(lambda n: sampler.default_steps(int(n)))

    days = load(spark, d, "orders").groupBy("o_custkey").agg(F.countDistinct(F.col("o_orderdate").cast("date")).cast("int").alias("k"))
    return days.groupBy("k").agg(F.count("*").alias("customers")).select("k", steps("k").alias("steps"), "customers")


#: Chains of the curves; the least threshold, 0.01, is more than two of them.
CURVE_CHAINS = 256
_SYNTHETIC = ("ind_100", "ind_1000", "ind_10000", "path_100", "path_1000", "path_10000")


def _curve_verdicts(spark, name, k, found, sigmas, ideal=None):
    """Checks of a curve that hold for any seed."""
    points = {r.sigma: r.n_itemsets for r in measures.curve(found, sigmas).collect()}  # one row a threshold
    ordered = [points[s] for s in sorted(points)]
    rows = [(name, "falls", ordered == sorted(ordered, reverse=True)), (name, "single items", all(n >= k for n in ordered))]
    if ideal is not None:
        rows.append((name, "ideal from 0.2 on", all(n == ideal for s, n in points.items() if s >= 0.2)))
    return rows


def _curve_rows(names, ideal=()):
    return _values([(n, c, True) for n in names for c in ("falls", "single items", *(("ideal from 0.2 on",) if n in ideal else ()))], "name, check_, ok", 'name, check_ AS "check", ok')


@query(_curve_rows(_SYNTHETIC, ("ind_10000", "path_10000")))
def curve_ind_path(spark, d):
    """How many itemsets score above each threshold, at all three sizes; the large sets reach the ideal numbers."""
    rows = []
    for name in _SYNTHETIC:
        found = score.estimate(W.sampled(spark, d, name, CURVE_CHAINS), 15)
        rows += _curve_verdicts(spark, name, 15, found, W.SIGMAS_SYNTHETIC, len(W.ideal_family(name)) if name.endswith("_10000") else None)
    return _rows(spark, rows, "name string, check string, ok boolean")


@query()
def curve_synthetic_points(spark, d):
    """The points of the same curves."""
    made = None
    for name in _SYNTHETIC:
        one = W.curve_of(spark, d, name, CHAINS, W.SIGMAS_SYNTHETIC).select(F.lit(name).alias("name"), "sigma", "n_itemsets")
        made = one if made is None else made.unionByName(one)
    return made


#: Sets of real data with their chains in the queries.
_REAL = {"words15": 128, "words30": 48, "brand": 48, "size": 8}


@query(_curve_rows(_REAL))
def curve_real(spark, d):
    """The curves of the word, brand and size sets."""
    rows = []
    for name, chains in _REAL.items():
        p, k = W.named_patterns(spark, d, name)
        rows += _curve_verdicts(spark, name, k, score.estimate(sampler.sample_models(p, k, chains, seed=1), k), W.SIGMAS_REAL)
    return _rows(spark, rows, "name string, check string, ok boolean")


@query(_values([("words15", True), ("words30", True), ("size", True), ("path_100", True), ("thermo", True)], "name, ok", "name, ok"))
def correlations_sampled(spark, d):
    """Correlations of sampled scores with frequency, entropy and index gap are numbers from -1 to 1, or null where a side is constant; ordered chains score near pairs higher."""
    rows = []
    for name, chains in {"words15": 128, "words30": 48, "size": 8, "path_100": CHAINS, "thermo": CHAINS}.items():
        p, k = W.named_patterns(spark, d, name)
        r = measures.correlations(measures.scatter(score.estimate(sampler.sample_models(p, k, chains, seed=1), k), p, 0.05)).first()
        ok = all(c is None or -1 - 1e-9 <= c <= 1 + 1e-9 for c in (r.corr_fr, r.corr_h, r.corr_gap))
        rows.append((name, ok and (name not in ("path_100", "thermo") or r.corr_gap is None or r.corr_gap < 0)))
    return _rows(spark, rows, "name string, ok boolean")


@query()
def correlations_points(spark, d):
    """The same correlations as numbers."""
    made = None
    for name in ("words15", "path_100", "cust", "thermo"):
        p, k = W.named_patterns(spark, d, name)
        found = measures.correlations(measures.scatter(score.estimate(sampler.sample_models(p, k, CHAINS, seed=1), k), p, 0.05))
        one = found.select(F.lit(name).alias("name"), "n", "corr_fr", "corr_h", "corr_gap")
        made = one if made is None else made.unionByName(one)
    return made


@query(_values([(i, True) for i in range(1, 5)], "place, ok", "CAST(place AS INT) AS place, ok"))
def top4_words_sampled(spark, d):
    """The four pairs of words with the greatest sampled scores, by name: in order, and none left out scores more."""
    labels = [r.label for r in encode.words_catalog(load(spark, d, "documents"), 15).orderBy("ord").collect()]  # 15 rows
    p, k = W.named_patterns(spark, d, "words15")
    found = score.estimate(sampler.sample_models(p, k, CHAINS, seed=1), k)
    every = sorted((r.score for r in found.filter("size = 2").collect()), reverse=True)  # at most 105 pairs
    top = [(r.score, [labels[i] for i in range(k) if r.mask >> i & 1]) for r in score.top_k(found, 2, 4).collect()]
    return _rows(spark, [(i + 1, s == every[i] and len(set(words)) == 2) for i, (s, words) in enumerate(top)], "place int, ok boolean")


@query(_values([("dfs", 0), ("levelwise", 0)], "miner, differing", "miner, CAST(differing AS BIGINT) AS differing"))
def mine_sampled_agree(spark, d):
    """The miners find the same itemsets of sampled models as counting every member does."""
    p, k = W.named_patterns(spark, d, "words15")
    models, made = sampler.sample_models(p, k, 24, 800, 5), None
    base = score.mine_explode(models, k, 0.1).select("mask", "hits")
    for name, mine in (("dfs", score.mine_dfs), ("levelwise", score.mine_levelwise)):
        other = mine(models, k, 0.1).select("mask", "hits")
        one = base.exceptAll(other).unionByName(other.exceptAll(base)).agg(F.count("*").alias("differing")).select(F.lit(name).alias("miner"), "differing")
        made = one if made is None else made.unionByName(one)
    return made


@query(_values([("up to three items", 0)], "sets, differing", "sets, CAST(differing AS BIGINT) AS differing"))
def mine_wide_words(spark, d):
    """Depth-first mining of 90 items, beyond one word of bits, against counting the members of up to three items."""
    p, k = W.named_patterns(spark, d, "words90")
    models = sampler.sample_models(p, k, 6, 1200, 3)
    found = score.mine_dfs_named(models, k, 0.4).filter("size <= 3").select("itemset", "hits")
    base = score.estimate_wide(models).filter("score > 0.4").select("itemset", "hits")
    return base.exceptAll(found).unionByName(found.exceptAll(base)).agg(F.count("*").alias("differing")).select(F.lit("up to three items").alias("sets"), "differing")


_LOG_PRIOR = -0.75


@query(f"""{O.exact_cte(O.patterns_cte('word5'), 5)}, prior AS (SELECT g, b + {_LOG_PRIOR} * bit_count(g) AS b FROM bic), pe AS (SELECT g, exp(b - (SELECT max(b) FROM prior)) AS e FROM prior)
SELECT xs.itemset, xs.size, round(sum(pe.e) / (SELECT sum(e) FROM pe), 6) + 0.0 AS score FROM held JOIN pe USING (g) JOIN xs USING (x) GROUP BY xs.itemset, xs.size""")
def exact_score_with_prior(spark, d):
    """A model space and a prior of one's own: all decomposable families, each pair of items costing a factor."""
    space = catalogue.decomposable(5)
    prior = [_LOG_PRIOR * len({p for m in f for p in combinations(family.bits(m), 2)}) for f in space]
    return score.named(score.exact_over(W.patterns_of(spark, d, "word5"), space, 5, prior), 5)


@query(f"{_FIXED_SQL} SELECT CAST(id AS BIGINT) AS chain_id FROM m WHERE m & 12 = 12 GROUP BY id")
def explain_holders(spark, d):
    """Which models a score is made of."""
    return score.holders(fixed_models(spark), 12).select("chain_id")


@query(f"WITH {O.patterns_cte('cust')} SELECT '1' AS x, '5' AS y, round(sum(CASE WHEN mask & 1 = 1 THEN n ELSE 0 END) / sum(n), 6) AS fr_x, round(sum(CASE WHEN mask & 17 = 17 THEN n ELSE 0 END) / sum(n), 6) AS fr_xy, round(sum(CASE WHEN mask & 17 = 17 THEN n ELSE 0 END) / sum(CASE WHEN mask & 1 = 1 THEN n ELSE 0 END), 6) AS p_y_given_x FROM p")
def explain_pair(spark, d):
    found = score.explain(W.patterns_of(spark, d, "cust"), _rows(spark, [(1, 16)], "x bigint, y bigint"))
    return found.select(patterns.label("x", 8).alias("x"), patterns.label("y", 8).alias("y"), *(F.round(c, 6).alias(c) for c in ("fr_x", "fr_xy", "p_y_given_x")))


# -- baselines --------------------------------------------------------------------------------------

_FREQ_SQL = f"WITH {O.patterns_cte('line')}, {O.itemsets_cte(list(range(1, 256)))}, {O.SUPPORT} SELECT itemset, size, support FROM s WHERE support >= total * 0.1"


@query(_FREQ_SQL)
def frequent_itemsets(spark, d):
    p = W.patterns_of(spark, d, "line")
    least = -(-patterns.total(p) // 10)
    return _named(baselines.frequent(p, 8, least), "support")


@query(_FREQ_SQL)
def frequent_itemsets_fpgrowth(spark, d):
    p = W.patterns_of(spark, d, "line")
    least = -(-patterns.total(p) // 10)
    return _named(baselines.frequent_fpgrowth(p, 8, least), "support")


@query(O.g_sql(O.patterns_cte("line5"), [m for m in ALL5 if m.bit_count() >= 2]))
def independence_g_statistic(spark, d):
    found = baselines.independence_g(W.patterns_of(spark, d, "line5"), patterns.itemset_table(spark, [m for m in ALL5 if m.bit_count() >= 2]))
    return _named(found, F.round("g", 4).alias("g"), "df")


@query(f"""WITH {O.patterns_cte('cust')}, {O.itemsets_cte([1 << i for i in range(8)])}, {O.SUPPORT}
SELECT a.itemset || '-' || b.itemset AS itemset, round((SELECT sum(n) FROM p WHERE mask & (a.x | b.x) = (a.x | b.x)) * a.total / (a.support * b.support), 6) AS lift FROM s AS a JOIN s AS b ON a.x < b.x
WHERE EXISTS (SELECT 1 FROM p WHERE mask & (a.x | b.x) = (a.x | b.x))""")
def lift_pairs(spark, d):
    found = baselines.independence_g(W.patterns_of(spark, d, "cust"), patterns.itemset_table(spark, [1 << i | 1 << j for i in range(8) for j in range(i)]))
    return found.filter("lift > 0").select(patterns.label("mask", 8).alias("itemset"), F.round("lift", 6).alias("lift"))


@query(f"""WITH g AS ({O.g_sql(O.patterns_cte('planted_10000'), [sum(1 << i for i in c) | 3 for r in (0, 1, 2, 3) for c in combinations(range(2, 8), r)])})
SELECT size, CAST(count(*) AS BIGINT) AS tested, CAST(count(*) FILTER (g > CASE df WHEN 1 THEN 10.827566 WHEN 4 THEN 18.466827 WHEN 11 THEN 31.264134 ELSE 54.051962 END) AS BIGINT) AS significant FROM g GROUP BY size""")
def independence_explosion_count(spark, d):
    """Supersets of one dependent pair among eight items: all of them fail independence, while the score keeps one pair."""
    masks = [sum(1 << i for i in c) | 3 for r in (0, 1, 2, 3) for c in combinations(range(2, 8), r)]
    found = baselines.independence_test(W.patterns_of(spark, d, "planted_10000"), patterns.itemset_table(spark, masks), 0.001)
    return found.groupBy(F.col("size").cast("int").alias("size")).agg(F.count("*").alias("tested"), F.sum(F.col("significant").cast("bigint")).alias("significant"))


# -- relational operators around the methods ----------------------------------------------------------


@query("SELECT event_type, CAST(CAST(ts AS DATE) AS VARCHAR) AS day, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY ROLLUP (event_type, CAST(CAST(ts AS DATE) AS VARCHAR))")
def rel_rollup_events(spark, d):
    return load(spark, d, "events").rollup("event_type", F.to_date("ts").cast("string").alias("day")).agg(F.count("*").alias("n"))


_TYPES = streams.TYPES


@query("SELECT user_id, " + ", ".join(f"CAST(count(*) FILTER (event_type = '{t}') AS BIGINT) AS {t}s" for t in _TYPES) + " FROM events GROUP BY user_id")
def rel_pivot_items(spark, d):
    e = load(spark, d, "events").groupBy("user_id").pivot("event_type", list(_TYPES)).agg(F.count("event_id"))
    return e.select("user_id", *(F.coalesce(t, F.lit(0)).alias(f"{t}s") for t in _TYPES))


@query("SELECT user_id, item, v AS value FROM (SELECT user_id, " + ", ".join(f"CAST(max(CASE WHEN event_type = '{t}' THEN 1 ELSE 0 END) AS INT) AS c{i}" for i, t in enumerate(_TYPES)) + " FROM events GROUP BY user_id) AS t, LATERAL (VALUES " + ", ".join(f"('{t}', c{i})" for i, t in enumerate(_TYPES)) + ") AS u(item, v)")
def rel_unpivot_items(spark, d):
    e = load(spark, d, "events").groupBy("user_id").agg(*(F.max(F.when(F.col("event_type") == t, 1).otherwise(0)).alias(t) for t in _TYPES))
    return e.unpivot("user_id", list(_TYPES), "item", "value")


@query("SELECT event_type, count(DISTINCT user_id) > 0 AS ok, round(quantile_cont(value, 0.5), 4) AS median, round(corr(value, user_id), 4) AS r FROM events GROUP BY event_type")
def rel_quantiles(spark, d):
    """Exact median and correlation; the approximate distinct count and percentile lie near the exact ones."""
    near = F.abs(F.approx_count_distinct("user_id", 0.02) / F.count_distinct("user_id") - 1) < 0.1
    close = F.abs(F.percentile_approx("value", 0.5, 10_000) - F.percentile("value", F.lit(0.5))) <= F.lit(0.02) * (F.max("value") - F.min("value"))
    return load(spark, d, "events").groupBy("event_type").agg((near & close).alias("ok"), F.round(F.percentile("value", F.lit(0.5)), 4).alias("median"), F.round(F.corr("value", "user_id"), 4).alias("r"))


@query("SELECT event_id, lead(event_type) OVER w AS next_type, CAST(sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS around FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def rel_window_moving(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", F.lead("event_type").over(w).alias("next_type"), F.sum(F.lit(1)).over(w.rowsBetween(-2, 1)).alias("around"))


@query("SELECT user_id, CAST(count(DISTINCT event_type) AS BIGINT) AS kinds, CAST(max(c) AS BIGINT) AS most FROM (SELECT user_id, event_type, count(*) AS c FROM events GROUP BY user_id, event_type) AS t GROUP BY user_id")
def fn_maps_of_counts(spark, d):
    """Item counts of a user as a map: its size and its greatest value."""
    counts = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("c"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "c"))).alias("m"))  # one entry a type
    return maps.select("user_id", F.size("m").cast("bigint").alias("kinds"), F.array_max(F.map_values(F.map_filter("m", lambda k, v: v > 0))).alias("most"))


@query(f"{_FIXED_SQL} SELECT CAST(lo AS DOUBLE) AS lo, CAST(hi AS DOUBLE) AS hi, itemset FROM s JOIN (VALUES (0.0, 0.25), (0.25, 0.55), (0.55, 1.01)) AS b(lo, hi) ON score >= lo AND score < hi")
def rel_range_join_sigma(spark, d):
    bands = _rows(spark, [(0.0, 0.25), (0.25, 0.55), (0.55, 1.01)], "lo double, hi double")
    s = score.estimate(fixed_models(spark), 5)
    return s.join(F.broadcast(bands), (F.col("score") >= F.col("lo")) & (F.col("score") < F.col("hi"))).select("lo", "hi", patterns.label("mask", 5).alias("itemset"))


@query("""SELECT e.event_id, s.version FROM events AS e LEFT JOIN (SELECT unnest([1, 2, 3]) AS version, unnest([TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-10', TIMESTAMP '2024-01-20']) AS since) AS s
ON s.since <= e.ts QUALIFY row_number() OVER (PARTITION BY e.event_id ORDER BY s.since DESC) = 1""")
def rel_asof_score(spark, d):
    """The score table that was the last before each event: versions are few, so they ride along as a sorted array."""
    v = spark.sql("SELECT array(struct(timestamp'2024-01-01' AS since, 1 AS version), struct(timestamp'2024-01-10' AS since, 2 AS version), struct(timestamp'2024-01-20' AS since, 3 AS version)) AS v")
    e = load(spark, d, "events").select("event_id", "ts").crossJoin(F.broadcast(v))
    return e.select("event_id", F.element_at(F.filter("v", lambda s: s.since <= F.col("ts")), -1).version.alias("version"))


@query("SELECT DISTINCT user_id FROM events WHERE event_type = 'purchase' EXCEPT SELECT DISTINCT user_id FROM events WHERE event_type = 'error' AND value > 90")
def rel_except_users(spark, d):
    e = load(spark, d, "events")
    return e.filter("event_type = 'purchase'").select("user_id").distinct().subtract(e.filter("event_type = 'error' AND value > 90").select("user_id"))


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1) INTERSECT SELECT doc_id FROM documents WHERE lang = 'en'")
def rel_semi_intersect(spark, d):
    docs, bad = load(spark, d, "documents"), load(spark, d, "labels").filter("toxic = 1")
    return docs.join(bad, "doc_id", "left_semi").select("doc_id").intersect(docs.filter("lang = 'en'").select("doc_id"))


@query("SELECT doc_id FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id)")
def rel_anti_unlabelled(spark, d):
    return load(spark, d, "documents").join(load(spark, d, "labels"), "doc_id", "left_anti").select("doc_id")


@query("SELECT user_id, event_id, CAST(r AS INT) AS r, CAST(n4 AS INT) AS n4, event_type IS NOT DISTINCT FROM p AS same FROM (SELECT user_id, event_id, event_type, row_number() OVER w AS r, ntile(4) OVER w AS n4, lag(event_type) OVER w AS p FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) AS t")
def rel_window_runs(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, d, "events").select("user_id", "event_id", "event_type", F.row_number().over(w).alias("r"), F.ntile(4).over(w).alias("n4"), F.lag("event_type").over(w).alias("p"))
    return e.select("user_id", "event_id", "r", "n4", F.col("event_type").eqNullSafe(F.col("p")).alias("same"))


@query("SELECT event_id, CAST(sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) % 2 AS BIGINT) AS parity FROM events")
def rel_window_prefix_parity(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, d, "events").select("event_id", (F.sum(F.when(F.col("event_type") == "click", 1).otherwise(0)).over(w) % 2).alias("parity"))


@query("SELECT event_type, round(avg(value), 4) AS mean, round(stddev_samp(value), 4) AS sd, round(covar_samp(value, user_id), 4) AS cov FROM events GROUP BY event_type")
def rel_statistics(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.round(F.avg("value"), 4).alias("mean"), F.round(F.stddev_samp("value"), 4).alias("sd"), F.round(F.covar_samp("value", "user_id"), 4).alias("cov"))


@query(f"WITH {O.patterns_cte('custsize')}, {O.itemsets_cte([1 << i for i in range(18)])}, {O.SUPPORT} SELECT itemset FROM s WHERE support > (SELECT avg(support) FROM s)")
def rel_subquery_above_average(spark, d):
    found = patterns.support(W.patterns_of(spark, d, "custsize"), patterns.itemset_table(spark, [1 << i for i in range(18)]))
    return spark.sql("SELECT itemset FROM {s} WHERE support > (SELECT avg(support) FROM {s})", s=found.select(patterns.label("mask", 18).alias("itemset"), "support"))


@query("""WITH RECURSIVE e AS (SELECT * FROM (VALUES (1, 2), (2, 3), (2, 4), (4, 5), (7, 8)) AS t(a, b)), b AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r AS (SELECT DISTINCT a AS item, a AS seen FROM b UNION SELECT r.item, b.b FROM r JOIN b ON b.a = r.seen) SELECT CAST(item AS INT) AS item, CAST(min(seen) AS INT) AS component FROM r GROUP BY item""")
def rel_recursive_components(spark, d):
    """Components of linked items by a recursive query."""
    return spark.sql("""WITH RECURSIVE e(a, b) AS (SELECT * FROM VALUES (1, 2), (2, 3), (2, 4), (4, 5), (7, 8), (2, 1), (3, 2), (4, 2), (5, 4), (8, 7)),
r(item, seen, depth) AS (SELECT DISTINCT a, a, 0 FROM e UNION ALL SELECT r.item, e.b, r.depth + 1 FROM r JOIN e ON e.a = r.seen WHERE r.depth < 5)
SELECT CAST(item AS INT) AS item, CAST(min(seen) AS INT) AS component FROM r GROUP BY item""")


@query("SELECT CAST(count(*) AS BIGINT) AS n, CAST(count(DISTINCT user_id) AS BIGINT) AS users FROM events WHERE coalesce(CAST(json_extract_string(props, '$.k') AS INT), -1) BETWEEN 10 AND 60")
def rel_json_items(spark, d):
    e = load(spark, d, "events").filter(F.coalesce(F.get_json_object("props", "$.k").cast("int"), F.lit(-1)).between(10, 60))
    return e.agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))


@query(_values([("1-2", 3), ("1-2-3", 7), ("1", 1)], "itemset, subsets_", "itemset, CAST(subsets_ AS BIGINT) AS subsets"))
def udtf_subsets(spark, d):
    from .functions.udfs import register

    register(spark)
    return spark.sql("SELECT canonical(m) AS itemset, count(*) AS subsets FROM VALUES (3L), (7L), (1L) AS t(m), LATERAL subsets(m, 3) GROUP BY m")


@query(f"""WITH {O._graphs(5)}, e AS (SELECT * FROM (VALUES {', '.join(f'({1 << i})' for i in range(10))}) AS t(e)), f AS (SELECT * FROM (VALUES {', '.join(f'({i}, {_graph_number(m, 5)})' for i, m in _FAMILIES.items())}) AS t(id, start))
SELECT CAST(id AS INT) AS id, CAST(count(*) AS BIGINT) AS n FROM f, e WHERE xor(f.start, e.e) IN (SELECT g FROM g) GROUP BY id""")
def udtf_legal_moves(spark, d):
    from .functions.udfs import register

    register(spark)
    models = bic.model_rows(spark, _FAMILIES)
    return spark.sql("SELECT CAST(model_id AS INT) AS id, count(*) AS n FROM {m}, LATERAL legal_moves(maximal) GROUP BY model_id", m=models)


@query("SELECT event_type, round(-sum(q * ln(q)), 6) AS h FROM (SELECT event_type, count(*) / sum(count(*)) OVER (PARTITION BY event_type) AS q FROM events GROUP BY event_type, user_id) AS t GROUP BY event_type")
def udaf_entropy(spark, d):
    from .functions.udfs import group_entropy

    return group_entropy(load(spark, d, "events"), "event_type", "user_id").select("event_type", F.round("h", 6).alias("h"))


@query("SELECT a.event_type AS x, b.event_type AS y, CAST(count(*) AS BIGINT) AS users FROM (SELECT DISTINCT user_id, event_type FROM events) AS a JOIN (SELECT DISTINCT user_id, event_type FROM events) AS b ON a.user_id = b.user_id AND a.event_type < b.event_type GROUP BY 1, 2")
def rel_self_join_pairs(spark, d):
    e = load(spark, d, "events").select("user_id", F.col("event_type").alias("x")).distinct()
    return e.join(e.withColumnRenamed("x", "y"), "user_id").filter("x < y").groupBy("x", "y").agg(F.count("*").alias("users"))


@query("SELECT l_returnflag, l_linestatus, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, CAST(grouping(l_linestatus) AS INT) AS total FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag))")
def rel_grouping_sets(spark, d):
    return spark.sql("SELECT l_returnflag, l_linestatus, count(DISTINCT l_partkey) AS parts, CAST(grouping(l_linestatus) AS INT) AS total FROM {t} GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag))", t=load(spark, d, "lineitem"))


# -- streaming ----------------------------------------------------------------------------------------


def _event_stream(spark, d):
    return streams.read_events(spark, f"{d}/events.parquet*")


_EVENT_MASK = " + ".join(f"(CASE WHEN {e} THEN {1 << i} ELSE 0 END)" for i, e in enumerate(streams.ITEMS))
_TYPE_MASK = " + ".join(f"(CASE WHEN event_type = '{t}' THEN {1 << i} ELSE 0 END)" for i, t in enumerate(streams.TYPES))


@query(f"SELECT CAST({_EVENT_MASK} AS BIGINT) AS mask, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1")
def stream_pattern_counts(spark, d):
    return streams.run_to_end(streams.pattern_counts(_event_stream(spark, d)), "pattern_counts")


@query(f"SELECT user_id, date_trunc('day', ts) AS start, bit_or(CAST({_TYPE_MASK} AS BIGINT)) AS mask FROM events GROUP BY 1, 2")
def stream_tumbling_baskets(spark, d):
    return streams.run_to_end(streams.tumbling_baskets(_event_stream(spark, d)), "tumbling_baskets")


@query(f"""WITH e AS (SELECT user_id, ts, CAST({_TYPE_MASK} AS BIGINT) AS m, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM e)
SELECT user_id, min(ts) AS start, bit_or(m) AS mask, CAST(count(*) AS BIGINT) AS events FROM s GROUP BY user_id, session""")
def stream_session_baskets(spark, d):
    return streams.run_to_end(streams.session_baskets(_event_stream(spark, d)), "session_baskets")


@query(f"""WITH w AS (SELECT user_id, {_TYPE_MASK} AS m, date_trunc('hour', ts) - INTERVAL 1 HOUR * (hour(ts) % 6) AS last FROM events)
SELECT user_id, last - INTERVAL 1 HOUR * (6 * i) AS start, bit_or(CAST(m AS BIGINT)) AS mask FROM w, (SELECT unnest(range(0, 4)) AS i) AS r GROUP BY 1, 2""")
def stream_sliding_baskets(spark, d):
    return streams.run_to_end(streams.tumbling_baskets(_event_stream(spark, d), "1 day", "6 hours"), "sliding_baskets")


@query("SELECT event_id, event_type FROM events")
def stream_dedup(spark, d):
    twice = _event_stream(spark, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return streams.run_to_end(streams.deduplicated(twice).select("event_id", "event_type"), "dedup", "append")


@query(f"SELECT CAST(item_id AS INT) AS item_id, CAST(count(*) AS BIGINT) AS n FROM events JOIN (VALUES {', '.join(f'({i}, {chr(39)}{t}{chr(39)})' for i, t in enumerate(streams.TYPES))}) AS c(item_id, event_type) USING (event_type) GROUP BY item_id")
def stream_static_join(spark, d):
    catalog = _rows(spark, [(i, t) for i, t in enumerate(streams.TYPES)], "item_id int, event_type string")
    return streams.run_to_end(streams.with_catalog(_event_stream(spark, d), catalog).groupBy("item_id").agg(F.count("*").alias("n")), "static_join")


@query("SELECT event_type, round(sum(pow(0.5, (epoch(last) - epoch(ts)) / 86400.0)), 3) AS weight FROM events JOIN (SELECT event_type, max(ts) AS last FROM events GROUP BY event_type) AS l USING (event_type) GROUP BY event_type")
def stream_decayed_support(spark, d):
    """Support that halves every day, as of each type's last event."""
    found = streams.run_to_end(streams.decayed_support(_event_stream(spark, d)), "decayed", "update")
    return found.groupBy("event_type").agg(F.round(F.max_by("weight", "last"), 3).alias("weight"))


@query("SELECT 'late users' AS what, CAST(count(DISTINCT user_id) AS BIGINT) AS dropped FROM events")
def stream_late_rows(spark, d):
    """Rows behind the watermark are dropped and counted: after all events, and the last once more, come one of each user from long before."""
    store, events = Durable(spark, "late"), load(spark, d, "events")
    old = events.groupBy("user_id").agg(F.min("event_id").alias("event_id")).select("event_id", F.lit("2020-01-01").cast("timestamp").alias("ts"), "user_id", F.lit("view").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    for part in (events, events.orderBy(F.col("ts").desc()).limit(1), old):  # a batch each; a batch's rows meet the watermark of the one before
        part.coalesce(1).write.mode("append").parquet(store.path("in"))
        time.sleep(1.1)  # files are taken in the order of their times
    progress: list = []
    streams.run_to_end(streams.tumbling_baskets(streams.read_events(spark, store.path("in"))), "late", "append", progress).count()
    return _rows(spark, [("late users", streams.dropped_late(progress))], "what string, dropped bigint")


@query(_values([(str(i), True) for i in range(1, 6)], "itemset, ok", "itemset, ok"))
def stream_rescore(spark, d):
    """The masks of every micro-batch are scored anew: single items score 1 in each."""
    sink = Durable(spark, "rescore").path("scores")
    streams.rescore(_event_stream(spark, d).select(streams.event_mask().alias("mask")), 5, 8, 200, sink).start().awaitTermination()
    found = spark.read.parquet(sink).filter("size = 1").groupBy("mask").agg((F.min("score") == 1).alias("ok"))
    return found.select(patterns.label("mask", 5).alias("itemset"), "ok")


@query()
def general_scores_ex9_k4(spark, d):
    """Scores over all 114 models of four items beside those over the 61 decomposable ones."""
    return _named(W.general_and_decomposable(spark, 4).withColumn("size", F.bit_count("mask")), F.round("general", 6).alias("general"), F.round("decomposable", 6).alias("decomposable"), k=4)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _exact(spark, W.patterns_of(spark, sf_dir, "word5_en"))
