"""Tables as binary transactions.

An item is a predicate; a transaction is a row, or with `group` the rows of a key, an item being
present if any of them has it.  Null predicates count as absent; empty transactions stay unless asked.
Predicates are SQL expressions over pushed-down scans, so Catalyst prunes columns, and grouped
encodings aggregate masks with bit_or before the shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.patterns import WORD_BITS
from .tables import TABLES, load



@dataclass(frozen=True)
class BasketSpec:
    """relation names tables in braces; {rx} and {at} stand for an engine's regex test and 1-based array access."""

    name: str
    relation: str
    items: tuple[str, ...]
    labels: tuple[str, ...] = ()
    group: str | None = None
    ordered: bool = False
    drop_empty: bool = False
    tables: tuple[str, ...] = field(init=False, default=())

    @property
    def k(self) -> int:
        return len(self.items)

    def sql(self, names: dict[str, str], rx: str, at: str) -> str:
        """SELECT of the mask of every transaction."""
        fill = names | {"rx": rx, "at": at}
        bits = " + ".join(f"(CASE WHEN {e} THEN {1 << i} ELSE 0 END)" for i, e in enumerate(self.items))
        return self.select(f"CAST({bits} AS BIGINT)", fill)

    def select(self, mask: str, fill: dict[str, str]) -> str:
        made = f"SELECT bit_or({mask}) AS mask FROM {self.relation} GROUP BY {self.group}" if self.group else f"SELECT {mask} AS mask FROM {self.relation}"
        made = made.format(**fill)
        return f"SELECT mask FROM ({made}) AS enc WHERE mask <> 0" if self.drop_empty else made

    def shifted(self) -> str | None:
        """The same mask as one shift, where items are the values of an integer expression in a row: a sum of dozens of
        cases makes code too long to be compiled, and evaluates every one of them for every row."""
        cut = [e.rpartition(" = ") for e in self.items]
        if len({of for of, *_ in cut}) > 1 or not all(v.isdigit() for *_, v in cut):
            return None
        of, first = cut[0][0], int(cut[0][2])
        if [int(v) for *_, v in cut] != list(range(first, first + self.k)):
            return None
        return f"CASE WHEN {of} BETWEEN {first} AND {first + self.k - 1} THEN shiftleft(1L, CAST({of} AS INT) - {first}) ELSE 0L END"

    def spark(self) -> str:
        fill = {t: "{" + t + "}" for t in TABLES} | {"rx": "regexp_like", "at": "element_at"}
        mask = self.shifted()
        return self.select(mask, fill) if mask else self.sql(fill, "regexp_like", "element_at")

    def duckdb(self) -> str:
        return self.sql({t: t for t in TABLES}, "regexp_matches", "list_extract")


def to_baskets(spark: SparkSession, sf_dir: str, spec: BasketSpec) -> DataFrame:
    """(mask) for every transaction."""
    used = {t: load(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in spec.relation}
    return spark.sql(spec.spark(), **used)


def _word(w: str) -> str:
    return f"{{rx}}(lower(text), '(^|[^a-z]){w}([^a-z]|$)')"


def _draw(tag: str, i: int, below: str) -> str:
    """A repeatable draw: the first 8 hex digits of a digest, compared as text."""
    return f"substr(md5(concat('{tag}:', event_id, ':', {i})), 1, 8) < '{below}'"


def ind(n: int) -> BasketSpec:
    """15 independent items of frequency 0.1."""
    return BasketSpec(f"ind_{n}", f"{{events}} WHERE event_id < {n}", tuple(_draw("ind", i, "1999999a") for i in range(1, 16)))


def path(n: int) -> BasketSpec:
    """15 items, each agreeing with the one before with probability 0.75."""
    flips = ", ".join(f"CASE WHEN {_draw('path', i, '80000000' if i == 1 else '40000000')} THEN 1 ELSE 0 END AS f{i}" for i in range(1, 16))
    rows = f"(SELECT {flips} FROM {{events}} WHERE event_id < {n}) AS f"
    return BasketSpec(f"path_{n}", rows, tuple(f"({' + '.join(f'f{j}' for j in range(1, i + 1))}) % 2 = 1" for i in range(1, 16)), ordered=True)


def planted(n: int) -> BasketSpec:
    """15 independent items, but that the second is the first."""
    return BasketSpec(f"planted_{n}", f"{{events}} WHERE event_id < {n}", tuple(_draw("ind", 1 if i == 2 else i, "1999999a") for i in range(1, 16)))


_LINE_PART = "{lineitem} AS l JOIN {part} AS p ON l_partkey = p_partkey"
_TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")
_TAGS = ("html", "head", "meta", "title", "style", "script", "body", "nav", "ul", "li", "a", "div", "article", "h1", "p", "b", "br", "footer")
_ROLES = "(SELECT conv_id, max(CASE WHEN role = 'system' THEN 1 ELSE 0 END) AS has_system, max(CASE WHEN role = 'assistant' THEN 1 ELSE 0 END) AS has_assistant, count(*) AS turns, max(CASE WHEN text LIKE '%the%' THEN 1 ELSE 0 END) AS has_the, max(CASE WHEN text LIKE '%de%' THEN 1 ELSE 0 END) AS has_de FROM {conversations} GROUP BY conv_id) AS c"
_EVENT_TYPES = ("view", "click", "signup", "purchase", "error")

SPECS = {
    s.name: s
    for s in (
        BasketSpec("line", "{lineitem}", ("l_quantity > 25", "l_extendedprice > 30000", "l_discount >= 0.05", "l_tax >= 0.04", "l_returnflag = 'R'", "l_returnflag = 'N'", "l_linestatus = 'O'", "l_shipdate >= TIMESTAMP '1998-06-01 00:00:00'")),
        BasketSpec("thermo", "{lineitem}", tuple(f"l_quantity > {5 * i}" for i in range(1, 10)), ordered=True),
        BasketSpec("cust", "{customer} AS c JOIN {nation} AS n ON c_nationkey = n_nationkey", (*(f"n_regionkey = {r}" for r in range(4)), "c_mktsegment = 'BUILDING'", "c_mktsegment = 'MACHINERY'", "c_acctbal > 0", "c_acctbal > 5000")),
        BasketSpec("userday", "{events}", tuple(f"event_type = '{t}'" for t in _EVENT_TYPES), _EVENT_TYPES, group="user_id, CAST(ts AS DATE)"),
        BasketSpec(
            "userday_all",
            "(SELECT u.user_id, d.day FROM (SELECT DISTINCT user_id FROM {events}) AS u CROSS JOIN (SELECT DISTINCT CAST(ts AS DATE) AS day FROM {events}) AS d) AS g LEFT JOIN {events} AS e ON e.user_id = g.user_id AND CAST(e.ts AS DATE) = g.day",
            tuple(f"event_type = '{t}'" for t in _EVENT_TYPES), _EVENT_TYPES, group="g.user_id, g.day",
        ),
        BasketSpec("line5", "{lineitem}", ("l_quantity > 25", "l_discount >= 0.05", "l_returnflag = 'R'", "l_returnflag = 'N'", "l_linestatus = 'O'")),
        BasketSpec("lines5", "{lineitem}", ("l_returnflag = 'R'", "l_returnflag = 'A'", "l_discount >= 0.08", "l_tax >= 0.06", "l_quantity > 40"), group="l_orderkey"),
        BasketSpec("cust5", "{customer} AS c JOIN {nation} AS n ON c_nationkey = n_nationkey", ("n_regionkey = 0", "n_regionkey = 1", "c_mktsegment = 'MACHINERY'", "c_acctbal > 0", "c_acctbal > 5000")),
        BasketSpec("word5", "{documents}", tuple(map(_word, ("that", "with", "this", "from", "thed"))), ("that", "with", "this", "from", "thed")),
        BasketSpec("word5_en", "{documents} WHERE lang = 'en'", tuple(map(_word, ("that", "with", "this", "from", "thed"))), ("that", "with", "this", "from", "thed")),
        BasketSpec("ord5", "{orders}", ("o_orderstatus = 'F'", "o_orderstatus = 'O'", "o_orderpriority = '1-URGENT'", "o_totalprice > 250000", "o_orderdate >= TIMESTAMP '1998-01-01 00:00:00'")),
        BasketSpec("brand", _LINE_PART, tuple(f"p_brand = 'Brand#{i}'" for i in range(1, 26)), group="l_orderkey"),
        BasketSpec(
            "custsize", "{lineitem} AS l JOIN {orders} AS o ON l_orderkey = o_orderkey JOIN {part} AS p ON l_partkey = p_partkey",
            tuple(f"p_type = '{t}' AND p_size BETWEEN {lo} AND {hi}" for t in _TYPES for lo, hi in ((1, 16), (17, 33), (34, 50))), group="o_custkey",
        ),
        BasketSpec("doclabel", "{documents} AS d JOIN {labels} AS b ON d.doc_id = b.doc_id", ("quality = 1", "toxic = 1", "lang = 'en'", "n_chars > 1000", "text LIKE '%http%'", "source = 'src0'")),
        BasketSpec("size", "(SELECT l_suppkey, date_trunc('month', l_shipdate) AS m, p_size FROM " + _LINE_PART + ") AS s", tuple(f"p_size = {i}" for i in range(1, 51)), group="l_suppkey, m", ordered=True),
        BasketSpec("hour", "{events}", tuple(f"hour(ts) = {h}" for h in range(24)), group="user_id", ordered=True),
        BasketSpec("sign", "{embeddings}", tuple(f"{{at}}(embedding, {i}) > 0" for i in range(1, 17))),
        BasketSpec("tag", "{pages}", tuple(f"html LIKE '%<{t}%'" for t in _TAGS), _TAGS),
        BasketSpec("role", _ROLES, ("has_system = 1", "has_assistant = 1", "turns > 2", "turns > 4", "turns > 6", "has_the = 1", "has_de = 1")),
        ind(100), ind(1000), ind(10_000), path(100), path(1000), path(10_000), planted(10_000),
    )
}


def words_catalog(docs: DataFrame, k: int, text: str = "text") -> DataFrame:
    """(ord, label, n_docs): the k tokens of four or more letters that most documents hold; ties by token."""
    tokens = docs.select(F.explode(F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit("[a-z]{4,}"), F.lit(0)))).alias("label"))
    top = tokens.groupBy("label").agg(F.count("*").alias("n_docs")).orderBy(F.col("n_docs").desc(), "label").limit(k)
    rows = [(i, r.label, r.n_docs) for i, r in enumerate(top.collect())]  # k rows, in order
    return docs.sparkSession.createDataFrame(rows, "ord int, label string, n_docs bigint")


def word_baskets(docs: DataFrame, k: int, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(mask), or (words) for more than 62 items: documents without a catalogued token are dropped."""
    catalog = F.broadcast(words_catalog(docs, k, text))
    tokens = docs.select(key, F.explode(F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit("[a-z]{4,}"), F.lit(0)))).alias("label"))
    met = tokens.join(catalog, "label")
    bit = lambda at: F.call_function("shiftleft", F.lit(1).cast("bigint"), at)
    if k <= WORD_BITS:
        return met.groupBy(key).agg(F.bit_or(bit(F.col("ord"))).alias("mask")).select("mask")
    slots = range(-(-k // WORD_BITS))
    made = met.groupBy(key).agg(*(F.coalesce(F.bit_or(F.when((F.col("ord") / WORD_BITS).cast("int") == s, bit(F.col("ord") % WORD_BITS))), F.lit(0).cast("bigint")).alias(f"w{s}") for s in slots))
    return made.select(F.array(*(f"w{s}" for s in slots)).alias("words"))
