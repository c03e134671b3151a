"""Secret scans over an incremental ledger of content-addressed blobs.

Every version of a text is a blob named by its SHA-256.  The ledger is a Parquet table (blob, rule
version, spans); a run scans only the (blob, rule version) pairs that it lacks, appends them, also
those without findings, and joins findings back to every path or document that holds the blob, in a
join that spreads the rows of hot blobs.

Base rules: assignments of a password, token or key, cloud access keys, long lower-case hex runs.
The method's further rules (private-key blocks, signed web tokens, prefixed service tokens) add
spans of their own kinds.  Positions are code points with an exclusive end.

Defined cases: null texts count as empty; empty texts have no spans; copies are scanned once;
repeated rows and ids keep one result row each; an empty table gives an empty result; further
columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from functools import cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import arrow_map, blob, one_of_each_new, with_class

# Kind, pattern, group whose length counts, least length.
BASE = [
    ("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    ("access", r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", r"[0-9a-f]+", 0, 24),
]
ADDED = [
    ("keyblock", r"-----BEGIN [A-Z ]*PRIVATE KEY-----[\s\S]*?-----END [A-Z ]*PRIVATE KEY-----", 0, 1),
    ("webtoken", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 1),
    ("service", r"(?:gh[pousr]_[A-Za-z0-9]{36,}|sk_live_[A-Za-z0-9]{16,}|xox[abprs]-[A-Za-z0-9-]{10,})", 0, 1),
]
RULES = BASE + ADDED
LEDGER_SCHEMA = "blob string, rules string, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"


def rule_version(rules: list[tuple] = RULES) -> str:
    return hashlib.sha256(repr(rules).encode()).hexdigest()[:16]


RULE_VERSION = rule_version()


@cache
def _compiled(rules: tuple) -> list[tuple]:
    """Patterns with their flags; a long run is searched for at its least length at once."""
    made = []
    for kind, pattern, group, least in rules:
        flags = re.ASCII | (re.IGNORECASE if kind == "assign" else 0)
        made.append((kind, re.compile(pattern.replace("[0-9a-f]+", "[0-9a-f]{24,}") if kind == "hex" else pattern, flags), group, least))
    return made


#: A text without any of these can't match the rule; looked for before the pattern is tried.
_HINT = {"access": "AKIA", "keyblock": "PRIVATE KEY-----", "webtoken": "eyJ"}
_ASSIGN_HINT = re.compile(r"passw|secret|token|api", re.ASCII | re.IGNORECASE)


def find_spans(text: str, rules: tuple = tuple(RULES)) -> list[tuple[str, int, int]]:
    """All spans (kind, start, end), by start and then by kind as listed."""
    made, order = [], {kind: i for i, (kind, *_) in enumerate(rules)}
    for kind, pattern, group, least in _compiled(rules):
        if kind in _HINT and _HINT[kind] not in text:
            continue
        if kind == "assign" and not _ASSIGN_HINT.search(text):
            continue
        made += [(kind, m.start(), m.end()) for m in pattern.finditer(text) if m.end(group) - m.start(group) >= least]
    return sorted(made, key=lambda s: (s[1], order[s[0]], s[2]))


def _joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def _scanner(rules: tuple, version: str):
    """Blobs and their bytes to columns of the ledger."""
    base = {kind for kind, *_ in BASE}

    def scan_blobs(blobs: list[str], data: list[bytes]) -> tuple[list, ...]:
        found = [find_spans(d.decode("utf-8", "replace"), rules) for d in data]
        own = [[s for s in x if s[0] in base] for x in found]
        count = lambda kind: [sum(s[0] == kind for s in x) for x in own]
        sums = [hashlib.sha256(_joined(x).encode()).hexdigest() for x in own]
        return blobs, [version] * len(blobs), count("assign"), count("access"), count("hex"), sums, [_joined(x) for x in found]

    return scan_blobs


def _ledger(spark: SparkSession, path: str) -> DataFrame:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    if not at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at):
        return spark.createDataFrame([], LEDGER_SCHEMA)
    return spark.read.schema(LEDGER_SCHEMA).parquet(path)


def scan(docs: DataFrame, ledger: str, id_col: str = "doc_id", text_col: str = "text", also: tuple[str, ...] = (), rules: list[tuple] = RULES) -> DataFrame:
    """(doc_id, *also, blob, n_assign, n_access, n_hex, base_sha256, spans) for every row.

    Rows may be versions of files, `also` naming their path and version columns.  The ledger gains the
    (blob, rule version) pairs that it lacked; nothing else is scanned.
    """
    spark, data, version = docs.sparkSession, blob(F.col(text_col)), rule_version(rules)
    store = Durable(spark, "secret-blobs")
    rows = docs.select(F.col(id_col).alias("doc_id"), *also, F.sha2(data, 256).alias("blob"), data.alias("data"))
    held = store.save(rows.drop("data"), "rows")
    blobs = store.save(held.groupBy("blob").agg(F.count("*").alias("rows")), "blobs")
    known = _ledger(spark, ledger).filter(F.col("rules") == version)
    new = store.save(blobs.select("blob").join(known.select("blob"), "blob", "left_anti"), "new")
    unseen = one_of_each_new(rows.select("blob", "data"), new, "blob")
    arrow_map(unseen, _scanner(tuple(rules), version), LEDGER_SCHEMA).write.mode("append").parquet(ledger)
    known = _ledger(spark, ledger).filter(F.col("rules") == version).dropDuplicates(["blob"]).drop("rules")
    found = store.save(blobs.join(known, "blob"), "found")
    met = with_class(held, found, "blob", "rows", "doc_id")
    return met.select("doc_id", *also, "blob", *(f"class.{c}" for c in ("n_assign", "n_access", "n_hex", "base_sha256", "spans")))
