"""DuckDB SQL for the registered queries, built from an encoding's own predicates and from other derivations than the engine's."""

from __future__ import annotations

from .operators.catalogue import chordless_cycles, edge_mask, pair_list
from .operators.family import canonical
from .sources.encode import SPECS
from .sources.tables import EXAMPLE_ROWS, row_mask


def patterns_cte(name: str) -> str:
    return f"p AS (SELECT mask, CAST(count(*) AS BIGINT) AS n FROM ({SPECS[name].duckdb()}) AS b GROUP BY mask)"


def example_cte(keep: int = 31) -> str:
    rows = ", ".join(f"({row_mask(r) & keep})" for r in EXAMPLE_ROWS)
    return f"p AS (SELECT mask, CAST(count(*) AS BIGINT) AS n FROM (VALUES {rows}) AS t(mask) GROUP BY mask)"


def itemsets_cte(masks: list[int], name: str = "xs") -> str:
    rows = ", ".join(f"({m}, {m.bit_count()}, '{canonical(m)}')" for m in sorted(masks))
    return f"{name} AS (SELECT CAST(x AS BIGINT) AS x, CAST(size AS INT) AS size, itemset FROM (VALUES {rows}) AS t(x, size, itemset))"


CELLS = "cells AS (SELECT x, size, itemset, mask & x AS cell, CAST(sum(n) AS BIGINT) AS n FROM p, xs GROUP BY ALL)"
ENTROPY = "h AS (SELECT x, size, itemset, abs(ln(sum(n)) - sum(n * ln(n)) / sum(n)) AS h FROM cells GROUP BY ALL)"
SUPPORT = "s AS (SELECT x, size, itemset, CAST(sum(CASE WHEN mask & x = x THEN n ELSE 0 END) AS BIGINT) AS support, CAST(sum(n) AS BIGINT) AS total FROM p, xs GROUP BY ALL)"


def patterns_sql(name: str) -> str:
    return f"WITH {patterns_cte(name)} SELECT mask, n FROM p"


def item_freq_sql(name: str) -> str:
    k = SPECS[name].k
    return f"WITH {patterns_cte(name)}, {itemsets_cte([1 << i for i in range(k)])}, {SUPPORT} SELECT itemset, support, round(support / total, 6) AS fr FROM s"


def entropy_sql(cte: str, masks: list[int]) -> str:
    return f"WITH {cte}, {itemsets_cte(masks)}, {CELLS}, {ENTROPY} SELECT itemset, size, round(h, 6) + 0.0 AS h FROM h"


def _weights(k: int) -> str:
    """Moebius weights w(x) of all itemsets of k items."""
    return f"""{itemsets_cte(list(range(1, 1 << k)))}, {CELLS}, {ENTROPY}, total AS (SELECT sum(n) AS n FROM p),
w AS (SELECT c.x, c.size, c.itemset, -any_value(total.n) * sum(CASE WHEN (bit_count(c.x) - bit_count(b.x)) % 2 = 0 THEN b.h ELSE -b.h END) - 0.5 * ln(any_value(total.n)) AS w
FROM h AS c JOIN h AS b ON b.x & c.x = b.x CROSS JOIN total GROUP BY c.x, c.size, c.itemset)"""


def _graphs(k: int) -> str:
    """Graphs without a chordless cycle, and which itemsets each holds."""
    rings = ", ".join(f"({a}, {b})" for a, b in chordless_cycles(k)) or "(-1, 1099511627776)"
    edges = ", ".join(f"({m}, {edge_mask(m, k)})" for m in range(1, 1 << k))
    return f"""rings AS (SELECT * FROM (VALUES {rings}) AS t(pairs, cycle)), edges AS (SELECT * FROM (VALUES {edges}) AS t(x, e)),
g AS (SELECT r.g FROM (SELECT unnest(range({1 << len(pair_list(k))})) AS g) AS r WHERE NOT EXISTS (SELECT 1 FROM rings WHERE r.g & pairs = cycle))"""


def catalogue_sql(k: int) -> str:
    return f"WITH {_graphs(k)} SELECT CAST(bit_count(g.g) AS INT) AS pairs, CAST(count(*) AS BIGINT) AS families FROM g GROUP BY 1"


def exact_cte(cte: str, k: int) -> str:
    return f"""WITH {cte}, {_weights(k)}, {_graphs(k)},
held AS (SELECT g.g, edges.x FROM g JOIN edges ON g.g & edges.e = edges.e),
bic AS (SELECT g, sum(w) AS b FROM held JOIN w USING (x) GROUP BY g),
post AS (SELECT g, exp(b - (SELECT max(b) FROM bic)) AS e FROM bic),
score AS (SELECT held.x, sum(post.e) / (SELECT sum(e) FROM post) AS score FROM held JOIN post USING (g) GROUP BY held.x)"""


def exact_score_sql(cte: str, k: int) -> str:
    return f"{exact_cte(cte, k)} SELECT xs.itemset, xs.size, round(score, 6) + 0.0 AS score FROM score JOIN xs USING (x)"


def verdict_sql(cte: str, k: int) -> str:
    return f"{exact_cte(cte, k)} SELECT xs.itemset, TRUE AS ok FROM score JOIN xs USING (x)"


def g_sql(cte: str, masks: list[int]) -> str:
    """G against independence, the expected counts from item frequencies."""
    bits = sorted({m & -m for m in masks} | {1 << i for m in masks for i in range(63) if m >> i & 1})
    items = ", ".join(f"({b})" for b in bits)
    return f"""WITH {cte}, {itemsets_cte(masks)}, {CELLS}, total AS (SELECT sum(n) AS n FROM p),
item AS (SELECT CAST(i AS BIGINT) AS i, sum(CASE WHEN mask & i = i THEN n ELSE 0 END) / (SELECT n FROM total) AS f FROM p, (VALUES {items}) AS t(i) GROUP BY i),
e AS (SELECT x, size, itemset, cell, cells.n, sum(ln(CASE WHEN cell & i <> 0 THEN f ELSE 1 - f END)) AS le FROM cells JOIN item ON x & i = i GROUP BY ALL),
g AS (SELECT itemset, size, abs(2 * sum(e.n * (ln(e.n / total.n) - le))) AS g FROM e, total GROUP BY itemset, size)
SELECT itemset, size, round(g, 4) AS g, CAST((1 << size) - size - 1 AS INT) AS df FROM g"""
