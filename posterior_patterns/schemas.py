"""Schemas of the engine's own tables."""

PATTERNS = "mask bigint, n bigint"
WIDE_PATTERNS = "words array<bigint>, n bigint"
ITEMSETS = "mask bigint, size int"
ENTROPIES = "mask bigint, size int, h double"
MODELS = "model_id bigint, maximal array<bigint>, separators array<bigint>, family_size bigint"
SAMPLED = "chain_id bigint, maximal array<string>, log_bic double, steps bigint, accepted bigint, entropies bigint"
TRACE = "chain_id bigint, step int, op string, s string, x int, y int, delta double, deg bigint, deg_new bigint, accepted boolean, log_bic double"
SCORES = "itemset string, size int, score double, hits bigint, n_models bigint, se double"
