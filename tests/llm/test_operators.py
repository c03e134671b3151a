"""Text operators against brute force, with nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns."""

import base64
import hashlib
import json
import math
import random
import re
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F

from posterior_patterns.llm import brown_lm, decontaminate, exact_dedup, graph, mixing, near_copies, pii, queries, secrets, simhash, token_counts, toxicity, warc
from posterior_patterns.plans.durable import Durable

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, h string, kept int, fp long, size string, row int"
WORDS = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def rows_of(texts, sources=None):
    return [(i, t, "en", (sources or {}).get(i, f"src{(i or 0) % 3}"), len(t or ""), "x", 0, 7, "s", 1) for i, t in texts]


ODD = [(0, None), (1, ""), (2, "  \n\t "), (3, "Alpha beta"), (4, "alpha  beta"), (5, "word"), (6, "a b c d e f g h i j"), (7, "a b c d e f g h i j"), (8, "é" * 50), (9, "long " * 30_000), (10, "ünï cödé ß <|endoftext|> x")]


def docs_of(spark, texts, sources=None):
    return spark.createDataFrame(rows_of(texts, sources), DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    return docs_of(spark, ODD + [(3, "Alpha beta")]).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return docs_of(spark, [])


@pytest.fixture(scope="module")
def given(spark, sf_dir):
    return {r.doc_id: r for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}


def brute_fingerprint(text, k):
    w = WORDS.findall((text or "").translate(LOWER))
    if not w:
        return 0
    s = [" ".join(w[i : i + k]) for i in range(max(1, len(w) - k + 1))]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(fps, radius):
    home = {i: i for i in fps}

    def find(x):
        while home[x] != x:
            x = home[x]
        return x

    for a in fps:
        for b in fps:
            if a < b and (fps[a] ^ fps[b]).bit_count() <= radius:
                ra, rb = find(a), find(b)
                home[max(ra, rb)] = min(ra, rb)
    return {i: find(i) for i in fps}


# -- SimHash -----------------------------------------------------------------------------------------


@pytest.mark.parametrize("radius", [0, 2, 4])
def test_masks_cover_every_pair_within_the_radius(radius):
    rng, found = random.Random(1), [m & (1 << 64) - 1 for m in simhash.masks(radius)]
    assert len(found) == 2 ** (radius + 1) - 1
    for _ in range(3000):
        flips = sum(1 << b for b in rng.sample(range(64), radius))
        assert any(m & flips == 0 for m in found)


def test_op1_equals_brute_force(spark, sf_dir, given):
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op1_simhash_near_dedup(spark, sf_dir).collect()}
    fps = {i: brute_fingerprint(r.text, 3) for i, r in given.items()}
    comps = brute_components(fps, 2)
    assert got == {i: (f"{fps[i]:016x}", comps[i]) for i in given}


@pytest.mark.parametrize("hot", [2, 48])
def test_links_of_crowded_buckets_are_exact(spark, hot):
    rng, base = random.Random(5), [random.Random(9).getrandbits(64) for _ in range(4)]
    fps = {b ^ sum(1 << x for x in rng.sample(range(64), rng.choice([0, 1, 2, 3, 5]))) for b in base for _ in range(60)}
    signed = lambda v: v - (1 << 64) if v >> 63 else v
    store = Durable(spark, "t")
    made = simhash.links(spark.createDataFrame([(signed(f),) for f in fps], "fp long"), 2, store, hot)
    got = {r.node: r.root for r in graph.components(made, store).collect()}
    want = brute_components({f: f for f in fps}, 2)
    groups = lambda pairs: sorted(sorted(v) for v in pairs.values() if len(v) > 1)
    mine, theirs = defaultdict(set), defaultdict(set)
    for node, root in got.items():
        mine[root] |= {node, root}
    for node, root in want.items():
        theirs[root].add(signed(node))
    assert groups(mine) == groups(theirs)


def test_components_of_chains_and_stars(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 30)] + [(7, 7), (200, 201), (201, 200)]
    got = {r.node: r.root for r in graph.components(spark.createDataFrame(links, "a long, b long"), Durable(spark, "t")).collect()}
    assert got == {i: 0 for i in range(1, 41)} | {100 + i: 100 for i in range(1, 30)} | {201: 200}
    assert graph.components(spark.createDataFrame([], "a long, b long"), Durable(spark, "t")).count() == 0


def test_simhash_odd_rows(odd, empty):
    got = simhash.near_duplicate_groups(odd, 3).collect()
    assert len(got) == len(ODD) + 1
    by = {r.doc_id: r for r in got}
    assert by[0].component_id == by[1].component_id == by[2].component_id == 0 and by[0].fp == 0
    assert by[7].component_id == 6 and by[4].component_id == 3
    assert simhash.near_duplicate_groups(empty).count() == 0


# -- near copies -------------------------------------------------------------------------------------


def edited(rng, words, n):
    made = list(words)
    for _ in range(n):
        made[rng.randrange(len(made))] = f"new{rng.randrange(10**6)}"
    return " ".join(made)


def test_near_copies_are_found_and_others_left(spark):
    rng = random.Random(3)
    vocabulary = [f"w{i}" for i in range(3000)]
    texts, near = [], 0
    for i in range(40):
        base = [rng.choice(vocabulary) for _ in range(rng.randrange(120, 260))]
        texts += [(10 * i, " ".join(base)), (10 * i + 1, edited(rng, base, 2)), (10 * i + 2, edited(rng, base, 1))]
    got = {r.doc_id: r.group_id for r in near_copies.near_copy_groups(docs_of(spark, texts)).collect()}
    sets = {i: set(near_copies.shingle_set(t.encode())) for i, t in texts}
    for i in range(40):
        for j in (1, 2):
            a, b = sets[10 * i], sets[10 * i + j]
            if len(a & b) / len(a | b) >= 0.8:
                near += got.get(10 * i + j) == 10 * i
            else:
                near += 1
    assert near >= 76  # of 80
    assert all(i // 10 == g // 10 for i, g in got.items())


def brute_near_copies(texts):
    """{id: least id of its group} for ids that aren't it, comparing all pairs of texts."""
    sets = {i: set(near_copies.shingle_set(t.encode())) for i, t in texts}
    root = {i: i for i in sets}

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, x in sets.items():
        for b, y in sets.items():
            if a < b and 5 * len(x & y) >= 4 * len(x | y):
                p, q = top(a), top(b)
                root[max(p, q)] = min(p, q)
    return {i: top(i) for i in sets if top(i) != i}


def near_members(spark, rows):
    return {r.doc_id: r.group_id for r in near_copies.near_copy_groups(docs_of(spark, rows)).collect() if r.doc_id != r.group_id}


def test_near_copies_match_all_pairs(spark):
    rng, vocabulary, texts = random.Random(11), [f"w{i}" for i in range(3000)], []
    for i in range(60):
        base = [rng.choice(vocabulary) for _ in range(rng.randrange(8, 260))]
        texts += [(10 * i, " ".join(base)), *((10 * i + k, edited(rng, base, max(1, len(base) * k // 90))) for k in range(1, 5))]
    given = [(r.doc_id, r.text or "") for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").collect()]
    for rows in (texts, given):
        want = brute_near_copies(rows)
        assert want and near_members(spark, rows) == want


def test_near_copies_of_large_families_match_all_pairs(spark):
    rng, vocabulary, texts = random.Random(12), [f"w{i}" for i in range(3000)], []
    for f in range(3):  # versions drift: far ones are alike only through those between
        base = [rng.choice(vocabulary) for _ in range(150)]
        for k in range(150):
            base = edited(rng, base, 2).split()
            texts.append((f * 1000 + k * 37 % 150, " ".join(base)))
    head = [rng.choice(vocabulary) for _ in range(100)]  # one passage, tails at any distance
    texts += [(5000 + k, " ".join(head + [rng.choice(vocabulary) for _ in range(rng.randrange(1, 30))])) for k in range(150)]
    want = brute_near_copies(texts)
    assert len(set(want.values())) >= 3
    assert near_members(spark, texts) == want


def test_near_copies_odd_rows(odd, empty):
    got = {r.doc_id: r.group_id for r in near_copies.near_copy_groups(odd).collect()}
    assert got[7] == 6 and got[4] == 3 and got[1] == got[2] == 0
    odd = odd.withColumn("rec", F.lit(1)).withColumn("d", F.lit(2)).withColumn("gone rec", F.lit("z"))
    kept = near_copies.one_of_each(odd)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} == {0, 3, 5, 6, 8, 9, 10}
    assert near_copies.near_copy_groups(empty).count() == 0 and near_copies.one_of_each(empty).count() == 0


def test_near_copies_with_repeated_and_null_ids(spark):
    a, b, c = (" ".join(f"{x}{i}" for i in range(60)) for x in "abc")
    rows = [(1, a), (2, a + " end"), (2, b), (None, b + " end"), (None, c), (5, c), (5, c), (6, "x y z")]
    kept = [(r.doc_id, r.text) for r in near_copies.one_of_each(docs_of(spark, rows)).collect()]
    assert sorted(kept, key=str) == sorted([(1, a), (2, b), (5, c), (5, c), (6, "x y z")], key=str)


def test_all_pairs_are_left_to_groups_that_do_not_link(spark, monkeypatch):
    """While turns find links they go on, so a chain of versions is one group before all pairs are compared; groups are those of two turns."""
    rng, words, rows = random.Random(4), [f"w{i}" for i in range(3000)], []
    text = [rng.choice(words) for _ in range(120)]
    for i in range(48):
        rows.append((i, " ".join(text)))
        text = [*text]
        text[rng.randrange(120)] = rng.choice(words)
    left, every = [], near_copies.with_all
    monkeypatch.setattr(near_copies, "with_all", lambda *a: left.append(made := every(*a).cache()) or made)
    many = {r.doc_id: r.group_id for r in near_copies.near_copy_groups(docs_of(spark, rows)).collect()}
    more = sum(df.count() for df in left)
    monkeypatch.setattr(near_copies, "MOST_TURNS", 0)
    monkeypatch.setattr(near_copies, "TURNS", 0)
    left.clear()
    assert many == {r.doc_id: r.group_id for r in near_copies.near_copy_groups(docs_of(spark, rows)).collect()}
    assert more < sum(df.count() for df in left)


def test_a_turn_meets_texts_that_may_be_alike(spark):
    """Row 9 shares most buckets with row 1, which is five times as large, and fewer with row 2: it meets row 2."""
    open_ = spark.createDataFrame([(t, r, r) for r, tokens in ((1, range(6)), (2, (6, 7, 8)), (9, range(9))) for t in tokens], "token long, row long, root long")
    odd = [0] * (near_copies.LEAST_PARITIES // 64)
    sketches = spark.createDataFrame([(1, 100, odd), (2, 20, odd), (9, 20, odd)], "row long, n int, odd array<long>")
    tested = spark.createDataFrame([], "a long, b long")
    met = lambda turn: {tuple(r) for r in near_copies.with_one(open_, sketches, tested, turn).collect()}
    assert met(0) == met(1) == {(2, 9)}
    assert not near_copies.with_one(open_, sketches, spark.createDataFrame([(2, 9)], "a long, b long"), 0).count()


def test_rest_of_a_large_group_joins_it_without_all_its_pairs(spark, monkeypatch):
    """A group of 40 and three other texts in its buckets: one row of the group meets the three, not all 40."""
    rows = [(t, r, r if r >= 40 else 0) for t in range(5) for r in range(43)]
    kept = near_copies.one_a_group(spark.createDataFrame(rows, "token long, row long, root long")).collect()
    assert len(kept) == 5 * 4 and {(r.token, r.root) for r in kept} == {(t, g) for t in range(5) for g in (0, 40, 41, 42)}
    assert len({r.row for r in kept}) == 4
    rng, words, tables = random.Random(12), [f"w{i}" for i in range(3000)], []
    base = [rng.choice(words) for _ in range(200)]
    texts = [(i, edited(rng, base, 3)) for i in range(60)]
    every = near_copies.with_all
    monkeypatch.setattr(near_copies, "with_all", lambda open_, *a: tables.append(open_) or every(open_, *a))
    got = {r.doc_id: r.group_id for r in near_copies.near_copy_groups(docs_of(spark, texts)).collect()}
    want = brute_near_copies(texts)
    assert {i: g for i, g in got.items() if i != g} == want
    assert all(df.groupBy("token", "root").count().filter("count > 1").count() == 0 for df in tables[:1])


def test_few_links_are_joined_as_many_are(spark):
    rng = random.Random(7)
    for n, many in ((1, 0), (30, 20), (400, 380), (300, 900)):
        rows = [(rng.randrange(n), rng.randrange(n)) for _ in range(many)] + [(i, i + 1) for i in range(n, 2 * n)]
        links = spark.createDataFrame(rows, "a long, b long")
        roots = [{tuple(r) for r in graph.components(links, Durable(spark, "few"), few=few).collect()} for few in (0, 10_000, len(rows) // 2)]
        assert roots[0] == roots[1] == roots[2]
    assert graph.components(links.limit(0), Durable(spark, "few"), few=10).count() == 0

# -- exact dedup -------------------------------------------------------------------------------------


def test_exact_groups(odd, empty):
    got = {r.doc_id: r for r in exact_dedup.duplicate_groups(odd, keep="largest").collect()}
    assert (got[0].keep_id, got[0].group_size, got[0].kept, got[1].kept) == (1, 2, False, True)
    assert (got[6].keep_id, got[7].keep_id, got[6].kept) == (7, 7, False) and got[3].group_size == 2 and got[3].kept
    assert got[8].text_sha256 == hashlib.sha256(("é" * 50).encode()).hexdigest()
    assert exact_dedup.duplicate_groups(empty).count() == 0


def test_exact_groups_with_colliding_hashes(odd):
    weak = lambda c: F.unhex(F.substring(F.md5(F.coalesce(c, F.lit("")).cast("binary")), 1, 1))
    pick = lambda df: sorted((r.doc_id, r.keep_id, r.group_size, r.kept, r.text_sha256) for r in df.collect())
    assert pick(exact_dedup.duplicate_groups(odd, content_hash=weak)) == pick(exact_dedup.duplicate_groups(odd))


def test_distinct_documents(odd, empty):
    got = exact_dedup.distinct_documents(odd)
    assert got.columns == odd.columns and sorted(r.doc_id for r in got.collect()) == [0, 2, 3, 4, 5, 6, 8, 9, 10]
    assert sorted(r.doc_id for r in exact_dedup.distinct_documents(odd, "largest").collect()) == [1, 2, 3, 4, 5, 7, 8, 9, 10]
    assert exact_dedup.distinct_documents(empty).count() == 0


# -- token counts ------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"])
def test_token_counts_equal_the_library(odd, tmp_path, name):
    path, cache = public_tokenizers.path(name), f"file://{tmp_path}/cache"
    got = {r.doc_id: r for r in token_counts.token_counts(odd, path, cache).collect()}
    if name.endswith(".json"):
        from tokenizers import Tokenizer

        model = Tokenizer.from_file(path)
        model.no_truncation()
        count = lambda t: len(model.encode(t, add_special_tokens=False).ids)
    else:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        count = lambda t: len(model.encode(t))
    for i, t in ODD:
        assert (got[i].n_tokens, got[i].n_bytes, got[i].over_limit) == (count(t or ""), len((t or "").encode()), count(t or "") > 1024)


def test_cut_pieces_equal_whole_texts(given):
    count = token_counts.Counter(public_tokenizers.path("byte_bpe_50k.json"))
    texts = [r.text for r in list(given.values())[:60]] + ["a  b\n\n c\t\td", "don't  we'll 's x's", "  lead", "trail  ", "\x1c\x1d a \x85 b c　d", "\r\n\r\n a\x00b", "x y ​ z"]
    assert count(texts) == count.encode(texts)


def test_cache_is_used_and_extended(spark, odd, empty, tmp_path):
    path, cache = public_tokenizers.path("byte_bpe_50k.json"), f"file://{tmp_path}/c"
    token_counts.token_counts(odd, path, cache)
    first = spark.read.parquet(cache).count()
    assert first == len({(t or "") for _, t in ODD})
    more = docs_of(spark, ODD + [(99, "something new")])
    assert token_counts.token_counts(more, path, cache).count() == len(ODD) + 1
    assert spark.read.parquet(cache).count() == first + 1
    assert token_counts.token_counts(empty, path, cache).count() == 0


# -- mixing ------------------------------------------------------------------------------------------


def brute_targets(sizes):
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + ([None] if None in sizes else [])
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    total, full = 1.5 * sum(sizes.values()), {}
    while True:
        left = total - sum(full.values())
        rest = [s for s in names if s not in full]
        w = sum(weight[s] for s in rest)
        over = [s for s in rest if left * weight[s] / w > 2 * sizes[s] + 1e-9]
        if not over:
            return full | {s: left * weight[s] / w for s in rest}
        full |= {s: 2.0 * sizes[s] for s in over}


def check_mix(rows, source_of):
    sizes, taken = defaultdict(int), defaultdict(int)
    for r in rows:
        sizes[source_of(r)] += r["size"]
        taken[source_of(r)] += r.taken
        assert 0 <= r.taken <= 2 * r["size"]
    want = brute_targets(sizes)
    for r in rows:
        s = source_of(r)
        assert r.source_size == sizes[s] and r.target == pytest.approx(want[s])
    for s in sizes:
        assert abs(taken[s] - want[s]) <= 1, s
    return taken


def test_op4_meets_its_targets(spark, sf_dir, given):
    got = queries.op4_mixing(spark, sf_dir).collect()
    assert {r.doc_id: r["size"] for r in got} == {i: len(WORDS.findall(r.text or "")) for i, r in given.items()}
    check_mix(got, lambda r: given[r.doc_id].source)
    again = queries.op4_mixing(spark, sf_dir).collect()
    assert sorted(got) == sorted(again)


def test_mixing_odd_rows(spark, empty):
    texts = [(i, "w " * (i % 7)) for i in range(60)] + [(60, None), (61, "")]
    sources = {i: (None if i % 5 == 0 else "héé" if i % 5 == 1 else "zero" if i in (7, 14) else f"s{i % 4}") for i in range(62)}
    docs = docs_of(spark, texts, sources)
    got = mixing.assign(docs).collect()
    assert len(got) == 62
    check_mix(got, lambda r: sources[r.doc_id])
    mixed = mixing.mix_documents(docs)
    assert mixed.count() == 62 and [c for c in docs.columns if c != "size"] == mixed.columns[:9]
    copies = mixing.shard_rows(mixed).collect()
    assert {r.doc_id for r in copies} == {r.doc_id for r in mixed.collect() if r.taken}
    assert Counter((r.doc_id, r.shard) for r in copies) == Counter((r.doc_id, s) for r in mixed.collect() for s in r.shards)
    clash = docs.select("*", *(F.lit(1).alias(c) for c in ("_id", "_size", "_block", "id", "block", "rank", "place", "words", "caller", "at source.x")))
    assert sorted((r.doc_id, r.taken) for r in mixing.mix_documents(clash).collect()) == sorted((r.doc_id, r.taken) for r in got)
    other = mixing.assign(docs, seed=5).collect()  # another tree and permutation: other documents, the same targets
    check_mix(other, lambda r: sources[r.doc_id])
    assert sorted((r.doc_id, r.taken) for r in other) != sorted((r.doc_id, r.taken) for r in got)
    assert mixing.assign(empty).count() == 0 and mixing.mix_documents(empty).count() == 0


def test_splitting_tree_is_exact_and_spread(spark):
    quotas = {1: 200, 2: 37, 3: 0, 4: 1}
    counts = defaultdict(list)
    for seed in range(12):
        leaves = mixing.splitting_tree(spark.createDataFrame(list(quotas.items()), "rank int, draws long"), 3, seed).collect()
        by = defaultdict(dict)
        for r in leaves:
            by[r["rank"]][r.shard] = r.draws
        assert {k: sum(v.values()) for k, v in by.items()} == quotas and all(len(v) == 8 and min(v.values()) >= 0 for v in by.values())
        whole = [sum(by[k][s] for k in by) for s in range(8)]
        assert max(whole) - min(whole) <= 3
        counts[2] += by[2].values()
    assert np.mean(counts[2]) == pytest.approx(37 / 8) and np.var(counts[2]) == pytest.approx(37 / 8 * (7 / 8) * (201 / 237), rel=0.5)


# -- decontamination ---------------------------------------------------------------------------------


def brute_tiles(item, text, least):
    done_i, done_t, made = set(), set(), []
    while True:
        best, found = least, []
        for i in range(len(item)):
            for t in range(len(text)):
                n = 0
                while i + n < len(item) and t + n < len(text) and item[i + n] == text[t + n] and i + n not in done_i and t + n not in done_t:
                    n += 1
                if n > best or (n == best and n >= least):
                    best, found = n, (found if n == best else []) + [(i, t, n)]
        if not found:
            return made
        for i, t, n in found:
            if not done_i & set(range(i, i + n)) and not done_t & set(range(t, t + n)):
                done_i |= set(range(i, i + n))
                done_t |= set(range(t, t + n))
                made.append((i, t, n))


def test_items_without_an_id_are_matched(spark):
    bench = spark.createDataFrame([(None, "a b c d e f g h"), (4, "q r s t u v"), (9, "i j k l m n o p"), (None, "i j k l m n o p")], "item_id long, text string")
    docs = docs_of(spark, [(0, "x a b c d e f g h y"), (1, "i j k l m n o p"), (2, "other words")])
    got = {r.doc_id: (r.contaminated, r.item_id, r.coverage) for r in decontaminate.decontaminate(docs, bench).collect()}
    assert got == {0: (True, None, 1.0), 1: (True, 9, 1.0), 2: (False, None, 0.0)}
    assert [r.doc_id for r in decontaminate.keep_uncontaminated(docs, bench).collect()] == [2]


def test_tiles_equal_greedy_tiling():
    rng = random.Random(2)
    for least in (1, 3, 5):
        for _ in range(120):
            item = np.array([rng.randrange(1, 6) for _ in range(rng.randrange(1, 40))], dtype=np.uint64)
            text = np.array([rng.randrange(1, 6) for _ in range(rng.randrange(1, 60))], dtype=np.uint64)
            if rng.random() < 0.5 and len(item) > 10:
                text = np.concatenate([text[:10], item[6:], text[10:], item[:6]])
            assert decontaminate.tiles(item, text, least) == brute_tiles(item.tolist(), text.tolist(), least)


def test_tiles_of_one_repeated_word_are_quick():
    began = time.time()
    assert decontaminate.tiles(np.full(400, 7, dtype=np.uint64), np.full(20_000, 7, dtype=np.uint64)) == [(0, 0, 400)]
    assert decontaminate.tiles(np.full(400, 7, dtype=np.uint64), np.r_[np.full(150, 7), 8, np.full(90, 7)].astype(np.uint64)) == [(0, 0, 150), (150, 151, 90)]
    assert time.time() - began < 1


def brute_leaks(docs, bench, least=5, coverage=0.5):
    """{doc id: (contaminated, item)} by tiling every pair."""
    made = {}
    for i, t in docs:
        text, best = decontaminate.word_ids(t or "").tolist(), []
        for key, body in bench:
            item = decontaminate.word_ids(body or "").tolist()
            if item:
                share = sum(n for *_, n in brute_tiles(item, text, min(least, len(item)))) / len(item)
                best.append((-share, key is None, key))
        share, _, key = min(best, default=(0, True, None))
        made[i] = (-share >= coverage, key if -share >= coverage else None)
    return made


def test_leaks_equal_tiling_of_all_pairs(spark):
    rng, w = random.Random(6), [f"w{i}" for i in range(12)]
    bench = [(f"q{i}", " ".join(rng.choice(w) for _ in range(rng.randrange(1, 24)))) for i in range(40)] + [(None, "w1 w2 w3"), ("q99", ""), ("q98", None)]
    docs = [(i, " ".join(rng.choice(w) for _ in range(rng.randrange(0, 30)))) for i in range(60)]
    for i in range(60, 120):  # parts of an item, in another order
        item = rng.choice(bench[:40])[1].split()
        cut = rng.randrange(len(item) + 1)
        docs.append((i, " ".join(item[cut:] + ["pad"] * rng.randrange(3) + item[: rng.randrange(cut + 1)])))
    got = decontaminate.decontaminate(docs_of(spark, docs), spark.createDataFrame(bench, "item_id string, text string")).collect()
    want = brute_leaks(docs, bench)
    assert {r.doc_id: (r.contaminated, r.item_id if r.contaminated else None) for r in got} == want and 20 < sum(c for c, _ in want.values()) < 115


def test_leaks_whole_and_reordered(spark, odd, empty):
    item = "One two three four five six. Seven eight nine ten eleven twelve! Thirteen fourteen fifteen sixteen seventeen eighteen"
    parts = item.split(". ")[0], item.split("! ")[1], item.split(". ")[1].split("!")[0]
    bench = spark.createDataFrame([(1, item), (2, item), (3, None), (4, ""), (5, "tiny item"), (None, "x y z")], "item_id long, text string")
    texts = [(1, "pad " * 40 + item.upper() + " pad" * 9), (2, "start " + " mid words here ".join(reversed(parts)) + " end"), (3, "one two three four five six only"), (4, "nothing at all"), (5, "a Tiny, item b"), (6, None), (7, "")]
    got = {r.doc_id: r for r in decontaminate.decontaminate(docs_of(spark, texts), bench).collect()}
    assert [i for i in got if got[i].contaminated] == [1, 2, 5] and got[1].item_id == 1 and got[1].coverage == 1.0 and got[2].coverage == 1.0
    clash = docs_of(spark, texts).withColumn("name", F.lit(1)).withColumn("seed", F.lit(1)).withColumn("leaked", F.lit(1))
    assert sorted(r.doc_id for r in decontaminate.keep_uncontaminated(clash, bench).collect()) == [3, 4, 6, 7]
    assert decontaminate.keep_uncontaminated(docs_of(spark, texts), bench).columns == odd.columns
    assert decontaminate.decontaminate(empty, bench).count() == 0
    none = decontaminate.decontaminate(odd, bench.limit(0)).collect()
    assert len(none) == len(ODD) + 1 and not any(r.contaminated for r in none)


def test_op5_finds_the_given_passages(spark, sf_dir, given):
    bench = [r.text for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    got = {r.doc_id for r in queries.op5_decontamination(spark, sf_dir).collect() if r.contaminated}
    assert got >= {i for i, r in given.items() if any(b in r.text for b in bench)}


# -- class language model ----------------------------------------------------------------------------


def test_op6_base_score_and_counts(spark, sf_dir, given):
    got = {r.doc_id: r for r in queries.op6_brown_lm(spark, sf_dir).collect()}
    words = {i: WORDS.findall((r.text or "").translate(LOWER)) + [""] for i, r in given.items()}
    learn = [i for i in given if zlib.crc32(str(i).encode()) % 10]
    counts = Counter(w for i in learn for w in words[i])
    n, v = sum(counts.values()), len(counts)
    assert len(got) == len(given)
    for i, w in words.items():
        assert (got[i].held_out, got[i].n_tokens, got[i].n_known, got[i].train_tokens) == (i not in set(learn), len(w), sum(x in counts for x in w), n)
        assert got[i].base_score == pytest.approx(sum(math.log10((counts[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w))
    held = [r for r in got.values() if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_small_dictionary_gives_the_same_scores(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").limit(60).cache()
    a, b = ({r.doc_id: (r.n_known, round(r.base_score, 6), round(r.score, 6)) for r in brown_lm.score(docs, most=m, units=20, classes=6).collect()} for m in (200, 100_000))
    assert a == b


def brute_brown(docs, units, classes):
    """Scores by plain loops: counts, exchange of the most frequent words, insertion of the others, class bigrams."""
    words = {i: WORDS.findall((t or "").translate(LOWER)) for i, t in docs}
    learn = [i for i in words if zlib.crc32(str(i).encode()) % 10]
    counts = Counter(w for i in learn for w in [*words[i], ""])
    own = sorted((w for w in counts if w), key=lambda w: (-counts[w], w.encode()))[:units]
    table = {"": 0} | {w: i + 1 for i, w in enumerate(own)}
    other = len(table)
    pairs = np.zeros((other + 1, other + 1))
    for i in learn:
        seq = [0, *(table.get(w, other) for w in words[i]), 0]
        for x, y in zip(seq, seq[1:], strict=False):
            pairs[x, y] += 1
    of_unit = brown_lm.exchange(pairs, classes)
    grid = np.zeros((classes, classes))
    for x in range(other + 1):
        for y in range(other + 1):
            grid[of_unit[x], of_unit[y]] += pairs[x, y]
    size_in, size_out = grid.sum(0), grid.sum(1)
    gains = defaultdict(lambda: np.zeros(classes))
    for i in learn:
        seq = ["", *words[i], ""]
        for k in range(1, len(seq) - 1):
            if seq[k] not in table:
                for side, w in ((0, seq[k - 1]), (1, seq[k + 1])):
                    if w in table:
                        for g in range(classes):
                            x = of_unit[table[w]]
                            gains[seq[k]][g] += math.log((grid[x, g] + 0.5) / (size_in[g] + 0.5 * classes)) if side == 0 else math.log((grid[g, x] + 0.5) / (size_out[g] + 0.5 * classes))
    open_ = [g for g in range(1, classes - 1) if size_out[g]]
    at = {w: int(of_unit[i]) for w, i in table.items()}
    for w in counts:
        if w not in at:
            at[w] = max(open_, key=lambda g: (round(gains[w][g], 9), -g)) if w in gains else 1
    tokens, types, big = np.zeros(classes), np.zeros(classes), np.zeros((classes, classes))
    for w, n in counts.items():
        tokens[at[w]] += n
        types[at[w]] += 1
    last = classes - 1
    for i in learn:
        seq = [0, *(at[w] for w in words[i]), 0]
        for x, y in zip(seq, seq[1:], strict=False):
            big[x, y] += 1
    n, v = sum(counts.values()), len(counts)
    new = (sum(c == 1 for c in counts.values()) + 0.5) / (n + 1)
    held = sum(tokens[g] + 0.1 for g in range(last) if types[g])

    def p(prev, w):
        c, g = counts.get(w, 0), at.get(w, last)
        if g == last:
            step, mass = new, 0.1
        else:
            step = (1 - new) * (big[prev, g] + 5 * (tokens[g] + 0.1) / held) / (big[prev, :last].sum() + 5)
            mass = tokens[g] + 0.1 * types[g]
        return (c + 0.1) * (0.95 * step / mass + 0.05 / (n + 0.1 * (v + 1)))

    made = {}
    for i, w in words.items():
        seq = ["", *w, ""]
        made[i] = sum(math.log10(p(at.get(x, last), y)) for x, y in zip(seq, seq[1:], strict=False))
    return made, p, counts, at


def test_scores_equal_plain_loops(spark):
    rng = random.Random(21)
    vocabulary = [f"{c}{i}" for c in "abc" for i in range(20)]
    texts = []
    for i in range(150):
        text, kind = [], rng.randrange(3)
        for _ in range(rng.randrange(0, 40)):
            text.append(f"{'abc'[kind]}{min(int(rng.expovariate(0.2)), 19)}" if rng.random() < 0.95 else f"x{rng.randrange(200)}")
            kind = (kind + 1) % 3
        texts.append((i, " ".join(text)))
    texts += [(150, None), (151, ""), (152, "never seen words " + vocabulary[0])]
    want, p, counts, at = brute_brown(texts, 12, 6)
    for most in (40, 100_000):
        got = {r.doc_id: r.score for r in brown_lm.score(docs_of(spark, texts), most=most, units=12, classes=6).collect()}
        assert set(got) == set(want) and all(got[i] == pytest.approx(want[i], abs=1e-6) for i in want)
    for prev in sorted(set(at.values()) | {5}):  # all words seen and one that was not
        assert sum(p(prev, w) for w in counts) + p(prev, "not in any text") == pytest.approx(1, abs=1e-9)


def test_exchange_raises_the_likelihood():
    rng = np.random.default_rng(0)
    block = np.r_[0, np.repeat([1, 2, 3], 8), 4]
    rate = np.where(block[:, None] == np.r_[0, 2, 3, 1, 4][block][None, :], 30.0, 0.2)
    pairs = rng.poisson(rate).astype(float)
    at = brown_lm.exchange(pairs, 5)

    def likelihood(at):
        m = np.eye(5)[at]
        g = m.T @ pairs @ m
        f = brown_lm._x_log_x
        return f(g).sum() - f(g.sum(1)).sum() - f(g.sum(0)).sum()

    assert at[0] == 0 and at[-1] == 4 and set(at[1:-1]) <= {1, 2, 3}
    start = np.r_[0, 1 + np.arange(24) % 3, 4]
    assert likelihood(at) > likelihood(start) and likelihood(at) >= likelihood(block) - 1e-6


def test_neighbours_of_a_word_go_in_one_row(spark, monkeypatch):
    """A task hands on a row for each word, not for each word and pair of classes; sums are the same in pieces of any size."""
    texts = [("a x b y x",), ("x b x a x x",), ("y a",)]
    df = spark.createDataFrame(texts, "t string").select(F.col("t").cast("binary").alias("data")).coalesce(1)
    at = np.array([0, 1, 2, 3])  # the end token, a, b, all other words
    got = {bytes(r.word): np.frombuffer(r.told, dtype=brown_lm.TOLD) for r in brown_lm.neighbour_counts(df, {b"": 0, b"a": 1, b"b": 2}, at).collect()}
    want = defaultdict(Counter)
    for (t,) in texts:
        seq = ["", *t.split(), ""]
        code = [{"": 0, "a": 1, "b": 2}.get(w, 3) for w in seq]
        for i in range(1, len(seq) - 1):
            if code[i] == 3 and (code[i - 1], code[i + 1]) != (3, 3):
                want[seq[i].encode()][code[i - 1] * 4 + code[i + 1]] += 1
    assert {w: dict(zip(*(told[c].tolist() for c in ("around", "n")), strict=True)) for w, told in got.items()} == want
    table, told = np.random.default_rng(1).random((16, 4)), np.concatenate([got[b"x"], got[b"y"], got[b"x"]])
    firsts = np.array([0, len(got[b"x"]), len(got[b"x"]) + len(got[b"y"])])
    whole = brown_lm.weighed(table, told, firsts)
    monkeypatch.setattr(brown_lm, "PIECE", 1)
    assert np.allclose(whole, brown_lm.weighed(table, told, firsts)) and np.allclose(whole[0], whole[2])
    assert np.allclose(whole[1], sum(table[e["around"]] * e["n"] for e in got[b"y"]))


def test_brown_odd_rows(odd, empty):
    got = brown_lm.score(odd).collect()
    assert len(got) == len(ODD) + 1 and all(math.isfinite(r.score) and math.isfinite(r.base_score) for r in got)
    assert {r.n_tokens for r in got if r.doc_id in (0, 1, 2)} == {1}
    assert brown_lm.score(empty).count() == 0


# -- secrets -----------------------------------------------------------------------------------------


def brute_secrets(text):
    text, found = text or "", []
    rules = [("assign", re.compile(r"""((?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd])|(?:[Pp][Aa][Ss][Ss][Ww][Dd])|(?:[Ss][Ee][Cc][Rr][Ee][Tt])|(?:[Tt][Oo][Kk][Ee][Nn])|(?:[Aa][Pp][Ii]_?[Kk][Ee][Yy]))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), 2, 6), ("access", re.compile("AKIA[A-Z0-9]+"), 0, 20), ("hex", re.compile("[0-9a-f]+"), 0, 24)]
    for order, (kind, rx, group, least) in enumerate(rules):
        found += [(m.start(), order, m.end(), kind) for m in rx.finditer(text) if len(m[group]) >= least]
    return [(k, s, e) for s, _, e, k in sorted(found)]


def test_op7_equals_brute_force(spark, sf_dir):
    sf_dir = sf_dir.replace("sf0.001", "sf0.01")  # the smallest table holds no secrets
    given = {r.doc_id: r for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    got = {r.doc_id: r for r in queries.op7_secret_scan(spark, sf_dir).collect()}
    some = 0
    for i, r in given.items():
        want = brute_secrets(r.text)
        some += len(want)
        count = Counter(k for k, *_ in want)
        assert (got[i].n_assign, got[i].n_access, got[i].n_hex) == (count["assign"], count["access"], count["hex"])
        assert got[i].base_sha256 == hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e in want).encode()).hexdigest()
        assert {f"{k}:{s}:{e}" for k, s, e in want} <= set(got[i].spans.split(",")) | {""}
    assert some


@pytest.mark.parametrize("text", ["TOKEN = 'abcdefg'", "toKen=abc token==abcdef", "ſecret: abcdefgh apiKey=abcdefg", "AKIA" + "A1" * 8, "AKIAAKIA" + "B" * 11, "é" * 3 + "f" * 24 + "0g" + "a" * 23, "password:'x' passwd: \"y\" apikey =  secret=abcdefgh"])
def test_secret_patterns(text):
    base = {k for k, *_ in secrets.BASE}
    assert [s for s in secrets.find_spans(text) if s[0] in base] == brute_secrets(text)


def test_ledger_grows_by_unseen_blobs(spark, odd, empty, tmp_path):
    ledger = f"file://{tmp_path}/ledger"
    assert secrets.scan(odd, ledger).count() == len(ODD) + 1
    first = spark.read.parquet(ledger).count()
    assert secrets.scan(docs_of(spark, ODD + [(77, "password = hunter22")]), ledger).filter("n_assign = 1").count() == 1
    assert spark.read.parquet(ledger).count() == first + 1
    assert secrets.scan(empty, ledger).count() == 0


def test_only_new_versions_and_rules_are_scanned(spark, tmp_path):
    ledger = f"file://{tmp_path}/versions"
    rows = [(1, "a.py", 1, "token=abcdef1"), (2, "a.py", 2, "token=abcdef2"), (3, "b.py", 1, "token=abcdef1"), (4, "c.py", 1, None)]
    df = lambda more: spark.createDataFrame(rows + more, "doc_id bigint, path string, version int, text string")
    assert secrets.scan(df([]), ledger, also=("path", "version")).count() == 4
    seen = {r.blob for r in spark.read.parquet(ledger).collect()}
    assert len(seen) == 3
    more = [(5, "a.py", 3, "token=abcdef3"), (6, "d.py", 1, "token=abcdef2")]
    got = {(r.path, r.version): r.n_assign for r in secrets.scan(df(more), ledger, also=("path", "version")).collect()}
    assert got == {("a.py", 1): 1, ("a.py", 2): 1, ("b.py", 1): 1, ("c.py", 1): 0, ("a.py", 3): 1, ("d.py", 1): 1}
    after = [r.blob for r in spark.read.parquet(ledger).collect()]
    assert len(after) == 4 and len(set(after) - seen) == 1  # one new blob was scanned, the known ones were not
    rules = [*secrets.RULES, ("ticket", r"TICKET-[0-9]+", 0, 1)]
    assert secrets.scan(df(more), ledger, rules=rules).count() == 6
    assert spark.read.parquet(ledger).groupBy("rules").count().count() == 2 and spark.read.parquet(ledger).count() == 8


# -- PII ---------------------------------------------------------------------------------------------

PEOPLE = "Write to Ann.Lee7@mail3.example.com or ann.lee7@mail3.example.com; call +1 (017) 555-7713, ip 10.20.30.40. Card 4111 1111 1111 1111 or 4111111111111111. Mrs. Anna Novak met Mr Karl Braun; id 123-45-6789."


def luhn(digits):
    s = sum(d if i % 2 else d * 2 - 9 * (d > 4) for i, d in enumerate(digits))
    return s % 10 == 0


def test_surrogates_keep_type_and_format(spark, odd, empty):
    texts = [(1, PEOPLE), (2, "again Ann.Lee7@mail3.example.com and Mrs. Anna Novak"), (3, "no entity here"), (4, None), (5, ""), (6, "Госпожа Анна Петрова")]
    got = {r.doc_id: r for r in pii.pseudonymise(docs_of(spark, texts), "k").collect()}
    assert len(got) == 6 and got[4].text is None and got[5].text == "" and got[3].text == texts[2][1] and got[3].n_entities == 0
    new = got[1].text
    for old in ("Ann.Lee7@", "555-7713", "10.20.30.40", "4111 1111 1111 1111", "Novak", "Braun", "123-45-6789"):
        assert old not in new
    mail, phone, ip = re.search(r"[A-Z][a-z]{2}\.[A-Z][a-z]{2}\d@[a-z]{4}\d\.[a-z]{7}\.com", new), re.search(r"\+1 \(\d{3}\) \d{3}-\d{4}", new), re.search(r"ip (\d+)\.(\d+)\.(\d+)\.(\d+)\.", new)
    assert mail and phone and ip and all(int(x) < 256 for x in ip.groups())
    cards = re.findall(r"4\d{3} \d{4} \d{4} \d{4}|\b4\d{15}\b", new)
    assert len(cards) == 2 and all(luhn([int(c) for c in x if c.isdigit()]) for x in cards)
    lady = re.search(r"Mrs\. (\w+) (\w+) met Mr (\w+) ", new)
    assert lady and lady[1] in pii.GIVEN["f", "latin"] and lady[3] in pii.GIVEN["m", "latin"]
    assert mail[0] in got[2].text and f"Mrs. {lady[1]} {lady[2]}" in got[2].text
    assert re.fullmatch(r"Госпожа [А-Я][а-я]+ [А-Я][а-я]+", got[6].text) and got[6].text != texts[5][1]
    other = {r.doc_id: r.text for r in pii.pseudonymise(docs_of(spark, texts), "another key").collect()}
    assert other[1] != new
    assert pii.pseudonymise(odd, "k").count() == len(ODD) + 1 and pii.pseudonymise(empty, "k").count() == 0


def test_surrogates_are_distinct(spark):
    mails = [f"{a}{b}@x.io" for a in "abcdefghij" for b in "abcdefghij"]  # few letters: collisions are certain
    store = Durable(spark, "t")
    people = [("surname", f"{a}{b}") for a in "ABCDEFGH" for b in "abcdefghij"] + [("given m", f"N{b}") for b in "abcdefghijklmnopqrstuvwxyz"]
    rows = [("email", m) for m in mails] + people
    found = store.save(spark.createDataFrame(rows, "kind string, entity string"), "found")
    got = {(r.kind, r.entity): r.surrogate for r in pii.surrogate_table(found, store, "k").collect()}
    assert set(got) == set(rows) and len({(k, s) for (k, _), s in got.items()}) == len(rows)
    assert not {(k, s) for (k, _), s in got.items()} & set(rows)


def test_one_entity_has_one_surrogate(spark):
    texts = [
        (1, "Mr Karl Braun came. Later Mr Braun left, Karl Braun that is, not Karl Brauner. Mrs Eva Braun stayed."),
        (2, "Call +49 30 1234567 or +49301234567, card 4111 1111 1111 1111 or 4111111111111111, a.B@Mail.org or A.b@mail.ORG"),
        (3, "Karl Braun has no title here. Mr Braun has."), (4, "Mr Karl Braun came."), (4, "Mr Karl Braun came."), (5, "+49-30-1234567"),
    ]
    docs = docs_of(spark, texts).withColumn("caller", F.lit(1)).withColumn("_d", F.lit("mine")).withColumn("found", F.lit(2)).withColumn("class", F.lit(3)).withColumn("d", F.lit(4))
    rows = pii.pseudonymise(docs, "k").collect()
    assert len(rows) == 6 and all((r["caller"], r["_d"], r["found"], r["class"], r["d"]) == (1, "mine", 2, 3, 4) for r in rows)
    got = {r.doc_id: r.text for r in rows}
    m = re.fullmatch(r"Mr (\w+) (\w+) came\. Later Mr (\w+) left, (\w+) (\w+) that is, not Karl Brauner\. Mrs (\w+) (\w+) stayed\.", got[1])
    given, name, again, plain_given, plain_name, wife, wife_name = m.groups()
    assert name == again == plain_name == wife_name != "Braun" and given == plain_given != "Karl" and wife not in ("Eva", given)
    assert got[3] == f"Karl Braun has no title here. Mr {name} has." and got[4] == f"Mr {given} {name} came."
    a, b, c, d, e, f = re.fullmatch(r"Call (\+49 \d\d \d{7}) or (\+49\d{9}), card ([\d ]{19}) or (\d{16}), (\S+) or (\S+)", got[2]).groups()
    assert re.sub(r"\D", "", a) == b[1:] == re.sub(r"\D", "", got[5]) != "49301234567" and re.fullmatch(r"\+49-\d\d-\d{7}", got[5])
    assert c.replace(" ", "") == d != "4111111111111111" and luhn([int(x) for x in d])
    assert e.lower() == f.lower() != "a.b@mail.org" and e.endswith(".org") and re.fullmatch(r"[a-z]\.[A-Z]@[A-Z][a-z]{3}\.org", e) and re.fullmatch(r"[A-Z]\.[a-z]@[a-z]{4}\.ORG", f)


def test_op8_leaves_no_entity(spark, sf_dir, given):
    got = {r.doc_id: r for r in queries.op8_pii_surrogates(spark, sf_dir).collect()}
    rx = re.compile(r"[\w.%+-]+@[\w.-]+\.[a-z]+|\+\d \(\d{3}\) \d{3}-\d{4}|(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?![\d.])|(?<!\d)\d{16}(?!\d)")
    assert len(got) == len(given) and any(r.n_entities for r in got.values())
    for i, r in given.items():
        assert not set(rx.findall(r.text)) & set(rx.findall(got[i].text))
        if not got[i].n_entities:
            assert got[i].text == r.text


# -- toxicity ----------------------------------------------------------------------------------------


def test_classifier_on_held_out_rows(spark):
    rng = random.Random(4)
    bad = ["zorkish", "flumph", "grobnik"]
    texts, labels = [], []
    for i in range(900):
        w = ["".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 7))) for _ in range(60)]
        toxic = i % 4 == 0
        if toxic:
            w[rng.randrange(60)] = rng.choice(bad)
        texts.append((i, " ".join(w)))
        labels.append((i, int(toxic)))
    got = toxicity.toxicity(docs_of(spark, texts), spark.createDataFrame(labels, "doc_id bigint, toxic int")).collect()
    held = [r for r in got if r.held_out]
    assert {r.doc_id for r in held} == {i for i, _ in texts if zlib.crc32(str(i).encode()) % 3 == 1}
    assert sum((r.predicted == 1) == (r.doc_id % 4 == 0) for r in held) / len(held) > 0.97
    assert all(0 <= r.score <= 1 and (r.predicted == 1) == (r.score >= 0.7) for r in got)


def test_fit_equals_plain_loops(spark):
    rng, texts, labels = random.Random(14), [], []
    for i in range(160):
        toxic = i % 3 == 0
        w = ["".join(rng.choice("abcd") for _ in range(4)) for _ in range(12)] + (["Zorky"] if toxic and rng.random() < 0.8 else ["mild"] if rng.random() < 0.5 else [])
        texts.append((i, " ".join(w)))
        labels.append((i, int(toxic)))
    learn = [i for i, _ in texts if zlib.crc32(str(i).encode()) % 3 != 1]
    grams = {i: {(b" " + t.encode().lower() + b" ")[k : k + n] for n in (4, 5, 6) for k in range(len(t) + 3 - n)} for i, t in texts}
    n_pos, n_neg = sum(i % 3 == 0 for i in learn), sum(i % 3 != 0 for i in learn)
    pos, neg = (Counter(g for i in learn if (i % 3 == 0) == y for g in grams[i]) for y in (True, False))
    chosen = {}
    for g in set(pos) | set(neg):
        a, b, n = pos[g], neg[g], n_pos + n_neg
        cells = [(a, (a + b) * n_pos / n), (b, (a + b) * n_neg / n), (n_pos - a, (n - a - b) * n_pos / n), (n_neg - b, (n - a - b) * n_neg / n)]
        if sum(2 * o * math.log(o / e) for o, e in cells if o) >= toxicity.TEST:
            chosen[g] = math.log((a + 1) / (n_pos + 2)) - math.log((b + 1) / (n_neg + 2))
    assert len(chosen) >= 5
    keys = sorted(chosen)
    x = np.array([[chosen[g] if g in grams[i] else 0.0 for g in keys] for i in learn])
    y = np.array([i % 3 == 0 for i in learn], dtype=float)
    w, b = np.zeros(len(keys)), 0.0
    for _ in range(60):  # Newton's method on the same objective
        q = 1 / (1 + np.exp(-(x @ w + b)))
        z = np.c_[x, np.ones(len(y))]
        hess = z.T @ (z * (q * (1 - q))[:, None]) / len(y) + np.diag(np.r_[np.full(len(keys), 1e-3), 1e-9])
        step = np.linalg.solve(hess, z.T @ (q - y) / len(y) + np.r_[1e-3 * w, 0.0])
        w, b = w - step[:-1], b - step[-1]
    got = {r.doc_id: r.score for r in toxicity.toxicity(docs_of(spark, texts), spark.createDataFrame(labels, "doc_id bigint, toxic int")).collect()}
    for i, _ in texts:
        want = 1 / (1 + math.exp(-(sum(chosen[g] * w[j] for j, g in enumerate(keys) if g in grams[i]) + b)))
        assert got[i] == pytest.approx(want, abs=0.03)


def test_ngrams_of_long_texts_are_whole(monkeypatch):
    data = bytes(random.Random(1).choices(b"abcde ", k=1000))
    whole = toxicity.ngrams(data)
    monkeypatch.setattr(toxicity, "PIECE", 64)
    assert (toxicity.ngrams(data) == whole).all()


def test_toxicity_odd_rows(spark, odd, empty):
    none = spark.createDataFrame([], "doc_id bigint, toxic int")
    some = spark.createDataFrame([(3, 1), (3, 0), (5, 0), (None, 1), (6, None)], "doc_id bigint, toxic int")
    for labels in (none, some):
        got = toxicity.toxicity(odd, labels).collect()
        assert len(got) == len(ODD) + 1 and all(0 <= r.score <= 1 for r in got)
    assert toxicity.keep_clean(odd, none).columns == odd.columns
    assert toxicity.toxicity(empty, none).count() == 0


# -- WARC --------------------------------------------------------------------------------------------


def test_op10_round_trip(spark, sf_dir):
    pages = {r.page_id: (r.html or "").encode() for r in spark.read.parquet(f"{sf_dir}/pages.parquet").collect()}
    first = {}
    for i in sorted(pages):
        first.setdefault(pages[i], i)
    got = {r.page_id: r for r in queries.op10_warc(spark, sf_dir).collect()}
    assert set(got) == set(pages)
    for i, data in pages.items():
        assert (got[i].payload_bytes, got[i].payload_digest) == (len(data), base64.b32encode(hashlib.sha1(data).digest()).decode())
        assert (got[i].record_type, got[i].refers_to) == (("response", None) if first[data] == i else ("revisit", first[data]))


@pytest.mark.parametrize("split", [7, 100, 1 << 20])
def test_ranges_own_each_record_once(spark, tmp_path, split):
    inner = warc.record_bytes(9, "http://x", b"inner", warc.sha1_base32(b"inner"), None, False)
    pages = [(1, "http://a", "hello"), (2, None, None), (3, "http://b", ""), (4, "http://a", "hello"), (5, "http://c", "x\r\n\r\nWARC/1.1\r\n" * 50), (None, "u", "hello"), (7, "u", inner.decode("latin-1")), (7, "u", "again")]
    df = spark.createDataFrame(pages, "page_id bigint, url string, html string")
    folder = f"file://{tmp_path}/w{split}"
    assert warc.write_archives(warc.classify(df), folder, 3) == 8
    got = warc.read_archives(spark, folder, split).collect()
    assert sorted(str(r.page_id) for r in got) == sorted(str(p[0]) for p in pages)
    by = {r.page_id: r for r in got if r.page_id not in (7, None)}
    assert (by[2].record_type, by[3].record_type, by[3].refers_to, by[3].payload_bytes) == ("response", "revisit", 2, 0)
    assert (by[4].refers_to, by[4].payload_bytes, by[5].payload) == (1, 5, pages[4][2].encode())
    assert warc.read_archives(spark, folder + "-none").count() == 0
    assert warc.round_trip(df.limit(0), f"{folder}-empty").count() == 0


def brute_records(pages, least):
    """Sorted (page_id, bytes, digest, type, refers_to) of the records of pages."""
    data = [(i, (h or "").encode()) for i, _, h in pages]
    home = {d: min((i for i, x in data if x == d and i is not None), default=None) for _, d in data if len(d) >= least}
    made, done = [], set()
    for i, d in data:
        to = home.get(d)
        response = to is None or (to == i and d not in done)
        if response and to is not None:
            done.add(d)
        made.append((i, len(d), base64.b32encode(hashlib.sha1(d).digest()).decode(), "response" if response else "revisit", None if response else to))
    return sorted(made, key=str)


@pytest.mark.parametrize("least", [0, 3])
def test_records_equal_brute_force(spark, tmp_path, least):
    rng, bodies = random.Random(8), ["ab", "abcdef", "", None, "<p>x</p>", "zz" * 50]
    pages = [(rng.choice([None, *range(12)]), rng.choice(["u", "v", None]), rng.choice(bodies)) for _ in range(150)] + [(3, "u", "same")] * 40
    df = spark.createDataFrame([(*p, 1, "c") for p in pages], "page_id bigint, url string, html string, n long, class string")
    for part in (df, df.filter("page_id < 6"), df.limit(0)):  # smaller archives in the same folder leave none of the larger ones
        got = warc.round_trip(part, f"file://{tmp_path}/again", least).collect()
        want = brute_records([(r.page_id, r.url, r.html) for r in part.collect()], least)
        assert sorted((tuple(r) for r in got), key=str) == want


def test_names():
    numbers = sorted(int(json.loads(json.dumps(n))[2:].split("_")[0]) for n in queries.queries() if n.startswith("op"))
    assert numbers == list(range(1, 11)) and "pipeline" in queries.queries()
