"""The pipeline: each stage on odd tables, and planted cases through all stages."""

import random

import corpus_pipeline

from .test_operators import DOCS, ODD, docs_of, edited


def write(spark, folder, docs, bench, labels):
    docs.write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(bench, "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")


def test_stages_keep_columns_on_odd_and_empty_tables(spark, tmp_path):
    for name, texts in (("odd", [*ODD, (3, "Alpha beta"), (None, "no id"), (None, None)]), ("empty", [])):
        docs = docs_of(spark, texts)
        write(spark, f"{tmp_path}/{name}", docs, [(1, "a b c d e f g h i j")], [(3, 1, 1), (5, 1, 0)])
        for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
            got = stage(spark, docs, f"{tmp_path}/{name}")
            assert i == 4 or got.columns == docs.columns
            assert got.count() <= len(texts) * (2 if i == 4 else 1)
            if i == 4:
                rows = got.collect()
                assert sum(r.size for r in rows if r.shard is not None) >= sum({(r.doc_id, r.text): r.taken for r in rows}.values())
                assert all((r.taken == 0) == (r.shard is None) for r in rows)


def test_planted_cases(spark, tmp_path):
    rng = random.Random(8)
    vocabulary = ["".join(rng.choice("abcdefghijkl") for _ in range(rng.randrange(2, 8))) for _ in range(4000)]
    base = {i: [rng.choice(vocabulary) for _ in range(150)] for i in range(300)}
    toxic = set(range(0, 300, 3))
    for i in toxic:
        base[i][rng.randrange(150)] = rng.choice(["zorkish", "flumph"])
    item = " ".join(rng.choice(vocabulary) for _ in range(40))
    texts = [(i, " ".join(w)) for i, w in base.items()]
    texts += [(1000, " ".join(base[1])), (1001, edited(rng, base[2], 1)), (1002, " ".join(base[4][:50]) + " " + item + " ok")]
    write(spark, f"{tmp_path}/p", docs_of(spark, texts), [(1, item)], [(i, 1, int(i in toxic)) for i in range(300)])
    got = {r.doc_id for r in corpus_pipeline.run(spark, f"{tmp_path}/p").collect()}
    clean = set(range(300)) - toxic
    assert len(clean - got) <= 1 and not got & {1000, 1001, 1002} and len(got & toxic) <= 3
    assert DOCS
