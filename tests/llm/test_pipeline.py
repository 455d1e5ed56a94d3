"""Every stage's decisions on a small corpus, against brute force."""

import random

import corpus_pipeline
import pytest
from test_near_dup import brute as near_brute
from test_suffix_dedup import brute as repeat_brute


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = random.Random(1)
    word = lambda: f"w{rng.randrange(4000)}"
    text = lambda n: " ".join(word() for _ in range(n))
    items = [text(25) for _ in range(5)]
    passage = text(60)
    rows = []
    for i in range(120):
        t = text(rng.randint(30, 90))
        if i % 10 == 3:
            t = " ".join(w + "###" for w in t.split())
        if i % 10 == 4 and i > 10:
            t = rows[i - 5][1].replace(" w1", " x1", 1)
        if i % 20 == 7:
            t = f"{t} {passage} {text(5)}"
        if i % 30 == 9:
            t = f"{t} {items[i % 5]} {text(3)}"
        rows.append((i, t, "en", "src", len(t)))
    path = str(tmp_path_factory.mktemp("sf"))
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").repartition(3).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(i, int(i % 10 != 3), 0) for i in range(120)], "doc_id bigint, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string").write.parquet(f"{path}/benchmark.parquet")
    return path


def test_stages_one_by_one(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    columns, stages = docs.columns, dict(corpus_pipeline.STAGES)
    texts = lambda df: {r.doc_id: r.text for r in df.collect()}
    before = texts(docs)

    good = stages["quality classifier"](spark, docs, folder)
    assert good.columns == columns
    kept = texts(good)
    assert all(i % 10 != 3 for i in kept) and len(kept) >= 100

    single = stages["MinHash near-dedup"](spark, good, folder)
    assert single.columns == columns
    want = {i for i, (_, comp) in near_brute(list(kept.items()), 5).items() if i == comp}
    assert set(texts(single)) == want and len(want) < len(kept)

    cut = stages["suffix-array dedup"](spark, single, folder)
    assert cut.columns == columns
    left = texts(cut)
    removed = {i: n for i, _, n, _, _ in repeat_brute([(i, kept[i]) for i in want])}
    assert {i: len(kept[i]) - len(left[i]) for i in want} == removed and any(removed.values())
    assert all(r.n_chars == len(r.text) for r in cut.collect())

    clean = stages["benchmark decontamination"](spark, cut, folder)
    assert clean.columns == columns
    bench = [r.text for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect()]
    assert set(texts(clean)) == {i for i, t in left.items() if not any(b in t for b in bench)}
    assert set(texts(clean)) < set(left)

    out = stages["SentencePiece encoding and decoding"](spark, clean, folder).collect()
    assert {r.doc_id for r in out} == set(texts(clean)) and all(r.round_trip for r in out)

    assert sorted(corpus_pipeline.run(spark, folder).collect()) == sorted(out)
    assert before == texts(docs)


def test_stages_carry_columns_whatever_their_names(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(40)
    names = ["score", "predicted", "stats", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text", "Score_2"]
    for name in names:
        docs = docs.selectExpr("*", f"concat('{name} of ', doc_id) AS {name}")
    stages = dict(corpus_pipeline.STAGES)
    for name in ("quality classifier", "suffix-array dedup"):
        out = stages[name](spark, docs, folder)
        assert out.columns == docs.columns
        rows = out.collect()
        assert rows and all(r[n] == f"{n} of {r.doc_id}" for r in rows for n in names)
