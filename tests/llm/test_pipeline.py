"""The pipeline against a brute-force version on a small fixture."""

import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tests.llm.test_operators import brute_links
from vpcoreset.llm import decontaminate, mixing, pii, toxicity


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    rng = random.Random(5)
    words = [f"w{i}" for i in range(300)]
    rows, labels = [], []
    for i in range(240):
        t = rng.choices(words, k=rng.randrange(20, 70))
        toxic = int(i % 6 == 0)
        if toxic:
            t[5:5] = rng.sample(["badword", "worseword", "worstword", "vileword"], 3)
        rows.append((i, " ".join(t), "en", f"s{i % 3}", 0))
        labels.append((i, 1, toxic))
    item = " ".join(rng.choices(words, k=25))
    rows += [(300 + i, rows[2 * i + 1][1] + " tail", "en", "s0", 0) for i in range(20)]
    rows += [(400 + i, " ".join(rng.choices(words, k=30)) + " " + item, "en", "s1", 0) for i in range(5)]
    rows += [(500, "write to jo.doe@site.org " + " ".join(rng.choices(words, k=30)), "en", "s2", 0), (501, None, None, None, None)]
    d = str(tmp_path_factory.mktemp("small"))
    spark.createDataFrame([(a, b, c, s, len(b) if b else None) for a, b, c, s, _ in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    return d


def test_pipeline_equals_brute_force(spark, small):
    got = {r.doc_id: (r.size, r.taken) for r in corpus_pipeline.run(spark, small).collect()}
    docs = spark.read.parquet(f"{small}/documents.parquet")
    verdict = {r.doc_id: r.predicted for r in toxicity.toxicity(docs, spark.read.parquet(f"{small}/labels.parquet")).collect()}
    assert {i for i, v in verdict.items() if v} == {i for i in range(0, 240, 6)}
    rows = {r.doc_id: r for r in docs.collect() if not verdict[r.doc_id]}
    classes = brute_links([(i, r.text) for i, r in rows.items()])
    rows = {i: r for i, r in rows.items() if classes[i][0] == i}
    assert not any(300 <= i < 320 for i in rows)
    item = spark.read.parquet(f"{small}/benchmark.parquet").collect()[0].text
    index = decontaminate.build_index([(1, item)])
    rows = {i: r for i, r in rows.items() if not list(decontaminate.leaks(r.text, index, decontaminate.Vocabulary(index["names"]), 10, 0.8))}
    assert not any(400 <= i < 405 for i in rows)
    act = pii.Surrogates("surrogates")
    left = spark.createDataFrame([(i, act(r.text)[0], r.source) for i, r in rows.items()], "doc_id long, text string, source string")
    assert got == {r.doc_id: (r.size, r.taken) for r in mixing.pareto_mix(left).collect()}


def test_stages_keep_the_columns(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near duplicates", "benchmark decontamination", "personal data", "source mix"]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, small)
        assert out.columns == docs.columns
    masked = corpus_pipeline.surrogates_in(spark, docs, small).where("doc_id = 500").collect()[0]
    assert "jo.doe@site.org" not in masked.text and masked.n_chars == len(masked.text)


def test_stages_on_an_empty_table(spark, small, tmp_path):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    docs.limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    for name in ("labels", "benchmark"):
        spark.read.parquet(f"{small}/{name}.parquet").write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    assert docs.where(F.col("doc_id") < 0).count() == 0
