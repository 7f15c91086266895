"""Every operator on nulls, empty and long texts, ties, repeated rows, empty tables and clashing extra columns."""

import pytest
from pyspark.sql import functions as F

from vpcoreset.llm import decontaminate, language_model, licenses, mixing, neighbours, ngram_join, pii, secrets, toxicity, warc

LONG = "word " * 30_000 + "x" * 1_200_000
ITEM = "one two three four five six seven eight nine ten eleven twelve"
ROWS = [
    (1, None, None, None, None, 5), (2, "", "en", "b", 0, 5), (3, "  \n\t ", "en", "a", 5, 5), (4, LONG, "en", "a", 9, 5), (5, f"so {ITEM} so", "en", None, 9, 5),
    (5, f"so {ITEM} so", "en", None, 9, 5), (6, "token = abcdefghijklmnop me@site.org", "en", "a", 9, 5), (7, "token = abcdefghijklmnop me@site.org", "de", "b", 9, 5), (None, "lonely words here", "en", "a", 9, 5), (8, "one two", "en", "a", 7, 5),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, {} int"
#: Names that the operators use inside.
CLASH = ("id", "size", "score", "label", "row", "blob", "weight", "sig", "entities")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, i % 2) for i in range(1, 9)] + [(None, 1, 1), (2, 0, None)], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame([(1, ITEM), (2, None), (3, "too short"), (4, ITEM)], "item_id long, text string")


OPS = {
    "lm": lambda d, b, l: language_model.score_documents(d),
    "leaks": lambda d, b, l: decontaminate.find_leaks(d, b),
    "drop_leaking": lambda d, b, l: decontaminate.drop_leaking(d, b),
    "ngrams": lambda d, b, l: ngram_join.ngram_join(d),
    "toxicity": lambda d, b, l: toxicity.toxicity(d, l),
    "reject_toxic": lambda d, b, l: toxicity.reject_toxic(d, l),
    "secrets": lambda d, b, l: secrets.scan_secrets(d),
    "licenses": lambda d, b, l: licenses.scan_licenses(d),
    "mix": lambda d, b, l: mixing.pareto_mix(d),
    "pii": lambda d, b, l: pii.anonymise(d, found_col="entities"),
}
#: Rows out of the ten rows in; None: not one for each.
COUNTS = {"lm": 10, "ngrams": 10, "toxicity": 10, "secrets": 10, "licenses": 10, "mix": 10, "pii": 10}


@pytest.mark.parametrize("extra", CLASH)
@pytest.mark.parametrize("name", ["ngrams", "mix", "secrets", "pii"])
def test_clashing_columns(spark, labels, items, name, extra):
    docs = spark.createDataFrame(ROWS, SCHEMA.format(extra))
    assert OPS[name](docs, items, labels).count() == 10


@pytest.mark.parametrize("name", OPS)
def test_odd_rows(spark, labels, items, name):
    docs = spark.createDataFrame(ROWS, SCHEMA.format("score"))
    rows = OPS[name](docs, items, labels).collect()
    if name in COUNTS:
        assert len(rows) == COUNTS[name]


@pytest.mark.parametrize("name", OPS)
def test_empty_tables(spark, labels, items, name):
    docs = spark.createDataFrame([], SCHEMA.format("score"))
    assert OPS[name](docs, items.limit(0), labels.limit(0)).count() == 0


@pytest.mark.parametrize("name", OPS)
@pytest.mark.parametrize("text", [None, " "])
def test_nothing_but_empty_texts(spark, labels, items, name, text):
    docs = spark.createDataFrame([(i, text, "en", "a", 0, 1) for i in range(1, 13)], SCHEMA.format("score"))
    rows = OPS[name](docs, items, labels).count()
    assert rows == 12 if name in COUNTS or name.startswith(("drop", "reject")) else rows == 0


def test_values_of_odd_rows(spark, labels, items):
    docs = spark.createDataFrame(ROWS, SCHEMA.format("size"))
    lm = {r.doc_id: r for r in language_model.score_documents(docs).collect()}
    assert lm[1].n_tokens == lm[2].n_tokens == lm[3].n_tokens == 1 and lm[4].n_tokens == 30_002
    groups = ngram_join.ngram_join(docs).collect()
    assert {(r.doc_id, r.class_id, r.n_links) for r in groups} == {(1, 1, 0), (2, 2, 0), (3, 3, 0), (4, 4, 0), (5, 5, 1), (6, 6, 1), (7, 6, 1), (8, 8, 0), (None, None, 0)}
    assert {(r.doc_id, r.item_id) for r in decontaminate.find_leaks(docs, items).collect()} == {(5, 1), (5, 4)}
    assert {r.doc_id for r in decontaminate.drop_leaking(docs, items).collect()} == {1, 2, 3, 4, 6, 7, 8, None}
    text = {r.doc_id: r.text for r in pii.anonymise(docs).collect()}
    assert text[1] is None and text[2] == "" and text[4] == LONG and text[6] == text[7] and "me@site.org" not in text[6]
    found = {r.doc_id: r for r in secrets.scan_secrets(docs).collect()}
    assert found[1].n_assign == 0 and found[6].spans == "assign:0:24" == found[7].spans and found[None].spans == ""
    mix = mixing.pareto_mix(docs).collect()
    assert all(r.taken <= 2 * r.size for r in mix) and {r.size for r in mix if r.doc_id in (1, 2, 3)} == {0}
    lic = licenses.scan_licenses(docs).collect()
    assert len({r.digest for r in lic if r.doc_id in (1, 2, 3)}) == 1
    assert toxicity.score_toxicity(docs.select(F.lit("1").alias("id"), "text"), {"tokens": {}, "stems": {}, "lambda": 1.0, "K": 1.0, "curve": (0, 0), "significance": 0.05}).agg(F.max("score")).collect()[0][0] == 0


def test_vectors(spark):
    inf, nan = float("inf"), float("nan")
    rows = [(0, [1.0, 0.0], 0), (1, [2.0, 0.0], 0), (2, [1.0, 0.0], 0), (3, None, 0), (4, [0.0, 0.0], 0), (5, [1.0, None], 0), (6, [inf, 1.0], 0), (7, [nan, 1.0], 0), (8, [1.0, 0.0, 0.0], 0), (9, [0.0, 1.0], 0), (0, [1.0, 0.0], 0), (50, [0.0, -1.0], 0), (100, [], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, score int")
    got = [(r.query_id, r["rank"], r.vec_id, r.score) for r in neighbours.nearest(df).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 1, 1.0), (0, 2, 2, 1.0), (0, 3, 9, 0.0), (0, 4, 50, 0.0), (50, 1, 0, 0.0), (50, 2, 0, 0.0), (50, 3, 1, 0.0), (50, 4, 2, 0.0), (50, 5, 9, -1.0)]
    assert neighbours.nearest(df.limit(0)).count() == 0


def test_pages(spark):
    rows = [(1, "u", "a" * 1000, 0), (2, None, "a" * 1000, 0), (3, "u\r\nx", None, 0), (4, "u", "", 0), (5, "u", "é" * 600, 0), (5, "u", "é" * 600, 0), (None, "u", "a" * 1000, 0), (7, "u", "short", 0), (8, "u", "short", 0)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, payload int")
    got = sorted(((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in warc.archive_round_trip(df).collect()), key=str)
    assert got == sorted([(1, 1000, "revisit", 2), (2, 1000, "response", None), (3, 0, "response", None), (4, 0, "response", None), (5, 1200, "response", None), (5, 1200, "response", None), (None, 1000, "response", None), (7, 5, "response", None), (8, 5, "response", None)], key=str)
    assert warc.archive_round_trip(df.limit(0)).count() == 0
