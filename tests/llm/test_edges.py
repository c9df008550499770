"""Nulls, empty and very long texts, repeated rows, empty tables and clashing column names, for every text operator."""

import pytest
from pyspark.sql import functions as F

from subsetheavy.llm import decontamination as dc
from subsetheavy.llm import jaccard as jc
from subsetheavy.llm import language as la
from subsetheavy.llm import packing as pk
from subsetheavy.llm import quality as qu
from subsetheavy.llm import secrets as sc
from subsetheavy.llm import tokens as tk
from subsetheavy.llm import toxicity as tx
from subsetheavy.llm.queries import tokenizer_file

LONG = "one two three four five six seven eight nine ten\n" * 30_000
PLAIN = "a plain text of some quiet words about rivers and old stone houses"
ROWS = [(1, PLAIN, "en"), (1, PLAIN, "en"), (2, None, None), (None, "no id here but words", "en"), (None, None, "de"), (3, "", "de"), (4, " \n\t ", "en"),
        (5, LONG, "en"), (6, "日本語のテキスト 🙂 naïve", "ja"), (7, "password = Zk9mQ2vXr7aa", "en"), (1, "another text of the same id", "en")]
#: Names that operators use inside.
CLASH = ("n", "node", "key", "kind", "score", "shard", "bucket", "n_tokens", "component_id", "label", "id", "words", "a", "b", "held_out", "spans", "share")


def labels(spark):
    return spark.createDataFrame([(i, i % 2, (i + 1) % 2) for i in (1, 3, 4, 5, 6, 7)] + [(None, None, None), (1, 1, 0)], "doc_id bigint, quality int, toxic int")


def bench(spark):
    return spark.createDataFrame([(1, PLAIN), (2, None), (3, ""), (1, PLAIN), (None, "x y")], "item_id bigint, text string")


ROW_WISE = {
    "op1": lambda s, d: pk.packed(tk.token_counts(d, tokenizer_file())).where("piece = 0"),
    "op2": lambda s, d: qu.quality_scores(d, labels(s)),
    "op3": lambda s, d: jc.jaccard_classes(d),
    "op4": lambda s, d: tk.read_ids(s, tk.write_ids(d, tokenizer_file())),
    "op5": lambda s, d: tx.toxicity_scores(d, labels(s)),
    "op7": lambda s, d: la.languages(d),
    "op10": lambda s, d: sc.secret_digests(d),
}


@pytest.fixture(scope="module")
def table(spark):
    got = spark.createDataFrame(ROWS, "doc_id bigint, text string, lang string")
    return got.select("*", *(F.lit(f"{c}?").alias(c) for c in CLASH)).persist()


@pytest.mark.parametrize("op", ROW_WISE)
def test_every_row_has_its_result(spark, table, op):
    got = ROW_WISE[op](spark, table).collect()
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0) for r in got) == sorted((r[0] is None, r[0] or 0) for r in ROWS)
    assert ROW_WISE[op](spark, table.limit(0)).count() == 0
    if op in ("op2", "op5", "op7"):
        assert all(0 <= r["score"] <= 1 for r in got)
    if op == "op10":
        assert all(len(r["base_sha256"]) == 64 and r["spans"] is not None for r in got) and sum(r["n_assign"] for r in got) == 1
    if op == "op1":
        assert next(r["n_tokens"] for r in got if r["doc_id"] == 5) == pk.LENGTHS[-1]


def test_leaks_of_odd_rows(spark, table):
    got = dc.benchmark_leaks(table, bench(spark)).collect()
    assert {(r["doc_id"], r["item_id"]) for r in got} == {(1, 1)}
    assert dc.benchmark_leaks(table.limit(0), bench(spark)).count() == 0
    assert dc.clean_docs(table, bench(spark)).count() == len(ROWS) - 2 and dc.clean_docs(table, bench(spark)).columns == table.columns


def test_filters_keep_all_columns(spark, table):
    assert sc.masked_docs(table).columns == table.columns and sc.masked_docs(table).count() == len(ROWS)
    assert qu.good_docs(table, labels(spark)).columns == table.columns
    assert jc.distinct_docs(table).columns == table.columns
    with pytest.raises(ValueError):
        jc.distinct_docs(table.withColumn("__set", F.lit(1)))


def test_vectors_of_odd_rows(spark):
    from subsetheavy.llm.embeddings import near_vectors

    rows = [(1, [1.0, 0.0], "x"), (1, [1.0, 0.0], "x"), (2, [1.0, 0.001], "y"), (None, [1.0, 0.0], "z"), (3, None, "k"), (4, [], "k"), (5, [0.0, 0.0], "k"), (6, [float("inf"), 1.0], "k")]
    for kind in ("float", "double"):
        frame = spark.createDataFrame(rows, f"vec_id bigint, embedding array<{kind}>, raw string")
        got = near_vectors(frame).collect()
        assert len(got) == len(rows) and all(r["component_id"] == 1 and r["n_links"] == 3 for r in got if r["vec_id"] in (1, 2, None))
        assert all(r["n_links"] == 0 for r in got if r["vec_id"] in (3, 4, 5, 6))
        assert near_vectors(frame.limit(0)).count() == 0


def test_urls_of_odd_rows(spark):
    from subsetheavy.llm.urls import url_verdicts

    rows = [(1, "http://x.org/a", "h"), (1, "http://x.org/a", "h"), (None, None, None), (2, "", "h"), (3, "http://" + "a." * 200 + "com/" + "p" * 100_000, "h"), (4, "://", "h")]
    frame = spark.createDataFrame(rows, "page_id bigint, url string, host string")
    assert url_verdicts(frame).count() == len(rows) and url_verdicts(frame.limit(0)).count() == 0
