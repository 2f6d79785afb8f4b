"""The pipeline's stages, and their registration."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from catalogflow.llm import queries
from catalogflow.session import staged, table


def test_ten_operators_are_registered():
    assert sorted(int(n[2:].split("_")[0]) for n in queries.QUERIES) == list(range(1, 11))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_duplicates", "mixture", "packing"]


def test_stages_keep_columns_and_whole_documents(spark, sf):
    docs = table(spark, sf, "documents")
    before = {r["doc_id"]: r["text"] for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = staged(stage(spark, docs, sf), f"t-{name}")
        assert out.columns == docs.columns and 0 < out.count() <= docs.count()
        docs = out
    kept = docs.collect()
    assert all(before[r["doc_id"]] == r["text"] for r in kept) and max(Counter(r["text"] for r in kept).values()) == 1
    windows = corpus_pipeline.STAGES[-1][1](spark, docs, sf).toPandas()
    assert windows.groupby("doc_id")["tokens"].sum().to_dict() == {r["doc_id"]: len(r["text"].split()) for r in kept}
    whole = corpus_pipeline.run(spark, sf).toPandas()
    assert sorted(map(str, whole.values.tolist())) == sorted(map(str, windows.values.tolist()))


@pytest.mark.parametrize("stage", [f for _, f in corpus_pipeline.STAGES])
def test_stages_on_empty_and_odd_tables(spark, sf, stage):
    docs = table(spark, sf, "documents")
    assert stage(spark, docs.where("false"), sf).count() == 0
    nulls = spark.createDataFrame([(None, None, None, None, None), (1, None, "en", "a", 0), (2, "", "en", None, 0)], docs.schema)
    assert stage(spark, docs.where("doc_id < 20").unionByName(nulls), sf).count() > 0


def test_stages_on_long_texts_ties_repeated_rows_and_clashing_columns(spark, sf):
    """Every column of the operators' own names comes back unchanged; equal rows are treated alike."""
    names = ["digest", "h", "level", "threshold", "mix_cut", "nd_rank", "group_id", "kept", "copies", "rep", "bands", "li_pred", "tokens", "part", "n"]
    docs = table(spark, sf, "documents").where("doc_id < 40")
    for i, n in enumerate(names):
        docs = docs.withColumn(n, F.lit(i).cast("bigint"))
    long = " ".join(f"the word{i % 999} and of that" for i in range(40_000))
    own = ",".join(str(i) for i in range(len(names)))
    more = spark.createDataFrame([(7000, long, "en", "a", len(long)), (7000, long, "en", "a", len(long)), (7001, long, "en", None, len(long)), (None, "the cat and the dog of that man", None, "a", 31)], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs = staged(docs.unionByName(more.selectExpr("*", *[f"cast({v} as bigint) {n}" for v, n in zip(own.split(","), names)])), "odd")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = staged(stage(spark, docs, sf), "odd")
        got = out.collect()
        assert out.columns == docs.columns and got and all([r[n] for n in names] == list(range(len(names))) for r in got)
        docs = out
        if name == "near_duplicates":
            ids = Counter(r["doc_id"] for r in got)
            assert ids[7000] == 1 and ids[7001] == 0 and ids[None] == 1
            unmixed = out
    windows = corpus_pipeline.STAGES[-1][1](spark, unmixed, sf).toPandas()
    assert windows[windows["doc_id"] == 7000]["tokens"].sum() == 200_000
