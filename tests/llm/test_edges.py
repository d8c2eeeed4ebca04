"""Nulls, empty and very long texts, ties, repeated rows, empty tables and clashing columns, for every operator and stage."""

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from chartrel.llm import decontam, embeddup, langid, linededup, minhash, mixing, pii, quality, tokencounts, toxicity

from .conftest import EDGE, SCHEMA

LABELS = "doc_id long, toxic int, size long"
ITEMS = "item_id long, text string, doc_id long"


def labels(spark, rows=((1, 1), (6, 0), (7, None), (7, 5), (None, 1), (99, 1))):
    return spark.createDataFrame([(i, t, 3) for i, t in rows], LABELS)


def items(spark, rows=((1, "same text here for the tie of two rows at least today"), (2, None), (3, ""), (4, "no id"))):
    return spark.createDataFrame([(i, t, 0) for i, t in rows], ITEMS)


OPERATORS = {
    "pii": lambda s, d: pii.personal_data(d),
    "tokens": lambda s, d: tokencounts.counted(d.select("doc_id", "text", "source", "lang"), "/opt/tokenizers/byte_bpe_50k.tiktoken"),
    "quality": lambda s, d: quality.classify(d),
    "minhash": lambda s, d: minhash.classes(d),
    "langid": lambda s, d: langid.identify(d),
    "toxicity": lambda s, d: toxicity.score(d, labels(s)),
    "mixing": lambda s, d: mixing.taken_by_document(*mixing.mix_sources(mixing.sized(d))),
    "lines": lambda s, d: linededup.dedup_lines(d),
}


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_one_row_per_row(spark, edge, name):
    got = OPERATORS[name](spark, edge).collect()
    assert len(got) == len(EDGE)
    assert sorted(str(r["doc_id"]) for r in got) == sorted(str(r[0]) for r in EDGE)


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_empty_table(spark, none, name):
    assert OPERATORS[name](spark, none).count() == 0


@pytest.mark.parametrize("stage", [s for s, _ in corpus_pipeline.STAGES])
def test_stages(spark, edge, none, tmp_path, stage):
    labels(spark).write.parquet(str(tmp_path / "labels.parquet"))
    items(spark).write.parquet(str(tmp_path / "benchmark.parquet"))
    f = dict(corpus_pipeline.STAGES)[stage]
    got = f(spark, edge, str(tmp_path))
    ids = {str(r["doc_id"]) for r in got.collect()}
    assert f(spark, none, str(tmp_path)).count() == 0
    if stage != "mixing":
        assert got.columns == edge.columns and [t for _, t in got.dtypes] == [t for _, t in edge.dtypes]
    if stage == "near_dedup":
        assert "7" not in ids and {"6", "1", "2", "None"} <= ids
    if stage == "decontamination":
        assert not {"6", "7"} & ids and {"1", "2", "3", "5", "None"} <= ids
    if stage == "toxicity":
        assert {"2", "3", "4"} <= ids


def test_defined_results(spark, edge):
    t = {r["doc_id"]: r for r in toxicity.score(edge, labels(spark)).collect()}
    assert t[2]["score"] == t[3]["score"] == t[4]["score"] == 0 and t[2]["predicted"] == 0
    g = {r["doc_id"]: r for r in langid.identify(edge).collect()}
    assert all(g[i]["lang_pred"] == "und" and g[i]["score"] == 0 and g[i]["rejected"] for i in (2, 3, 4, 9)) and all(0 <= r["score"] <= 1 for r in g.values())
    q = {r["doc_id"]: r for r in quality.classify(edge).collect()}
    assert not q[2]["kept"] and q[3]["score"] == 0
    p = {r["doc_id"]: r for r in pii.personal_data(edge).collect()}
    assert p[1]["n_email"] == 1 and p[2]["spans"] == "" and p[2]["n_card"] == 0
    m = {r["doc_id"]: r for r in minhash.classes(edge).collect()}
    assert m[7]["class_id"] == 6 and not m[7]["kept"] and m[6]["kept"] and m[None]["class_id"] is None and m[None]["kept"] and m[2]["class_id"] == 2
    x = {r["doc_id"]: r for r in mixing.taken_by_document(*mixing.mix_sources(mixing.sized(edge))).collect()}
    assert x[2]["size"] == 0 == x[2]["taken"] and x[10]["size"] == 1 and all(r["taken"] <= 3 * r["size"] for r in x.values())


def test_embeddings_edges(spark):
    v = [1.0, 0.0, 0.0, 0.0]
    rows = [(1, v), (2, v), (2, v), (3, [0.0] * 4), (4, None), (5, [1.0, None, 0.0, 0.0]), (6, [float("nan"), 1.0, 0.0, 0.0]), (7, [float("inf"), 1.0, 0.0, 0.0]), (8, [2.0, 0.0, 0.0, 0.0]), (9, [0.0, 1.0, 0.0, 0.0]), (10, [1.0, 0.0]), (11, []), (None, v)]
    df = spark.createDataFrame([(i, e, 1, 2) for i, e in rows], "vec_id long, embedding array<float>, copies int, home int")
    got = embeddup.near_duplicates(df).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault(r["vec_id"], []).append((r["n_links"], r["component_id"]))
    assert by[1] == [(3, 1)] and by[2] == [(3, 1)] * 2 and by[8] == [(3, 1)] and by[9] == [(0, 9)]
    assert all(by[i] == [(0, i)] for i in (3, 4, 5, 6, 7, 10, 11)) and by[None] == [(0, None)]
    assert embeddup.near_duplicates(df.limit(0)).count() == 0


def test_decontamination_edges(spark, edge, none):
    got = {(r["doc_id"], r["item_id"]): r for r in decontam.matches(edge, items(spark)).collect()}
    assert {(6, 1), (7, 1)} <= set(got) and got[6, 1]["similarity"] == 1 and got[6, 1]["position"] == 0
    assert all(i not in (2, 3) for _, i in got)
    assert decontam.matches(none, items(spark)).count() == 0 and decontam.matches(edge, items(spark, ())).count() == 0
    assert decontam.matches(edge, items(spark, ((2, None), (3, " ")))).count() == 0


def test_schema_is_kept(spark, edge):
    assert linededup.dedup_lines(edge).drop("dropped_lines").schema.simpleString() == spark.createDataFrame([], SCHEMA).schema.simpleString()
    assert linededup.dedup_lines(edge).filter(F.col("doc_id") == 2).first()["text"] is None
