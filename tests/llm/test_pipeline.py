"""The corpus pipeline, stage by stage, against brute force on the smallest table."""

import re

import pytest

import corpus_pipeline as C
from shapesig.llm import entries, quality_qda
from tests_llm_data import DATA, docs


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    at, out = spark.read.parquet(f"{DATA}/documents.parquet"), []
    for k, (name, stage) in enumerate(C.STAGES):
        path = str(tmp_path_factory.mktemp("stage") / str(k))
        stage(spark, at, DATA).write.parquet(path)
        at = spark.read.parquet(path)
        out.append(at)
    return out


def test_stages_keep_the_columns(spark, stages):
    columns = spark.read.parquet(f"{DATA}/documents.parquet").columns
    assert all(s.columns == columns for s in stages[:-1]) and 4 <= len(C.STAGES) <= 5


def test_quality_stage_follows_the_scores(spark, stages):
    got = quality_qda.score(spark.read.parquet(f"{DATA}/documents.parquet"), spark.read.parquet(f"{DATA}/labels.parquet"))
    assert {r.doc_id for r in stages[0].collect()} == {r.doc_id for r in got.where("predicted = 1").collect()}


def test_dedup_stages_equal_brute_force(stages):
    rows = sorted((r.doc_id, r.text) for r in stages[0].collect())
    first = {}
    for i, t in rows:
        first.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", t or ""), i)
    assert {r.doc_id for r in stages[1].collect()} == set(first.values())
    sets = {}
    for i, t in sorted((r.doc_id, r.text) for r in stages[1].collect()):
        w = t.translate({c: c + 32 for c in range(65, 91)}).split()
        sets[i] = {" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    root = {i: i for i in sets}
    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            if root[a] != root[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                low, high = sorted((root[a], root[b]))
                root = {k: low if v == high else v for k, v in root.items()}
    assert {r.doc_id for r in stages[2].collect()} == {i for i in ids if root[i] == i}


def test_last_stage_encodes_every_row(stages):
    assert stages[4].count() == stages[3].count() and stages[4].where("n_tokens <> size(tokens)").count() == 0


def test_run_equals_the_stages(spark, stages):
    assert sorted((r.doc_id, r.n_tokens) for r in C.run(spark, DATA).select("doc_id", "n_tokens").collect()) == sorted((r.doc_id, r.n_tokens) for r in stages[4].select("doc_id", "n_tokens").collect())


def test_stages_take_nulls_and_empty_tables(spark):
    for rows in ([], [None, "", "The one text, and another one of it. " * 5, None]):
        at = docs(spark, rows)
        for _, stage in C.STAGES:
            at = stage(spark, at, DATA)
        assert at.count() <= len(rows)


def test_every_operator_has_a_query():
    assert {re.match(r"op\d+_", k)[0] for k in entries.queries()} == {f"op{n}_" for n in range(1, 11)}
