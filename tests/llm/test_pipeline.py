"""The pipeline: its stages' contract, and decisions held against plain code on the smallest tables."""

import importlib

import pytest
from test_free_style import brute_decontaminate, brute_simhash, pairs
from test_native import brute_base

from ruleclosure.llm import secret_scan

pipeline = importlib.import_module("corpus_pipeline")
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark, sf, tmp_path_factory):
    folder, docs = tmp_path_factory.mktemp("stages"), spark.read.parquet(f"{sf}/documents.parquet")
    out = [docs]
    for name, f in pipeline.STAGES:
        f(spark, out[-1], sf).write.parquet(str(folder / name))
        out.append(spark.read.parquet(str(folder / name)))
    return out


def test_names_and_columns(stages):
    assert [n for n, _ in pipeline.STAGES] == ["language", "near_duplicates", "decontamination", "secrets", "mixture"]
    assert all(df.columns == COLUMNS for df in stages[:5]) and stages[5].columns[:5] == COLUMNS


def test_language_keeps_texts_with_letters_and_their_rows(stages):
    before, after = ({r.doc_id: r for r in df.collect()} for df in stages[:2])
    assert all(before[k] == r for k, r in after.items())
    assert len(after) >= 0.97 * len(before)


def test_near_duplicates_keep_the_first_of_each_group(stages):
    want = {i for i, _, c in brute_simhash(pairs(stages[1], "doc_id", "text")) if i == c}
    assert {r.doc_id for r in stages[2].collect()} == want


def test_decontamination_drops_by_the_rule(spark, sf, stages):
    items = pairs(spark.read.parquet(f"{sf}/benchmark.parquet"), "item_id", "text")
    want = {r[0] for r in brute_decontaminate(pairs(stages[2], "doc_id", "text"), items) if not r[5]}
    assert {r.doc_id for r in stages[3].collect()} == want


def test_secrets_are_masked_and_clean_texts_stay(stages):
    before, after = ({r.doc_id: r for r in df.collect()} for df in stages[3:5])
    assert before.keys() == after.keys()
    for k, r in after.items():
        assert not brute_base(r.text) and r.n_chars == len(r.text)
        if secret_scan.MASK not in r.text:
            assert r == before[k]


def test_mixture_takes_rows_of_its_input(stages):
    before = {r.doc_id: r for r in stages[4].collect()}
    for r in stages[5].collect():
        assert r.copies >= 1 and r.text == before[r.doc_id].text


def test_run_equals_the_stages(spark, sf, stages):
    assert sorted(r.doc_id for r in pipeline.run(spark, sf).collect()) == sorted(r.doc_id for r in stages[5].collect())


@pytest.mark.parametrize("k", range(5))
def test_stages_take_odd_and_empty_tables(spark, sf, odd, none, k):
    _, f = pipeline.STAGES[k]
    assert f(spark, none, sf).count() == 0
    assert f(spark, odd, sf).columns[: len(odd.columns)] == odd.columns
