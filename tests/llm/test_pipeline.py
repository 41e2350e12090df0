"""The pipeline's stages on the smallest tables, each against plain Python on its own input."""

from collections import Counter

import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from subgraph_engine.llm.common import written
from tests.llm.test_operators import brute_components

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    docs = [spark.read.parquet(f"{SF}/documents.parquet")]
    for name, stage in corpus_pipeline.STAGES:
        docs.append(written(stage(spark, docs[-1], SF), name))
    return docs


def test_stages_keep_the_columns_and_drop_rows(stages):
    for before, after in zip(stages[:3], stages[1:4], strict=True):
        assert after.columns == before.columns
        assert after.exceptAll(before).isEmpty()


def test_clean_documents_stay(stages, spark):
    assert stages[0].count() - stages[1].count() <= 2
    labels = spark.read.parquet(f"{SF}/labels.parquet").where("toxic = 0")
    gone = stages[1].join(stages[2], "doc_id", "left_anti").join(labels, "doc_id").count()
    assert gone <= 0.03 * labels.count()


def test_one_of_each_group_stays(stages):
    rows = [(r["doc_id"], r["text"]) for r in stages[2].collect()]
    firsts = {i for i, _, c in brute_components(rows) if i == c}
    assert {r["doc_id"] for r in stages[3].collect()} == firsts


def test_all_tokens_are_packed(stages):
    reference = Tokenizer.from_file(public_tokenizers.path(corpus_pipeline.VOCABULARY))
    held = Counter()
    for r in stages[4].collect():
        held[r["doc_id"]] += r["length"]
    assert held == {r["doc_id"]: len(reference.encode(r["text"], add_special_tokens=False).ids) + 1 for r in stages[3].collect()}


def test_run_gives_the_last_stage(spark, stages):
    assert sorted(map(tuple, corpus_pipeline.run(spark, SF).select("doc_id", "start", "length").collect())) == sorted(map(tuple, stages[4].select("doc_id", "start", "length").collect()))
