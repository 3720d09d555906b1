"""Stages of the pipeline on a small corpus."""

import random

import pytest

import corpus_pipeline
from tests.llm.test_operators import words


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = random.Random(3)
    good = [words(rng, rng.randint(60, 200)) for _ in range(120)]
    rows = [(i, t, "en", f"s{i % 3}", len(t)) for i, t in enumerate(good)]
    rows += [(200 + i, good[i] if i % 2 else good[i] + " more", "en", "s0", 1) for i in range(30)]
    rows += [(300 + i, "### $$$ " * 40, "en", None, 1) for i in range(40)]
    rows += [(400, good[0] + " new words here that differ " + words(rng, 80) + " a@b.co", "en", "s1", 1), (401, None, None, None, None)]
    at = str(tmp_path_factory.mktemp("sf"))
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{at}/documents.parquet")
    labels = [(i, 1, 0) for i in range(120)] + [(300 + i, 0, 0) for i in range(40)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    return at


def test_stages(spark, folder, tmp_path):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    columns, seen = docs.columns, []
    for i, (_, stage) in enumerate(corpus_pipeline.STAGES[:-1]):
        stage(spark, docs, folder).write.parquet(str(tmp_path / str(i)))
        docs = spark.read.parquet(str(tmp_path / str(i)))
        assert docs.columns == columns
        seen.append([r.doc_id for r in docs.collect()])
    quality, near, private, mixed = seen
    assert set(range(120)) <= set(quality) and not set(range(300, 340)) & set(quality)
    assert set(range(120)) <= set(near) and not set(range(200, 230)) & set(near) and len(set(near)) == len(near)
    assert sorted(private) == sorted(near)
    assert set(mixed) <= set(private)
    assert not docs.where("text like '%a@b.co%'").count()
    packed = corpus_pipeline.run(spark, folder)
    assert {r.doc_id for r in packed.collect()} == set(mixed)
