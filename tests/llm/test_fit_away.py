"""Models of the pipeline are fitted in a task: the same models, and the driver holds bytes."""

import pytest

import corpus_pipeline
from tourspark.llm import langid, quality
from tourspark.llm.rows import Packed

SF = "/root/testdata/sf0.01"


@pytest.fixture
def tables(spark):
    return spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")


def test_models_are_the_same(tables):
    docs, labels = tables
    here, away = quality.train(docs, labels), quality.train_away(docs, labels)
    assert isinstance(away, Packed) and away.open() == here
    here, away = langid.train(docs), langid.train_away(docs)
    assert isinstance(away, Packed)
    away = away.open()
    assert (away.langs, away.word, away.gram, away.longest) == (here.langs, here.word, here.gram, here.longest) and (away.table == here.table).all()


def test_no_rows_give_a_model_too(tables):
    docs, labels = tables
    nothing = docs.where("false")
    assert quality.keep_good(docs, quality.train_away(nothing, labels)).count() == docs.count()
    assert langid.keep_known(docs, langid.train_away(nothing)).count() == 0


def test_pipeline_fits_nothing_in_the_driver(spark, tables, monkeypatch):
    """Its stages keep the rows that models of the driver would keep."""
    docs, labels = tables
    good, known = quality.keep_good(docs, quality.train(docs, labels), least=0.4).count(), langid.keep_known(docs, langid.train(docs)).count()

    def never(*args, **options):
        raise AssertionError("fitted in the driver")

    # tasks import the modules anew and see nothing of this
    monkeypatch.setattr(quality, "train", never)
    monkeypatch.setattr(langid, "train", never)
    assert corpus_pipeline.keep_quality(spark, docs, SF).count() == good
    assert corpus_pipeline.keep_languages(spark, docs, SF).count() == known
