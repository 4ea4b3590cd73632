from pyspark.sql import functions as F

import corpus_pipeline
from vecpath.llm.queries import ORACLES, QUERIES


def test_stages_and_names():
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
    assert [n.split("_")[0] for n in QUERIES] == [f"op{i}" for i in range(1, 11)]
    assert set(ORACLES) <= set(QUERIES)


def test_pipeline_keeps_what_it_should(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    columns = docs.columns
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf).cache()
        kept[name] = docs
        if name != corpus_pipeline.STAGES[-1][0]:
            assert docs.columns == columns
    good = kept["quality_classifier"]
    rejected = labels.where("quality = 1").join(good, "doc_id", "left_anti").count()
    assert rejected <= 0.02 * labels.count()
    once = kept["exact_dedup"]
    assert once.groupBy(F.lower("text")).count().where("count > 1").count() <= 1
    assert kept["near_dedup"].count() <= once.count() <= good.count()
    assert kept["mix_sources"].join(kept["near_dedup"], "doc_id", "left_anti").count() == 0
    assert docs.count() == kept["mix_sources"].count() > 0


ODD = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = "size target copies source_size kept keep_id group_size text_sha256 score predicted _rank _class _hash _part _copy component_id n_tokens".split()


def odd_documents(spark):
    prose = "The history of the town begins with a small market, and its people, who came from the hills, built a bridge over the river in the year of the flood. "
    rows = [
        (1, prose * 3, "en", "a", 5), (2, prose * 3, "en", "a", 5), (2, prose * 3, "en", "a", 5), (3, prose.upper() * 3, None, None, None),
        (4, prose * 3 + "More was built later.", "en", "b", 1), (5, None, None, None, None), (6, "", "en", "b", 0), (6, "", "en", "b", 0),
        (None, prose * 3, "en", "a", 5), (None, None, None, None, None), (7, prose * 4000, "en", "c", 9), (8, "one two", "de", "é", 2),
    ]
    return spark.createDataFrame(rows, ODD).withColumns({c: F.lit(f"own {c}") for c in CLASH})


def test_stages_with_odd_rows_and_clashing_columns(spark, sf):
    docs = odd_documents(spark)
    every = sorted(map(str, docs.collect()))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        rows = list(map(str, out.collect()))
        assert rows and set(rows) <= set(every), name
        none = stage(spark, docs.where("false"), sf)
        assert none.columns == docs.columns and none.count() == 0, name
    stages = dict(corpus_pipeline.STAGES)
    once = stages["exact_dedup"](spark, docs, sf).collect()
    assert sorted((r.doc_id is None, r.doc_id) for r in once) == [(False, 3), (False, 4), (False, 6), (False, 7), (False, 8)]
    near = [r.doc_id for r in stages["near_dedup"](spark, docs, sf).collect()]
    # equal sets, however often their words repeat: 1, 2, 3, 4 and 7 are one group
    assert sorted(x for x in near if x is not None) == [1, 5, 6, 6, 8] and near.count(None) == 2
    taken = stages["mix_sources"](spark, docs, sf)
    assert taken.groupBy("doc_id", "source").count().where("count > 6").count() == 0
    coded = stages["bpe_encode"](spark, docs, sf)
    assert coded.count() == docs.count() and coded.where("doc_id = 6 and n_tokens = 0").count() == 2
    assert stages["bpe_encode"](spark, docs.where("false"), sf).count() == 0
