"""The pipeline's stages against what is planted."""

import numpy as np
import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages_and_columns():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "simhash_near_dedup", "benchmark_decontamination", "best_fit_packing"]


def test_planted_cases_go_and_clean_documents_stay(spark, tmp_path):
    rng = np.random.default_rng(0)
    text = lambda n: " ".join(f"{chr(97 + rng.integers(26))}{rng.integers(9999)}w" for _ in range(n))
    clean = [text(120) for _ in range(30)]
    passage = text(60)
    rows = [*clean, clean[3], " ".join(["new", *clean[4].split()[1:]])]  # 30, 31: copies
    rows += [f"{text(50)}\n{passage}\n{text(50)}" for _ in range(6)]  # 32 to 37: a passage in six documents
    items = [text(40) for _ in range(2)]
    rows += [f"{text(60)} {items[0]} {text(60)}", f"{text(60)} {items[1]} {text(30)}"]  # 38, 39: leaks
    rows += [f"{text(20)} idiot {text(5)} moron scum {text(20)}" for _ in range(2)]  # 40, 41: toxic
    rows += [None, ""]  # 42, 43
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in enumerate(rows)], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(list(enumerate(items)), "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    now, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, str(tmp_path))
        seen[name] = {r.doc_id for r in now.select("doc_id").collect()}
        if name != "best_fit_packing":
            assert now.columns == docs.columns
        if name == "line_dedup":
            assert [r.doc_id for r in now.filter(now.text.contains(passage)).collect()] == [37]
    every = set(range(len(rows)))
    assert seen["toxicity"] == every - {40, 41}
    assert seen["line_dedup"] == seen["toxicity"]
    assert seen["simhash_near_dedup"] == seen["line_dedup"] - {30, 31}
    assert seen["benchmark_decontamination"] == seen["simhash_near_dedup"] - {38, 39}
    assert seen["best_fit_packing"] == seen["benchmark_decontamination"]


def test_stages_on_empty_tables_nulls_repeats_and_clashing_names(spark, tmp_path):
    ddl = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    none = spark.createDataFrame([], ddl)
    some = spark.createDataFrame([(1, "a text of a few words", "en", "s", 21)] * 2 + [(None, None, None, None, None), (None, "", "de", None, 0), (2, "\n\n", None, "s", 2)], ddl)
    some = some.selectExpr("*", "1 as fp", "2 as gone", "3 as c0", "4 as key", "5 as score", "6 as length", "7 as shard", "8 as rep")
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, str(tmp_path)).count() == 0, name
        found = stage(spark, some, str(tmp_path))
        assert found.count() == 5, name
        if name != "best_fit_packing":
            assert found.columns == some.columns, name
