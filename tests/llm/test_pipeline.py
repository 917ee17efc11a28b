"""The pipeline, its stages against brute force, and the registered queries."""

import duckdb
import pytest
from test_similar import _kept as near_copies_kept

import __spark_entry__
import corpus_pipeline
from cohort_engine.llm import decontam, pii, queries, quality_rules, sp_codec


def test_registered():
    names = __spark_entry__.queries()
    assert [n for n in queries.QUERIES if n not in names] == []
    assert sorted(int(n[2:].split("_")[0]) for n in queries.QUERIES if n.startswith("op")) == list(range(1, 11)) and "pipeline" in names


def test_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    names = docs.columns
    after = {}
    frame = docs
    for name, stage in corpus_pipeline.STAGES:
        frame = stage(spark, frame, data).cache()
        after[name] = {r["doc_id"]: r for r in frame.collect()}
        if name != "encoding":
            assert frame.columns == names
    rows = docs.toPandas()
    con = duckdb.connect()
    con.register("documents", rows)
    kept = {i for i, k in con.execute(f"SELECT doc_id, kept FROM ({queries.ORACLE['op5_line_rules']})").fetchall() if k}
    assert set(after["quality rules"]) == kept
    assert set(after["near duplicates"]) == near_copies_kept({i: r["text"] for i, r in after["quality rules"].items()})
    bench = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{data}/benchmark.parquet").collect()]
    held = {i for i, r in after["near duplicates"].items() if any(" ".join(decontam.tokens(t)) in " ".join(decontam.tokens(r["text"])) for _, t in bench)}
    assert not held & set(after["decontamination"]) and len(after["decontamination"]) >= len(after["near duplicates"]) - 2 * len(held)
    assert set(after["personal data"]) == set(after["decontamination"]) == set(after["encoding"])
    assert not any(pii.base_spans(r["text"]) for r in after["personal data"].values())
    assert all(r["n_chars"] == len(r["text"]) for r in after["personal data"].values())
    assert all(r["round_trip"] and r["n_ids"] == len(r["ids"]) for r in after["encoding"].values())


@pytest.mark.parametrize("stage", [s for _, s in corpus_pipeline.STAGES])
def test_stages_on_odd_rows(spark, data, stage):
    odd = spark.createDataFrame([(None, None, None, None, None), (1, "", "en", "s", 0), (1, "", "en", "s", 0), (2, "word " * 3000, "en", "s", None)], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    assert stage(spark, odd, data).count() <= 4
    assert stage(spark, odd.where("doc_id > 5"), data).count() == 0


@pytest.mark.parametrize("stage", [s for n, s in corpus_pipeline.STAGES if n != "encoding"])
def test_stages_leave_columns_with_clashing_names(spark, data, stage):
    names = ["kept", "base_failed", "clean_text", "lost_chars", "n_words", "fp", "id", "_id", "_fp", "_print", "_rank", "root", "_clean", "_row", "_measures", "votes", "spans", "_0"]
    text = "One clean document, with words enough to be kept. It has a second sentence, too."
    docs = spark.createDataFrame([(4, text, "en", "s", len(text), *(f"own {n}" for n in names))], ", ".join(["doc_id bigint, text string, lang string, source string, n_chars bigint", *(f"{n} string" for n in names)]))
    out = stage(spark, docs, data)
    assert out.columns == docs.columns and out.collect() == docs.collect()


def test_oracle_names():
    assert set(queries.ORACLE) <= set(queries.QUERIES) and corpus_pipeline.ORACLE_SQL is None
    assert sp_codec.default_model().endswith(".model")


def test_clashing_names_of_operators(spark):
    """Extra columns named like an operator's own, in any case."""
    text = "One clean document, with words enough to be kept. It has a second sentence, too."
    names = ["_measures", "m", "KEPT", "N_Words", "_0"]
    docs = spark.createDataFrame([(1, text, *names)], ", ".join(["doc_id bigint, text string", *(f"{n} string" for n in names)]))
    judged = quality_rules.judge(docs)
    assert judged.select("kept", "n_words", "_measures", "m", "`_0`").collect() == [(True, 15, "_measures", "m", "_0")]
    coded = sp_codec.encode(docs.withColumns({"IDS": docs["m"], "N_IDS": docs["m"]}))
    assert coded.select("n_ids").first()[0] == len(coded.first()["ids"]) and coded.columns[-1] == "round_trip"
    upper = docs.withColumnRenamed("text", "TEXT")
    assert sp_codec.encode(upper).first()["round_trip"] and quality_rules.keep_clean(upper).count() == 1


def test_one_folder_stays(spark, data):
    import os

    folder = spark.sparkContext.getCheckpointDir().removeprefix("file:")
    before = {f for f in os.listdir(folder) if f.startswith("pipeline-")}
    assert corpus_pipeline.run(spark, data).count() > 0
    assert len({f for f in os.listdir(folder) if f.startswith("pipeline-")} - before) == 1


def test_a_cluster_needs_a_shared_folder():
    from types import SimpleNamespace

    from cohort_engine.llm import common

    context = SimpleNamespace(master="local-cluster[3,2,1024]", getCheckpointDir=lambda: None)
    with pytest.raises(RuntimeError):
        common.shared_folder(SimpleNamespace(sparkContext=context, conf=SimpleNamespace(get=lambda key, default=None: None)))
