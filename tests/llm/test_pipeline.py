"""The pipeline's stages hand on whole documents, and its result agrees with stages run apart."""

import pytest

pytest.importorskip("tricell.llm")

import corpus_pipeline  # noqa: E402

WORDS = r"[^\x20\x09-\x0D]+"


def test_stages_and_their_results(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["toxicity", "line dedup", "near duplicates", "mixing", "packing"]
    from tricell.llm.storage import materialise

    seen = [docs]
    for name, stage in corpus_pipeline.STAGES:
        seen.append(materialise(stage(spark, seen[-1], sf_dir), "stage"))
        if name != "packing":
            assert seen[-1].columns == docs.columns
    ids = [{r.doc_id for r in d.select("doc_id").distinct().collect()} for d in seen]
    assert all(b <= a for a, b in zip(ids, ids[1:]))
    assert len(ids[1]) >= 0.8 * len(ids[0]), "clean documents stay"
    mixed = seen[4].selectExpr(f"sum(regexp_count(text, r'{WORDS}')) as n").first().n
    assert seen[5].selectExpr("sum(length) as n").first().n == mixed
    assert corpus_pipeline.run(spark, sf_dir).count() == seen[5].count()


@pytest.mark.parametrize("rows", [[], [(None, None, None, None, None)], [(1, "", "en", None, 0), (1, "", "en", None, 0), (2, None, None, "s", None), (None, "a b", "en", "s", 3)]])
def test_awkward_tables_pass_every_stage(spark, sf_dir, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf_dir)
        docs = spark.createDataFrame(out.collect(), out.schema)
    assert docs.count() >= 0
