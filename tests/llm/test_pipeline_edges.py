import corpus_pipeline

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, row string, kept_text string, score double"


def stages(spark, docs, folder, labels=()):
    spark.createDataFrame(list(labels), "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    docs.coalesce(1).write.parquet(f"{folder}/documents.parquet")
    stage, out = spark.read.parquet(f"{folder}/documents.parquet"), []
    for i, (_, f) in enumerate(corpus_pipeline.STAGES):
        f(spark, stage, str(folder)).write.parquet(f"{folder}/{i}")
        stage = spark.read.parquet(f"{folder}/{i}")
        assert i == 4 or stage.columns == docs.columns
        out.append(stage.collect())
    return out


def test_nulls_repeats_and_clashing_columns(spark, tmp_path):
    lead = " ".join(f"w{i}" for i in range(30))
    other = f"{' '.join(f'v{i}' for i in range(40))} {lead}"
    rows = [(1, None, "x", None, 0, "r", "k", 0.5), (2, "", "x", "s", 0, "r", None, None), (3, lead, "x", "s", 1, "r", "k", 0.5), (3, lead, "x", "s", 1, "r", "k", 0.5), (5, other, "x", "s", 1, "r", "k", 0.5), (None, lead + " ", None, None, None, None, None, None)]
    out = stages(spark, spark.createDataFrame(rows, SCHEMA), tmp_path)
    assert len(out[0]) == len(rows)  # no labels: nothing is rejected
    assert [(r["doc_id"], r["text"], r["row"], r["score"]) for r in sorted(out[1], key=lambda r: r["doc_id"] or 0)] == [(None, lead + " ", None, None), (1, None, "r", 0.5), (5, other, "r", 0.5)]
    assert {r["doc_id"] for r in out[2]} == {None, 1, 5}
    cut = {r["doc_id"]: (r["text"], r["n_chars"], r["kept_text"]) for r in out[3]}
    assert cut[5] == (other, 1, "k") and cut[None] == ("", 0, None) and cut[1][0] is None
    assert sum(r["length"] for r in out[4]) == sum(r["doc_tokens"] for r in {r["doc_id"]: r for r in out[4]}.values())


def test_an_empty_table_goes_through(spark, tmp_path):
    assert [len(x) for x in stages(spark, spark.createDataFrame([], SCHEMA), tmp_path)] == [0] * 5
