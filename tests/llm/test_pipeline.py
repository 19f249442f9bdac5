import corpus_pipeline
from semjoin.llm import queries

SF = "/root/testdata/sf0.001"


def test_stages_keep_what_they_should(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows, columns = docs.count(), docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.materialize(stage(spark, docs, SF), name)
        assert docs.columns == columns and 0 < docs.count() <= rows
        rows = docs.count()
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert packed.select("doc_id").distinct().count() == rows


def test_run_and_names(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0
    assert [f"op{i}_" for i in range(1, 11)] == [k[: k.index("_") + 1] for k in queries.QUERIES if k.startswith("op")]


def test_empty_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("false")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0
        docs = docs if "text" in docs.columns else docs


def test_stages_take_odd_tables(spark, tmp_path):
    """Nulls, repeated ids and rows, columns of helper names; labels and benchmark empty: no unique text is lost."""
    for name, schema in (("labels", "doc_id long, quality int, toxic int"), ("benchmark", "item_id long, text string")):
        spark.createDataFrame([], schema).write.parquet(f"{tmp_path}/{name}.parquet")
    text = lambda tag: "\n".join(" ".join(f"{tag}{i}x{j}" for j in range(12)) for i in range(8))
    rows = [(1, text("a")), (1, text("b")), (2, text("c")), (2, text("c")), (3, text("c")), (4, None), (5, ""), (None, text("d")), (6, text("e") + "\n" + text("a").split("\n")[0])]
    schema = "doc_id long, text string, lang string, source string, n_chars long, __n_words int, __row int, __cut int, __new string, __id long, __gone long"
    docs = spark.createDataFrame([(i, t, None, None, None, 1, 2, 3, "x", 4, 5) for i, t in rows], schema)
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.materialize(stage(spark, docs, str(tmp_path)), name)
        assert docs.columns == columns
    got = sorted((str(r["doc_id"]), r["text"]) for r in docs.collect())
    assert got == sorted([("1", text("a")), ("1", text("b")), ("2", text("c")), ("None", text("d")), ("6", text("e"))])
    assert corpus_pipeline.STAGES[-1][1](spark, docs, str(tmp_path)).select("doc_id").distinct().count() == 4
