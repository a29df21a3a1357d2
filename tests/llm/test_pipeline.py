"""The pipeline's stages one by one, on the smallest tables and on odd rows."""

import corpus_pipeline as P

SMALL = "/root/testdata/sf0.001"
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_keep_the_columns_and_only_take_away(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    ids = {r.doc_id for r in docs.select("doc_id").collect()}
    for i, (_, stage) in enumerate(P.STAGES):
        docs = stage(spark, docs, SMALL)
        docs = spark.createDataFrame(docs.collect(), docs.schema)
        now = {r.doc_id for r in docs.select("doc_id").collect()}
        assert now <= ids and len(now) > 0
        assert docs.columns == COLUMNS if i < 4 else set(COLUMNS) < set(docs.columns)
        ids = now


def test_odd_tables_pass(spark):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "one two three four five six", "en", "a", 27), (3, "one two three four five six", "en", "a", 27), (None, "x y", "en", "a", 3)]
    for data in (rows, []):
        docs = spark.createDataFrame(data, schema)
        for _, stage in P.STAGES:
            docs = stage(spark, docs, SMALL)
            docs = spark.createDataFrame(docs.collect(), docs.schema)
        assert docs.count() <= len(data)
        assert not data or [r.doc_id for r in docs.collect()].count(3) == 1


def test_clashing_columns_and_long_texts_pass(spark):
    names = ["_drop", "dropped_id", "n_deleted", "n_lines", "gone", "_id", "copies", "taken", "taken_id", "component_id", "score"]
    text = "\n".join(f"w{i} w{i * 7} w{i * 11} words" for i in range(20_000))
    rows = [(d, text if d < 2 else f"some other words of document {d} that no one else has", "en", "a", 9, *range(len(names))) for d in range(5)]
    docs = spark.createDataFrame(rows, [*COLUMNS, *names])
    for i, (_, stage) in enumerate(P.STAGES):
        docs = stage(spark, docs, SMALL)
        if i < 4:
            assert docs.columns == [*COLUMNS, *names]
        docs = spark.createDataFrame(docs.collect(), docs.schema)
    got = docs.collect()
    assert 1 <= len(got) <= 4 and all(r._drop == 0 and r.gone == 4 and r.copies >= 1 for r in got)
