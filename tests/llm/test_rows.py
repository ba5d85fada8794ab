from featsift.llm import exact_dedup


def test_copies_go_by_row(spark):
    rows = [(3, "x  y"), (5, "x y"), (5, "unique"), (None, "x y"), (None, "alone"), (7, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = {tuple(r) for r in exact_dedup.drop_exact_duplicates(docs).collect()}
    assert kept == {(3, "x  y"), (5, "unique"), (None, "x y"), (None, "alone"), (7, None)}
