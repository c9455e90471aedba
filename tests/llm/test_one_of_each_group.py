"""One row of each group of near copies stays, whatever ids repeat or miss."""

from transitlens.llm.jaccard_join import one_of_each_group


def test_repeated_ids_repeated_rows_and_null_ids(spark):
    def text(name):
        return " ".join(f"{name}{i}" for i in range(60))

    rows = [(3, text("c"), "x"), (5, text("a"), "x"), (5, text("c") + " more", "x")]  # id 5: a text of its own, and a near copy of 3
    rows += [(7, text("d"), "x"), (7, text("d"), "x"), (7, text("d"), "w")]  # rows that repeat id and text
    rows += [(None, text("c"), "x"), (None, text("e"), "x"), (None, text("e"), "x"), (None, text("f"), "x")]
    rows += [(9, text("g"), "x"), (9, text("h"), "x"), (10, None, "x"), (10, None, "x"), (None, "", "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    left = one_of_each_group(docs)
    want = [(3, text("c"), "x"), (5, text("a"), "x"), (7, text("d"), "w"), (None, text("e"), "x"), (None, text("f"), "x"), (9, text("g"), "x"), (9, text("h"), "x"), (10, None, "x"), (10, None, "x"), (None, "", "x")]
    assert left.columns == docs.columns
    assert sorted(map(str, map(tuple, left.collect()))) == sorted(map(str, want))
