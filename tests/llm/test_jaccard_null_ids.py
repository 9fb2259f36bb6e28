from streamcut.llm.jaccard_join import jaccard_classes


def test_row_without_id_does_not_hide_its_copy(spark):
    words = [f"w{k}" for k in range(60)]
    near = [*words[:-3], "x", "y", "z"]  # 53 of 59 shingles in common
    rows = [(None, " ".join(words)), (5, " ".join(words)), (9, " ".join(near)), (None, " ".join(near)), (11, "other words than those of the rest of them")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    got = sorted(((r.doc_id, r.component_id) for r in jaccard_classes(docs).collect()), key=str)
    assert got == sorted([(None, None), (5, 5), (9, 5), (None, None), (11, 11)], key=str)
