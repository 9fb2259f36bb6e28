from streamcut.llm import decontaminate
from streamcut.llm.decontaminate import remove_contaminated


def test_each_row_is_judged_by_itself(spark, monkeypatch):
    item = " ".join(f"q{k}" for k in range(40))
    clean = " ".join(f"c{k}" for k in range(40))
    docs = spark.createDataFrame([(None, item), (None, clean), (1, item), (1, clean), (2, clean), (3, None)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    want = sorted([(None, clean), (1, clean), (2, clean), (3, None)], key=str)
    for limit in (10, 0):  # the removed texts broadcast, and by the salted join
        monkeypatch.setattr(decontaminate, "BROADCAST_ROWS", limit)
        assert sorted((tuple(r) for r in remove_contaminated(docs, bench).collect()), key=str) == want
