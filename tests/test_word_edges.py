"""Edges of words, made in the JVM, against a plain plan; whose tasks have executors for themselves."""

from types import SimpleNamespace

from pyspark.sql import functions as F

from streamcut.functions.hashing import vertex_id
from streamcut.operators import whole
from streamcut.sources import graphs

TEXTS = [None, "", " ", "a", "a b a b", "É é ß İI x", "1a2b3", "𝒳𝒴 z 𐐀", "áb́c", "你好 world", "_-_", "x" * 3000 + " y", "ªº ʰa", "ǅ Ǆ", "b�c", "w " * 3000]


def test_word_edges_are_those_of_a_plain_plan(spark):
    df = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string")
    words = df.select("doc_id", F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda x: x != "").alias("w"))
    each = words.select("doc_id", F.posexplode("w").alias("k", "w")).withColumn("v", vertex_id(F.col("w")))
    rows = [(r.doc_id, r.k, r.v) for r in each.collect()]
    there = {(d, k): v for d, k, v in rows}
    got = graphs._next_words(df).collect()
    assert sorted(map(tuple, got)) == sorted({(v, there[d, k + 1]) for d, k, v in rows if (d, k + 1) in there})
    assert sorted(map(tuple, graphs._bag("doc_id")(df).collect())) == sorted({(d, -1 - v) for d, _, v in rows})
    plan = graphs._next_words(df)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("hashpartitioning") == 1  # one exchange: vertices, not words, are made distinct


def test_tasks_alone_where_an_executor_has_known_cores():
    def cpus(master, **conf):
        got = whole.alone(SimpleNamespace(sparkContext=SimpleNamespace(master=master, getConf=lambda: SimpleNamespace(get=conf.get))))
        return got and got.taskResources["cpus"].amount

    assert cpus("local[4]") is None
    assert cpus("spark://host:7077") is None
    assert cpus("local-cluster[3,2,3000]") == 2
    assert cpus("yarn", **{"spark.executor.cores": "4"}) == 4
