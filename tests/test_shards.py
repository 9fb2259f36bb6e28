from pyspark.sql import functions as F

from streamcut.operators import greedy


def test_each_shard_has_a_task_of_its_own(spark):
    s = spark.range(400).select("id", (F.col("id") % 37 + 1000).alias("dst"), F.lit(0).alias("cmp"), F.lit(True).alias("guarded"), F.lit("small").alias("class"))
    s = s.select(F.col("id").alias("src"), "dst", F.col("id").alias("arrival"), F.col("id").alias("seq"), F.col("id").alias("place_seq"), "cmp", "class", "guarded")
    for shards in (2, 8):
        rows = greedy.sharded(s, 4, shards).select("src", F.pmod(F.xxhash64("src", F.lit(0)), F.lit(shards)).alias("shard"), F.spark_partition_id().alias("task")).collect()
        assert len(rows) == 400 and len({r.task for r in rows}) == len({(r.shard, r.task) for r in rows}) == shards
