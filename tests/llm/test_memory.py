"""What the driver and a waiting worker of the pipeline may hold."""

import pyarrow as pa
from pyspark.sql import functions as F

from treeloom.llm import bpe, store
from treeloom.llm.queries import VOCABULARY


def test_tables_are_not_broadcast_because_their_files_are_small(spark, tmp_path):
    """250,000 keys lie in a file of a fraction of the default limit, and came to the driver as a hash table."""
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "10m")
    try:
        spark.range(250_000).coalesce(1).write.parquet(f"{tmp_path}/keys")
        joined = spark.range(1000).withColumn("x", F.lit(1)).join(spark.read.parquet(f"{tmp_path}/keys").withColumnRenamed("id", "k"), F.col("id") == F.col("k"), "left_anti")
        with store.shuffles_removed(spark):
            plan = joined.filter("x = 1")._jdf.queryExecution().executedPlan().toString()
            assert "BroadcastHashJoin" not in plan and "SortMergeJoin" in plan
        assert spark.conf.get("spark.sql.autoBroadcastJoinThreshold") == "10m"
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        with store.shuffles_removed(spark):
            assert spark.conf.get("spark.sql.autoBroadcastJoinThreshold") == "-1"
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_word_cache_is_bounded_and_keeps_frequent_words(monkeypatch):
    with open(VOCABULARY, encoding="utf-8") as f:
        spec = f.read()
    free, tight = bpe.WordBpe(spec), bpe.WordBpe(spec)
    text = " ".join(f"the word{i:03d}x{'abcdefghij'[i % 10]}" for i in range(400))
    whole = free.encode(text)
    monkeypatch.setattr(bpe, "CACHE_WORDS", 20)
    merged = []
    once = tight.merge
    monkeypatch.setattr(tight, "merge", lambda w: (merged.append(w), once(w))[1])
    assert tight.encode(text) == whole
    assert len(tight.cache) + len(tight.older) <= 20 and merged.count("the") == 1


def test_a_task_gives_back_what_it_held(monkeypatch):
    class Pool:
        released = 0

        def release_unused(self):
            Pool.released += 1

    batch = pa.RecordBatch.from_pydict({"a": [1]})
    monkeypatch.setattr(pa, "default_memory_pool", Pool)
    assert list(store.lean(lambda batches: (b for b in batches))(iter([batch, batch]))) == [batch, batch] and Pool.released == 1
