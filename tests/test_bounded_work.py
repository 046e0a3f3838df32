"""What a worker holds at a time, and how many steps an index takes, on inputs where that was without bound."""

import random
import time

import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from tests.trees import random_tree
from treeloom.baselines import engines
from treeloom.baselines.engines import recurse_count
from treeloom.sources import store
from treeloom.sources.trees import _gene, open_tree
from treeloom.text.fm import TextIndex, merge
from treeloom.text.shards import build_shards, locate
from treeloom.tree import encode


def test_a_worker_hands_on_nodes_before_a_batch_of_records_is_done(spark, monkeypatch):
    made = []
    df = spark.createDataFrame([(0, "a")], "doc long, text string")
    monkeypatch.setattr(type(df), "mapInArrow", lambda self, run, schema: made.append(run), raising=False)
    encode.encode_records(df, _gene, ["doc", "text"], ["doc"])
    text = "\n".join(["acgt. gtca. ttga. acca"] * 20)
    batch = pa.RecordBatch.from_arrays([pa.array(range(2000)), pa.array([text] * 2000)], ["doc", "text"])
    sizes, docs, one = [], set(), len(encode.flatten(_gene(7, text)))
    for out in made[0](iter([batch])):
        sizes.append(out.num_rows)
        docs.update(out.column("doc").to_pylist())
    assert sum(sizes) == 2000 * one and docs == set(range(2000))
    assert max(sizes) < encode.BATCH_NODES + one


@pytest.mark.parametrize("kind", ["blocks", "wavelet", "huffman", "runs"])
def test_all_texts_at_once_and_the_merge_of_few_long_with_many_short_ones(kind):
    rng = random.Random(5)
    texts = [bytes(rng.choice(b"abcd") for _ in range(rng.choice([0, 1, 5, 40, 300]))) for _ in range(120)]
    for sample in (1, 4, 64):
        a, b = TextIndex.build(texts[:50], sample, kind), TextIndex.build(texts[50:], sample, kind)
        whole, both = TextIndex.build(texts, sample, kind), merge(a, b)
        assert whole.extract_all() == both.extract_all() == texts and TextIndex.build([], sample, kind).extract_all() == []
        assert (both.column == whole.column).all() and (both.doc == whole.doc).all() and (both.starts == whole.starts).all()
        assert both.contains("ab").tolist() == [i for i, t in enumerate(texts) if b"ab" in t]


def test_steps_of_an_index_do_not_grow_with_the_longest_text():
    """A text of 200,000 bytes: reading it back byte by byte took seconds, and so did a merge."""
    rng = random.Random(6)
    long = bytes(rng.choice(b"abcdefgh") for _ in range(200_000))
    a, b = TextIndex.build([b"abc", b"hgf"]), TextIndex.build([long, b"x"])
    began = time.process_time()
    assert merge(a, b).extract_all() == [b"abc", b"hgf", long, b"x"]
    assert time.process_time() - began < 2


def test_wide_rows_are_read_a_few_at_a_time(spark):
    """Indexes of one megabyte each: a row group held up to 128 MB of them, and all of a batch were copied at once."""
    texts = spark.range(24).selectExpr("id as text_id", "concat(repeat(string(id * 7919), 200000), 'needle') as value")
    index = store.built_once(spark, "test-wide-rows", "shards", lambda: build_shards(texts, 4, "blocks", 1 << 20, 1), wide=True)
    groups = [pq.ParquetFile(f.removeprefix("file://")).metadata for f in index.inputFiles()]
    sizes = [m.row_group(i).total_byte_size for m in groups for i in range(m.num_row_groups)]
    assert max(sizes) < 32 << 20 < sum(sizes)
    assert locate(index, "needle").count() == 24


def test_more_texts_go_to_more_tasks(spark):
    texts = spark.range(400).selectExpr("id as text_id", "repeat('abcdefgh', 100) as value")
    index = build_shards(texts, 64, "blocks", 1 << 10, 2)
    assert index.rdd.getNumPartitions() > 2 and index.agg({"n_texts": "sum"}).first()[0] == 400


def test_a_document_with_a_spine_is_walked_in_more_than_one_task(spark, small):
    nodes = open_tree(spark, small, "market").nodes
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        got = recurse_count(nodes)
        walk = got._jdf.queryExecution().optimizedPlan().toString()
        assert "RepartitionByExpression [doc" in walk and "frag" in walk.split("RepartitionByExpression [doc")[1].split("]")[0]
        assert got.first()["n"] == nodes.filter("kind = 'elem'").count()
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")


def test_walks_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(engines, "WALK_ROWS", 3)
    rng = random.Random(9)
    rows = []
    for doc in range(12):
        for r in encode.flatten(random_tree(rng, rng.randint(1, 60))):
            rows.append((doc, 0, r[0], r[1], r[6]))
    # one document whose nodes below the root's children lie in fragments of their own
    rows += [(99, -1, 1, 7, "doc"), (99, -1, 2, 7, "elem"), (99, 5, 3, 4, "elem"), (99, 5, 4, 4, "text"), (99, 6, 5, 7, "elem"), (99, 6, 6, 6, "elem"), (99, 6, 7, 7, "elem")]
    nodes = spark.createDataFrame(rows, "doc long, frag long, pre long, last long, kind string")
    for tasks in ("1", "8"):
        spark.conf.set("spark.sql.shuffle.partitions", tasks)
        assert recurse_count(nodes).first()["n"] == sum(r[4] == "elem" for r in rows)
    spark.conf.set("spark.sql.shuffle.partitions", "8")
