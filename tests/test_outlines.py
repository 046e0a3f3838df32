"""Records that are outlined first and numbered when their places are known: the rows that ``flatten`` makes."""

import random

import pyarrow as pa

from tests.trees import random_tree
from treeloom.sources.trees import _market_records, open_tree
from treeloom.tree.encode import _joined, _numbered, _pylist, flatten, outline


def test_numbered_outlines_are_flattened_trees():
    rng = random.Random(7)
    trees = [random_tree(rng, rng.randint(1, 40)).children[0] for _ in range(60)]
    outlines = [outline(t) for t in trees]
    assert [n for *_, n in outlines] == [len(flatten(t)) for t in trees]
    shift = [1000 * i for i in range(len(trees))]
    cols = {
        "id": pa.array(range(len(trees)), pa.int64()), "shift": pa.array(shift, pa.int64()), "up": pa.array([5] * len(trees), pa.int64()), "depth": pa.array([3] * len(trees), pa.int32()),
        "shape": pa.array([x for x, *_ in outlines]),
    }
    texts, ends = [], [0]
    for _, own, _ in outlines:
        texts += own
        ends.append(len(texts))
    cols["lengths"], cols["texts"] = _joined(texts, ends)
    want = [[i, r[0] + s, r[1] + s, r[2], r[3] + s if r[3] else 5, *r[4:7], r[7] + s if r[7] else None, r[8]] for i, (t, s) in enumerate(zip(trees, shift)) for r in flatten(t, depth=3)]
    batch = pa.RecordBatch.from_pydict(cols)
    got = [list(x.values()) for b in (batch.slice(0, 20), batch.slice(20)) for x in _numbered(b, ["id"]).to_pylist()]
    assert got == want


def test_lists_are_taken_column_by_column():
    column = pa.array([[{"a": 1, "b": "x"}], None, [], [{"a": None, "b": "y"}, {"a": 3, "b": "z"}]])
    assert _pylist(column) == column.to_pylist() and _pylist(column.slice(2)) == column.slice(2).to_pylist()


def test_no_node_of_the_market_tree_is_dealt_out(spark, small):
    """All nodes were joined with the places of their records; only records are sorted now."""
    tree = open_tree(spark, small, "market")
    local, _ = _market_records(spark, small)
    assert local.groupBy("section", "o").count().filter("count > 1").isEmpty()
    assert tree.nodes.filter("frag <> -1").count() == local.agg({"size": "sum"}).first()[0]
    rows = tree.nodes.agg({"pre": "max"}).first()[0]
    assert tree.nodes.select("pre").distinct().count() == tree.nodes.count() == rows
