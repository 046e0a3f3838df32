"""Queries that take every row, every whole text and every level."""

from collections import Counter

import __spark_entry__ as entry_module
from treeloom.sources.trees import open_tree


def test_all_whole_texts_come_back_from_the_index(spark, small):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = {r["text_id"] for r in entry_module.queries()["index_extract"](spark, small).collect()}
    assert got == set(docs) and max(len(docs[i]) for i in got) >= 4000 and max(got) >= 40


def test_members_past_the_first_200_go_through_markup_files(spark):
    folder = "/root/testdata/sf0.01"
    keys = [r["c_custkey"] for r in spark.read.parquet(f"{folder}/customer.parquet").select("c_custkey").collect()]
    got = entry_module.queries()["source_markup_files"](spark, folder).first()["n"]
    assert got == sum(k % 4 == 0 for k in keys) > sum(k % 4 == 0 for k in keys if k <= 200)


def test_pointers_reach_every_level(spark, small):
    parent = {(r["doc"], r["pre"]): r["parent"] for r in open_tree(spark, small, "threads").nodes.select("doc", "pre", "parent").collect()}
    want: Counter = Counter()
    for doc, pre in parent:
        depth = 1
        while parent[doc, pre]:
            pre, depth = parent[doc, pre], depth + 1
        want[depth] += 1
    got = {r["depth"]: r["n"] for r in entry_module.queries()["baseline_pointer_all_levels"](spark, small).collect()}
    assert got == want and max(got) > 3
