"""Paths answered by the text index, from the matches upward."""

import random

import pytest

from tests.trees import Direct, random_tree
from treeloom.engine.columnar import Columnar
from treeloom.engine.planner import choose, query
from treeloom.engine.textindex import chain_of, climb, count_hits, search_texts
from treeloom.engine.topdown import can_run_bottom_up, near_seeds, pred_hits, run_bottom_up, run_top_down, seed_of
from treeloom.sources.trees import COLUMNS, Tree, open_tree
from treeloom.text.cutoff import calibrated
from treeloom.tree.encode import flatten
from treeloom.xpath.parser import parse

SCHEMA = "doc long, frag int, pre long, last long, depth int, parent long, ord int, label string, kind string, host long, value string"


def chain_path(rng: random.Random) -> str:
    step = lambda: rng.choice(["/", "//"]) + rng.choice("abcd*")
    main = "".join(step() for _ in range(rng.randint(1, 3)))
    test = f'{rng.choice(["contains", "starts-with", "ends-with"])}(%s, "{rng.choice("xyz")}")'
    r = rng.random()
    if r < 0.3:
        return f"{main}[{test % '.'}]"
    if r < 0.45:
        return f"{main}[{test % '@m'}]"
    if r < 0.6:
        return f"{main}[{test % 'text()'}]"
    if r < 0.8:
        return f"{main}[{test % ('.//' + rng.choice('abcd*'))}]"
    return f"{main}[.//{rng.choice('abcd*')}[{test % rng.choice(['.', 'a', '@n'])}]]"


def keys(df) -> list:
    return sorted(map(tuple, df.select("doc", "pre").collect()))


def test_climbing_agrees_with_definitions(spark):
    rng = random.Random(71)
    docs = {d: flatten(random_tree(rng, 50)) for d in range(12)}
    nodes = spark.createDataFrame([(d, 0, *r) for d, rs in docs.items() for r in rs], SCHEMA).select(*COLUMNS)
    tree = Tree(spark, nodes, "random", "test_tree_index", True)
    done = 0
    while done < 40:
        path = chain_path(rng)
        parsed = parse(path)
        assert chain_of(parsed) is not None and can_run_bottom_up(parsed), path
        got = climb(tree.index, parsed)
        want = sorted((d, p) for d, rs in docs.items() for p in Direct(rs).select(parsed))
        assert keys(got) == want, path
        last = {(d, r[0]): r[1] for d, rs in docs.items() for r in rs}
        assert all(last[r["doc"], r["pre"]] == r["last"] for r in got.collect()), path
        done += 1
    assert chain_of(parse('//a[contains(., "x")]/b')) is None and not can_run_bottom_up(parse('//a[contains(., "x")]/b'))
    assert chain_of(parse('//a[not(contains(., "x"))]')) is None and chain_of(parse('//a[b[c][contains(., "x")]]')) is None


def test_index_and_scan_find_the_same_texts(spark, small):
    tree = open_tree(spark, small, "citations")
    scan = open_tree(spark, small, "citations", use_index=False)
    for kind, word in (("contains", "License"), ("starts-with", "The"), ("ends-with", "."), ("=", "1997"), ("<", "B")):
        assert keys(search_texts(tree.index, kind, word)) == keys(scan.matching(kind, word)), (kind, word)
        values = [r["value"] for r in tree.texts.select("value").collect()]
        if kind == "contains":
            assert count_hits(tree.index, kind, word)[0] == sum(v.count(word) for v in values)


def physical(df) -> str:
    return df._jdf.queryExecution().toString().split("== Physical Plan ==")[1]


def test_rare_words_read_neither_nodes_nor_texts(spark, small):
    tree = open_tree(spark, small, "citations")
    path = '//art[.//abs[contains(., "License")]]'
    assert tree.by_index("contains", "License") and choose(tree, path).strategy == "bottom-up"
    for df in (run_bottom_up(tree, path), query(tree, path)):
        plan = physical(df)
        assert "keys" in plan and "value" not in plan and "label" not in plan
    assert "Contains(value" not in physical(pred_hits(tree, seed_of(parse(path))))
    assert "Contains(value" not in physical(Columnar(tree).select(path))
    assert keys(run_bottom_up(tree, path)) == keys(run_top_down(tree, path))


def test_bottom_up_shuffles_only_what_is_near_a_seed(spark, small):
    tree = open_tree(spark, small, "citations", use_index=False)
    path = parse('//abs[contains(., "License")]')
    seeds = tree.nodes.join(pred_hits(tree, path.steps[-1].filters[0]), ["doc", "pre"], "left_semi")
    n, depth = seeds.count(), 5
    assert 0 < near_seeds(tree, seeds).count() <= n * depth
    rows = run_bottom_up(tree, path, counters=True).agg({"rows": "sum"}).first()[0]
    assert rows <= n * depth


def test_cut_off_from_measured_times():
    assert calibrated([(0, 10.0, 60.0), (100, 20.0, 60.0), (200, 30.0, 60.0)]) == pytest.approx(500)
    assert calibrated([(5, 10.0, 60.0)]) is None and calibrated([(0, 10.0, 9.0), (9, 10.0, 9.0)]) is None


@pytest.mark.parametrize("name", ["market", "pages", "threads"])
def test_label_pairs_by_definition(spark, small, name):
    """Child and descendant pairs, also below a spine, from the ancestors of every element."""
    tree = open_tree(spark, small, name)
    rows = sorted((r["doc"], r["pre"], r["last"], r["parent"], r["label"]) for r in tree.nodes.filter("kind = 'elem'").select("doc", "pre", "last", "parent", "label").collect())
    want, above = set(), []
    for doc, pre, last, parent, label in rows:
        while above and (above[-1][0] != doc or above[-1][2] < pre):
            above.pop()
        want |= {("descendant", x[3], label) for x in above} | {("child", x[3], label) for x in above if x[1] == parent}
        above.append((doc, pre, last, label))
    assert {p for p in tree.pairs() if p[0] in ("child", "descendant")} == want
