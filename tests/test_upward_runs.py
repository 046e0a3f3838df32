"""Bottom-up runs of spined documents by array steps: nothing but seeds and what lies above them, dealt out once."""

import random

import numpy as np

from tests.test_plans import _fragment
from tests.trees import Direct, random_tree
from treeloom.automaton.arrays import Forest
from treeloom.engine import topdown
from treeloom.engine.columnar import count_nodes
from treeloom.engine.topdown import run_bottom_up
from treeloom.sources.trees import COLUMNS, Tree, open_tree
from treeloom.tree.encode import flatten
from treeloom.workloads.paths import MARKET, _each
from treeloom.xpath.parser import parse

NODES = "doc long, frag int, pre long, last long, depth int, parent long, ord int, label string, kind string, host long, value string"


def test_a_forest_up_from_rows_has_these_and_what_lies_above():
    rng = random.Random(3)
    for _ in range(20):
        rows = flatten(random_tree(rng, 40))[1:]  # all below the document node
        pre = np.array([r[0] for r in rows])
        above = np.where(np.array([r[3] for r in rows]) == 1, -1, np.searchsorted(pre, [r[3] for r in rows]))
        whole = Forest.below(np.arange(len(rows)), above, np.searchsorted(pre, [r[1] for r in rows], "right"), [(r[6], r[5]) for r in rows])
        seeds = {r[0] for r in rng.sample(rows, 3)}
        cut, kept = whole.up_from(np.array(sorted(1 + int(np.searchsorted(pre, s)) for s in seeds)))
        want = [r for r in rows if any(r[0] <= s <= r[1] for s in seeds)]
        assert [rows[k - 1][0] for k in kept[1:]] == [r[0] for r in want]
        at = {r[0]: i for i, r in enumerate(want, 1)} | {1: 0}
        assert cut.above.tolist() == [-1, *(at[r[3]] for r in want)]
        assert cut.after.tolist()[1:] == [1 + sum(x[0] <= r[1] for x in want) for r in want]


def test_upward_runs_agree_with_direct_evaluation(spark, monkeypatch):
    rng = random.Random(77)
    docs = {d: flatten(random_tree(rng, 60)) for d in range(4)}
    rows = [(d, _fragment(r, {x[0]: x for x in rs}), *r) for d, rs in docs.items() for r in rs]
    tree = Tree(spark, spark.createDataFrame(rows, NODES).select(*COLUMNS).cache())
    by = {d: {r[0]: r for r in rs} for d, rs in docs.items()}
    for k, path in enumerate(["//*", "//a", "//*//b", "/*/*/*", "//a//text()", "//b/@m", "//*/@n", "//*/node()"]):
        monkeypatch.setattr(topdown, "FEW_SEEDS", (0, 10_000)[k % 2])
        want = sorted((d, p, by[d][p][1]) for d, rs in docs.items() for p in Direct(rs).select(parse(path)))
        assert sorted(map(tuple, run_bottom_up(tree, path).collect())) == want, path


def test_queries_of_one_kind_of_seeds_deal_the_nodes_out_once(spark, small, monkeypatch):
    """Each query dealt all nodes out twice and ran from node to node."""
    monkeypatch.setattr(topdown, "FEW_SEEDS", 0)
    tree = open_tree(spark, small, "market")
    both = _each(spark, [(q, count_nodes(run_bottom_up(tree, MARKET[q][0]))) for q in ("w03", "w16", "w17")])
    both.collect()
    plan = both._jdf.queryExecution().executedPlan().toString()
    final = plan.split("Initial Plan")[0]
    assert final.count("ReusedExchange") == 2 and "Window" not in plan
