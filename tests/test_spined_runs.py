"""Documents that are larger than a task: no strategy puts one into a single task, or runs what nobody asked for."""

import random

from tests.test_plans import _fragment
from tests.trees import Direct, random_path, random_tree
from treeloom.baselines.engines import StepJoin
from treeloom.engine.topdown import can_run_bottom_up, run_bottom_up
from treeloom.sources.trees import COLUMNS, Tree, open_tree
from treeloom.tree.encode import flatten
from treeloom.workloads import paths
from treeloom.workloads.paths import MARKET
from treeloom.xpath.parser import parse


def plan_of(df) -> str:
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_a_bottom_up_run_of_a_document_with_a_spine_has_more_than_one_task(spark, small):
    tree = open_tree(spark, small, "market")
    for name in ("w03", "w15", "x09"):
        plan = plan_of(run_bottom_up(tree, MARKET[name][0]))
        dealt = [x.split("]")[0] for x in plan.split("RepartitionByExpression [")[1:]]
        assert dealt and all("frag" in x for x in dealt), name


def test_bottom_up_runs_over_fragments_agree_with_whole_documents(spark):
    rng = random.Random(34)
    docs = {d: flatten(random_tree(rng, 60)) for d in range(5)}
    rows = [(d, _fragment(r, {x[0]: x for x in rs}), *r) for d, rs in docs.items() for r in rs]
    nodes = spark.createDataFrame(rows, "doc long, frag int, pre long, last long, depth int, parent long, ord int, label string, kind string, host long, value string").select(*COLUMNS).cache()
    tree, done = Tree(spark, nodes), 0
    while done < 8:
        path = random_path(rng)
        if "sibling" in path or not can_run_bottom_up(parse(path)):
            continue
        want = sorted((d, p) for d, rs in docs.items() for p in Direct(rs).select(parse(path)))
        assert sorted(map(tuple, run_bottom_up(tree, path).select("doc", "pre").collect())) == want, path
        done += 1


def test_a_step_join_broadcasts_the_spine(spark, small):
    """Joined by document alone, all candidates of the market tree were sorted in one task."""
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = StepJoin(open_tree(spark, small, "market")).select("//entry//term")._jdf.queryExecution().executedPlan().toString()
        assert "BroadcastHashJoin" in plan
        assert not [x for x in plan.splitlines() if "SortMergeJoin" in x and "frag" not in x]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_result_counts_run_no_pass_over_all_nodes(spark, small, monkeypatch):
    """Filters are asked of every fragment while the plan is made, so a run that is filtered out afterwards had cost that already."""
    asked = []

    def visits(tree, path, jump=True):
        asked.append(jump)
        return spark.createDataFrame([(0, 1, 1, 1, 1)], "doc long, rows long, visited long, marked long, results long")

    monkeypatch.setattr(paths, "visits", visits)
    assert paths.measure_visits(spark, small).columns == ["query", "results"] and set(asked) == {True}
    asked.clear()
    assert len(paths.measure_visited(spark, small).columns) == 7 and set(asked) == {True, False}
