"""Step joins of spined documents: what is broadcast is at hand, whatever the step before."""

import random

from tests.test_plans import _fragment
from tests.trees import Direct, random_path, random_tree
from treeloom.baselines.engines import StepJoin
from treeloom.sources.trees import COLUMNS, Tree, open_tree
from treeloom.tree.encode import flatten
from treeloom.xpath.parser import parse

NODES = "doc long, frag int, pre long, last long, depth int, parent long, ord int, label string, kind string, host long, value string"


def test_step_joins_over_fragments_agree_with_direct_evaluation(spark):
    rng = random.Random(61)
    docs = {d: flatten(random_tree(rng, 50)) for d in range(3)}
    rows = [(d, _fragment(r, {x[0]: x for x in rs}), *r) for d, rs in docs.items() for r in rs]
    tree = Tree(spark, spark.createDataFrame(rows, NODES).select(*COLUMNS).cache())
    for path in ["/*[.//*]", "//*[not(.//a) or b]//c", "//a/following-sibling::*", '//*[contains(., "x")]', *(random_path(rng) for _ in range(4))]:
        want = sorted((d, p) for d, rs in docs.items() for p in Direct(rs).select(parse(path)))
        assert [tuple(r) for r in StepJoin(tree).select(path).select("doc", "pre").collect()] == want, path


def test_no_broadcast_of_a_step_join_waits_for_a_job(spark, small):
    """The spine was broadcast as a part of the step before, and its scans stood in line with all others."""
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = StepJoin(open_tree(spark, small, "market")).select("//*//*//*")._jdf.queryExecution().executedPlan().toString().splitlines()
        at = [i for i, x in enumerate(plan) if "BroadcastExchange" in x]
        assert len(at) == 3 and all("LocalTableScan" in plan[i + 1] for i in at)
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
