"""Counting, materialising and serialising the results of a spined document: array runs that deal nothing out, and whole markup."""

import random

from tests.test_plans import _fragment
from tests.trees import Direct, random_path, random_tree
from treeloom.automaton.arrays import Scans
from treeloom.automaton.compile import to_automaton
from treeloom.engine.planner import query
from treeloom.engine.topdown import count_top_down, goes_by_arrays, markup_top_down
from treeloom.sources.trees import COLUMNS, Tree, open_tree
from treeloom.tree.encode import flatten
from treeloom.workloads.paths import MARKET
from treeloom.xpath.parser import parse

NODES = "doc long, frag int, pre long, last long, depth int, parent long, ord int, label string, kind string, host long, value string"


def escaped(text, quote=False):
    text = text.replace("&", "&amp;").replace("<", "&lt;").replace(">", "&gt;")
    return text.replace('"', "&quot;") if quote else text


def markup(rows, top):
    """By recursion over the rows of a document."""
    me = next(r for r in rows if r[0] == top)
    if me[6] == "text":
        return escaped(me[8])
    attrs = "".join(f' {r[5]}="{escaped(r[8], True)}"' for r in rows if r[6] == "attr" and r[7] == top)
    return f"<{me[5]}{attrs}>" + "".join(markup(rows, r[0]) for r in rows if r[3] == top and r[6] in ("elem", "text")) + f"</{me[5]}>"


def put_together(df):
    pieces = {}
    for doc, pre, at, xml in df.select("doc", "pre", "at", "xml").collect():
        pieces.setdefault((doc, pre), []).append((at, xml))
    return {k: "".join(x for _, x in sorted(v)) for k, v in pieces.items()}


def test_markup_of_fragments_and_of_the_spine_is_whole(spark):
    rng = random.Random(51)
    docs = {d: flatten(random_tree(rng, 50)) for d in range(4)}
    for rows in docs.values():
        for r in rows:
            r[8] = r[8] and r[8].replace("x", '<&"é')
    rows = [(d, _fragment(r, {x[0]: x for x in rs}), *r) for d, rs in docs.items() for r in rs]
    tree, done = Tree(spark, spark.createDataFrame(rows, NODES).select(*COLUMNS).cache()), 0
    assert tree.spined
    for path in ["//*", "/*", *(random_path(rng) for _ in range(200))]:
        if done == 8:
            break
        if not Scans.fits(to_automaton(parse(path))):
            continue
        want = {(d, p): markup(rs, p) for d, rs in docs.items() for p in Direct(rs).select(parse(path))}
        if not want:
            continue
        assert put_together(markup_top_down(tree, path)) == want, path
        assert count_top_down(tree, path).first()["n"] == len(want), path
        done += 1
    assert done == 8


def test_no_mode_deals_the_nodes_out_again(spark, small):
    tree = open_tree(spark, small, "market")
    for q in (q for q in MARKET if q.startswith("w")):
        assert goes_by_arrays(tree, MARKET[q][0]), q
    for q in ("w03", "w11", "w17"):
        for mode in ("materialise", "serialise"):
            plan = query(tree, MARKET[q][0], mode)._jdf.queryExecution().optimizedPlan().toString()
            assert not any(x in plan for x in ("RepartitionByExpression", "Window", "Join")), (q, mode)


def test_the_whole_document_is_serialised_and_counts_are_those_of_columnar_runs(spark, small):
    tree = open_tree(spark, small, "market")
    rows = sorted([[*r] for r in tree.all.select("pre", "last", "depth", "parent", "ord", "label", "kind", "host", "value").collect()])
    want, opened = [], []
    for r in rows:
        while opened and opened[-1][1] < r[0]:
            want.append(f"</{opened.pop()[5]}>")
        if r[6] == "elem":
            want += [f"<{r[5]}", ">"]
            opened.append(r)
        elif r[6] == "attr":
            want.insert(len(want) - 1, f' {r[5]}="{escaped(r[8], True)}"')
        elif r[6] == "text":
            want.append(escaped(r[8]))
    want += [f"</{r[5]}>" for r in reversed(opened)]
    assert list(put_together(query(tree, MARKET["w13"][0], "serialise")).values()) == ["".join(want)]
    for q in ("w10", "w12", "w16"):
        n = query(tree, MARKET[q][0], "count", hint="columnar").first()["n"]
        assert query(tree, MARKET[q][0], "count").first()["n"] == n == query(tree, MARKET[q][0]).count(), q
        assert len(put_together(query(tree, MARKET[q][0], "serialise"))) == n, q
