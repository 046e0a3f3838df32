import random

import pytest

from tests.trees import Direct, random_path, random_tree
from treeloom.automaton.compile import to_automaton
from treeloom.automaton.evaluate import AllStates, Counters, Runner
from treeloom.automaton.jump import Jumper
from treeloom.automaton.model import FALSE, TRUE, conj, disj, down, neg
from treeloom.baselines.engines import _holds, document_of
from treeloom.tree.encode import ROOT, Node, flatten
from treeloom.xpath.parser import PathError, parse

OPTIONS = [{}, {"memo": False}, {"early": False}, {"lazy": False}, {"memo": False, "early": False, "lazy": False}]


def results(tree: Node, path: str, **options) -> list[int]:
    a = to_automaton(parse(path))
    doc, values, parents = document_of(tree)
    doc.flags = [_holds(p, doc, values, parents) for p in a.preds]
    runner = Runner(a, **options)
    return [doc.pre[i] for i in runner.nodes_of(doc, runner.run(doc, Counters()))]


def test_random_paths_agree_with_definitions():
    rng = random.Random(11)
    for k in range(700):
        tree = random_tree(rng, rng.randint(1, 40))
        path = random_path(rng)
        want = Direct(flatten(tree)).select(parse(path))
        assert results(tree, path, **OPTIONS[k % len(OPTIONS)]) == want, path


def test_jumping_runs_agree_with_definitions():
    rng = random.Random(12)
    done = 0
    while done < 1500:
        tree = random_tree(rng, rng.randint(1, 40))
        path = random_path(rng)
        a = to_automaton(parse(path))
        if not Jumper.fits(a):
            continue
        doc, values, parents = document_of(tree)
        doc.flags = [_holds(p, doc, values, parents) for p in a.preds]
        run = Jumper(a)
        found = run.run(doc, Counters())
        want = Direct(flatten(tree)).select(parse(path))
        assert [doc.pre[i] for i in run.nodes_of(doc, found)] == want, path
        assert run.count(doc, found) == len(want), path
        done += 1


def test_runs_of_all_states_agree_with_definitions():
    rng = random.Random(13)
    for _ in range(500):
        tree, path = random_tree(rng, rng.randint(1, 40)), random_path(rng)
        a = to_automaton(parse(path))
        doc, values, parents = document_of(tree)
        doc.flags = [_holds(p, doc, values, parents) for p in a.preds]
        run = AllStates(a)
        assert [doc.pre[i] for i in run.nodes_of(doc, run.run(doc, Counters()))] == Direct(flatten(tree)).select(parse(path)), path


def pairs_of(tree: Node) -> set[tuple[str, str, str]]:
    direct = Direct(flatten(tree))
    elems = [r for r in direct.rows if r[6] == "elem"]
    return {(axis, r[5], direct.by_pre[x][5]) for r in elems for axis in ("child", "descendant", "following-sibling") for x in direct.axis(r[0], axis) if direct.by_pre[x][6] == "elem"}


def test_label_pairs_leave_answers_as_they_are():
    rng = random.Random(14)
    folded = 0
    for _ in range(1500):
        tree, path = random_tree(rng, rng.randint(1, 12)), random_path(rng)
        plain, a = to_automaton(parse(path)), to_automaton(parse(path), pairs_of(tree))
        folded += len(a.states) < len(plain.states)
        want = Direct(flatten(tree)).select(parse(path))
        for run in [Runner(a), AllStates(a)] + ([Jumper(a)] if Jumper.fits(a) else []):
            doc, values, parents = document_of(tree)
            doc.flags = [_holds(p, doc, values, parents) for p in a.preds]
            assert [doc.pre[i] for i in run.nodes_of(doc, run.run(doc, Counters()))] == want, path
    assert folded > 100


def test_hopeless_filters_are_not_read():
    pairs = {("child", "a", "b"), ("descendant", "a", "b")}
    assert len(to_automaton(parse("//a[.//c or .//b]/b"), pairs).states) == 3 and len(to_automaton(parse("//a[.//c or .//b]/b")).states) == 4
    assert to_automaton(parse('//a[c/b[contains(., "x")]]'), pairs).preds == []


def test_jumps_visit_matches_only():
    entries = [Node("entry", [Node("note", [Node("term") for _ in range(5)])]) for _ in range(50)]
    tree = Node(ROOT, [Node("market", entries)])
    for path, most in (("//entry//term", 101), ("//*", 1), ("//*//*", 3), ("/market/entry", 52), ("//entry[.//strong]//term", 50)):
        doc, _, _ = document_of(tree)
        counters, run = Counters(), Jumper(to_automaton(parse(path)))
        run.run(doc, counters)
        assert counters.visited <= most, (path, counters)


def test_mixed_content_before_a_match():
    tree = Node(ROOT, [Node("a", ["x", Node("b")])])
    assert results(tree, "//b") == [4]


def test_deep_chain_and_wide_node():
    top = Node("a")
    node = top
    for _ in range(10_000):
        node.children.append(Node("a"))
        node = node.children[0]
    assert len(results(Node(ROOT, [top]), "//a//a", lazy=False)) == 10_000
    wide = Node(ROOT, [Node("a", [Node("b") for _ in range(10_000)])])
    assert len(results(wide, "/a/b")) == 10_000


def test_nested_matches_come_once():
    tree = Node(ROOT, [Node("e", [Node("e", [Node("e", [Node("t")])])])])
    for options in OPTIONS:
        assert results(tree, "//e//t", **options) == [5]
        assert results(tree, "//e//e//t", **options) == [5]
        assert results(tree, "//e[e]//t", **options) == [5]


def test_jumps_and_lazy_results_visit_less():
    tree = Node(ROOT, [Node("a", [Node("b", [Node("c")]) for _ in range(50)])])
    a = to_automaton(parse("//*"))
    doc, _, _ = document_of(tree)
    eager, lazy = Counters(), Counters()
    Runner(a, lazy=False).run(doc, eager)
    Runner(a).run(doc, lazy)
    assert lazy.visited == 1 and eager.visited > 100


def test_formulas_simplify_and_are_shared():
    x, y = down(1, 0), down(2, 1)
    assert conj(x, TRUE) is x and conj(x, FALSE) is FALSE and disj(x, TRUE) is TRUE and disj(FALSE, y) is y
    assert neg(neg(x)) is x and conj(x, y) is conj(x, y)


@pytest.mark.parametrize("text", ["//a[", "/", "//comment()", "//a[b", "//a]", "//unknown::b", "//a[contains(.)]", "//a b"])
def test_errors(text):
    with pytest.raises(PathError):
        parse(text)
