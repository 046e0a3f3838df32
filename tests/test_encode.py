import random

import pytest

from tests.trees import random_tree
from treeloom.sources.html import parse_html
from treeloom.tree.encode import ROOT, Node, flatten


def test_root_and_one_element():
    rows = flatten(Node(ROOT, [Node("a")]))
    assert [(r[0], r[1], r[2], r[5]) for r in rows] == [(1, 2, 1, "&"), (2, 2, 2, "a")]


def test_attributes_come_first_with_one_leaf_each():
    rows = flatten(Node(ROOT, [Node("a", ["t", Node("b")], {"x": "1", "y": "2"})]))
    assert [r[5] for r in rows] == ["&", "a", "@", "x", "%", "y", "%", "#", "b"]
    assert [r[7] for r in rows if r[6] == "attr"] == [2, 2]


def test_parenthesis_arithmetic_on_random_trees():
    rng = random.Random(5)
    for _ in range(200):
        rows = flatten(random_tree(rng, rng.randint(1, 60)))
        events = []

        def walk(i):
            stack = [(i, False)]
            while stack:
                j, done = stack.pop()
                events.append((j, done))
                if not done:
                    stack.append((j, True))
                    stack += [(k, False) for k in range(len(rows) - 1, -1, -1) if rows[k][3] == rows[j][0]]

        walk(0)
        place = {e: p for p, e in enumerate(events, 1)}
        for j, r in enumerate(rows):
            assert place[j, False] == 2 * r[0] - r[2]
            assert place[j, True] == 2 * r[0] - r[2] + 2 * (r[1] - r[0] + 1) - 1
            assert r[1] == max(x[0] for x in rows if x[0] >= r[0] and (x[0] == r[0] or _below(rows, x, r[0])))


def _below(rows, x, top):
    by = {r[0]: r for r in rows}
    while x[3]:
        if x[3] == top:
            return True
        x = by[x[3]]
    return False


def test_whitespace_texts_are_kept_unless_stripped():
    html = "<a>\n <b>x</b>\n <b>y</b>\n</a>"
    texts = lambda **o: sum(r[6] == "text" for r in flatten(parse_html(html, **o)))
    assert texts() == 5 and texts(strip_space=True) == 2


@pytest.mark.parametrize(
    ("html", "labels"),
    [
        ("<p>a<p>b", ["p", "p"]),
        ("<ul><li>a<li>b<ul><li>c</ul></ul>", ["ul", "li", "li", "ul", "li"]),
        ("<div><b>x</div>y", ["div", "b"]),
        ("a<br>b</p>", ["br"]),
        ("<script>if (a</p>b)</script><p>x", ["script", "p"]),
        (None, []),
    ],
)
def test_recovery(html, labels):
    assert [r[5] for r in flatten(parse_html(html)) if r[6] == "elem"] == labels
