"""Random trees and a direct evaluator of paths over them."""

import random

from treeloom.tree.encode import ROOT, Node
from treeloom.xpath.ast import And, Exists, Not, Or, Path, ValuePred


def random_tree(rng: random.Random, size: int, labels: str = "abcd", attrs: bool = True) -> Node:
    top = Node(rng.choice(labels))
    nodes = [top]
    while len(nodes) < size:
        up = rng.choice(nodes[-8:] if rng.random() < 0.5 else nodes)
        if rng.random() < 0.25:
            up.children.append("".join(rng.choice("xyz") for _ in range(rng.randint(1, 4))))
            if len(up.children) > 1 and isinstance(up.children[-2], str):
                text = up.children.pop()
                up.children[-1] += text
            nodes.append(up)
            continue
        new = Node(rng.choice(labels))
        if attrs and rng.random() < 0.2:
            new.attrs = {rng.choice("mn"): rng.choice(["x", "yz"])}
        up.children.append(new)
        nodes.append(new)
    return Node(ROOT, [top])


def random_path(rng: random.Random, depth: int = 0) -> str:
    def filt(d: int) -> str:
        r = rng.random()
        if r < 0.2 and d < 2:
            return f"not({filt(d + 1)})"
        if r < 0.35 and d < 2:
            return f"{filt(d + 1)} {rng.choice(['and', 'or'])} {filt(d + 1)}"
        if r < 0.5:
            return f'{rng.choice(["contains", "starts-with", "ends-with"])}({rng.choice([".", "a", "text()", "@m"])}, "{rng.choice("xyz")}")'
        if r < 0.6:
            return "@m"
        return rng.choice(["", ".//"]) + rng.choice("abcd*") + rng.choice(["", "/" + rng.choice("abcd")])

    out = ""
    for i in range(rng.randint(1, 3)):
        axis = rng.choice(["/", "//"])
        step = rng.choice(["a", "b", "c", "d", "*"])
        if i and rng.random() < 0.15:
            axis, step = "/", "following-sibling::" + step
        out += axis + step
        if rng.random() < 0.4:
            out += f"[{filt(0)}]"
    return out


class Direct:
    """Nodes as rows in document order; every axis by its definition."""

    def __init__(self, rows: list[list]):
        self.rows = rows
        self.by_pre = {r[0]: r for r in rows}

    def axis(self, pre: int, axis: str) -> list[int]:
        r = self.by_pre[pre]
        hidden = ("attrs", "attr", "value")
        visible = [x for x in self.rows if x[6] not in hidden]
        if axis == "child":
            return [x[0] for x in visible if x[3] == pre]
        if axis == "descendant":
            return [x[0] for x in visible if pre < x[0] <= r[1]]
        if axis == "self":
            return [pre]
        if axis == "following-sibling":
            return [x[0] for x in visible if x[3] == r[3] and x[0] > r[1]]
        if axis == "attribute":
            return [x[0] for x in self.rows if x[6] == "attr" and x[7] == pre]
        raise AssertionError(axis)

    def test(self, pre: int, axis: str, test: str) -> bool:
        r = self.by_pre[pre]
        if axis == "attribute":
            return test in ("*", "node()") or r[5] == test
        if test == "*":
            return r[6] == "elem"
        if test == "text()":
            return r[6] == "text"
        if test == "node()":
            return r[6] in ("elem", "text", "attr")
        return r[6] == "elem" and r[5] == test

    def value(self, pre: int, p: ValuePred) -> bool:
        r = self.by_pre[pre]
        texts = [r[8]] if r[6] in ("text", "attr") else [x[8] for x in self.rows if x[3] == pre and x[6] == "text"]
        return any({"contains": p.word in t, "starts-with": t.startswith(p.word), "ends-with": t.endswith(p.word), "=": t == p.word}[p.kind] for t in texts)

    def holds(self, pre: int, f) -> bool:
        if isinstance(f, And):
            return self.holds(pre, f.left) and self.holds(pre, f.right)
        if isinstance(f, Or):
            return self.holds(pre, f.left) or self.holds(pre, f.right)
        if isinstance(f, Not):
            return not self.holds(pre, f.inner)
        if isinstance(f, Exists):
            return bool(self.walk([pre], f.path))
        return any(self.value(x, f) for x in self.walk([pre], f.path))

    def walk(self, context: list[int], path: Path) -> list[int]:
        for s in path.steps:
            found = {y for x in context for y in self.axis(x, s.axis) if self.test(y, s.axis, s.test)}
            context = sorted(y for y in found if all(self.holds(y, f) for f in s.filters))
        return context

    def select(self, path: Path) -> list[int]:
        return self.walk([1], path)
