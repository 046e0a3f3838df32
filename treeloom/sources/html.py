"""A forgiving reader of web pages: always a tree, whatever the markup.

Script and style keep their text whole; comments, doctypes and processing instructions are dropped; void elements are
leaves; a new p or li closes an open one unless a block lies between; a closing tag closes back to its match or is
ignored; what is left open closes at the end, and inline elements close with the block around them.
"""

from __future__ import annotations

from html.parser import HTMLParser

from treeloom.tree.encode import ROOT, Node

#: Element names by role (fixed values of the HTML standard).
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("html head body nav ul ol div article section header footer main aside table tr td th form".split())
CLOSES_SELF = frozenset(("p", "li"))


class _Reader(HTMLParser):
    def __init__(self, strip_space: bool):
        super().__init__(convert_charrefs=True)
        self.root = Node(ROOT)
        self.open = [self.root]
        self.strip_space = strip_space

    def handle_starttag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        if tag in CLOSES_SELF:
            for i in range(len(self.open) - 1, 0, -1):
                if self.open[i].label == tag:
                    del self.open[i:]
                    break
                if self.open[i].label in BLOCK:
                    break
        node = Node(tag, attrs={k: v or "" for k, v in attrs})
        self.open[-1].children.append(node)
        if tag not in VOID:
            self.open.append(node)

    def handle_startendtag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.open.pop()

    def handle_endtag(self, tag: str) -> None:
        for i in range(len(self.open) - 1, 0, -1):
            if self.open[i].label == tag:
                del self.open[i:]
                return

    def handle_data(self, data: str) -> None:
        if data and not (self.strip_space and not data.strip()):
            here = self.open[-1].children
            if here and isinstance(here[-1], str):
                here[-1] += data
            else:
                here.append(data)


def parse_html(html: str | None, strip_space: bool = False) -> Node:
    reader = _Reader(strip_space)
    reader.feed(html or "")
    reader.close()
    return reader.root
