"""Brute force over small trees in Python, written from the definitions and sharing no code with the engine."""

from __future__ import annotations

from treefacts.plans.path import And, Not, Or, Path, Step, Test, parse
from treefacts.sources.markup import Element


class Node:
    """An element, text run or attribute, with its number and parent."""

    def __init__(self, kind: str, tag: str, value: str | None, number: tuple[int, ...], parent: Node | None):
        self.kind, self.tag, self.value, self.number, self.parent = kind, tag, value, number, parent
        self.children: list[Node] = []
        self.attributes: list[Node] = []


def tree(x: Element, number: tuple[int, ...] = (1,), parent: Node | None = None) -> Node:
    leaf = not x.atts and all(isinstance(c, str) for c in x.children)
    node = Node("leaf" if leaf else "inner", x.tag, "".join(x.children) if leaf else None, number, parent)
    node.attributes = [Node("att", f"@{k}", v, number, node) for k, v in x.atts.items()]
    if not leaf:
        for i, c in enumerate(x.children, 1):
            own = (*number, i)
            node.children.append(Node("text", "#text", c, own, node) if isinstance(c, str) else tree(c, own, node))
    return node


def below(x: Node) -> list[Node]:
    out = []
    for c in x.children:
        out += [c, *below(c)]
    return out


def string_value(x: Node) -> str:
    return x.value if x.value is not None else "".join(c.value for c in below(x) if c.value is not None)


def whole(x: Node) -> set[Node]:
    return {n for y in (x, *below(x)) for n in (y, *y.attributes)}


def between(x: Node, y: Node) -> set[Node]:
    """Elements strictly between x and y below it, with their attributes."""
    out: set[Node] = set()
    while y.parent is not None and y.parent is not x and y is not x:
        y = y.parent
        out |= {y, *y.attributes}
    return out


def tests_of(c) -> list[Test]:
    if c is None:
        return []
    return [c] if isinstance(c, Test) else [t for p in (c.parts if isinstance(c, And | Or) else (c.part,)) for t in tests_of(p)]


class Reference:
    def __init__(self, root: Element, value_test: str = "leaf", text_mode: str = "leaf"):
        self.top = Node("document", "", None, (), None)
        self.top.children = [tree(root, (1,), self.top)]
        self.value_test, self.text_mode = value_test, text_mode

    def step(self, nodes: list[Node], step: Step) -> list[Node]:
        out: list[Node] = []
        for n in nodes:
            around = [n, *below(n)] if step.axis == "descendant" or step.deep else [n]
            if step.axis == "parent":
                found = [n.parent] if n.parent is not None and n.parent.kind != "document" else []
            elif step.axis == "attribute":
                found = [a for x in around for a in x.attributes if step.tags is None or a.tag[1:] in step.tags]
            elif step.axis == "text":
                found = [c for x in around for c in x.children if c.kind == "text"]
                if self.text_mode != "strict":
                    found += [x for x in around if x.kind == "leaf"]
            else:
                found = [c for x in around for c in x.children if c.kind in ("inner", "leaf") and (step.tags is None or c.tag in step.tags)]
            out += [x for x in found if x not in out]
        if step.condition is not None:
            out = [x for x in out if self.satisfies(x, step.condition)]
        return out

    def satisfies(self, x: Node, c) -> bool:
        if isinstance(c, And):
            return all(self.satisfies(x, p) for p in c.parts)
        if isinstance(c, Or):
            return any(self.satisfies(x, p) for p in c.parts)
        if isinstance(c, Not):
            return not self.satisfies(x, c.part)
        return any(c.op is None or self.compares(n, c) for n in self.walk([x], c.path))

    def compares(self, n: Node, test: Test) -> bool:
        values = [n.value] if n.value is not None else []
        if n.kind == "inner" and self.value_test == "own_text":
            values = [c.value for c in n.children if c.kind == "text"]
        if n.kind == "inner" and self.value_test == "string_value":
            values = [string_value(n)]
        for v in values:
            if isinstance(test.literal, float):
                try:
                    v = float(v)
                except ValueError:
                    continue
            good = {"=": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, ">": lambda a, b: a > b, "<=": lambda a, b: a <= b, ">=": lambda a, b: a >= b, "contains": lambda a, b: b in a, "starts-with": lambda a, b: a.startswith(b)}
            if good[test.op](v, test.literal):
                return True
        return False

    def walk(self, nodes: list[Node], path: Path) -> list[Node]:
        for s in path.steps:
            nodes = self.step(nodes, s)
        return nodes

    def witnesses(self, x: Node, condition) -> set[Node]:
        """What the tests of a condition find from x, whole, and what lies between."""
        out: set[Node] = set()
        for t in tests_of(condition):
            for n in self.walk([x], t.path):
                if t.op is None or self.compares(n, t):
                    out |= {*whole(n), *between(x, n)}
        return out

    def reach(self, x: Node, steps: tuple[Step, ...]) -> set[Node] | None:
        """The part of x that a path is about, x being a node of its first step; None if it leads to no answer."""
        if len(steps) == 1:
            return whole(x) | self.witnesses(x, steps[0].condition)
        out: set[Node] | None = None
        for y in self.step([x], steps[1]):
            part = self.reach(y, steps[1:])
            if part is not None:
                out = (out or set()) | part | between(x, y)
        return None if out is None else out | {x, *x.attributes} | self.witnesses(x, steps[0].condition)

    def subtree(self, path: str) -> list[tuple[str, str, str]]:
        """(dotted number, tag, kind) of the part of the tree that a path is about: answers whole, what its conditions found, all
        elements above with their attributes. For paths without parent steps."""
        found: set[Node] = set()
        steps = parse(path).steps
        for x in self.step([self.top], steps[0]):
            part = self.reach(x, steps)
            if part is not None:
                found |= part | between(self.top, x)
        return sorted((".".join(map(str, n.number)), n.tag, n.kind) for n in found)

    def query(self, path: str) -> list[tuple[str, str]]:
        """(dotted number, tag) of the answers, sorted."""
        return sorted((".".join(map(str, n.number)), n.tag) for n in self.walk([self.top], parse(path)))
