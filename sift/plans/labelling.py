"""Labelling of predicate trees with keep tests, and folding of the labels into one test for the root."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from sift.plans.keep import AlwaysKeep, KeepTest, NeverKeep, all_of, any_of
from sift.plans.predicate import Node, normalised


class Matcher:
    """Gives tests for nodes that it understands. Each test must be sound for its node: it holds for every object
    with a row that satisfies the node."""

    def match(self, node: Node) -> Iterable[KeepTest]:
        raise NotImplementedError


@dataclass
class Labelled:
    node: Node
    labels: list[KeepTest]
    children: list["Labelled"] = field(default_factory=list)

    def explain(self, depth: int = 0) -> str:
        own = "  " * depth + self.node.text() + "".join(f"\n{'  ' * depth}  <- {t.sql()}" for t in self.labels)
        return "\n".join([own, *(c.explain(depth + 1) for c in self.children)])


def label(node: Node, matchers: Iterable[Matcher]) -> Labelled:
    """Every matcher sees every node; a node may get several tests."""
    matchers = list(matchers)

    def visit(n: Node) -> Labelled:
        return Labelled(n, list(dict.fromkeys(t for m in matchers for t in m.match(n))), [visit(c) for c in n.children])

    return visit(normalised(node))


def fold(tree: Labelled) -> KeepTest:
    """One test for the root. A row that satisfies an AND satisfies all children, so all their tests hold for its
    object; one that satisfies an OR satisfies a child, so that one's does. Other nodes have their labels only."""
    own = tree.labels
    if tree.node.kind == "and":
        return all_of([*own, *map(fold, tree.children)])
    if tree.node.kind == "or":
        return all_of([*own, any_of(list(map(fold, tree.children)))])
    if tree.node.kind == "const":
        return NeverKeep() if tree.node.op == "false" else AlwaysKeep()
    return all_of(own)
