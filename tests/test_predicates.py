"""Labelling and folding, by enumeration."""

import itertools

import pytest

from sift.plans.keep import AlwaysKeep, AndTest, NeverKeep, OrTest, SummaryTest
from sift.plans.labelling import Matcher, fold, label
from sift.plans.predicate import Lit, Node, Ref, both, either, normalised

LEAVES = [Node("cmp", term=Ref(c), op="=", values=(Lit("1", "integer"),)) for c in "abc"]


def shapes(depth):
    yield from LEAVES
    if depth:
        smaller = list(shapes(depth - 1))[:7]
        for a, b in itertools.product(smaller, repeat=2):
            yield Node("and", (a, b))
            yield Node("or", (a, b))
        for a in smaller:
            yield Node("not", (a,))


def truth(node, row):
    """Three-valued: True, False or None."""
    if node.kind == "cmp":
        v = row[node.term.path]
        return None if v is None else (v == 1) == (node.op == "=")
    parts = [truth(c, row) for c in node.children]
    if node.kind == "not":
        return None if parts[0] is None else not parts[0]
    if node.kind == "and":
        return False if False in parts else None if None in parts else True
    return True if True in parts else None if None in parts else False


class Exact(Matcher):
    """For every leaf the tightest sound test: some row satisfies it; given as a name that the evaluator looks up."""

    def match(self, node):
        if node.kind == "cmp" and node.term.path != "c":  # c has no summary
            yield SummaryTest(f"{node.term.path}{node.op}", "x")


def holds(test, rows):
    if isinstance(test, AlwaysKeep):
        return True
    if isinstance(test, NeverKeep):
        return False
    if isinstance(test, AndTest):
        return all(holds(p, rows) for p in test.parts)
    if isinstance(test, OrTest):
        return any(holds(p, rows) for p in test.parts)
    col, op = test.index[0], test.index[1:]
    return any(r[col] is not None and (r[col] == 1) == (op == "=") for r in rows)


def test_every_small_tree_is_sound():
    rows = [dict(zip("abc", v, strict=True)) for v in itertools.product([0, 1, None], repeat=3)]
    objects = [[r] for r in rows] + [[a, b] for a, b in itertools.combinations(rows[::4], 2)]
    n = 0
    for tree in shapes(2):
        nnf = normalised(tree)
        for r in rows:
            assert (truth(tree, r) is True) == (truth(nnf, r) is True)
        test = fold(label(tree, [Exact()]))
        for o in objects:
            if any(truth(tree, r) is True for r in o):
                assert holds(test, o), (tree.text(), o)
            n += not holds(test, o)
    assert n > 1000  # and it does skip


def test_folding_rules():
    a, b, c = LEAVES
    t = {x.term.path: next(iter(Exact().match(x)), None) for x in LEAVES}
    assert fold(label(both([a, b]), [Exact()])) == AndTest((t["a"], t["b"]))
    assert fold(label(either([a, c]), [Exact()])) == AlwaysKeep()
    assert fold(label(both([a, c]), [Exact()])) == t["a"]
    assert fold(label(Node("not", (Node("const", op="true"),)), [])) == NeverKeep()
    assert fold(label(Node("unknown"), [Exact()])) == AlwaysKeep()
    assert fold(label(Node("not", (Node("unknown"),)), [Exact()])) == AlwaysKeep()


def test_in_lists_with_null():
    one, null = Lit("1", "integer"), Lit(None, "integer")
    assert normalised(Node("not", (Node("in", term=Ref("a"), values=(one, null)),))) == Node("const", op="false")
    assert normalised(Node("in", term=Ref("a"), values=(one, null))).values == (one,)


@pytest.mark.parametrize("lit, text", [(Lit("a'b\\", "string"), "'a\\'b\\\\'"), (Lit("2024-01-05", "date"), "CAST('2024-01-05' AS date)"), (Lit("true", "boolean"), "true"), (Lit(None, "long"), "CAST(NULL AS long)")])
def test_literals(lit, text):
    assert lit.sql() == text
