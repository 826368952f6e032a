"""Letter formulas (over edge variables) and clock guards, read from text."""

from __future__ import annotations

import ast
import operator
import re
from collections.abc import Iterable

from pyspark.sql import Column
from pyspark.sql import functions as F

TRUE = ("true",)
_OPS = {ast.LtE: "<=", ast.GtE: ">=", ast.Lt: "<", ast.Gt: ">"}
_PY = {"<=": operator.le, ">=": operator.ge, "<": operator.lt, ">": operator.gt}


def _tree(text: str) -> tuple:
    text = re.sub(r"!(?!=)", " not ", text).replace("&", " and ").replace("|", " or ").replace("true", "True").strip()

    def walk(n: ast.AST) -> tuple:
        if isinstance(n, ast.BoolOp):
            kind = "and" if isinstance(n.op, ast.And) else "or"
            return (kind, *map(walk, n.values))
        if isinstance(n, ast.UnaryOp) and isinstance(n.op, ast.Not):
            return ("not", walk(n.operand))
        if isinstance(n, ast.Constant) and n.value is True:
            return TRUE
        if isinstance(n, ast.Name):
            return ("var", n.id)
        if isinstance(n, ast.Compare) and len(n.ops) == 1 and isinstance(n.left, ast.Name) and type(n.ops[0]) in _OPS:
            return ("cmp", n.left.id, _OPS[type(n.ops[0])], ast.literal_eval(n.comparators[0]))
        raise ValueError(f"can't read {text!r}")

    return walk(ast.parse(text or "True", mode="eval").body)


def _holds(tree: tuple, leaf) -> bool:
    kind = tree[0]
    if kind == "true":
        return True
    if kind == "and":
        return all(_holds(t, leaf) for t in tree[1:])
    if kind == "or":
        return any(_holds(t, leaf) for t in tree[1:])
    if kind == "not":
        return not _holds(tree[1], leaf)
    return leaf(tree)


def letters(text: str, m: int) -> frozenset[int]:
    """The sets of edge variables (bit masks) that satisfy a formula over y1 .. ym."""
    tree = _tree(text)
    return frozenset(a for a in range(1 << m) if _holds(tree, lambda v: bool(a >> (int(v[1][1:]) - 1) & 1)))


def only(*variables: int) -> frozenset[int]:
    """Exactly these edge variables."""
    return frozenset([sum(1 << (v - 1) for v in variables)])


def guard(text: str) -> tuple:
    return _tree(text) if text else TRUE


def guard_clocks(tree: tuple) -> set[str]:
    return {tree[1]} if tree[0] == "cmp" else set().union(*(guard_clocks(t) for t in tree[1:] if isinstance(t, tuple)))


def guard_holds(tree: tuple, elapsed: dict[str, float]) -> bool:
    return _holds(tree, lambda c: _PY[c[2]](elapsed[c[1]], c[3]))


def guard_column(tree: tuple, elapsed: dict[str, Column]) -> Column:
    """The guard over columns of elapsed times."""
    kind = tree[0]
    if kind == "true":
        return F.lit(True)
    if kind == "not":
        return ~guard_column(tree[1], elapsed)
    if kind == "cmp":
        return _PY[tree[2]](elapsed[tree[1]], F.lit(tree[3]))
    parts = [guard_column(t, elapsed) for t in tree[1:]]
    out = parts[0]
    for p in parts[1:]:
        out = out & p if kind == "and" else out | p
    return out


def constants(trees: Iterable[tuple]) -> list[float]:
    """All constants that guards compare with."""
    out: set[float] = set()
    for t in trees:
        if t[0] == "cmp":
            out.add(t[3])
        else:
            out |= set(constants(x for x in t[1:] if isinstance(x, tuple)))
    return sorted(out)
