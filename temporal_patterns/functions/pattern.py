"""Graph patterns: edge variables between node variables, with labels and constants."""

from __future__ import annotations

import re
from dataclasses import dataclass, replace

_EDGE = re.compile(r"\(\s*(\w+)\s*(?::\s*(\w+))?\s*\)\s*-\s*\[\s*(\w*)\s*(?::\s*(\w+))?\s*\]\s*->\s*\(\s*(\w+)\s*(?::\s*(\w+))?\s*\)")


@dataclass(frozen=True)
class Pattern:
    """``edges``: (from, to) node variables of y1, y2, ...; labels by variable; constants by node variable."""

    edges: tuple[tuple[str, str], ...]
    edge_labels: tuple[str | None, ...] = ()
    node_labels: tuple[tuple[str, str], ...] = ()
    bound: tuple[tuple[str, int], ...] = ()
    distinct_edges: bool = False
    #: e1 < e2 < ...: one match for each set of edges
    break_symmetry: bool = False

    @classmethod
    def of(cls, text: str, **options) -> Pattern:
        """``(a:cust)-[y1:msg]->(b), (b)-[y2]->(a)``"""
        edges, labels, nodes = [], [], {}
        for m in _EDGE.finditer(text):
            edges.append((m[1], m[5]))
            labels.append(m[4])
            nodes |= {v: x for v, x in ((m[1], m[2]), (m[5], m[6])) if x}
        if not edges:
            raise ValueError(f"no edge in {text!r}")
        return cls(tuple(edges), tuple(labels), tuple(nodes.items()), **options)

    @property
    def m(self) -> int:
        return len(self.edges)

    @property
    def nodes(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for e in self.edges for v in e))

    def bind(self, **constants: int) -> Pattern:
        return replace(self, bound=self.bound + tuple(constants.items()))

    def is_connected_order(self, order: tuple[int, ...]) -> bool:
        """Every prefix of the edges in this order is connected."""
        seen = set(self.edges[order[0] - 1])
        for i in order[1:]:
            if not seen & set(self.edges[i - 1]):
                return False
            seen |= set(self.edges[i - 1])
        return True

    def join_order(self) -> tuple[int, ...]:
        """Edges in an order with connected prefixes; one that closes a cycle comes as soon as it can."""
        order, seen = [1], set(self.edges[0])
        while len(order) < self.m:
            rest = [i for i in range(1, self.m + 1) if i not in order and seen & set(self.edges[i - 1])]
            if not rest:
                raise ValueError("the pattern isn't connected; its matches would be a Cartesian product")
            i = max(rest, key=lambda i: (set(self.edges[i - 1]) <= seen, -i))
            order.append(i)
            seen |= set(self.edges[i - 1])
        return tuple(order)

    @property
    def is_cyclic(self) -> bool:
        return self.m >= len(self.nodes)


def path(m: int) -> Pattern:
    return Pattern(tuple((f"x{i}", f"x{i + 1}") for i in range(1, m + 1)))


def cycle(m: int) -> Pattern:
    return Pattern(tuple((f"x{i}", f"x{i % m + 1}") for i in range(1, m + 1)))


def in_star(m: int, **options) -> Pattern:
    return Pattern(tuple((f"x{i + 1}", "x1") for i in range(1, m + 1)), **({"break_symmetry": True} | options))


def out_star(m: int, **options) -> Pattern:
    return Pattern(tuple(("x1", f"x{i + 1}") for i in range(1, m + 1)), **({"break_symmetry": True} | options))


def leak() -> Pattern:
    return Pattern.of("(a)-[y1:message]->(x), (x)-[y2:message]->(b)")


def exchange() -> Pattern:
    return Pattern.of("(x1:customer)-[y1:message]->(x2:employee), (x2)-[y2:message]->(x1)")


def shared_office() -> Pattern:
    return Pattern.of("(x1)-[y1:visit]->(x3), (x2)-[y2:visit]->(x3)", break_symmetry=True)
