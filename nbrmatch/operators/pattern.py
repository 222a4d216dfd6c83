"""Patterns: small labelled graphs that live on the driver."""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from itertools import permutations

from ..functions.codes import ncode


@dataclass(frozen=True)
class Pattern:
    """vertices: name to label. edges: (name, name, edge label or None); one way if directed."""

    vertices: dict[str, str]
    edges: tuple[tuple[str, str, str | None], ...] = field(default=())
    directed: bool = False

    def __post_init__(self) -> None:
        for a, b, _ in self.edges:
            if a not in self.vertices or b not in self.vertices or a == b:
                raise ValueError(f"bad edge {a}-{b}")

    @property
    def labels(self) -> list[str]:
        return sorted(set(self.vertices.values()))

    def ranks(self, how: str = "lex", counts: dict[str, int] | None = None) -> dict[str, int]:
        """Label to rank from 1. lex; rare_first or frequent_first by counts in the graph; given: first use in the pattern."""
        names = self.labels
        if how == "given":
            names = list(dict.fromkeys(self.vertices.values()))
        elif how != "lex":
            names.sort(key=lambda n: ((counts or {}).get(n, 0) * (1 if how == "rare_first" else -1), n))
        return {n: k for k, n in enumerate(names, 1)}

    def neighbours(self, u: str) -> list[str]:
        """One entry for each incident edge."""
        return [b if a == u else a for a, b, _ in self.edges if u in (a, b)]

    def vector(self, u: str, ranks: dict[str, int] | None = None) -> list[int]:
        """How many neighbours of u have each label."""
        ranks = ranks or self.ranks()
        x = [0] * len(ranks)
        for w in self.neighbours(u):
            x[ranks[self.vertices[w]] - 1] += 1
        return x

    def pdeg(self, u: str) -> int:
        return len(self.neighbours(u))

    @property
    def max_degree(self) -> int:
        return max(map(self.pdeg, self.vertices), default=0)

    def mnd(self, u: str) -> int:
        return max((self.pdeg(w) for w in self.neighbours(u)), default=0)

    def code(self, u: str, ranks: dict[str, int] | None = None) -> int:
        return ncode(self.vector(u, ranks))

    def hops(self, u: str) -> dict[str, int]:
        """Distance of every vertex that u reaches."""
        seen, line = {u: 0}, [u]
        for v in line:
            for w in self.neighbours(v):
                if w not in seen:
                    seen[w] = seen[v] + 1
                    line.append(w)
        return seen

    def ball(self, u: str, q: int, exactly: bool = False) -> list[int]:
        """Label counts of the vertices within q hops of u, or at exactly q hops; without u."""
        ranks = self.ranks()
        x = [0] * len(ranks)
        for w, d in self.hops(u).items():
            if d == q or (not exactly and 0 < d < q):
                x[ranks[self.vertices[w]] - 1] += 1
        return x

    @property
    def connected(self) -> bool:
        return not self.vertices or len(self.hops(next(iter(self.vertices)))) == len(self.vertices)

    def automorphisms(self) -> list[dict[str, str]]:
        """Of patterns up to nine vertices; by trying the permutations within labels."""
        names = list(self.vertices)
        if len(names) > 9:
            raise ValueError("too many vertices to list automorphisms")
        key = lambda a, b, e: (a, b, e) if self.directed else (min(a, b), max(a, b), e)
        edges = {key(*e) for e in self.edges}
        out = []
        for p in permutations(names):
            m = dict(zip(names, p, strict=True))
            if all(self.vertices[a] == self.vertices[b] for a, b in m.items()) and {key(m[a], m[b], e) for a, b, e in self.edges} == edges:
                out.append(m)
        return out

    def core(self) -> list[str]:
        """Vertices left after vertices of degree one or less are taken off again and again; one vertex for trees."""
        alive = set(self.vertices)
        while True:
            thin = [u for u in alive if sum(w in alive for w in self.neighbours(u)) <= 1]
            if not thin:
                return sorted(alive)
            if len(alive) <= 1 or len(thin) == len(alive):
                return [max(sorted(self.vertices), key=self.pdeg)]
            alive -= set(thin)

    def triples(self) -> set[tuple[str, str, str | None]]:
        """(label, label, edge label) of the edges, both ways round unless directed."""
        found = {(self.vertices[a], self.vertices[b], e) for a, b, e in self.edges}
        return found if self.directed else found | {(b, a, e) for a, b, e in found}


VERTEX = r"\(\s*(\w+)\s*(?::\s*([^()]*?)\s*)?\)"
EDGE = re.compile(rf"{VERTEX}\s*(<)?-(?:\s*\[\s*([^\]]*?)\s*\]\s*-)?(>)?\s*(?={VERTEX})")


def parse(text: str, directed: bool | None = None) -> Pattern:
    """A pattern from text such as (a:C:BUILDING)-[placed]-(b:O:1-URGENT), (b)->(c:P). Arrows make it directed.

    Parts are separated by commas; a vertex needs its label once; a vertex alone is a part of its own.
    """
    vertices: dict[str, str] = {}
    edges, arrows = [], False
    for name, label in re.findall(VERTEX, text):
        if label:
            if vertices.get(name, label) != label:
                raise ValueError(f"{name} has two labels")
            vertices[name] = label
        else:
            vertices.setdefault(name, "")
    for m in EDGE.finditer(text):
        a, _, back, e, on, b, _ = m.groups()
        arrows |= bool(back or on)
        edges.append((b, a, e or None) if back else (a, b, e or None))
    if missing := [n for n, label in vertices.items() if not label]:
        raise ValueError(f"no label for {', '.join(missing)}")
    return Pattern(vertices, tuple(edges), arrows if directed is None else directed)
