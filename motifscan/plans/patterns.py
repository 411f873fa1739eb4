"""Sample graphs: small immutable patterns, their symmetry and the catalogue of named ones."""

from __future__ import annotations

import itertools
from dataclasses import dataclass
from functools import lru_cache


@dataclass(frozen=True)
class Pattern:
    """p nodes 0..p-1 and edges (a, b); a < b unless directed. edge_labels names a relation for each edge, in the order of edges."""

    p: int
    edges: tuple[tuple[int, int], ...]
    directed: bool = False
    edge_labels: tuple[str, ...] | None = None
    name: str = ""

    def __post_init__(self) -> None:
        edges = tuple(tuple(e) if self.directed else tuple(sorted(e)) for e in self.edges)
        if len(set(edges)) != len(edges) or any(a == b or not (0 <= a < self.p and 0 <= b < self.p) for a, b in edges):
            raise ValueError(f"not a simple pattern on {self.p} nodes: {self.edges}")
        if self.edge_labels is not None and len(self.edge_labels) != len(edges):
            raise ValueError("edge_labels must name a relation for each edge")
        object.__setattr__(self, "edges", edges)

    def label(self, e: tuple[int, int]) -> str | None:
        return self.edge_labels[self.edges.index(e)] if self.edge_labels else None

    def neighbours(self, v: int) -> set[int]:
        return {b if a == v else a for a, b in self.edges if v in (a, b)}

    def degrees(self) -> list[int]:
        return [sum(v in e for e in self.edges) for v in range(self.p)]

    def connected(self, nodes: tuple[int, ...] | None = None) -> bool:
        nodes = tuple(range(self.p)) if nodes is None else tuple(nodes)
        if not nodes:
            return True
        seen, todo, within = {nodes[0]}, [nodes[0]], set(nodes)
        while todo:
            for w in (self.neighbours(todo.pop()) & within) - seen:
                seen.add(w)
                todo.append(w)
        return len(seen) == len(within)

    def regular(self) -> int | None:
        d = set(self.degrees())
        return d.pop() if len(d) == 1 else None

    def induced(self, nodes: tuple[int, ...]) -> Pattern:
        """The pattern on some of the nodes, renumbered in their order."""
        at = {v: i for i, v in enumerate(nodes)}
        return Pattern(len(nodes), tuple((at[a], at[b]) for a, b in self.edges if a in at and b in at), self.directed)


@lru_cache(maxsize=None)
def automorphisms(s: Pattern) -> tuple[tuple[int, ...], ...]:
    """All permutations g of the nodes (v goes to g[v]) that keep edges, directions and labels. Backtracking, cut by degree and by each placed edge."""
    kind = {(a, b): s.label((a, b)) or "" for a, b in s.edges}
    if not s.directed:
        kind |= {(b, a): k for (a, b), k in list(kind.items())}
    degree = [tuple(sorted([("o", k) for (a, _), k in kind.items() if a == v] + [("i", k) for (_, b), k in kind.items() if b == v])) for v in range(s.p)]
    out: list[tuple[int, ...]] = []

    def place(g: list[int]) -> None:
        v = len(g)
        if v == s.p:
            out.append(tuple(g))
            return
        for w in range(s.p):
            if w not in g and degree[w] == degree[v] and all(kind.get((u, v)) == kind.get((g[u], w)) and kind.get((v, u)) == kind.get((w, g[u])) for u in range(v)):
                place([*g, w])

    place([])
    return tuple(out)


def break_symmetry(group: tuple[tuple[int, ...], ...]) -> tuple[tuple[int, int], ...]:
    """Pairs (i, j), x_i < x_j, that hold for exactly one image of any assignment of different values under the group: the lexicographically least.

    Node by node: a node is least in its orbit under what fixes all nodes before it.
    """
    pairs, fixing = [], list(group)
    for i in range(len(group[0]) if group else 0):
        pairs += [(i, j) for j in sorted({g[i] for g in fixing} - {i})]
        fixing = [g for g in fixing if g[i] == i]
    return tuple(pairs)


def cycle(p: int) -> Pattern:
    return Pattern(p, tuple((i, (i + 1) % p) for i in range(p)), name=f"cycle{p}")


def clique(p: int) -> Pattern:
    return Pattern(p, tuple(itertools.combinations(range(p), 2)), name=f"k{p}")


def star(p: int) -> Pattern:
    return Pattern(p, tuple((0, i) for i in range(1, p)), name=f"star{p}")


def path(p: int) -> Pattern:
    return Pattern(p, tuple((i, i + 1) for i in range(p - 1)), name=f"path{p}")


CATALOGUE: dict[str, Pattern] = {
    "edge": path(2),
    "path3": path(3),
    "path4": path(4),
    "star4": star(4),
    "star5": star(5),
    "triangle": clique(3),
    "square": cycle(4),
    "pentagon": cycle(5),
    "hexagon": cycle(6),
    "heptagon": cycle(7),
    "pendant_triangle": Pattern(4, ((0, 1), (1, 2), (1, 3), (2, 3))),
    "diamond": Pattern(4, (*cycle(4).edges, (0, 2))),
    "k4": clique(4),
    "k5": clique(5),
    "house": Pattern(5, (*cycle(5).edges, (1, 4))),
    "bowtie": Pattern(5, ((0, 1), (0, 2), (1, 2), (0, 3), (0, 4), (3, 4))),
    "gem": Pattern(5, (*cycle(5).edges, (0, 2), (0, 3))),
    "prism": Pattern(6, ((0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (0, 3), (1, 4), (2, 5))),
    "k33": Pattern(6, tuple((a, b) for a in range(3) for b in range(3, 6))),
    "cube": Pattern(8, tuple((a, a | 1 << i) for a in range(8) for i in range(3) if not a >> i & 1)),
}


def asymmetric_patterns(p: int) -> list[Pattern]:
    """The connected or unconnected patterns on p nodes without symmetry, one of each isomorphism class (p up to 6)."""
    pairs = list(itertools.combinations(range(p), 2))
    perms = list(itertools.permutations(range(p)))
    index = {e: i for i, e in enumerate(pairs)}
    moved = [[index[tuple(sorted((g[a], g[b])))] for a, b in pairs] for g in perms[1:]]
    seen: set[int] = set()
    out = []
    for bits in range(1 << len(pairs)):
        if bits in seen:
            continue
        edges = tuple(e for i, e in enumerate(pairs) if bits >> i & 1)
        degrees = sorted(sum(v in e for e in edges) for v in range(p))
        if len(set(degrees)) == 1 or degrees.count(p - 1) > 1 or degrees.count(0) > 1 or degrees.count(1) > p - 2:
            continue  # surely symmetric
        images = {sum(1 << m[i] for i in range(len(pairs)) if bits >> i & 1) for m in moved}
        if bits not in images:
            seen |= images
            out.append(Pattern(p, edges))
    return out
