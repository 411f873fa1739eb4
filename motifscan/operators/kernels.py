"""Serial algorithms on one key's local graph, as array work: edge and adjacency indexes, paths by degree order, odd cycles, growth, combination.

All give every mapping of the pattern or the canonical ones as columns of an array (rows, p), block by block, so that a
graph's whole result is never held. `probes` counts lookups. The local graphs of many keys may be one index, of nodes that
are pairs of key and id: a connected pattern never leaves its key.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable, Iterator, Sequence

import numpy as np

from motifscan.plans.cqs import MotifQuery
from motifscan.plans.decompose import Parts, decompose, elimination_order
from motifscan.plans.patterns import Pattern, automorphisms, break_symmetry

#: Rows that one expansion may make before it goes on block by block.
ROWS = 1 << 18


#: For rows of nodes: which further nodes (row, node) may still be part of an instance that the rows' key owns. Asked before any look-up.
Prune = Callable[[np.ndarray], Callable[[np.ndarray, np.ndarray], np.ndarray]]


#: Edges that are numbered at once; an index of more packed edges than SIEVE has a bit filter before its look-ups, of so many bits an edge.
STEP, SIEVE, BITS = 1 << 20, 1 << 16, 16


def _sorted_unique(x: np.ndarray) -> np.ndarray:
    """x's values, once each; x is sorted in place, and nothing of its size is made besides where no value repeats."""
    x.sort()
    new = np.ones(len(x), bool)
    np.not_equal(x[1:], x[:-1], out=new[1:])
    return x if new.all() else x[new]


class LocalIndex:
    """An undirected local graph: nodes renumbered by (degree, id), or by id, and a sorted list of packed edges in both directions, which is all that it holds of them. key: the number of each edge's key, where the graphs of several are one. marks: something of each edge's two ends, kept for each node."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, directed: bool = False, key: np.ndarray | None = None, by_id: bool = False, marks: tuple[np.ndarray, np.ndarray] | None = None):
        names, m = _sorted_unique(np.concatenate([src, dst])), len(src)
        steps = [slice(i, min(m, i + STEP)) for i in range(0, m, STEP)]
        wide = max(1, len(names))
        if key is None:
            self.key, nodes = np.zeros(len(names), np.int64), None
        else:
            nodes = _sorted_unique(np.concatenate([key[i] * wide + np.searchsorted(names, x[i]) for x in (src, dst) for i in steps] or [np.zeros(0, np.int64)]))
            self.key = nodes // wide

        def place(x: np.ndarray, i: slice) -> np.ndarray:
            at = np.searchsorted(names, x[i])
            return at if nodes is None else np.searchsorted(nodes, key[i] * wide + at)

        self.n = n = len(self.key)
        ids = names.astype(np.int64) if nodes is None else names[nodes % wide].astype(np.int64)
        rank, self.by_id = None, by_id
        if not by_id:
            degree = np.zeros(n, np.int64)
            for i in steps:
                for x in (src, dst):
                    degree += np.bincount(place(x, i), minlength=n)
            order = np.lexsort((ids, degree))
            rank = np.empty(n, np.int64)
            rank[order] = np.arange(n)
            ids, self.key = ids[order], self.key[order]
        self.ids, self.marks = ids, None if marks is None else np.zeros(n, marks[0].dtype)
        packed = np.empty(m if directed else 2 * m, np.int64)
        for i in steps:
            a, b = (at if rank is None else rank[at] for at in (place(src, i), place(dst, i)))
            packed[i] = a * n + b
            if not directed:
                packed[m + i.start : m + i.stop] = b * n + a
            if marks is not None:
                self.marks[a], self.marks[b] = marks[0][i], marks[1][i]
        self.packed = packed = _sorted_unique(packed)
        self.m, self.probes, self.sieve = len(packed) if directed else len(packed) // 2, 0, None
        self.first = np.searchsorted(packed, np.arange(n + 1) * n)
        self.middle = np.searchsorted(packed, np.arange(n) * n + np.arange(n))
        self.back, self.in_first = packed, self.first
        if directed:
            self.back = np.sort((packed % max(n, 1)) * n + packed // max(n, 1))
            self.in_first = np.searchsorted(self.back, np.arange(n + 1) * n)

    @property
    def head(self) -> np.ndarray:
        return self.packed // max(self.n, 1)

    @property
    def tail(self) -> np.ndarray:
        return self.packed % max(self.n, 1)

    def _bits(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = (key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.sieve_bits)
        return (h >> np.uint64(3)).astype(np.int64), np.left_shift(np.uint8(1), (h & np.uint64(7)).astype(np.uint8))

    def _listed(self, key: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.packed, key), len(self.packed) - 1)
        return self.packed[at] == key

    def has(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        self.probes += len(a)
        if not len(self.packed):
            return np.zeros(len(a), bool)
        key = a * self.n + b
        if len(self.packed) <= SIEVE:
            return self._listed(key)
        if self.sieve is None:
            self.sieve_bits = (len(self.packed) * BITS).bit_length()
            self.sieve = np.zeros(1 << (self.sieve_bits - 3), np.uint8)
            for i in range(0, len(self.packed), STEP):
                np.bitwise_or.at(self.sieve, *self._bits(self.packed[i : i + STEP]))
        at, bit = self._bits(key)
        out = (self.sieve[at] & bit) != 0
        likely = np.flatnonzero(out)
        out[likely] = self._listed(key[likely])
        return out

    def expand(self, nodes: np.ndarray, incoming: bool = False, side: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """(row, neighbour) of each row's node. side: only neighbours of a larger (1) or smaller (-1) number."""
        first, packed = (self.in_first, self.back) if incoming else (self.first, self.packed)
        begin, end = self.middle[nodes] if side > 0 else first[nodes], self.middle[nodes] if side < 0 else first[nodes + 1]
        count = end - begin
        row = np.repeat(np.arange(len(nodes)), count)
        at = np.repeat(begin - (np.cumsum(count) - count), count) + np.arange(len(row))
        self.probes += len(row)
        return row, packed[at] - np.repeat(nodes * self.n, count)

    def later(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, neighbour) for neighbours that come later in degree order."""
        row, to = self.expand(nodes)
        keep = to > nodes[row]
        return row[keep], to[keep]


def two_paths(g: LocalIndex) -> np.ndarray:
    return _stacked(two_path_blocks(g), 3)


def two_path_blocks(g: LocalIndex) -> Iterator[np.ndarray]:
    """(end, middle, end): all paths whose middle comes before both ends in degree order, first end before the second."""
    later = g.first[1:] - g.middle
    for nodes in pieces(np.flatnonzero(later > 1), (later * (later - 1) // 2)[later > 1]):
        begun = g.probes
        row, to = g.expand(nodes, side=1)
        after = np.cumsum(later[nodes])[row] - np.arange(len(row)) - 1  # later neighbours of the same middle
        one = np.repeat(np.arange(len(row)), after)
        other = one + 1 + np.arange(len(one)) - np.repeat(np.cumsum(after) - after, after)
        g.probes = begun + len(one)
        yield np.stack([to[one], nodes[row[one]], to[other]], 1)


def triangles(g: LocalIndex) -> np.ndarray:
    return _stacked((w[g.has(w[:, 0], w[:, 2])][:, [1, 0, 2]] for w in two_path_blocks(g)), 3)


def pieces(x: np.ndarray, cost: np.ndarray) -> Iterator[np.ndarray]:
    """Runs of rows whose costs add up to ROWS or so each."""
    if len(x):
        which = np.cumsum(cost) // ROWS
        cuts = np.flatnonzero(np.diff(which)) + 1
        yield from np.split(x, cuts)


def odd_cycles(g: LocalIndex, length: int, via: str = "adjacency") -> np.ndarray:
    return _stacked(odd_cycle_blocks(g, length, via), length)


def _stacked(blocks: Iterator[np.ndarray], width: int) -> np.ndarray:
    return np.concatenate([np.zeros((0, width), np.int64), *blocks])


def odd_cycle_blocks(g: LocalIndex, length: int, via: str = "adjacency", prune: Prune | None = None) -> Iterator[np.ndarray]:
    """Each cycle of an odd length once: its first node comes before all others in degree order, its second before its last.

    via='edges': a two-path at the first node, and for the nodes opposite, all sets of disjoint later edges, joined in
    all orders and directions. via='adjacency' grows the paths' ends instead, with the same result; the last node is sought
    at that of its two neighbours which has fewer.
    """
    if length == 3:
        for w in two_path_blocks(g):
            yield w[g.has(w[:, 0], w[:, 2])][:, [1, 0, 2]]
        return
    degree = g.first[1:] - g.first[:-1]

    def end(x: np.ndarray) -> np.ndarray:
        return x[:, 1] if x.shape[1] == 3 else x[:, -1]

    def source(x: np.ndarray) -> np.ndarray:
        a, b = end(x), x[:, 2]
        return np.where(degree[b] < degree[a], b, a) if x.shape[1] == length - 1 else a

    def along(x: np.ndarray) -> Iterator[np.ndarray]:
        last = x.shape[1] == length - 1
        for old in pieces(x, degree[source(x)]):
            at = source(old)
            row, to = g.expand(at)
            ok = to > old[:, 0][row]
            if prune:
                ok &= prune(old)(row, to)
            row, to = row[ok], to[ok]
            if last:
                ok = g.has((end(old) + old[:, 2] - at)[row], to)
                row, to = row[ok], to[ok]
            old = old[row]
            ok = ~(to[:, None] == old).any(1)
            yield np.concatenate([old[ok], to[ok][:, None]], 1)

    def by_edges(x: np.ndarray) -> Iterator[np.ndarray]:
        e = np.stack([g.head, g.tail], 1)  # both directions
        for old in pieces(x, np.full(len(x), len(e))):
            # the edge's first node must hang on the path that begins at the second node
            a, b = np.repeat(np.arange(len(old)), len(e)), np.tile(np.arange(len(e)), len(old))
            old, new = old[a], e[b]
            ok = (new > old[:, :1]).all(1) & ~(new[:, :1] == old).any(1) & ~(new[:, 1:] == old).any(1)
            ok[ok] = g.has(end(old)[ok], new[ok, 0])
            x = np.concatenate([old[ok], new[ok]], 1)
            yield x[g.has(x[:, -1], x[:, 2])] if x.shape[1] == length else x

    def step(x: np.ndarray) -> Iterator[np.ndarray]:
        if x.shape[1] == length:
            yield np.concatenate([x[:, :2], x[:, 3:], x[:, 2:3]], 1)
            return
        for more in along(x) if via == "adjacency" else by_edges(x):
            yield from step(more)

    for w in two_path_blocks(g):
        x = w[:, [1, 0, 2]]  # least node, second, last
        if prune:
            for i in (1, 2):
                x = x[prune(x[:, :i])(np.arange(len(x)), x[:, i])]
        yield from step(x)


def odd_hamilton(g: LocalIndex, s: Pattern, walk: tuple[int, ...]) -> np.ndarray:
    return _stacked(odd_hamilton_blocks(g, s, walk), s.p)


def odd_hamilton_blocks(g: LocalIndex, s: Pattern, walk: tuple[int, ...], prune: Prune | None = None) -> Iterator[np.ndarray]:
    """All mappings of a pattern with an odd Hamilton cycle: each cycle of the graph, in all turns and both ways, whose chords are there too."""
    p = s.p
    chords = [(a, b) for a, b in s.edges if abs(walk.index(a) - walk.index(b)) not in (1, p - 1)]
    for found in odd_cycle_blocks(g, p, prune=prune):
        for turn, back in itertools.product(range(p), (False, True)):
            seat = [(turn + (-i if back else i)) % p for i in range(p)]
            x = np.empty_like(found)
            for i, v in enumerate(walk):
                x[:, v] = found[:, seat[i]]
            for a, b in chords:
                x = x[g.has(x[:, a], x[:, b])]
            yield x


def _distinct(x: np.ndarray) -> np.ndarray:
    if x.shape[1] < 2 or not len(x):
        return np.ones(len(x), bool)
    y = np.sort(x, axis=1)
    return (y[:, 1:] != y[:, :-1]).all(1)


def grow(g: LocalIndex, s: Pattern, order: tuple[int, ...] | None = None, canonical: bool = True) -> np.ndarray:
    return _stacked(grow_blocks(g, s, order, canonical), s.p)


def grow_blocks(g: LocalIndex, s: Pattern, order: tuple[int, ...] | None = None, canonical: bool = True, prune: Prune | None = None) -> Iterator[np.ndarray]:
    """A connected pattern node by node along the neighbours of what is matched, probing the other edges; the least image only if canonical."""
    order = order or elimination_order(s)
    less = break_symmetry(automorphisms(s)) if canonical else ()
    arcs = set(s.edges)
    back = np.argsort(order)
    degree = g.first[1:] - g.first[:-1]
    if s.directed:
        degree = degree + g.in_first[1:] - g.in_first[:-1]

    name = (lambda x: x) if g.by_id else (lambda x: g.ids[x])  # numbers by id compare as ids do

    def directed_step(part: np.ndarray, placed: tuple[int, ...], v: int, u: int) -> tuple[np.ndarray, np.ndarray]:
        row, to = g.expand(part[:, placed.index(u)], incoming=(u, v) not in arcs)
        for w in placed:
            for a, b in ((w, v), (v, w)):
                if (a, b) in arcs and not (w == u and not ((w, v) in arcs and (v, w) in arcs)):
                    old = part[:, placed.index(w)][row]
                    hit = g.has(old, to) if a == w else g.has(to, old)
                    row, to = row[hit], to[hit]
        return row, to

    def step(x: np.ndarray) -> Iterator[np.ndarray]:
        placed = order[: x.shape[1]]
        if len(placed) == s.p:
            yield x[:, back]
            return
        v = order[len(placed)]
        near = [i for i, u in enumerate(placed) if u in s.neighbours(v)]

        def source(x: np.ndarray) -> np.ndarray:
            """Each row's node to go on from: the neighbour of v that has the fewest."""
            if len(near) == 1 or s.directed:
                return x[:, near[0]]
            return x[np.arange(len(x)), np.array(near)[np.argmin(degree[x[:, near]], axis=1)]]

        for part in pieces(x, degree[source(x)]):
            if s.directed:
                row, to = directed_step(part, placed, v, placed[near[0]])
                if prune:
                    ok = prune(part)(row, to)
                    row, to = row[ok], to[ok]
            else:
                at, u = source(part), placed[near[0]]
                side = 0 if len(near) > 1 or not g.by_id else 1 if (u, v) in less else -1 if (v, u) in less else 0
                row, to = g.expand(at, side=side)
                if prune:
                    ok = prune(part)(row, to)
                    row, to = row[ok], to[ok]
                for i in near if len(near) > 1 else ():
                    if len(near) == 2 and i == near[1]:
                        break
                    other = part[:, i] if len(near) > 2 else part[:, near[0]] + part[:, near[1]] - at
                    hit = g.has(other[row], to)
                    row, to = row[hit], to[hit]
            ok = np.ones(len(to), bool)
            for i, w in enumerate(placed):
                old = part[:, i][row]
                if (w, v) in less:
                    ok &= name(old) < name(to)
                elif (v, w) in less:
                    ok &= name(to) < name(old)
                elif i not in near:
                    ok &= old != to
            yield from step(np.concatenate([part[row[ok]], to[ok][:, None]], 1))

    for part in pieces(np.arange(g.n)[:, None], degree):
        yield from step(part)


def canonical(g: LocalIndex, x: np.ndarray, s: Pattern) -> np.ndarray:
    ok = np.ones(len(x), bool)
    for a, b in break_symmetry(automorphisms(s)):
        ok &= g.ids[x[:, a]] < g.ids[x[:, b]]
    return x[ok]


def combine(g: LocalIndex, s: Pattern, parts: Parts | None = None) -> np.ndarray:
    return _stacked(combine_blocks(g, s, parts), s.p)


def parts_order(s: Pattern, parts: Parts) -> tuple[int, ...] | None:
    """The pattern's nodes part by part, each part along its walk from a node that hangs on an earlier part; None if one hangs on none.

    Of a part's turns and directions, the one in which edges to earlier nodes come soonest: they leave few partial matches to go on with.
    """
    left, have = parts.all(), []

    def closing(walk: tuple[int, ...]) -> list[int]:
        return [len(s.neighbours(v) & {*have, *walk[:i]}) for i, v in enumerate(walk)]

    while left:
        part = next((q for q in left if any(u in s.neighbours(v) for u in have for v in q)), None if have else left[0])
        if part is None:
            return None
        left.remove(part)
        turned = [(*part[i:], *part[:i]) for i in range(len(part))]
        walks = [w for t in turned for w in (t, (t[0], *t[:0:-1])) if not have or s.neighbours(w[0]) & set(have)]
        have += max(walks, key=closing)
    return tuple(have)


def combine_blocks(g: LocalIndex, s: Pattern, parts: Parts | None = None, prune: Prune | None = None) -> Iterator[np.ndarray]:
    """All parts' mappings, joined along an edge between them where there is one, checked for the other edges and different nodes; the least images only.

    Where every part hangs on an earlier one, its mappings are made along its own walk from there, not listed before; edges,
    order and owner decide as soon as a node is there.
    """
    parts = parts or decompose(s)
    if not s.directed and (order := parts_order(s, parts)):
        yield from grow_blocks(g, s, order, prune=prune)
        return
    left, have, levels = parts.all(), (), []
    degree = g.first[1:] - g.first[:-1]
    while left:
        part = next((q for q in left if any(u in s.neighbours(v) for u in have for v in q)), left[0])
        left.remove(part)
        if len(part) == 1:
            y = np.arange(g.n)[:, None]
        elif len(part) == 2:
            y = np.stack([g.head, g.tail], 1)
        else:
            y = odd_hamilton(g, s.induced(part), tuple(range(len(part))))
        cross = [(u, v) for v in part for u in have if u in s.neighbours(v)]
        if cross:
            column = y[:, part.index(cross[0][1])]
            by = np.argsort(column, kind="stable")
            y, column = y[by], column[by]
        else:
            column = None
        levels.append((part, have, cross, y, column))
        have = (*have, *part)
    back = np.argsort(have)

    def step(x: np.ndarray, level: int) -> Iterator[np.ndarray]:
        if level == len(levels):
            yield canonical(g, x[:, back], s)
            return
        part, before, cross, y, column = levels[level]
        both = (*before, *part)
        for piece in pieces(x, degree[x[:, before.index(cross[0][0])]] if cross else np.full(len(x), max(1, len(y)))):
            if cross:
                row, to = g.expand(piece[:, before.index(cross[0][0])])
                lo, hi = np.searchsorted(column, to, "left"), np.searchsorted(column, to, "right")
                count = hi - lo
                a = np.repeat(row, count)
                b = np.repeat(lo - (np.cumsum(count) - count), count) + np.arange(len(a))
            else:
                a, b = np.repeat(np.arange(len(piece)), len(y)), np.tile(np.arange(len(y)), len(piece))
            for i in range(0, len(a), ROWS):
                z = np.concatenate([piece[a[i : i + ROWS]], y[b[i : i + ROWS]]], 1)
                z = z[_distinct(z)]
                for u, v in cross[1:]:
                    z = z[g.has(z[:, both.index(u)], z[:, both.index(v)])]
                # edges inside an odd part beyond its own walk were checked as chords; nothing else is open
                yield from step(z, level + 1)

    yield from step(np.zeros((1, 0), np.int64), 0)


def query_blocks(g: LocalIndex, s: Pattern, queries: Sequence[MotifQuery], prune: Prune | None = None) -> Iterator[np.ndarray]:
    """What a set of queries finds together, each along a connected pattern's edges in the directions it asks for, its comparisons applied as soon as both nodes are there; as least images. The index numbers nodes by id."""
    order, symmetry = elimination_order(s), automorphisms(s)
    back, least = np.argsort(order), break_symmetry(symmetry)
    degree = g.first[1:] - g.first[:-1]

    def step(x: np.ndarray, q: MotifQuery) -> Iterator[np.ndarray]:
        placed = order[: x.shape[1]]
        if len(placed) == s.p:
            yield x[:, back]
            return
        v = order[len(placed)]
        near = [u for u in placed if u in s.neighbours(v)]
        up = {u: (u, v) in q.subgoals for u in near}
        for part in pieces(x, degree[x[:, placed.index(near[0])]]):
            row, to = g.expand(part[:, placed.index(near[0])], side=1 if up[near[0]] else -1)
            if prune:
                ok = prune(part)(row, to)
                row, to = row[ok], to[ok]
            for u in near[1:]:  # what a probe leaves is little
                hit = g.has(part[:, placed.index(u)][row], to)
                row, to = row[hit], to[hit]
            ok = np.ones(len(to), bool)
            for i, u in enumerate(placed):
                if u == near[0]:
                    continue
                old = part[:, i][row]
                if (u, v) in q.less or (u in near and up[u]):
                    ok &= old < to
                elif (v, u) in q.less or u in near:
                    ok &= to < old
                else:
                    ok &= old != to
            yield from step(np.concatenate([part[row[ok]], to[ok][:, None]], 1), q)

    for q in queries:
        for first in pieces(np.arange(g.n)[:, None], degree):
            for x in step(first, q):
                if q.orders:
                    ok = np.zeros(len(x), bool)
                    for o in q.orders:
                        ok |= (x[:, o[:-1]] < x[:, o[1:]]).all(1)
                    x = x[ok]
                out = np.empty_like(x)
                for a in symmetry:
                    y = x[:, a]
                    mine = np.ones(len(x), bool)
                    for i, j in least:
                        mine &= y[:, i] < y[:, j]
                    out[mine] = y[mine]
                yield out


def find_blocks(g: LocalIndex, s: Pattern, algorithm: str = "grow", prune: Prune | None = None) -> Iterator[np.ndarray]:
    """The canonical mappings of a pattern in a local graph, in its numbers of nodes. prune is used where the algorithm can."""
    if not len(g.packed):
        return
    if algorithm == "combine" or not s.connected():
        yield from combine_blocks(g, s, prune=prune)
    elif algorithm == "odd":
        for x in odd_hamilton_blocks(g, s, decompose(s).odd[0], prune):
            yield canonical(g, x, s)
    elif algorithm == "grow":
        yield from grow_blocks(g, s, prune=prune)
    else:
        raise ValueError(f"no such algorithm: {algorithm}")


def find(g: LocalIndex, s: Pattern, algorithm: str = "grow") -> np.ndarray:
    """The canonical mappings of a pattern in a local graph, in node ids."""
    x = _stacked(find_blocks(g, s, algorithm), s.p)
    return g.ids[x] if len(x) else x


def serial(src: np.ndarray, dst: np.ndarray, s: Pattern, algorithm: str = "grow") -> tuple[np.ndarray, int]:
    """Baseline: the serial algorithm on a whole graph, on one machine: its instances and probes."""
    g = LocalIndex(src, dst, s.directed)
    return find(g, s, algorithm), g.probes
