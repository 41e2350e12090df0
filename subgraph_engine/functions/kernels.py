"""Local searches over one piece of a graph, without Spark.

A piece is a dictionary from each vertex to its neighbours inside the piece. Sets of vertices are
Python integers, one bit for each vertex in ascending order of ids. All searches are exact; each
counts the nodes of its search tree.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field
from math import comb


@dataclass
class Piece:
    """Adjacency of a piece as bit sets over ``ids`` (ascending)."""

    ids: list[int]
    rows: list[int]
    nodes: int = 0  # search nodes visited so far
    place: dict[int, int] = field(default_factory=dict)

    @staticmethod
    def of(neighbours: dict[int, Iterable[int]]) -> Piece:
        """Edges count in both directions; neighbours outside the piece are left out."""
        ids = sorted(neighbours)
        place = {v: k for k, v in enumerate(ids)}
        rows = [0] * len(ids)
        for v, others in neighbours.items():
            k = place[v]
            for u in others:
                if u != v and (j := place.get(u)) is not None:
                    rows[k] |= 1 << j
                    rows[j] |= 1 << k
        return Piece(ids, rows, place=place)

    def mask(self, members: Iterable[int]) -> int:
        out = 0
        for v in members:
            out |= 1 << self.place[v]
        return out

    def members(self, mask: int) -> list[int]:
        return [self.ids[k] for k in bits(mask)]


def bits(mask: int) -> Iterator[int]:
    """Positions of the set bits, lowest first."""
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


def largest_clique(piece: Piece, within: int, floor: int = 0, bound: str = "color") -> int:
    """A largest clique inside ``within`` of more than ``floor`` vertices, as a bit set, or 0.

    Branches in reverse order of a greedy colouring: the number of colours up to a vertex bounds
    any clique of the vertices up to it. ``bound="none"`` keeps only the size bound.
    """
    best = [0, floor]

    def colours(candidates: int) -> list[tuple[int, int]]:
        out, colour, rest = [], 0, candidates
        while rest:
            colour += 1
            free = rest
            while free:
                low = free & -free
                k = low.bit_length() - 1
                out.append((k, colour))
                rest ^= low
                free &= ~(low | piece.rows[k])
        return out

    def grow(clique: int, size: int, candidates: int) -> None:
        piece.nodes += 1
        if not candidates:
            if size > best[1]:
                best[:] = clique, size
            return
        order = colours(candidates) if bound == "color" else [(k, candidates.bit_count()) for k in bits(candidates)]
        for k, limit in reversed(order):
            if size + limit <= best[1] and bound == "color":
                return
            if size + candidates.bit_count() <= best[1]:
                return
            grow(clique | 1 << k, size + 1, candidates & piece.rows[k])
            candidates &= ~(1 << k)

    grow(0, 0, within)
    return best[0]


def heaviest_clique(piece: Piece, within: int, sizes: list[int]) -> int:
    """The most that the sizes of a clique's vertices inside ``within`` add up to.

    As ``largest_clique``, with the largest size of each colour in the bound.
    """
    best = 0

    def colours(candidates: int) -> list[tuple[int, int]]:
        out, limit, rest = [], 0, candidates
        while rest:
            free, own = rest, []
            while free:
                low = free & -free
                k = low.bit_length() - 1
                own.append(k)
                rest ^= low
                free &= ~(low | piece.rows[k])
            limit += max(sizes[k] for k in own)
            out += [(k, limit) for k in own]
        return out

    def grow(size: int, candidates: int) -> None:
        nonlocal best
        piece.nodes += 1
        best = max(best, size)
        for k, limit in reversed(colours(candidates)):
            if size + limit <= best:
                return
            grow(size + sizes[k], candidates & piece.rows[k])
            candidates &= ~(1 << k)

    grow(0, within)
    return best


def choices(n: int, top: int) -> list[int]:
    """In how many ways 0 to ``top`` of ``n`` are taken."""
    return [comb(n, k) for k in range(top + 1)]


def product(a: list[int], b: list[int]) -> list[int]:
    """Of two polynomials, up to the power that ``a`` has."""
    return [sum(a[i] * b[k - i] for i in range(k + 1) if k - i < len(b)) for k in range(len(a))]


def cliques_of_classes(piece: Piece, within: int, sizes: list[int], start: list[int], top: int) -> int:
    """In how many ways ``top`` vertices are taken, of which ``start[k]`` ways take k beside the piece, and the
    others are members of the classes of a clique inside ``within`` (of ``sizes`` members, each class with one at least).
    """
    kinds: dict[int, int] = {}
    for k, n in enumerate(sizes):
        kinds[n] = kinds.get(n, 0) | 1 << k
    ways = {n: [0, *choices(n, top)[1:]] for n in kinds}

    def grow(made: list[int], least: int, candidates: int) -> int:
        piece.nodes += 1
        total = made[top]
        while least < top and not made[least]:
            least += 1
        if least + 1 == top:  # one more vertex, of any class
            return total + made[least] * sum(n * (candidates & mask).bit_count() for n, mask in kinds.items())
        while least < top and candidates:
            low = candidates & -candidates
            candidates ^= low
            k = low.bit_length() - 1
            total += grow(product(made, ways[sizes[k]]), least + 1, candidates & piece.rows[k])
        return total

    return grow([*start[: top + 1], *[0] * (top + 1 - len(start))], 0, within)


def greedy_clique(piece: Piece, within: int) -> int:
    """Some clique inside ``within``: always the candidate with most candidates beside it, then the lowest."""
    clique = 0
    while within:
        k = max(bits(within), key=lambda j: ((piece.rows[j] & within).bit_count(), -j))
        clique |= 1 << k
        within &= piece.rows[k]
    return clique


def cliques_of_size(piece: Piece, within: int, size: int) -> Iterator[int]:
    """Every clique of exactly ``size`` vertices inside ``within``, once."""

    def grow(clique: int, missing: int, candidates: int) -> Iterator[int]:
        piece.nodes += 1
        if not missing:
            yield clique
            return
        while candidates.bit_count() >= missing:
            low = candidates & -candidates
            candidates ^= low
            yield from grow(clique | low, missing - 1, candidates & piece.rows[low.bit_length() - 1])

    return grow(0, size, within)


def maximal_cliques(piece: Piece, start: int, candidates: int, excluded: int) -> Iterator[int]:
    """Maximal cliques that hold ``start``, none of ``excluded``, and else only ``candidates``.

    A clique is given only if no candidate and no excluded vertex extends it. Each level branches
    on the candidates that the pivot, the vertex with most candidates beside it, doesn't cover.
    """
    stack = [(start, candidates, excluded)]
    while stack:
        clique, p, x = stack.pop()
        piece.nodes += 1
        if not p:
            if not x:
                yield clique
            continue
        pivot = max(bits(p | x), key=lambda k: (p & piece.rows[k]).bit_count())
        for k in bits(p & ~piece.rows[pivot]):
            own = piece.rows[k]
            stack.append((clique | 1 << k, p & own, x & own))
            p &= ~(1 << k)
            x |= 1 << k


def count_maximal(piece: Piece, candidates: int, excluded: int) -> int:
    """How many cliques ``maximal_cliques`` gives, without making them."""
    rows = piece.rows

    def count(p: int, x: int) -> int:
        if not p:
            return not x
        best, cover, last = -1, 0, p.bit_count()
        rest = p | x
        while rest:
            low = rest & -rest
            rest ^= low
            own = p & rows[low.bit_length() - 1]
            n = own.bit_count()
            if n > best:
                best, cover = n, own
                if n == last:  # beside all candidates, from outside them
                    return 0
                if n == last - 1 and low & p and not x:
                    break
        total, rest = 0, p & ~cover
        while rest:
            low = rest & -rest
            rest ^= low
            own = rows[low.bit_length() - 1]
            total += count(p & own, x & own)
            p ^= low
            x |= low
        return total

    return int(count(candidates, excluded))


def quasi_cliques(piece: Piece, root: int, num: int, den: int, least: int, most: int | None = None, largest: bool = False, maximal: bool = False, restart: tuple[int, int] | None = None) -> Iterator[int]:
    """Every set with ``root`` as its smallest vertex in which each member has at least
    num / den of the others as neighbours, of ``least`` to ``most`` vertices.

    For num / den of a half or more, any two members are at most two steps apart. With ``largest``,
    sets smaller than one given before may be left out; all of the largest size are given. With ``maximal``,
    sets inside another one may be left out. ``restart`` gives members and candidates to go on from.

    At each node, the edges that members have and can get bound how many vertices may still come; members
    that need all of these as neighbours cut the candidates to their own, and so do candidates' degrees.
    """
    rows, top = piece.rows, most or len(piece.ids)
    need = [0, *(-(-num * k // den) for k in range(len(piece.ids) + 1))]  # by size
    two = reach_two(piece)

    def grow(members: int, size: int, candidates: int) -> Iterator[int]:
        nonlocal least
        piece.nodes += 1
        while True:
            inside = [(k, (rows[k] & members).bit_count()) for k in bits(members)]
            edges, low, high = sum(d for _, d in inside), -1, -1
            ahead = sorted(((rows[k] & members).bit_count() for k in bits(candidates)), reverse=True)
            for t in range(min(len(ahead), top - size) + 1):
                edges += ahead[t - 1] if t else 0
                if size + t >= least and edges >= size * need[size + t]:
                    low, high = t if low < 0 else low, t
            if low < 0:
                return
            short, kept = need[size + high] - high, candidates  # neighbours inside that each member has at least
            for k, d in inside:
                if d < short or d + (rows[k] & candidates).bit_count() < need[size + low]:
                    return
                if d == short:
                    kept &= rows[k]
            every, want = members | kept, need[size + max(low, 1)]
            for k in bits(kept):
                if (rows[k] & every).bit_count() < want or (rows[k] & members).bit_count() <= short - 1 - (high == 0):
                    kept ^= 1 << k
            if kept == candidates:
                break
            candidates = kept
        n = candidates.bit_count()
        if n and (largest or maximal) and least <= size + n <= top:
            whole = members | candidates
            if all((rows[k] & whole).bit_count() >= need[size + n] for k in bits(whole)):
                least = size + n if largest else least
                yield whole
                return
        if size >= least and all(d >= need[size] for _, d in inside):
            least = size if largest else least
            yield members
        if size == top:
            return
        order = sorted(bits(candidates), key=lambda j: -(rows[j] & (members | candidates)).bit_count()) if largest else list(bits(candidates))
        for k in order:
            if size + candidates.bit_count() < least:
                return
            candidates ^= 1 << k
            yield from grow(members | 1 << k, size + 1, candidates & two[k])

    if restart:
        yield from grow(restart[0], restart[0].bit_count(), restart[1])
        return
    k = piece.place[root]
    yield from grow(1 << k, 1, two[k] & (-1 << (k + 1)))


def reach_two(piece: Piece) -> list[int]:
    """The vertices within two steps of each."""
    out = []
    for k, row in enumerate(piece.rows):
        reach = row
        for j in bits(row):
            reach |= piece.rows[j]
        out.append(reach & ~(1 << k))
    return out


@dataclass(frozen=True)
class QueryGraph:
    """A small labelled pattern: labels by query vertex, edges (i, j) or (i, j, edge label)."""

    labels: dict[int, str]
    edges: tuple[tuple, ...]

    def neighbours(self, q: int) -> list[int]:
        return sorted({e[1] if e[0] == q else e[0] for e in self.edges if q in e[:2]})

    def order(self, root: int) -> list[int]:
        """The root, then always the vertex with most neighbours before it."""
        out = [root]
        while len(out) < len(self.labels):
            rest = [q for q in self.labels if q not in out]
            out.append(max(rest, key=lambda q: (sum(n in out for n in self.neighbours(q)), -q)))
        return out

    def layers(self, root: int) -> list[set[int]]:
        seen, out = {root}, [{root}]
        while len(seen) < len(self.labels):
            layer = {n for q in out[-1] for n in self.neighbours(q)} - seen
            if not layer:
                raise ValueError("the pattern is not connected")
            out.append(layer)
            seen |= layer
        return out


#: The pattern of the matching experiments: a joined to c and b, these joined, another b beside c, d beside it.
FIVE = QueryGraph({1: "a", 2: "c", 3: "b", 4: "b", 5: "d"}, ((1, 2), (1, 3), (2, 3), (2, 4), (4, 5)))


def match(query: QueryGraph, candidates: dict[int, Iterable[int]], joined: Callable[[int, int, int, int], bool], root: int, injective: bool = True) -> Iterator[dict[int, int]]:
    """All mappings of query vertices to their candidates with every query edge present.

    ``joined(q1, v1, q2, v2)`` says whether v1 and v2 carry the query edge between q1 and q2.
    """
    order = query.order(root)
    before = {q: [n for n in query.neighbours(q) if n in order[:k]] for k, q in enumerate(order)}

    def place(k: int, got: dict[int, int]) -> Iterator[dict[int, int]]:
        if k == len(order):
            yield dict(got)
            return
        q = order[k]
        for v in candidates.get(q, ()):
            if (not injective or v not in got.values()) and all(joined(n, got[n], q, v) for n in before[q]):
                got[q] = v
                yield from place(k + 1, got)
                del got[q]

    return place(0, {})


def densest(neighbours: dict[int, set[int]]) -> tuple[float, list[int]]:
    """The densest vertex set of a small graph (edges / vertices) by trying all, ties to the smallest set."""
    ids = sorted(neighbours)
    piece = Piece.of(neighbours)
    best: tuple[float, list[int]] = (0.0, [])
    for mask in range(1, 1 << len(ids)):
        edges = sum((piece.rows[k] & mask).bit_count() for k in bits(mask)) / 2
        if (d := edges / mask.bit_count()) > best[0]:
            best = d, piece.members(mask)
    return best
