"""Local searches against all subsets and permutations of small random graphs; cost simulators by hand."""

import itertools
import random

import pytest

from subgraph_engine.functions import kernels as K
from subgraph_engine.functions.models import LruCache, OrderedQueue, StreamQueue


def random_graph(rng):
    n, p = rng.randint(1, 8), rng.random()
    edges = {(a, b) for a in range(n) for b in range(a + 1, n) if rng.random() < p}
    return n, edges, {v: [u for u in range(n) if (min(u, v), max(u, v)) in edges] for v in range(n)}


@pytest.mark.parametrize("seed", range(60))
def test_cliques_and_quasi_cliques_match_brute_force(seed):
    n, edges, near = random_graph(random.Random(seed))
    subsets = [s for k in range(1, n + 1) for s in itertools.combinations(range(n), k)]
    cliques = [s for s in subsets if all(p in edges for p in itertools.combinations(s, 2))]
    maximal = sorted(s for s in cliques if not any(set(s) < set(t) for t in cliques))
    piece = K.Piece.of(near)
    got = []
    for v in range(n):
        smaller, larger = piece.mask(u for u in near[v] if u < v), piece.mask(u for u in near[v] if u > v)
        got += [tuple(piece.members(c)) for c in K.maximal_cliques(piece, 1 << piece.place[v], larger, smaller)]
    assert sorted(got) == maximal
    every, most = (1 << n) - 1, max(map(len, cliques))
    assert K.largest_clique(piece, every).bit_count() == K.largest_clique(piece, every, bound="none").bit_count() == most
    assert K.largest_clique(piece, every, floor=most) == 0
    for k in (2, 3, 4):
        assert sorted(tuple(piece.members(c)) for c in K.cliques_of_size(piece, every, k)) == [s for s in cliques if len(s) == k]
    for num, den in ((1, 2), (3, 5), (4, 5), (1, 1)):
        want = sorted(s for s in subsets if len(s) >= 3 and all(sum(u in near[v] for u in s) >= -(-num * (len(s) - 1) // den) for v in s))
        assert sorted(tuple(piece.members(c)) for v in range(n) for c in K.quasi_cliques(piece, v, num, den, 3)) == want


@pytest.mark.parametrize("seed", range(30))
def test_matching_matches_permutations(seed):
    rng = random.Random(seed)
    n, edges, _ = random_graph(rng)
    labels = {v: rng.choice("abcd") for v in range(n)}

    def ok(m):
        return all(labels[m[q - 1]] == name for q, name in K.FIVE.labels.items()) and all((min(m[a - 1], m[b - 1]), max(m[a - 1], m[b - 1])) in edges for a, b in K.FIVE.edges)

    candidates = {q: [v for v in range(n) if labels[v] == name] for q, name in K.FIVE.labels.items()}
    for injective in (True, False):
        tuples = itertools.permutations(range(n), 5) if injective else itertools.product(range(n), repeat=5)
        got = [tuple(m[q] for q in range(1, 6)) for m in K.match(K.FIVE, candidates, lambda _, a, __, b: (min(a, b), max(a, b)) in edges, 1, injective)]
        assert sorted(got) == sorted(m for m in tuples if ok(m))


def test_moon_moser_has_three_to_the_third():
    near = {v: [u for u in range(9) if u // 3 != v // 3] for v in range(9)}
    piece = K.Piece.of(near)
    assert sum(1 for _ in K.maximal_cliques(piece, 0, (1 << 9) - 1, 0)) == 27


def test_cache_evicts_what_was_used_longest_ago():
    cache = LruCache(3)
    for v in "abcad":
        cache.request(v)
    assert list(cache._kept) == ["c", "a", "d"]
    assert (cache.hits, cache.misses, cache.evictions) == (1, 4, 1)


def test_oversized_batch_overflows_once():
    cache = LruCache(10)
    assert cache.batch(range(100)) == 100
    assert cache.peak == 100 and len(cache._kept) == 10


def test_ordered_queue_keeps_files_half_full_and_disjoint():
    queue = OrderedQueue(4, 4)
    for k in range(40, 0, -1):
        queue.put((k,), k)
    assert all(2 <= len(f) <= 4 for f in queue.files)
    assert all(a[-1] < b[0] for a, b in itertools.pairwise(queue.files))
    out = []
    while got := queue.take():
        out += got
    assert sorted(t for _, t in out) == list(range(1, 41))


def test_stream_queue_keeps_arrival():
    queue = StreamQueue(3)
    for k in range(7):
        queue.put((0,), k)
    assert [t for _, t in queue.take()] == [0, 1, 2]
    assert queue.writes == 2 and queue.reads == 1


@pytest.mark.parametrize("seed", range(40))
def test_quasi_cliques_equal_brute_force(seed):
    from subgraph_engine.functions.kernels import Piece, quasi_cliques

    rng = random.Random(seed)
    n, p = rng.randint(3, 10), rng.choice([0.2, 0.4, 0.6, 0.8])
    near = {v: set() for v in range(n)}
    for a, b in itertools.combinations(range(n), 2):
        if rng.random() < p:
            near[a].add(b)
            near[b].add(a)
    (num, den), least, most = rng.choice([(1, 2), (3, 5), (2, 3), (4, 5), (1, 1)]), rng.choice([1, 2, 3, 4]), rng.choice([None, None, 4, 5])
    want = {c for r in range(least, (most or n) + 1) for c in itertools.combinations(range(n), r) if all(den * len(near[v] & set(c)) >= num * (r - 1) for v in c)}

    def run(**how):
        out = []
        for root in range(n):
            piece = Piece.of({v: [u for u in near[v] if u >= root] for v in near if v >= root})
            out += [tuple(piece.members(m)) for m in quasi_cliques(piece, root, num, den, least, most, **how)]
        return out

    assert sorted(run()) == sorted(want)
    top = max(map(len, want), default=0)
    assert {c for c in run(largest=True) if len(c) == top} == {c for c in want if len(c) == top}
    some = set(run(maximal=True))
    assert some <= want and {c for c in some if not any(set(c) < set(x) for x in some)} == {c for c in want if not any(set(c) < set(x) for x in want)}
