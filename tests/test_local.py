import itertools
import random

from hypothesis import given, settings
from hypothesis import strategies as st

from gpart.operators import local
from gpart.operators.gains import ProbeTable


def graph(n, pairs):
    edges = [(a, b, w) for a, b, w in pairs] + [(b, a, w) for a, b, w in pairs]
    return local.LocalGraph.of(n, [1] * n, edges)


def grid(a, b):
    return graph(a * b, [(i * b + j, i * b + j + 1, 1) for i in range(a) for j in range(b - 1)] + [(i * b + j, (i + 1) * b + j, 1) for i in range(a - 1) for j in range(b)])


def test_known_optima():
    for g, k, best in ((graph(16, [(i, i + 1, 1) for i in range(15)]), 2, 1), (graph(16, [(i, (i + 1) % 16, 1) for i in range(16)]), 2, 2), (grid(8, 4), 2, 4)):
        assert g.cut(local.solve(g, k, len(g.weights) // k, 1)) == best


def test_small_graphs_against_all_bipartitions():
    rng = random.Random(5)
    for _ in range(10):
        n = 10
        g = graph(n, [(a, b, rng.randint(1, 5)) for a in range(n) for b in range(a) if rng.random() < 0.35])
        best = min(g.cut([0 if v in half else 1 for v in range(n)]) for half in itertools.combinations(range(n), n // 2))
        found = local.solve(g, 2, n // 2, 1)
        assert sorted(g.loads(found, 2)) == [5, 5] and g.cut(found) <= 1.5 * best + 1


def test_search_never_worsens_and_reports_its_moves():
    rng = random.Random(7)
    g = grid(6, 6)
    for seed in range(5):
        blocks = [rng.randrange(3) for _ in range(36)]
        before, copy = g.cut(blocks), list(blocks)
        caps = [max(13, x) for x in g.loads(blocks, 3)]
        log = local.search(g, blocks, caps, list(range(36)), random.Random(seed))
        assert g.cut(blocks) <= before and all(x <= c for x, c in zip(g.loads(blocks, 3), caps, strict=True))
        for v, a, b in log:
            assert copy[v] == a
            copy[v] = b
        assert copy == blocks


def test_more_blocks_than_vertices_and_one_block():
    g = grid(2, 2)
    assert set(local.solve(g, 1, 4, 1)) == {0} and len(set(local.solve(g, 8, 1, 1))) == 4


@given(st.lists(st.tuples(st.integers(0, 9), st.integers(1, 20)), max_size=60))
@settings(max_examples=200, deadline=None)
def test_probe_table_is_a_dictionary(steps):
    table, truth = ProbeTable(10, 2000), {}
    for key, value in steps:
        delta = -truth[key] if key in truth and value % 2 else value
        table.add(key, delta)
        truth[key] = truth.get(key, 0) + delta
        truth = {k: v for k, v in truth.items() if v}
        assert table.items() == truth and all(table.get(k) == truth.get(k, 0) for k in range(10))
