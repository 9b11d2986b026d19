import random

import numpy as np
import pytest

from gpart.operators import codec
from gpart.sources import generators


def coded(lists, runs=True, weights=None):
    sizes = np.array([len(x) for x in lists])
    first = np.r_[0, np.cumsum(sizes)[:-1]]
    nbrs = np.array([v for x in lists for v in x], dtype=np.int64)
    wts = None if weights is None else np.array([w for x in weights for w in x], dtype=np.int64)
    return first, codec.encode(np.arange(len(lists)), first, sizes, nbrs, wts, runs)


@pytest.mark.parametrize("runs", [True, False])
@pytest.mark.parametrize("weighted", [True, False])
def test_payloads_decode_to_what_was_coded(runs, weighted):
    rng = random.Random(3)
    lists = [[], [5], [1, 2], [1, 2, 3], [1, 2, 3, 4, 9, 10, 11, 40], [0, 127, 128, 255, 16383, 16384, 16385, 16386], list(range(100, 200))] + [sorted(rng.sample(range(500), rng.randrange(60))) for _ in range(50)]
    weights = [[rng.choice([1, 127, 128, 255, 256, 65535, 1]) for _ in x] for x in lists]
    first, payloads = coded(lists, runs, weights if weighted else None)
    for i, (own, w, payload) in enumerate(zip(lists, weights, payloads, strict=True)):
        start, nbrs, wts = codec.decode(i, len(own), payload, weighted)
        assert start == first[i] and sorted(nbrs) == own
        assert sorted(zip(nbrs, wts, strict=True)) == sorted(zip(own, w if weighted else [1] * len(own), strict=True))


def test_varints_at_their_limits():
    values = np.array([0, 127, 128, 16383, 16384, (1 << 21) - 1, 1 << 21, (1 << 62)])
    data, sizes = codec.varint_bytes(values)
    assert sizes.tolist() == [1, 1, 2, 2, 3, 3, 4, 9] and codec.varint_values(data).tolist() == values.tolist()


def test_runs_of_three_are_intervals_and_shorter_ones_are_not(spark):
    g = generators.from_pairs(spark, [(0, b) for b in (2, 4, 5, 7, 8, 9, 11, 12, 13, 14)], 15)
    assert [(r["start"], r["length"]) for r in codec.intervals(g).where("src = 0").orderBy("start").collect()] == [(7, 3), (11, 4)]


def test_hubs_are_chunked_only_beyond_the_limit(spark):
    g = generators.star(spark, 33)
    assert codec.to_csr(g, hub_degree=33, chunk=8).where("id = 0").count() == 1
    assert [r["degree"] for r in codec.to_csr(g, hub_degree=32, chunk=8).where("id = 0").orderBy("chunk").collect()] == [8, 8, 8, 8, 1]


def test_empty_and_isolated(spark):
    g = generators.from_pairs(spark, [], 3)
    rows = codec.compress(codec.to_csr(g)).orderBy("id").collect()
    assert [r["degree"] for r in rows] == [0, 0, 0] and codec.decompress(codec.compress(codec.to_csr(g))).count() == 0
