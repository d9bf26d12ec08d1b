"""Shards of the vantage-point tree grow with the fingerprints, and few fingerprints are in many of them."""

import numpy as np

from pathlore.llm import simhash


def test_number_of_shards():
    assert [simhash.shards_for(n) for n in (0, 1, 30_000, 30_001, 10**6)] == [1, 1, 1, 2, 34]
    assert simhash.shards_for(10**9) == 4096 and simhash.shards_for(10**11) == 100_000


def test_tree_has_the_shards_asked_for_and_few_copies():
    points = np.random.default_rng(1).integers(0, 1 << 64, 40_000, "uint64", endpoint=False)
    tree = simhash.grow(points, 64)
    names = [name for name, _, _ in simhash.route(tree, points, 2)]
    assert len(names) == len(set(names)) == 64
    homes = [len(home) for _, home, _ in simhash.route(tree, points, 2)]
    assert sum(homes) == len(points) and max(homes) < 4 * len(points) / 64
    plain = simhash.TRIED
    try:
        simhash.TRIED = 1
        assert simhash.copies_per_point(tree, points) < simhash.copies_per_point(simhash.grow(points, 64), points)
    finally:
        simhash.TRIED = plain
