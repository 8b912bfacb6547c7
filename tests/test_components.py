"""Components against a plain union-find, on both paths."""

import random

import pytest

from densesql.plans.components import connected_components
from densesql.plans.staging import Staging


def brute(edges):
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        if a != b:
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {x: find(x) for x in root}


@pytest.mark.parametrize("finish", [0, 1 << 20])
@pytest.mark.parametrize("kind", ["random", "chain", "star", "loops"])
def test_components(spark, finish, kind):
    rng = random.Random(3)
    edges = {
        "random": [(rng.randrange(60), rng.randrange(60)) for _ in range(45)],
        "chain": [(k, k + 1) for k in range(40)] + [(-5, -9)],
        "star": [(100, k) for k in range(30)] + [(200, 201), (201, 202)],
        "loops": [(1, 1), (2, 3), (3, 2), (2, 3)],
    }[kind]
    got = connected_components(spark.createDataFrame(edges, "a long, b long"), Staging(spark, "test"), finish_edges=finish)
    assert sorted(map(tuple, got.collect())) == sorted(brute(edges).items())
