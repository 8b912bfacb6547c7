"""Set joins against all pairs: copies meet once, passes change nothing."""

import random

import pytest

from densesql.operators import setjoin


@pytest.mark.parametrize("entries, compared", [(setjoin.ENTRIES, setjoin.COMPARED), (400, 2000)])
def test_joins_fold_copies_and_equal_all_pairs(spark, monkeypatch, entries, compared):
    monkeypatch.setattr(setjoin, "ENTRIES", entries)
    monkeypatch.setattr(setjoin, "COMPARED", compared)
    rng, given = random.Random(2), {}
    for base in range(8):
        words = [f"w{rng.randrange(60)}" for _ in range(30)]
        for copy in range(6):  # equal, similar and less similar ones, in any order and with repeats
            own = words[:] + [f"v{rng.randrange(9)}" for _ in range(copy)]
            rng.shuffle(own)
            given[len(given)] = own
            given[len(given)] = own[::-1] + own[:2]
    given |= {len(given): [], len(given) + 1: []}
    want = {(a, b): len(set(x) & set(y)) / len(set(x) | set(y)) for a, x in given.items() for b, y in given.items() if a < b and x and y}
    want = {k: v for k, v in want.items() if v >= 0.8 - 1e-9}
    written, table = {}, setjoin.Staging.table

    def counted(self, df, name, row_id=None):
        out = table(self, df, name, row_id)
        written[name] = out.count()
        return out

    monkeypatch.setattr(setjoin.Staging, "table", counted)
    df = spark.createDataFrame(list(given.items()), "id long, items array<string>").repartition(3)
    found = setjoin.prefix_join(df, "id", "items", 0.8).collect()
    assert len(found) == len(want) and {(r["left_id"], r["right_id"]): pytest.approx(r["overlap"]) for r in found} == want
    assert sum(n for name, n in written.items() if name.startswith("scored-")) < len(want)  # copies were not compared with each other
    near = setjoin.minhash_join(df, "id", "items", 0.8).collect()
    pairs = {(r["left_id"], r["right_id"]): r["overlap"] for r in near}
    assert len(pairs) == len(near) and all(want[k] == pytest.approx(v) for k, v in pairs.items())
    assert {k for k, v in want.items() if v == 1} <= set(pairs) and len(pairs) >= 0.9 * len(want)
