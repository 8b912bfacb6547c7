"""Near-duplicates of the pipeline against all pairs of shingle sets."""

import random

import corpus_pipeline
import pytest
from densesql.llm import near_copies


def brute_stays(given):
    def grams(text):
        w = (text or "").lower().split()
        return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or {tuple(w)}

    sets, root = [grams(t) for _, t in given], list(range(len(given)))

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for a in range(len(given)):
        for b in range(a):
            if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                root[find(a)] = find(b)
    groups = {}
    for k, (doc_id, _) in enumerate(given):
        groups.setdefault(find(k), []).append(doc_id)
    return sorted(min(ids) for ids in groups.values())


@pytest.mark.parametrize("few, one_pass", [(near_copies.FEW_PAIRS, near_copies.ONE_PASS), (0, 0)])
def test_stage_finds_planted_near_copies(spark, sf_dir, monkeypatch, few, one_pass):
    """The same rows stay whether ids are broadcast or joined, in one pass or in several."""
    monkeypatch.setattr(near_copies, "FEW_PAIRS", few)
    monkeypatch.setattr(near_copies, "ONE_PASS", one_pass)
    rng, given = random.Random(5), [(0, None), (1, " \n"), (2, "a few words"), (3, "A few  words"), (4, "a few others")]
    for base in range(12):  # copies with 0 to 8 of 200 words changed: similarities from 1 to about 0.67
        words = [f"w{rng.randrange(500)}" for _ in range(200)]
        for changed in range(9):
            copy = list(words)
            for at in rng.sample(range(0, 200, 5), changed):
                copy[at] = f"new{rng.randrange(10**9)}"
            given.append((10 + len(given), " ".join(copy)))
    common = " ".join(f"c{k}" for k in range(30))
    given += [(1000 + k, f"{common} " + " ".join(f"u{k}x{j}" for j in range(2 + k % 9))) for k in range(60)]  # one very common passage
    rng.shuffle(given)
    df = spark.createDataFrame(given, "doc_id long, text string").repartition(3)
    assert sorted(r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, df, sf_dir).collect()) == brute_stays(given)


def test_unlike_sets_under_common_shingles_are_not_written(spark, monkeypatch):
    """Texts that share only a common passage are told apart by their sketches inside the join."""
    rng, common = random.Random(7), " ".join(f"c{k}" for k in range(30))
    given = [(k, f"{common} " + " ".join(f"u{rng.randrange(10**9)}" for _ in range(120))) for k in range(80)]
    given.append((80, given[3][1] + " more"))
    written, table = {}, near_copies.Staging.table

    def counted(self, df, name, row_id=None):
        out = table(self, df, name, row_id)
        written[name] = out.count()
        return out

    monkeypatch.setattr(near_copies, "CLASSES", 1)  # one class of rarity, so that the passage is in the prefixes
    monkeypatch.setattr(near_copies.Staging, "table", counted)
    df = spark.createDataFrame(given, "doc_id long, text string").repartition(3)
    assert sorted(r["doc_id"] for r in near_copies.keep_one(df).collect()) == list(range(80))
    assert written["shared"] > 80 and sum(n for name, n in written.items() if name.startswith("met-")) <= 2


def test_unlike_long_texts_are_not_compared(spark, monkeypatch):
    """Bitmaps grow with the sets: long texts that share two fifths are told apart without their words, near copies of other lengths are not."""
    rng, counts, table = random.Random(11), {}, near_copies.Staging.table
    words = lambda n: [f"w{rng.randrange(10**9)}" for _ in range(n)]
    shared, long = words(2400), words(1030)
    given = [(k, " ".join(shared + words(1600))) for k in range(6)]
    given += [(6, " ".join(long)), (7, " ".join(long[:900]))]  # bitmaps of 4096 and 2048 bits, of 8192 the others
    assert [len(near_copies.bitmap(near_copies.shingles(t))) for _, t in given[5:]] == [128, 64, 32]

    def counted(self, df, name, row_id=None):
        out = table(self, df, name, row_id)
        counts[name] = out.count()
        return out

    monkeypatch.setattr(near_copies, "CLASSES", 1)  # one class of rarity, so that shared shingles are in the prefixes
    monkeypatch.setattr(near_copies.Staging, "table", counted)
    df = spark.createDataFrame(given, "doc_id long, text string").repartition(3)
    assert sorted(r["doc_id"] for r in near_copies.keep_one(df).collect()) == list(range(7))
    assert sum(n for name, n in counts.items() if name.startswith("pairs-")) == 1
