import random
from itertools import combinations

import pytest

from vpatterns.llm import jaccard


def brute(texts):
    sets = []
    for t in texts:
        w = (t or "").lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) > 4 else ({tuple(w)} if w else set()))
    home = list(range(len(texts)))

    def find(x):
        while home[x] != x:
            x = home[x]
        return x

    for a, b in combinations(range(len(texts)), 2):
        n = len(sets[a] & sets[b])
        if n and 100 * n >= 75 * len(sets[a] | sets[b]):
            x, y = find(a), find(b)
            home[max(x, y)] = min(x, y)
    return [(len(s), find(i)) for i, s in enumerate(sets)]


@pytest.mark.parametrize("seed, hot", [(1, jaccard.HOT_ENTRIES), (2, jaccard.HOT_ENTRIES), (3, jaccard.HOT_ENTRIES), (2, 1), (3, 1)])
def test_same_as_brute_force(make, seed, hot):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcde") for _ in range(4))
    shared = [word() for _ in range(30)]
    texts = ["", None, "one", "One", "a b c", "a b c d e"]
    for _ in range(25):
        base = [word() for _ in range(rng.choice([4, 5, 8, 30, 80]))]
        for _ in range(rng.choice([1, 2, 8])):
            w = list(base)
            for _ in range(rng.choice([0, 1, 2, 5])):
                w[rng.randrange(len(w))] = word()
            texts.append(" ".join((shared if rng.random() < 0.4 else []) + w))
    rng.shuffle(texts)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.classes(make(texts), hot_entries=hot).collect()}
    assert [got[i] for i in range(len(texts))] == brute(texts)


@pytest.mark.parametrize("few", [jaccard.FEW_PAIRS, 8])
def test_large_group_of_near_copies(make, monkeypatch, few):
    monkeypatch.setattr(jaccard, "FEW_PAIRS", few)
    base = [f"w{i}" for i in range(120)]
    texts = [" ".join(base[:k] + [f"x{i}"] + base[k + 1 :]) for i, k in ((i, i % 100) for i in range(300))]
    got = {r["component_id"] for r in jaccard.classes(make(texts)).collect()}
    assert got == {0}


def test_blocks_add_up_in_both_forms():
    import numpy as np

    rng = np.random.default_rng(1)
    total, want = np.zeros(jaccard.BLOCK, np.int64), np.zeros(jaccard.BLOCK, np.int64)
    for share, most in ((0.01, 5), (0.9, 9), (0.01, 1 << 40), (0.9, 1 << 40)):
        block = np.where(rng.random(jaccard.BLOCK) < share, rng.integers(1, most, jaccard.BLOCK), 0)
        jaccard._add_block(total, jaccard._block_bytes(block))
        want += block
    assert (total == want).all()


def test_components_in_one_task_and_by_stars(spark, tmp_path):
    from vpatterns.llm.components import components

    rng = random.Random(4)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(200)] + [(i, i + 1) for i in range(400, 450)] + [(7, 7)]
    home = {x: {x} for e in edges for x in e}
    for a, b in edges:
        if home[a] is not home[b]:
            home[a] |= home[b]
            for x in home[b]:
                home[x] = home[a]
    want = {x: min(s) for x, s in home.items() if len(s) > 1}
    for in_one in (1_000, 0):
        got = components(spark.createDataFrame(edges, "a long, b long").repartition(5), f"file://{tmp_path}/{in_one}", "c", in_one).collect()
        assert {r["node"]: r["component"] for r in got} == want and len(got) == len(want)
