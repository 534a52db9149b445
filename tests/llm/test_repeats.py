import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from vpatterns.llm import repeats


def brute(texts, length=200):
    raw = [(t or "").encode() for t in texts]
    seen = Counter(r[i : i + length] for r in raw for i in range(len(r) - length + 1))
    for r in raw:
        mask = np.zeros(len(r), bool)
        for i in range(len(r) - length + 1):
            if seen[r[i : i + length]] > 1:
                mask[i : i + length] = True
        turn = np.flatnonzero(np.diff(np.r_[False, mask, False].astype(np.int8)))
        kept = bytes(b for b, m in zip(r, mask) if not m)
        yield [tuple(map(int, x)) for x in turn.reshape(-1, 2)], hashlib.sha256(kept).hexdigest()


@pytest.mark.parametrize("seed, hot", [(1, repeats.HOT), (2, repeats.HOT), (3, 2)])
def test_same_as_brute_force(make, seed, hot):
    rng = random.Random(seed)
    base = ["".join(rng.choice("abcdé \n") for _ in range(rng.randint(150, 900))) for _ in range(25)]
    texts = [None, "", "a" * 199, "b" * 200, "b" * 500, "ab" * 400]
    for _ in range(250):
        t, u = rng.choice(base), rng.choice(base)
        a = rng.randint(0, len(t))
        x = rng.choice(["", "x" * rng.randint(0, 300)]) + t[a : rng.randint(a, len(t))] + rng.choice(["", u[: rng.randint(0, 400)], "y" * rng.randint(0, 600)])
        k = rng.randint(0, len(x))
        texts.append(x[:k] + rng.choice(["", "#"]) + x[k:])
    got = {r["doc_id"]: r for r in repeats.spans_of(make(texts).repartition(5), hot=hot).collect()}
    for i, (spans, digest) in enumerate(brute(texts)):
        assert [(s["start"], s["end"]) for s in got[i]["spans"]] == spans
        assert hashlib.sha256(bytes(got[i]["kept"])).hexdigest() == digest


def test_whole_characters(make):
    p = "é" * 150
    got = {r["doc_id"]: r["text"] for r in repeats.cleaned(make(["a" + p + "b", "cc" + p + "d", "alone"])).collect()}
    assert got == {0: "ab", 1: "ccd", 2: "alone"}


def test_ranks_of_a_dictionary_are_those_of_its_sorted_suffixes():
    rng = random.Random(5)
    phrases = list({bytes(rng.choice(b"ab\0") for _ in range(rng.randint(1, 40))) for _ in range(60)})
    ranks = repeats.dictionary_ranks(phrases)
    suffixes = sorted({p[i:] for p in phrases for i in range(len(p))})
    order = {x: i for i, x in enumerate(suffixes)}
    mine = {(int(ranks[k, i]), p[i:]) for k, p in enumerate(phrases) for i in range(len(p))}
    assert len({r for r, _ in mine}) == len(mine) == len(suffixes)
    assert [order[x] for _, x in sorted(mine)] == list(range(len(suffixes)))


def test_corpus_order_is_that_of_sorted_suffixes():
    rng = random.Random(6)
    length, trigger = 60, b"#" * repeats.TRIGGER
    tails = [bytes(rng.choice(b"xy") for _ in range(60)) for _ in range(4)]
    stretches, before, last = [], [], []
    for _ in range(40):
        head = bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 6)))
        tail = rng.choice(tails)
        tail = tail[: rng.randint(0, 50)] + bytes(rng.choice(b"xy") for _ in range(60))
        n = rng.randint(0, len(head))
        stretches.append((head + trigger + tail)[: n + length])
        before.append(len(head)), last.append(n)
    owner, place, equal = repeats.corpus_order(stretches, np.array(before), np.array(last), length)
    got = [stretches[o][p : p + length] for o, p in zip(owner, place)]
    assert all(len(x) == length for x in got) and len(got) == sum(n + 1 for n in last)
    # equal heads of phrases of one length compare by bytes; the order is by phrase, then by what follows
    assert all(x <= y for x, y in zip(got, got[1:]))
    assert equal.tolist() == [False] + [x == y for x, y in zip(got, got[1:])]
