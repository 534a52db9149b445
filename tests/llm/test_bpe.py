import random

import pytest
from tokenizers import Tokenizer

from vpatterns.llm import bpe

PATH = bpe.default_tokenizer()


@pytest.fixture(scope="module")
def library():
    t = Tokenizer.from_file(PATH)
    t.no_truncation()
    t.no_padding()
    return t


def texts():
    rng = random.Random(2)
    some = "the and ATTION thanedble é éeux ﬁ ’ ́e <|endoftext|> ½٣ Σας İ 中文 🙂 's don't \x1c \x85   aaaaaaa".split(" ")
    for _ in range(400):
        yield "".join(rng.choice(some) + rng.choice(["", "", " ", "\n"]) for _ in range(rng.randint(0, 50)))
    for n in (33, 64, 500, 4000):  # unsplit runs, joined as trees
        yield "".join(rng.choice("abcdeéin") for _ in range(n))
    yield "a" * 3000
    yield "!" * 777
    yield "<|startoftext|>x<|endoftext|><|EndOfText|>"


def test_same_as_the_library(library):
    enc = bpe.TextEncoder(PATH)
    for t in texts():
        ids = library.encode(t, add_special_tokens=False).ids
        assert enc(t) == (ids, library.decode(ids, skip_special_tokens=False)), repr(t)[:80]


@pytest.mark.parametrize("leaf", [2, 3, 8, 1000])
def test_any_leaf_gives_the_same(leaf):
    a, b = bpe.TextEncoder(PATH, leaf), bpe.TextEncoder(PATH)
    for t in texts():
        assert a(t) == b(t)


def test_decode_of_encode(make):
    df = make(["The cat's  here", None, "<|endoftext|>é"])
    got = bpe.encode(df, PATH)
    plain = {r["doc_id"]: r["decoded"] for r in got.collect()}
    assert {r["doc_id"]: r["decoded"] for r in bpe.decode(got, PATH).collect()} == plain


def test_long_runs_in_parallel_pieces(make, library):
    rng = random.Random(8)
    some = ["", None, "the cat", "the " + "ab" * 300 + " and <|endoftext|>" + "é" * 200 + " end", "x" * 65, "!" * 500 + "a" * 500]
    some += [" ".join("".join(rng.choice("abcdeéin!") for _ in range(rng.choice([3, 40, 300]))) for _ in range(6)) for _ in range(30)]
    df = make([*some, some[3]])
    got = {r["doc_id"]: (r["ids"], r["decoded"]) for r in bpe.encode(df, PATH, parallel=64, piece=16).collect()}
    assert len(got) == len(some) + 1 and got[3] == got[len(some)]
    for i, t in enumerate(some):
        ids = library.encode(t or "", add_special_tokens=False).ids
        assert got[i] == (ids, library.decode(ids, skip_special_tokens=False)), repr(t)[:60]


def test_encoder_holds_the_vocabulary_once():
    from vpatterns.llm.bpe import TextEncoder, default_tokenizer

    e = TextEncoder(default_tokenizer())
    assert e.library.get_vocab_size() == 0
    own = {s: s for s in e.vocab}
    assert all(own[x] is x for pair in e.run.ranks for x in pair if x in own)


def test_runs_are_merged_with_few_looks_at_the_ranks_and_kept_when_used(library, monkeypatch):
    class Counted(dict):
        looks = 0

        def get(self, *a):
            Counted.looks += 1
            return dict.get(self, *a)

    enc = bpe.TextEncoder(PATH)
    enc.run.ranks = Counted(enc.run.ranks)
    word = "internationalisation"
    tokens = enc.run.merged(enc.run.symbols(word))
    assert tokens == library.encode(word, add_special_tokens=False).tokens
    assert Counted.looks <= 3 * len(word)
    # a run in use outlives the change of caches
    monkeypatch.setattr(bpe, "CACHE", 10)
    enc = bpe.TextEncoder(PATH)
    missed, merge = [], enc.run.merged
    monkeypatch.setattr(enc.run, "merged", lambda parts: missed.append("".join(parts)) or merge(parts))
    rng = random.Random(3)
    rare = ["".join(rng.choice("abcdein") for _ in range(9)) for _ in range(200)]
    text = " ".join(x for i in range(0, 200, 4) for x in ["common", *rare[i : i + 4]])
    ids = library.encode(text, add_special_tokens=False).ids
    assert enc(text) == (ids, library.decode(ids, skip_special_tokens=False))
    assert len(missed) == len({"common", *rare}) and len(enc.cache) <= 10 and len(enc.older) <= 10
