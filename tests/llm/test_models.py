"""Language, quality, toxicity and language-model scores."""

import math
import random
import zlib
from collections import Counter

import numpy as np

from vpatterns.llm import hmm, langid, quality, tokens, toxicity
from vpatterns.llm.common import remainder


def corpus(rng, n=400):
    vocab = {"en": "the of and thing house with running water".split(), "de": "der und das haus schnell über straße wasser".split(), "fr": "le la été maison eau vite très où".split()}
    for _ in range(n):
        lang = rng.choice(list(vocab))
        yield " ".join(rng.choice(vocab[lang]) for _ in range(rng.randint(3, 60))), lang, rng.choice("ab")


def test_languages(make):
    docs = make(list(corpus(random.Random(1))))
    langs, table = langid.build_filter(langid.training_rows(docs))
    got = {r["doc_id"]: r["lang_pred"] for r in langid.identify(docs, langs, table).collect()}
    wrong = [r for r in docs.collect() if got[r["doc_id"]] != r["lang"]]
    assert len(wrong) <= 4


def test_filter_gives_all_languages_of_a_trigram(make):
    docs = make([("abc abd", "x", "s")] * 8 + [("abc xyz", "y", "s")] * 8)
    langs, table = langid.build_filter(langid.training_rows(docs))
    letters = langid.letter_table()
    bits = {}
    for word in ("abc", "abd", "xyz"):
        g = langid.trigrams([word], letters)[0][1:2]
        mask = table[0][langid.places(g, 0, table.shape[1])]
        for h in range(1, langid.HASHES):
            mask = mask & table[0][langid.places(g, h, table.shape[1])]
        bits[word] = {langs[i] for i in range(len(langs)) if int(mask[0]) >> i & 1}
    assert bits == {"abc": {"x", "y"}, "abd": {"x"}, "xyz": {"y"}}


def test_base_counts():
    assert quality.base_counts("a b\na b\n\n a b") == (6, 6, 0, 1, 0, 3)
    words = "p q r s t u p q r s t z".split()
    assert quality.repeated_words([w.encode() for w in words]) == 10
    assert quality.base_counts("é# |\x0bx")[:3] == (3, 4, 2)


def test_outliers(make):
    rng = random.Random(2)
    rows = [(" ".join("w" * rng.randint(2, 8) for _ in range(rng.randint(30, 300))), "en", "s") for _ in range(300)]
    rows += [(" ".join(f"w{i}$$$" for i in range(100)), "en", "s") for _ in range(10)]
    got = {r["doc_id"]: r["kept"] for r in quality.judged(make(rows)).collect() if not r["base_failed"]}
    assert not any(got[i] for i in range(300, 310) if i in got)
    assert sum(got[i] for i in range(300) if i in got) >= 0.99 * sum(i in got for i in range(300))


def test_chi2():
    for dof, q in ((1, 3.841459), (4, 9.487729), (6, 12.591587)):
        assert abs(quality.chi2_quantile(0.95, dof) - q) < 1e-5


def test_restoring():
    text = "you are an idiot and a loser and stupid trash the disgusting clown said to the other people here " * 20
    size = 1024
    counts = np.zeros((size, size))
    codes = [ord(c) if c.isalpha() else 0 for c in f" {text} "]
    for a, b in zip(codes, codes[1:]):
        counts[a, b] += 1
    used = [i for i in np.flatnonzero(counts.sum(axis=0)) if i]
    small = counts[np.ix_([*used, 0], [*used, 0])] + 0.5
    r = toxicity.Restorer("".join(map(chr, used)), np.log(small / small.sum(axis=1, keepdims=True)))
    for token, want in (("1d10t", "idiot"), ("l0s3r", "loser"), ("st.u.p.i.d", "stupid"), ("trrrash", "trash"), ("cl0wn", "clown"), ("d!sgu$ting", "disgusting")):
        assert r(token) == want
    assert "idiot" in toxicity.tokens("what an i d i o t")


def test_letters_set_apart(make):
    texts = ["you are an idiot and a moron", "i say that you are a stupid moron and not an idiot", "such a clown you are i say", "do not run to the sad old man and the dog"] * 60
    docs = make(texts)
    units = toxicity.Units(toxicity.Restorer(*toxicity.character_model(docs), toxicity.word_model(docs)))
    for text, want in (
        ("a m o r o n", "a moron"), ("what a s t u p i d man", "a stupid"), ("i d i o t i say", "idiot i"), ("y o u a r e a n i d i o t", "you are an idiot"),
        ("the s a d man", "sad"), ("a m.o.r.o.n", "moron"), ("a 1 d 1 o t", "a idiot"), ("y o u  a r e  a  m o r o n", "you are a moron"), ("y o u a r e a s t u p i d m o r o n a n d a n i d i o t", "you are a stupid moron and an idiot"),
    ):
        assert set(want.split()) <= set(units.tokens(text)), (text, units.tokens(text))
    # a word that has no price of its own is spelled
    assert "clowns" in units.tokens("you c l o w n s")


def test_long_tokens_are_restored(make):
    docs = make(["you are an idiot and a stupid moron", "such trash the clown and a loser said"] * 60)
    units = toxicity.Units(toxicity.Restorer(*toxicity.character_model(docs), toxicity.word_model(docs)))
    assert "stupid" in units.words("st" + "u" * 60 + "pid")
    joined = "/".join(["1d1ot", "m0ron", "such", "trrrash", "cl0wn,and", "the.stupid", "l0ser", "said", "you"])
    assert len(joined) > 40 and {"idiot", "moron", "trash", "clown", "stupid", "loser"} <= set(units.words(joined))
    assert units.words("x7" * 30_000)  # time grows with length, not its square


def test_toxicity(make, spark):
    rng = random.Random(3)
    words = ["".join(rng.choice("abcdeilnorst") for _ in range(5)) for _ in range(200)]
    texts, marks = [], []
    for i in range(400):
        bad = rng.random() < 0.25
        w = [rng.choice(words) for _ in range(rng.randint(10, 60))]
        if bad:
            w[rng.randrange(len(w))] = rng.choice(["idiot", "idiot", "1d1ot", "moron"])
        texts.append(" ".join(w))
        marks.append((i, 0, int(bad)))
    docs = make(texts)
    model = toxicity.fit(docs, spark.createDataFrame(marks, "doc_id long, quality int, toxic int"))
    got = {r["doc_id"]: r["score"] for r in toxicity.scored(docs, model).collect()}
    held = [i for i in range(400) if zlib.crc32(str(i).encode()) % 4 == 2]
    right = sum((got[i] >= 0.3) == bool(marks[i][2]) for i in held)
    assert right >= 0.95 * len(held) and all(0 <= s <= 1 for s in got.values())


def test_exact_likelihood():
    rng = np.random.default_rng(0)
    m = hmm.Model.first(3, 400)
    m.start, m.moves = np.array([0.5, 0.3, 0.2]), rng.dirichlet(np.ones(3), 3)
    lines = [rng.integers(0, 400, k).astype(np.uint32) for k in (1, 5, 64, 65, 200)]
    for line, got in zip(lines, hmm.likelihoods(m, lines)):
        a, want = m.start * m.emits[line[0]], 0.0
        for x in line[1:]:
            want += math.log10(a.sum())
            a = (a / a.sum() @ m.moves) * m.emits[x]
        assert abs(got - want - math.log10(a.sum())) < 1e-9


def test_expectation_raises_the_likelihood():
    rng = np.random.default_rng(1)
    lines = [np.repeat(rng.integers(0, 2, 6) * 50, 8).astype(np.uint16) + rng.integers(0, 5, 48).astype(np.uint16) for _ in range(50)]
    m, last = hmm.Model.first(2, 400), -np.inf
    for _ in range(4):
        *counts, now = hmm.expected(m, lines)
        assert now > last - 1e-6
        m, last = hmm.Model.of_counts(*counts), now


def test_base_scores_and_gain(make):
    docs = make(list(corpus(random.Random(4))))
    rows = hmm.scored(docs, remainder(7) == 2, 3, 4).collect()
    words = {r["doc_id"]: [*r["text"].lower().split(), None] for r in docs.collect()}
    c = Counter(w for i, ws in words.items() if zlib.crc32(str(i).encode()) % 7 != 2 for w in ws)
    n, v = sum(c.values()), len(c)
    for r in rows:
        ws = words[r["doc_id"]]
        assert abs(r["base_score"] - sum(math.log10((c[w] + 1) / (n + v + 1)) for w in ws)) < 1e-6
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(ws), sum(c[w] > 0 for w in ws), n)
    held = [r for r in rows if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)


def test_spans_same_as_the_library():
    e = tokens.SpanEncoder(tokens.default_tokenizer())
    for t in ("The cat's  here\n\n 12é ÿ", "  \n", "’ ﬁ 中文 🙂", "", "$$$ x!"):
        a, b = e(t)
        assert list(zip(a.tolist(), b.tolist())) == e.library.encode(t, add_special_tokens=False).offsets


def test_boundary_rules():
    s, e = np.array([0, 2, 6]), np.array([2, 6, 8])
    parts = [("x", 0, 3), ("y", 3, 8)]
    assert tokens.allocate(s, e, parts, "first", 8)[1].tolist() == [2, 1]
    assert tokens.allocate(s, e, parts, "most", 8)[1].tolist() == [1, 2]
    assert tokens.allocate(s, e, parts, "shared", 8)[1].tolist() == [1.25, 1.75]
    assert tokens.allocate(s, e, [("x", 2, 6)], "first", 8)[0] == ["", "x", ""]
