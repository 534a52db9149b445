"""Language masks, robust outliers, lattices and offsets against plain versions that try everything."""

import itertools
import math
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from vpatterns.llm import langid, quality, tokens, toxicity
from vpatterns.llm.queries import queries
from vpatterns.llm.tokens import allocate, line_sections


def texts(seed, n=160):
    rng = random.Random(seed)
    vocab = {"en": "the of and thing house with running water one".split(), "de": "der und das haus schnell über straße wasser one".split(), "fr": "le la été maison eau vite très où one".split()}
    for _ in range(n):
        lang = rng.choice([*vocab, None])
        yield " ".join(rng.choice(vocab[lang or "en"]) for _ in range(rng.randint(0, 25))) + rng.choice(["", " 12!", "\n"]), lang, rng.choice("ab")


def trigrams(text):
    t = "".join(c if c.isalpha() else " " for c in f"  {text.lower()}  ")
    return [t[i : i + 3] for i in range(len(t) - 2) if t[i + 1] != " "]


def test_languages_by_plain_sets(make):
    """With a filter that hardly fills, scores are those of sets of trigrams by language."""
    docs = make(list(texts(1)))
    rows = docs.collect()
    train = [r for r in rows if r["lang"] and zlib.crc32(str(r["doc_id"]).encode()) % 4 != 2]
    counts, totals = {}, {}
    for r in train:
        for g in trigrams(r["text"]):
            counts[g, r["lang"]] = counts.get((g, r["lang"]), 0) + 1
            totals[r["lang"]] = totals.get(r["lang"], 0) + 1
    langs = sorted(totals, key=lambda x: (-totals[x], x))
    rate = {k: n / totals[k[1]] for k, n in counts.items()}
    top = {g: max(rate.get((g, x), 0) for x in langs) for g, _ in counts}
    has = {k for k, n in counts.items() if n >= langid.LEAST and rate[k] >= langid.SHARE * top[k[0]]}
    got = {r["doc_id"]: r for r in langid.identify(docs, *langid.build_filter(langid.training_rows(docs))).collect()}
    for r in rows:
        grams = trigrams(r["text"])
        hits = [sum((g, x) in has for g in grams) for x in langs]
        mine = got[r["doc_id"]]
        if not grams:
            assert (mine["lang_pred"], mine["score"]) == ("und", 0.0)
            continue
        best, second = sorted(hits)[::-1][:2]
        assert mine["score"] == pytest.approx(best / (best + second) if best else 0.0, abs=1e-3)
        if best > second:
            assert mine["lang_pred"] == langs[hits.index(best)]


def test_filter_grows_with_its_trigrams(spark):
    few = spark.range(1000).select((F.col("id") % 7 + 2).alias("n"))
    assert langid.filter_size(few, 64, 1 << 24) == (8192, 0)
    # more than the largest filter has room for: the rarest go
    positions, cut = langid.filter_size(spark.createDataFrame([(n,) for n in [2] * 500 + [5] * 100 + [40] * 20], "n long"), 64, 1024)
    assert (positions, cut) == (1024, 4)


def plain_mcd(x, keep, steps):
    p = x.shape[1]

    def median(v):  # the smaller middle one, as the approximate percentile gives
        return np.sort(v)[max(0, math.ceil(len(v) * 0.5) - 1)]

    mu = np.array([median(x[:, i]) for i in range(p)])
    mad = np.array([median(np.abs(x[:, i] - mu[i])) for i in range(p)])
    inv = np.diag(1 / ((1.4826 * mad) ** 2 + quality.FLOOR**2))
    factor = keep / quality.chi2_cdf(quality.chi2_quantile(keep, p), p + 2)
    for _ in range(steps):
        d = np.einsum("ni,ij,nj->n", x - mu, inv, x - mu)
        ring = np.floor(np.log2(1 + d) * 32)
        last = np.sort(ring)[math.ceil(keep * len(x)) - 1]
        near = x[ring <= last]
        m, mu = len(near), near.mean(axis=0)
        cov = near.T @ near / m - np.outer(mu, mu)
        cov = (cov * m * factor + np.eye(p) * quality.FLOOR**2 * 10) / (m + 10) + np.eye(p) * quality.FLOOR**2
        inv = np.linalg.inv(cov)
    return np.einsum("ni,ij,nj->n", x - mu, inv, x - mu)


@pytest.mark.parametrize("shared", [quality.SHARED, 0])
def test_outliers_by_plain_concentration_steps(make, monkeypatch, shared):
    monkeypatch.setattr(quality, "SHARED", shared)
    rng = random.Random(4)
    rows = [(" ".join("w" * rng.randint(1, 9) + rng.choice(["", "", "", "$"]) for _ in range(rng.randint(12, 150))) + rng.choice(["", "\nx\nx"]), rng.choice(["en", None]), "s") for _ in range(240)]
    got = [r for r in quality.vectors(quality.judged(make(rows))).collect() if not r["base_failed"]]
    limit = quality.chi2_quantile(1 - quality.TAIL, 4)
    lang = {i: r[1] for i, r in enumerate(rows)}
    assert len(got) > 200
    for group in ("en", None):
        mine = [r for r in got if lang[r["doc_id"]] == group]
        want = plain_mcd(np.array([[r[n] for n in quality.NAMES] for r in mine]), quality.KEEP, quality.STEPS)
        assert [r["distance2"] for r in mine] == pytest.approx(want.tolist(), rel=1e-6, abs=1e-9)
        assert [r["kept"] for r in mine] == [d <= limit for d in want]


def test_lattices_by_all_paths(make):
    docs = make(["you are an idiot and a stupid moron", "such trash the clown and a loser said to all"] * 60)
    alphabet, logs = toxicity.character_model(docs)
    r = toxicity.Restorer(alphabet, logs)

    def price(word):
        at = [r.edge, *(r.at.get(c, -1) for c in word), r.edge]
        return sum(r.step(a, b) for a, b in zip(at, at[1:]))

    rng = random.Random(6)
    for _ in range(150):
        token = "".join(rng.choice("aidotm140!$.") * rng.choice([1, 1, 1, 3]) for _ in range(rng.randint(1, 5)))
        paths = {}
        for path in itertools.product(*r.lattice(token)):
            word = "".join(w for w, _ in path)
            paths[word] = max(paths.get(word, -math.inf), price(word) - sum(p for _, p in path))
        assert paths[r(token)] == pytest.approx(max(paths.values())), token


def test_letters_of_any_script_have_a_model(make):
    docs = make(["ты такой идиот и дурак", "אתה אידיוט", "the idiot"] * 40)
    alphabet, logs = toxicity.character_model(docs)
    assert {"и", "א", "t"} <= set(alphabet) and logs.shape == (len(alphabet) + 1,) * 2
    r = toxicity.Restorer(alphabet, logs)
    assert r("ид-ио-т") == "идиот" and r("дуууурак") == "дурак"


def test_offsets_are_the_librarys_on_random_texts():
    e = tokens.SpanEncoder(tokens.default_tokenizer())
    rng = random.Random(9)
    some = ["the", " ", "  ", "\n", "\t", "'s", "'LL", "é", "ÿ", "½", "12", "$", "…", "中", "🙂", "\r", "\x0b", "\xa0", "don't", "A", "ſ", "İ", "_", "<|endoftext|>", "\x85"]
    for _ in range(600):
        text = "".join(rng.choice(some) for _ in range(rng.randint(0, 30)))
        a, b = e(text)
        assert list(zip(a.tolist(), b.tolist())) == e.library.encode(text, add_special_tokens=False).offsets, repr(text)


def test_attribution_by_counting_each_token(make):
    rng = random.Random(10)
    rows = ["".join(rng.choice(["word", " ", "\n", "é", "x9", "…"]) for _ in range(rng.randint(0, 40))) for _ in range(40)]
    library = tokens.SpanEncoder(tokens.default_tokenizer()).library
    for rule in tokens.RULES:
        got = {r["doc_id"]: r for r in tokens.attribute(make(rows), tokens.default_tokenizer(), rule=rule).collect()}
        for i, text in enumerate(rows):
            spans = library.encode(text, add_special_tokens=False).offsets
            want: dict[str, float] = {}
            parts = line_sections(text)
            for a, b in spans:
                over = [(min(b, y) - max(a, x), k) for k, (_, x, y) in enumerate(parts) if min(b, y) > max(a, x)]
                if rule == "shared":
                    for n, k in over:
                        want[parts[k][0]] = want.get(parts[k][0], 0) + n / (b - a)
                else:
                    k = over[0][1] if rule == "first" else max(over, key=lambda o: (o[0], -o[1]))[1]
                    want[parts[k][0]] = want.get(parts[k][0], 0) + 1
            mine = {s["name"]: s["tokens"] for s in got[i]["sections"] if s["tokens"]}
            assert got[i]["n_tokens"] == len(spans) and mine == pytest.approx(want), (rule, text)


def test_every_query_is_registered():
    assert sorted(queries(), key=lambda k: int(k[2:].split("_")[0]))[0].startswith("op1_") and len(queries()) == 10
