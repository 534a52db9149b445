"""Toxicity by noisy-channel deobfuscation.

Suspicious tokens (symbols or digits among letters, a letter three times in a row,
single letters set apart) become lattices: every character may stand for itself or for
the letters it is used for, a repeated run may be one or two letters, a separator may
be nothing. The Viterbi path under a character bigram model, which is counted over all
texts, with a price for every change is the restored token. Letters set apart form one
lattice whose breaks are kept or dropped: its paths are words, priced by their share of
all texts' words, rare ones letter by letter. Restored tokens and their
stems are looked up among units whose share of toxic training documents is known, and a
logistic model over a document's strongest units gives the score.

Units and weights are learned on a bounded sample of labelled rows (``SAMPLE``), the
bound being on rows of each label, chosen by a digest of the id; the character model is
counted over all texts.

Defined cases: null and empty texts and texts without a known unit get the score of a
text with no evidence; without labels of both kinds every score is the base rate (0 with
no labels at all); a document with several labels is toxic if one says so; null labels
do not count; repeated rows agree; other columns are not read.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.llm.common import documents, remainder, table

#: Rows of each label that the classifier is fitted on at most.
SAMPLE = 20_000
#: Toxic documents of the sample that must have a unit.
LEAST = 4
#: Letters of the character model, the most frequent of any script: its size is their square.
LETTERS = 1024
#: Stems are the first so many letters of a word.
STEMS = (4, 5, 6)
CACHE = 500_000
#: Words with a price of their own: times seen at least, number; rarer ones are spelled.
WORD_LEAST, WORDS, WORD_LETTERS = 20, 100_000, 24
#: What a character is used for in disguised words.
STANDS_FOR = {"4": "a", "@": "a", "3": "e", "1": "il", "!": "il", "|": "il", "0": "o", "5": "s", "$": "s", "7": "t", "+": "t", "8": "b", "9": "g", "6": "g", "2": "z"}
SEPARATORS = set(".-_*~'`^:,/\\")
#: Prices in natural log: a substitution, a dropped separator, a shortened run.
SUBSTITUTE, DROP, SHORTEN = 1.0, 0.5, 0.3

#: Every character beside the ones it may be mistaken for gets one sign.
_ALIKE = str.maketrans({**{k: v[0] for k, v in STANDS_FOR.items()}, "l": "i"})
_SPACED = re.compile(r"(?<![^\s])(?:[^\W_][ .\-_*]{1,2}){3,}[^\W_](?![^\s.,!?])")
_APART = re.compile(r"(?<![^\s])(?:[^\W_][ .\-_*]{1,2}){2,}[^\W_](?![^\s.,!?])")
_EDGE = re.compile(r"^[^\w@$!|+]+|[^\w@$|+]+$")
_ODD = re.compile(r"[^\W\d_]")
_PLAIN_WORD = re.compile(r"^[^\W\d_]+$")
_RUN = re.compile(r"(.)\1{2,}")
#: What joins words to one token: signs that stand for no letter.
_PIECES = re.compile(r"[^\w@$!|+]+|_+")
_LETTERS = re.compile(r"[^\W\d_]+")


class Restorer:
    """Viterbi over a token's character lattice under a character bigram model."""

    def __init__(self, alphabet: str, logs: np.ndarray, words: dict[str, float] | None = None):
        self.words = words or {}
        self.longest = max(map(len, self.words), default=0)
        #: of a word that has no price of its own
        self.rare = math.log(max(1e-6, 1 - sum(map(math.exp, self.words.values()))))
        self.alike: dict[str, list[str]] | None = None
        self.at = {c: i for i, c in enumerate(alphabet)}
        self.logs = logs.tolist()
        self.edge = len(alphabet)
        self.floor = float(logs.min()) - 2.0

    def step(self, a: int, b: int) -> float:
        return self.logs[a][b] if a >= 0 and b >= 0 else self.floor

    def lattice(self, token: str) -> list[list[tuple[str, float]]]:
        """Choices of each place: letters to write and their price."""
        out, i = [], 0
        while i < len(token):
            c, n = token[i], 1
            while i + n < len(token) and token[i + n] == c:
                n += 1
            if c in STANDS_FOR:
                choices = [(x * k, SUBSTITUTE + SHORTEN * (n > k)) for x in STANDS_FOR[c] for k in {1, min(n, 2)}]
                if c in "!|+@$":
                    choices.append(("", DROP + SUBSTITUTE))
            elif c in SEPARATORS or not c.isalpha():
                choices = [("", DROP)]
            elif n >= 3:
                choices = [(c, SHORTEN), (c * 2, SHORTEN)]
            else:
                choices = [(c * n, 0.0)]
            out.append(choices)
            i += n
        return out

    def __call__(self, token: str) -> str:
        # by the last letter written, -2 being the word's start: score, (path so far, letters)
        best: dict[int, tuple[float, tuple | None]] = {-2: (0.0, None)}
        for choices in self.lattice(token):
            new: dict[int, tuple[float, tuple | None]] = {}
            for last, (score, path) in best.items():
                for write, price in choices:
                    now, s = last, score - price
                    for c in write:
                        b = self.at.get(c, -1)
                        s += self.step(self.edge if now == -2 else now, b)
                        now = b
                    if now not in new or s > new[now][0]:
                        new[now] = s, (path, write) if write else path
            best = new
        ends = [(s + self.step(self.edge if k == -2 else k, self.edge), k) for k, (s, _) in best.items()]
        path, out = best[max(ends)[1]][1], []
        while path:
            path, write = path
            out.append(write)
        return "".join(out[::-1])

    def split(self, region: str) -> list[str]:
        """Words of letters set apart: every break is kept or dropped, on one Viterbi path."""
        gaps = [len(x) for x in re.findall(r"[ .\-_*]+", region)]
        letters = re.sub(r"[ .\-_*]", "", region)
        if _RUN.search(letters):
            letters = self(letters)
            gaps = gaps if len(gaps) == len(letters) - 1 else [1] * (len(letters) - 1)
        raw, n = letters, len(letters)
        letters = "".join(STANDS_FOR.get(c, c)[0] for c in raw)
        drop = [0.0, 0.0]  # price of dropping all breaks before a letter
        for g in gaps:
            drop.append(drop[-1] + DROP * g)
        codes = [self.at.get(c, -1) for c in letters]
        best, back, word = [0.0] + [-math.inf] * n, [0] * (n + 1), [""] * (n + 1)
        spelled, since = -math.inf, 0  # the best rare word that is still open, and its start
        for i in range(1, n + 1):
            opened = best[i - 1] + self.rare + self.step(self.edge, codes[i - 1])
            if i > 1:
                spelled += self.step(codes[i - 2], codes[i - 1]) - (drop[i] - drop[i - 1])
            changed = SUBSTITUTE * (raw[i - 1] in STANDS_FOR)
            opened, spelled = opened - changed, spelled - changed
            if opened > spelled:
                spelled, since = opened, i - 1
            best[i], back[i] = spelled + self.step(codes[i - 1], self.edge), since
            word[i] = letters[since:i]
            for j in range(max(0, i - self.longest), i):
                for w, p in self.meant(raw[j:i]):
                    if (s := best[j] + p - (drop[i] - drop[j + 1])) > best[i]:
                        best[i], back[i], word[i] = s, j, w
        out = []
        while n:
            out.append(word[n])
            n = back[n]
        return out[::-1]

    def meant(self, piece: str) -> list[tuple[str, float]]:
        """Frequent words that a piece may stand for, with their prices."""
        if not any(c in STANDS_FOR for c in piece):
            return [(piece, self.words[piece])] if piece in self.words else []
        if self.alike is None:
            self.alike = {}
            for w in self.words:
                self.alike.setdefault(w.translate(_ALIKE), []).append(w)
        fit = [w for w in self.alike.get(piece.translate(_ALIKE), ()) if all(a == b or b in STANDS_FOR.get(a, "") for a, b in zip(piece, w))]
        price = SUBSTITUTE * sum(c in STANDS_FOR for c in piece)
        return [(w, self.words[w] - price) for w in fit]


def tokens(text: str) -> list[str]:
    """Lower-cased tokens; letters set apart by spaces or points are one token."""
    return [x for part in _split(text.lower())[:2] for x in part]


def _split(low: str) -> tuple[list[str], list[str], list[str]]:
    """(tokens, letters set apart as one token each, the stretches they were in) of a lower-cased text."""
    regions = _APART.findall(low)
    # four letters and more stand inside some stretch of three and more
    glued = [re.sub(r"[ .\-_*]", "", m) for m in _SPACED.findall(low)] if regions else []
    return low.split(), glued, regions


class Units:
    """The word and stems of a token, disguised ones restored first."""

    def __init__(self, restorer: Restorer):
        self.restorer = restorer
        self.split: dict[str, list[str]] = {}

    def tokens(self, text: str) -> list[str]:
        """Tokens of the text and the words that its letters set apart spell."""
        out, glued, regions = _split(text.lower())
        out += glued
        for region in regions:
            if region not in self.split:
                if len(self.split) >= CACHE:
                    self.split.clear()
                self.split[region] = self.restorer.split(region) if _ODD.search(region) else []
            out += self.split[region]
        return out

    def words(self, token: str) -> list[str]:
        if token.isalpha() and not _RUN.search(token):
            return [token]
        core = _EDGE.sub("", token)
        if _PLAIN_WORD.match(core) and not _RUN.search(core):
            return [core]
        if not core or not (_ODD.search(core) or any(c in STANDS_FOR for c in core)):
            return []
        parts = [p for p in _LETTERS.findall(core) if len(p) > 2]
        pieces = [p for p in _PIECES.split(core) if len(p) > 2 and p != core and not (_PLAIN_WORD.match(p) and not _RUN.search(p))]
        return list(dict.fromkeys([self.restorer(core), *parts, *map(self.restorer, pieces)]))

    def __call__(self, token: str) -> list[str]:
        out = []
        for w in self.words(token):
            out.append(w)
            out += [w[:k] + "*" for k in STEMS if len(w) > k]
        return out


def character_model(df: DataFrame, text_col: str = "text", least: int = 20) -> tuple[str, np.ndarray]:
    """(alphabet, log probabilities of one letter after another) over all texts.

    Letters of every script are counted. The alphabet is the LETTERS most frequent ones
    that come ``least`` times or more, all others share the place of what is no letter, so
    the matrix has a fixed size.
    """
    size, wide = 1024, 1 << 21

    def step(batches):
        total, rest = np.zeros(size * size, np.int64), []
        letters = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)

        def some(cells, n):
            return pa.RecordBatch.from_arrays([pa.array(cells), pa.array(n)], names=["cell", "n"])

        for batch in batches:
            texts = batch.column(0).to_pylist()
            for at in range(0, len(texts), 256):
                joined = " ".join(["", *(t or "" for t in texts[at : at + 256]), ""]).lower()
                codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
                codes[~letters[codes]] = 0
                x, y = codes[:-1], codes[1:]
                high = (x >= size) | (y >= size)
                if high.any():
                    rest.append(np.unique(x[high] * wide + y[high], return_counts=True))
                    x, y = x[~high], y[~high]
                total += np.bincount(x * size + y, minlength=size * size)
                if sum(len(c) for c, _ in rest) > 1_000_000:
                    yield some(*_summed(rest))
                    rest = []
        cells = np.flatnonzero(total)
        yield some(cells // size * wide + cells % size, total[cells])
        if rest:
            yield some(*_summed(rest))

    counts = df.select(text_col).mapInArrow(step, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).persist()
    a, b = F.expr(f"cell div {wide}").alias("a"), F.expr(f"cell % {wide}").alias("b")
    top = counts.select(b, "n").groupBy("b").agg(F.sum("n").alias("n")).where((F.col("b") > 0) & (F.col("n") >= least))
    used = sorted(r["b"] for r in top.orderBy(F.desc("n"), "b").limit(LETTERS).collect())
    known = F.array(*map(F.lit, used)) if used else F.array().cast("array<int>")
    place = lambda c: F.array_position(known, F.col(c).cast("int"))  # noqa: E731  0: no letter of the alphabet
    pairs = counts.select(a, b, "n").select(place("a").alias("a"), place("b").alias("b"), "n").groupBy("a", "b").agg(F.sum("n").alias("n")).toArrow()
    counts.unpersist()
    k = len(used)
    small = np.zeros((k + 1, k + 1))
    small[pairs.column("a").to_numpy() - 1, pairs.column("b").to_numpy() - 1] = pairs.column("n").to_numpy()  # 0 becomes the last
    small[k, k] = 0
    small += 0.5
    return "".join(map(chr, used)), np.log(small / small.sum(axis=1, keepdims=True))


def _summed(parts: list) -> tuple[np.ndarray, np.ndarray]:
    cells, at = np.unique(np.concatenate([c for c, _ in parts]), return_inverse=True)
    return cells, np.bincount(at, np.concatenate([n for _, n in parts])).astype(np.int64)


def word_model(df: DataFrame, text_col: str = "text", least: int = WORD_LEAST) -> dict[str, float]:
    """Log share of each frequent word among the words of all texts."""

    def rows(seen: Counter):
        return pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], names=["word", "n"])

    def step(batches):
        seen, total = Counter(), 0
        for batch in batches:
            for text in batch.column(0).to_pylist():
                found = _LETTERS.findall((text or "").lower())
                total += len(found)
                seen.update(w for w in found if len(w) <= WORD_LETTERS)
            if len(seen) > CACHE // 2:
                yield rows(seen)
                seen = Counter()
        seen[""] = total
        yield rows(seen)

    counts = df.select(text_col).mapInArrow(step, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    top = counts.where((F.col("n") >= least) | (F.col("word") == "")).orderBy(F.desc(F.col("word") == ""), F.desc("n"), "word").limit(WORDS + 1)
    got = top.toArrow().to_pydict()
    seen = dict(zip(got["word"], got["n"]))
    total = seen.pop("", 0)
    return {w: math.log(n / total) for w, n in seen.items()}


def features(weights: np.ndarray, n: int) -> list[float]:
    """Of one text: its strongest unit, the next, how many are strong, by length too."""
    top = np.sort(weights)[::-1][:3] if len(weights) else np.zeros(0)
    pad = np.concatenate([top, np.zeros(3 - len(top))])
    strong = float(np.sum(weights > 1.0))
    return [*pad, math.log1p(strong), math.log1p(100 * strong / (n + 20))]


class Scorer:
    def __init__(self, model: dict):
        self.units = Units(Restorer(model["alphabet"], model["logs"], model["words"]))
        self.weights, self.beta = model["weights"], model["beta"]
        self.seen: dict[str, float] = {}

    def weight(self, token: str) -> float:
        found = [self.weights[u] for u in self.units(token) if u in self.weights]
        best = max(found, default=0.0)
        if len(self.seen) >= CACHE:
            self.seen.clear()
        self.seen[token] = best
        return best

    def evidence(self, text: str) -> list[float]:
        got, seen = self.units.tokens(text), self.seen
        each = {t: seen[t] if t in seen else self.weight(t) for t in set(got)}
        return features(np.array([w for w in each.values() if w > 0]), len(got))

    def __call__(self, text: str | None) -> float:
        z = float(np.dot(self.beta, [1.0, *self.evidence(text or "")]))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def unit_counts(sample: DataFrame, alphabet: str, logs: np.ndarray, words: dict[str, float]) -> DataFrame:
    """unit, toxic, clean: documents of the sample with the unit."""

    shared = sample.sparkSession.sparkContext.broadcast(words)

    def step(batches):
        units, seen = Units(Restorer(alphabet, logs, shared.value)), {}
        for batch in batches:
            rows: dict[str, list[int]] = {}
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                mine = set()
                for token in set(units.tokens(text or "")):
                    if token not in seen:
                        if len(seen) >= CACHE:
                            seen.clear()
                        seen[token] = units(token)
                    mine.update(seen[token])
                for u in mine:
                    rows.setdefault(u, [0, 0])[0 if toxic else 1] += 1
            yield pa.RecordBatch.from_arrays([pa.array(list(rows), pa.string()), pa.array([v[0] for v in rows.values()], pa.int64()), pa.array([v[1] for v in rows.values()], pa.int64())], names=["unit", "toxic", "clean"])

    return sample.select("text", "toxic").mapInArrow(step, "unit string, toxic long, clean long").groupBy("unit").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 60) -> np.ndarray:
    """Newton steps with halving; a small penalty keeps separable data finite."""
    beta = np.zeros(x.shape[1])
    penalty = np.eye(x.shape[1]) * ridge
    penalty[0, 0] = 1e-6

    def loss(b):
        z = np.clip(x @ b, -30, 30)
        return float(np.sum(np.logaddexp(0, z) - y * z) + 0.5 * b @ penalty @ b)

    now = loss(beta)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        move = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty, x.T @ (y - p) - penalty @ beta)
        size = 1.0
        while size > 1e-6 and loss(beta + size * move) > now:
            size /= 2
        beta = beta + size * move
        new = loss(beta)
        if now - new < 1e-9 * max(1.0, now):
            break
        now = new
    return beta


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, least: int = LEAST) -> dict:
    """The whole model from documents and labelled training rows."""
    alphabet, logs = character_model(docs)
    words = word_model(docs)
    marks = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & (remainder(4) != 2)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    marks = marks.join(docs.select("doc_id").distinct(), "doc_id", "left_semi")
    picks = [marks.where(cond).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample) for cond in ("toxic = 1", "toxic <> 1")]
    chosen = picks[0].unionByName(picks[1])
    rates = {bool(r["t"]): r["n"] for r in marks.groupBy((F.col("toxic") == 1).alias("t")).count().withColumnRenamed("count", "n").collect()}
    empty = {"alphabet": alphabet, "logs": logs, "words": words, "weights": {}, "beta": np.zeros(6)}
    bias = np.zeros(6)
    n_toxic, n_clean = rates.get(True, 0), rates.get(False, 0)
    if not (n_toxic and n_clean):
        bias[0] = 30.0 if n_toxic else -30.0
        return empty | {"beta": bias}
    rows = docs.select("doc_id", "text").join(chosen, "doc_id").select("doc_id", "text", (F.col("toxic") == 1).cast("int").alias("toxic")).dropDuplicates(["doc_id"])
    rows = rows.withColumn("half", (F.crc32(F.reverse(F.col("doc_id").cast("string")).cast("binary")) % 2).cast("int")).persist()

    def weights(part: DataFrame) -> dict[str, float]:
        n1, n0 = (part.where(f"toxic = {k}").count() + 1 for k in (1, 0))
        counts = unit_counts(part, alphabet, logs, words).where(f"toxic >= {least} and toxic / {n1} > 3 * clean / {n0}")
        ratio = F.log((F.col("toxic") + 0.1) / n1) - F.log((F.col("clean") + 0.5) / n0)
        got = counts.select("unit", ratio.alias("w")).toArrow()  # the sample bounds it
        return dict(zip(got.column("unit").to_pylist(), got.column("w").to_pylist()))

    # Weights of one half are tried on the other, so the last model sees honest evidence.
    halves = [weights(rows.where(f"half = {k}")) for k in (0, 1)]
    shared = docs.sparkSession.sparkContext.broadcast([empty | {"weights": w} for w in halves])

    def evidence(batches):
        scorers = [Scorer(m) for m in shared.value]
        for batch in batches:
            got = [scorers[1 - h].evidence(t or "") for t, h in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(got, pa.list_(pa.float64()))], names=["toxic", "x"])

    data = rows.select("text", "toxic", "half").mapInArrow(evidence, "toxic int, x array<double>").toArrow()
    y = data.column("toxic").to_numpy().astype(float)
    if len(y):
        x = np.column_stack([np.ones(len(y)), np.array(data.column("x").to_pylist())])
        beta = logistic(x, y)
        # the sample holds labels in other shares than the corpus
        s1, s0 = max(1.0, y.sum()), max(1.0, len(y) - y.sum())
        beta[0] += math.log(n_toxic / n_clean) - math.log(s1 / s0)
    else:
        beta = bias
    final = weights(rows)
    rows.unpersist()
    return empty | {"weights": final, "beta": beta}


def scored(df: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and score of every row; no shuffle."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def step(batches):
        scorer = Scorer(shared.value)
        for batch in batches:
            got = []
            for at in range(0, batch.num_rows, 256):
                got += map(scorer, batch.column(1)[at : at + 256].to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(got, pa.float64())], names=[id_col, "score"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, text_col).mapInArrow(step, f"`{id_col}` {kind}, score double")


def op10_noisy_channel_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    got = scored(docs, fit(docs, table(spark, sf_dir, "labels")))
    return got.select("doc_id", (remainder(4) == 2).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
