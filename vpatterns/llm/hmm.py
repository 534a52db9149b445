"""Language-model scores by a hidden Markov model trained with Baum-Welch.

Tokens are lower-cased words and one end. The states emit word classes: a class of its
own for the most frequent words, for each other word with ``OWN_LEAST`` training
occurrences or more and for the end, and 256 classes of the others by their last bytes; inside such a class a word has its add-one share
of the class's training tokens, with one share left for unknown words. So the model is a
probability over whole texts, and its emissions grow with the vocabulary that the corpus
has evidence for, up to the ``HELD`` words whose counts every task holds.

Expectation steps run over the training texts in windows, add their counts up in each
partition and then across partitions; only the summed counts (states times classes) reach
the driver. Scores are exact for whole texts: the scaled forward recursion is run for all
windows at once from every state, and a text's windows are chained as matrices.

Counts of words outside a table of fixed size are looked up where the words are: each
text's rare words go to shards of the vocabulary, which send sums back.

Defined cases: null and empty texts are one end token; without training rows all words
are unknown and every count is 0; repeated rows agree; null ids are kept; other columns
are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.llm.common import ASCII_LOWER, documents, forget, remainder, scratch, shards, tidy, written

STATES, STEPS, WINDOW = 4, 5, 64
#: Most frequent words with a class of their own in any corpus, occurrences that give any
#: other word one, and words whose counts every task holds.
OWN, OWN_LEAST, HELD = 3840, 1000, 1 << 18
TAILS = 256
CACHE = 50_000


class WordNumbers(dict):
    """Word to a number: 56 bits of its digest, and a low byte that is the class of its last bytes.

    Two words share a number with a chance of 2**-56 a pair at most; that would add their
    counts up.
    """

    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE:
            self.clear()
        got = self[word] = xxhash.xxh3_64_intdigest(word) & ~0xFF | xxhash.xxh3_64_intdigest(word[-3:]) & 0xFF
        return got


def numbers(text: str | None, ids: WordNumbers) -> np.ndarray:
    words = (text or "").encode("utf-8", "surrogatepass").translate(ASCII_LOWER).split()
    return np.fromiter(map(ids.__getitem__, words), np.uint64, len(words))


def _sharded(values: np.ndarray, n_shards: int):
    shard = (values >> np.uint64(20)) % np.uint64(n_shards)
    order = np.argsort(shard, kind="stable")
    cuts = np.flatnonzero(np.r_[True, shard[order][1:] != shard[order][:-1]]) if len(order) else []
    for a, b in zip(cuts, [*cuts[1:], len(order)]):
        yield int(shard[order[a]]), order[a:b]


def vocabulary(train: DataFrame, n_shards: int) -> DataFrame:
    """shard, ids (sorted), counts: the words of all training texts."""

    def step(batches):
        ids, held, size = WordNumbers(), [], 0

        def flush():
            values, n = np.unique(np.concatenate(held), return_counts=True)
            rows = [(s, values[at].tobytes(), n[at].astype(np.int64).tobytes()) for s, at in _sharded(values, n_shards)]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary()))], names=["shard", "ids", "counts"])

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                for text in batch.column(0)[at : at + 256].to_pylist():
                    held.append(numbers(text, ids))
                    size += len(held[-1])
                if size > 4_000_000:
                    yield flush()
                    held, size = [], 0
        if size:
            yield flush()

    def add(key, t):
        ids = np.concatenate([np.frombuffer(x.as_py(), np.uint64) for x in t.column("ids")])
        n = np.concatenate([np.frombuffer(x.as_py(), np.int64) for x in t.column("counts")])
        values, at = np.unique(ids, return_inverse=True)
        total = np.bincount(at, n).astype(np.int64)
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "ids": pa.array([values.tobytes()], pa.binary()), "counts": pa.array([total.tobytes()], pa.binary())})

    rows = train.select("text").mapInArrow(step, "shard int, ids binary, counts binary")
    return rows.groupBy("shard").applyInArrow(add, "shard int, ids binary, counts binary")


def _summary(vocab: DataFrame, n_shards: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(most frequent words, their counts, tokens and types by tail class)."""
    each = max(64, 4 * HELD // n_shards)

    def top(batches):
        for batch in batches:
            for x, n in zip(batch.column(1), batch.column(2)):
                ids, n = np.frombuffer(x.as_py(), np.uint64), np.frombuffer(n.as_py(), np.int64)
                some = np.lexsort((ids, -n))[:each]
                yield pa.RecordBatch.from_arrays([pa.array(ids[some].view(np.int64)), pa.array(n[some])], names=["id", "n"])

    def tails(batches):
        tokens, types = np.zeros(TAILS, np.int64), np.zeros(TAILS, np.int64)
        for batch in batches:
            for x, n in zip(batch.column(1), batch.column(2)):
                tail = (np.frombuffer(x.as_py(), np.uint64) & np.uint64(0xFF)).astype(np.int64)
                tokens += np.bincount(tail, np.frombuffer(n.as_py(), np.int64), minlength=TAILS).astype(np.int64)
                types += np.bincount(tail, minlength=TAILS)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(TAILS)), pa.array(tokens), pa.array(types)], names=["tail", "tokens", "types"])

    # A count that at most HELD words reach, found on a histogram of counts by halves of a power of two.
    candidates = vocab.mapInArrow(top, "id long, n long")
    level = F.floor(2 * F.log2("n")).cast("int")
    ladder = sorted(((r["l"], r["m"]) for r in candidates.groupBy(level.alias("l")).agg(F.count(F.lit(1)).alias("m")).collect()), reverse=True)
    least, held = 1 << 30, 0
    for l, m in ladder:
        if held + m > HELD:
            break
        least, held = l, held + m
    got = candidates.where(level >= least).toArrow()
    ids, n = got.column("id").to_numpy().view(np.uint64), got.column("n").to_numpy()
    order = np.lexsort((ids, -n))
    sums = vocab.mapInArrow(tails, "tail long, tokens long, types long").groupBy("tail").agg(F.sum("tokens").alias("tokens"), F.sum("types").alias("types")).toArrow()
    tokens, types = np.zeros(TAILS, np.int64), np.zeros(TAILS, np.int64)
    tokens[sums.column("tail").to_numpy()] = sums.column("tokens").to_numpy()
    types[sums.column("tail").to_numpy()] = sums.column("types").to_numpy()
    return ids[order], n[order], tokens, types


def _sequences(docs: DataFrame, shared, n_shards: int) -> DataFrame:
    """Rows of kind 0: a text with its classes and sums; of kind 1: rare words for a shard."""
    names = ["kind", "pack", "row", "doc_id", "held_out", "n", "known", "base", "within", "classes", "shard", "ids", "rows"]
    kinds = [pa.int32(), pa.int64(), pa.int32(), None, pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary(), pa.int32(), pa.binary(), pa.binary()]

    def step(batches):
        ids, at = WordNumbers(), shared.value
        words, count, class_of, end_count, room, own = at["words"], at["counts"], at["classes"], at["end"], at["room"], at["own"]
        pack = TaskContext.get().partitionId() << 24
        for batch in batches:
            kinds[3] = batch.schema.field(0).type
            for start in range(0, batch.num_rows, 4096):
                pack += 1
                some = batch.slice(start, 4096)
                rows, rare, owner = [], [], []
                for i, (key, held, text) in enumerate(zip(*(some.column(k).to_pylist() for k in range(3)))):
                    w = numbers(text, ids)
                    place = np.minimum(np.searchsorted(words, w), max(0, len(words) - 1))
                    hit = words[place] == w if len(words) else np.zeros(len(w), bool)
                    tail = (w & np.uint64(0xFF)).astype(np.int64)
                    classes = own + 1 + tail
                    classes[hit] = class_of[place[hit]]
                    logs = np.log10(count[place[hit]] + 1.0)
                    shared_class = classes[hit] > own
                    within = logs[shared_class].sum() - room[tail[classes > own]].sum()
                    line = np.r_[classes, 0].astype(np.uint32)
                    rows.append((0, pack, i, key, held, len(w) + 1, int(hit.sum()) + (end_count > 0), float(logs.sum() + np.log10(end_count + 1.0)), float(within), line.tobytes(), None, None, None))
                    rare.append(w[~hit])
                    owner.append(np.full(len(rare[-1]), i, np.int32))
                rare, owner = np.concatenate(rare), np.concatenate(owner)
                rows += [(1, pack, None, None, None, None, None, None, None, None, s, rare[x].tobytes(), owner[x].tobytes()) for s, x in _sharded(rare, n_shards)]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=names)

    kind = docs.schema["doc_id"].dataType.simpleString()
    out = f"kind int, pack long, row int, doc_id {kind}, held_out boolean, n long, known long, base double, within double, classes binary, shard int, ids binary, rows binary"
    return docs.select("doc_id", "held_out", "text").mapInArrow(step, out)


def _rare_sums(asks: DataFrame, vocab: DataFrame) -> DataFrame:
    """pack, rows, sums, known: of each text the sum of log10(count + 1) over its rare words."""

    def look(key, asked, held):
        words = np.frombuffer(held.column("ids")[0].as_py(), np.uint64) if held.num_rows else np.zeros(0, np.uint64)
        counts = np.frombuffer(held.column("counts")[0].as_py(), np.int64) if held.num_rows else np.zeros(0, np.int64)
        out = []
        for pack, ids, rows in zip(*(asked.column(c).to_pylist() for c in ("pack", "ids", "rows"))):
            ids, rows = np.frombuffer(ids, np.uint64), np.frombuffer(rows, np.int32)
            n = np.zeros(len(ids), np.int64)
            if len(words):
                at = np.minimum(np.searchsorted(words, ids), len(words) - 1)
                same = words[at] == ids
                n[same] = counts[at[same]]
            mine, at = np.unique(rows, return_inverse=True)
            out.append((pack, mine.tobytes(), np.bincount(at, np.log10(n + 1.0)).tobytes(), np.bincount(at, n > 0).astype(np.int32).tobytes()))
        columns = list(zip(*out)) or [()] * 4
        return pa.table({n: pa.array(c, k) for n, c, k in zip(("pack", "rows", "sums", "known"), columns, (pa.int64(), pa.binary(), pa.binary(), pa.binary()))})

    return asks.groupBy("shard").cogroup(vocab.groupBy("shard")).applyInArrow(look, "pack long, rows binary, sums binary, known binary")


class Model:
    """Start, start of later windows, transitions, emissions (classes by states)."""

    def __init__(self, start, later, moves, emits):
        self.start, self.later, self.moves, self.emits = start, later, moves, emits

    @staticmethod
    def first(states: int, n_classes: int, seed: int = 7) -> Model:
        rng = np.random.default_rng(seed)
        moves = np.full((states, states), 0.1 / max(1, states - 1))
        np.fill_diagonal(moves, 0.9 if states > 1 else 1.0)
        emits = rng.uniform(0.2, 1.8, (n_classes, states))
        even = np.full(states, 1 / states)
        return Model(even, even, moves, emits / emits.sum(axis=0))

    @staticmethod
    def of_counts(start, later, moves, emits) -> Model:
        emits, moves = emits + 1e-2, moves + 1.0
        return Model((start + 1) / (start + 1).sum(), (later + 1) / (later + 1).sum(), moves / moves.sum(axis=1, keepdims=True), emits / emits.sum(axis=0))


def windows(lines: list[np.ndarray], width: int = WINDOW):
    """(table, lengths, text, place): windows of all lines, the longest first."""
    text, place, length, parts = [], [], [], []
    for i, line in enumerate(lines):
        for k in range(0, len(line), width):
            part = line[k : k + width]
            text.append(i), place.append(k // width), length.append(len(part)), parts.append(part)
    length = np.array(length)
    order = np.argsort(-length, kind="stable")
    table = np.zeros((len(parts), width), np.int64)
    for row, k in enumerate(order):
        table[row, : length[k]] = parts[k]
    return table, length[order], np.array(text)[order], np.array(place)[order]


def expected(model: Model, lines: list[np.ndarray]):
    """Counts of one expectation step over the lines' windows, and their log likelihood."""
    table, length, _, place = windows(lines)
    s, width, k = len(table), int(length.max(initial=0)), len(model.start)
    active = [int(np.searchsorted(-length, -t)) for t in range(width)]  # windows longer than t
    seen = model.emits[table[:, :width]]
    alpha, scale = np.zeros((s, width, k)), np.ones((s, width))
    now = np.where((place == 0)[:, None], model.start, model.later) * seen[:, 0]
    for t in range(width):
        n = active[t]
        if t:
            now = (now[:n] @ model.moves) * seen[:n, t]
        total = now.sum(axis=1)
        now = now / total[:, None]
        alpha[:n, t], scale[:n, t] = now, total
    moves, beta = np.zeros((k, k)), np.ones((s, k))
    gamma = np.zeros((s, width, k))
    for t in range(width - 1, -1, -1):
        n = active[t]
        gamma[:n, t] = alpha[:n, t] * beta[:n]
        if t:
            ahead = beta[:n] * seen[:n, t] / scale[:n, t][:, None]
            moves += alpha[:n, t - 1].T @ ahead
            beta[:n] = ahead @ model.moves.T
    moves *= model.moves
    used = np.arange(width) < length[:, None]
    which = table[:, :width][used]
    emits = np.column_stack([np.bincount(which, gamma[:, :, i][used], minlength=len(model.emits)) for i in range(k)])
    first = place == 0
    return gamma[first, 0].sum(axis=0), gamma[~first, 0].sum(axis=0), moves, emits, float(np.log(scale[used]).sum())


def likelihoods(model: Model, lines: list[np.ndarray]) -> np.ndarray:
    """log10 probability of each line: windows from every state, then chained."""
    table, length, text, place = windows(lines)
    width, k = int(length.max(initial=0)), len(model.start)
    seen = model.emits[table[:, :width]]
    state = np.repeat(np.eye(k)[None], len(table), axis=0)  # from each start to each state
    logs = np.zeros(len(table))
    for t in range(width):
        n = int(np.searchsorted(-length, -t))
        step = state[:n] * seen[:n, t][:, None, :] if t == 0 else (state[:n] @ model.moves) * seen[:n, t][:, None, :]
        total = step.max(axis=(1, 2))
        state[:n] = step / total[:, None, None]
        logs[:n] += np.log(total)
    out = np.zeros(len(lines))
    now = np.repeat(model.start[None], len(lines), axis=0)
    order = np.lexsort((text, place))
    for p in range(int(place.max(initial=-1)) + 1):
        a, b = np.searchsorted(place[order], [p, p + 1])
        some, who = order[a:b], text[order[a:b]]
        before = now[who] if p == 0 else now[who] @ model.moves
        after = np.einsum("ni,nij->nj", before, state[some])
        total = after.sum(axis=1)
        now[who] = after / total[:, None]
        out[who] += np.log(total) + logs[some]
    return out / np.log(10)


def train(lines: DataFrame, n_classes: int, states: int = STATES, steps: int = STEPS) -> Model:
    """Baum-Welch over the column ``classes``; a step's counts are added across partitions."""
    model = Model.first(states, n_classes)
    for _ in range(steps):
        shared = lines.sparkSession.sparkContext.broadcast((model.start, model.later, model.moves, model.emits))

        def step(batches, shared=shared):
            now, total = Model(*shared.value), None
            for batch in batches:
                for at in range(0, batch.num_rows, 2048):
                    some = [np.frombuffer(x.as_py(), np.uint32) for x in batch.column(0)[at : at + 2048]]
                    got = expected(now, some)
                    total = got if total is None else tuple(a + b for a, b in zip(total, got))
            if total is not None:
                flat = np.concatenate([total[0], total[1], total[2].reshape(-1), total[3].reshape(-1)])
                cells = np.flatnonzero(flat)
                yield pa.RecordBatch.from_arrays([pa.array(cells), pa.array(flat[cells])], names=["cell", "value"])

        got = lines.select("classes").mapInArrow(step, "cell long, value double").groupBy("cell").agg(F.sum("value").alias("value")).toArrow()
        shared.destroy()
        if not got.num_rows:
            break
        flat = np.zeros(states * (2 + states + n_classes))
        flat[got.column("cell").to_numpy()] = got.column("value").to_numpy()
        a, b, c = states, 2 * states, 2 * states + states * states
        model = Model.of_counts(flat[:a], flat[a:b], flat[b:c].reshape(states, states), flat[c:].reshape(n_classes, states))
    return model


def scored(docs: DataFrame, held_out, states: int = STATES, steps: int = STEPS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row."""
    spark = docs.sparkSession
    folder = scratch(spark)
    n_shards = shards(docs, 8 << 20)
    docs = docs.select("doc_id", "text", held_out.alias("held_out"))
    training = docs.where("not held_out")
    vocab = written(vocabulary(training, n_shards), folder, "vocabulary")
    n_docs = training.count()
    ids, n, tokens, types = _summary(vocab, n_shards)
    total, distinct = int(tokens.sum()) + n_docs, int(types.sum()) + bool(n_docs)
    n_own = max(min(OWN, len(n)), int(np.searchsorted(-n, -OWN_LEAST, "right")))  # ids come by falling count
    own = (ids[:n_own] & np.uint64(0xFF)).astype(np.int64)
    rest_tokens = tokens - np.bincount(own, n[:n_own], minlength=TAILS).astype(np.int64)
    rest_types = types - np.bincount(own, minlength=TAILS)
    room = np.log10(rest_tokens + rest_types + 1.0)
    classes = np.where(np.arange(len(ids)) < n_own, np.arange(len(ids)) + 1, n_own + 1 + (ids & np.uint64(0xFF)).astype(np.int64))
    order = np.argsort(ids)
    shared = spark.sparkContext.broadcast({"words": ids[order], "counts": n[order], "classes": classes[order], "end": n_docs, "room": room, "own": n_own})
    lines = written(_sequences(docs, shared, n_shards), folder, "lines")
    tidy(spark)
    sums = written(_rare_sums(lines.where("kind = 1").select("shard", "pack", "ids", "rows"), vocab), folder, "sums")
    forget(spark, folder, "vocabulary")
    tidy(spark)
    texts = lines.where("kind = 0")
    fitted = train(texts.where("not held_out"), n_own + 1 + TAILS, states, steps)
    model = spark.sparkContext.broadcast((fitted.start, fitted.later, fitted.moves, fitted.emits))
    per_token = float(np.log10(total + distinct + 1.0))

    def finish(key, mine, rare):
        m = mine.num_rows
        rows = mine.column("row").to_numpy()
        at = np.zeros(int(rows.max(initial=-1)) + 1, np.int64)
        at[rows] = np.arange(m)
        extra, known = np.zeros(m), np.zeros(m, np.int64)
        for r, s, k in zip(*(rare.column(c).to_pylist() for c in ("rows", "sums", "known"))):
            r = at[np.frombuffer(r, np.int32)]
            extra[r] += np.frombuffer(s, np.float64)
            known[r] += np.frombuffer(k, np.int32)
        lines = [np.frombuffer(x.as_py(), np.uint32) for x in mine.column("classes")]
        whole = np.concatenate([likelihoods(Model(*model.value), lines[a : a + 1024]) for a in range(0, m, 1024)]) if m else np.zeros(0)
        n = mine.column("n").to_numpy()
        return pa.table({
            "doc_id": mine.column("doc_id"), "held_out": mine.column("held_out"), "n_tokens": mine.column("n"),
            "n_known": pa.array(mine.column("known").to_numpy() + known),
            "base_score": pa.array(mine.column("base").to_numpy() + extra - n * per_token),
            "score": pa.array(whole + mine.column("within").to_numpy() + extra),
        })

    kind = docs.schema["doc_id"].dataType.simpleString()
    columns = texts.select("pack", "row", "doc_id", "held_out", "n", "known", "base", "within", "classes")
    out = columns.groupBy("pack").cogroup(sums.groupBy("pack")).applyInArrow(finish, f"doc_id {kind}, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return out.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), "base_score", "score")


def op7_hidden_markov(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(documents(spark, sf_dir), remainder(7) == 2)
