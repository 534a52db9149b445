"""Language identification with bit-sliced Bloom filters over character trigrams.

One filter serves all languages: each of its positions holds a mask with one bit a
language, so the AND of a trigram's positions names every language that has it. A
text's score for a language is the number of its trigrams whose bit is set, less the
number that false positives alone would set (the filter's fill to the power of the
number of hashes), over what they leave. A trigram belongs to a language when its rate
there is at least a tenth of the highest rate of any language, so borrowed lines do
not carry a whole vocabulary over.

Trigrams are of lower-cased letters; any other character is a word boundary.

Defined cases: null texts and texts without letters give ``und`` with score 0; texts
whose trigrams no language has get the language with most training trigrams, score 0;
null languages are not learned from; with no training rows every text is ``und``;
repeated rows agree; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.llm.common import documents, remainder

#: Positions of the filter at least and at most, positions for each kept trigram, hashes of one.
POSITIONS, MOST_POSITIONS, ROOM, HASHES = 1 << 20, 1 << 24, 8, 3
#: A trigram's rate in a language over its highest rate, and its least count, to be kept.
SHARE, LEAST = 0.1, 2
#: Bits used of one 64-bit mask; more languages take more masks a position.
BITS = 62


def letter_table() -> np.ndarray:
    return np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)


def trigrams(texts: list[str], letters: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(trigram codes, number of the text of each) of all texts, in order."""
    low = [t.lower() for t in texts]
    codes = np.frombuffer(("  ".join(["", *low, ""])).encode("utf-32-le", "surrogatepass"), np.uint32)
    owner = np.repeat(np.arange(len(low)), [len(t) + 2 for t in low])
    codes = np.where(letters[codes], codes, 32).astype(np.int64)
    middle = np.flatnonzero(codes[1:-1] != 32)
    grams = codes[middle] << 42 | codes[middle + 1] << 21 | codes[middle + 2]
    return grams, owner[middle - 1]


def places(grams: np.ndarray, number: int, positions: int) -> np.ndarray:
    x = grams.astype(np.uint64) + np.uint64((0x9E3779B97F4A7C15 * (number + 1)) & (2**64 - 1))
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return ((x ^ (x >> np.uint64(31))) & np.uint64(positions - 1)).astype(np.int64)


def text_runs(texts: list, limit: int = 500_000):
    """Runs of texts with about ``limit`` characters each."""
    start = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t or "") > limit:
            yield start, i
            start, size = i, 0
        size += len(t or "")
    yield start, len(texts)


def gram_counts(train: DataFrame) -> DataFrame:
    """lang, gram, n over all training rows; each partition adds up its own first."""

    def step(batches):
        letters, total = letter_table(), {}
        for batch in batches:
            langs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in text_runs(texts):
                groups: dict[str, list[str]] = {}
                for lang, text in zip(langs[a:b], texts[a:b]):
                    groups.setdefault(lang, []).append(text or "")
                for lang, some in groups.items():
                    values, n = np.unique(trigrams(some, letters)[0], return_counts=True)
                    if lang in total:
                        both, at = np.unique(np.concatenate([total[lang][0], values]), return_inverse=True)
                        values, n = both, np.bincount(at, np.concatenate([total[lang][1], n])).astype(np.int64)
                    total[lang] = values, n
        for lang, (values, n) in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(values), pa.string()), pa.array(values), pa.array(n.astype(np.int64))], names=["lang", "gram", "n"])

    rows = train.select("lang", "text").mapInArrow(step, "lang string, gram long, n long")
    return rows.groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def filter_size(kept: DataFrame, least: int = POSITIONS, most: int = MOST_POSITIONS) -> tuple[int, int]:
    """(positions, least count of a trigram) from the counted trigrams, so that the filter never fills.

    It has ROOM positions a trigram. Where that is more than ``most``, the size of the model
    that every task holds, trigrams below a power of two go: the rarest of more than
    ``most`` / ROOM, which few texts hold.
    """
    level = F.floor(F.log2("n")).cast("int")
    ladder = sorted(((r["l"], r["m"]) for r in kept.groupBy(level.alias("l")).agg(F.count(F.lit(1)).alias("m")).collect()), reverse=True)
    held, cut = 0, 0
    for at, m in ladder:
        if held and (held + m) * ROOM > most:
            cut = 1 << (at + 1)
            break
        held += m
    positions = least
    while positions < min(most, held * ROOM):
        positions *= 2
    return positions, cut


def build_filter(train: DataFrame, positions: int | None = None, hashes: int = HASHES, most: int = MOST_POSITIONS) -> tuple[list[str], np.ndarray]:
    """(languages, masks by word and position); what is collected is bounded by the filter.

    ``positions``: by default the number that the counted trigrams need (``filter_size``).
    """
    counts = gram_counts(train).persist()
    totals = {r["lang"]: r["n"] for r in counts.groupBy("lang").agg(F.sum("n").alias("n")).collect() if r["n"]}
    langs = sorted(totals, key=lambda x: (-totals[x], x))
    if not langs:
        counts.unpersist()
        return [], np.zeros((1, positions or POSITIONS), np.int64)
    index = F.create_map(*[F.lit(x) for i, lang in enumerate(langs) for x in (lang, i)])
    size = F.create_map(*[F.lit(x) for lang in langs for x in (lang, float(totals[lang]))])
    rated = counts.select("gram", index[F.col("lang")].alias("at"), "n", (F.col("n") / size[F.col("lang")]).alias("rate"))
    top = rated.groupBy("gram").agg(F.max("rate").alias("top"), F.collect_list(F.struct("at", "n", "rate")).alias("each"))
    kept = top.select("gram", F.explode("each").alias("e"), "top").where(f"e.n >= {LEAST} and e.rate >= {SHARE} * top")
    if positions is None:
        positions, least = filter_size(kept.groupBy("gram").agg(F.max("e.n").alias("n")), min(POSITIONS, most), most)
        kept = kept.where(F.col("e.n") >= least)
    bit = F.expr(f"shiftleft(1L, cast(e.at % {BITS} as int))")
    masks = kept.groupBy("gram", F.expr(f"cast(e.at div {BITS} as int)").alias("word")).agg(F.bit_or(bit).alias("mask"))

    def spread(batches):
        for batch in batches:
            grams = batch.column(0).to_numpy()
            for h in range(hashes):
                yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(places(grams, h, positions)), batch.column(2)], names=["word", "place", "mask"])

    cells = masks.select("gram", "word", "mask").mapInArrow(spread, "word int, place long, mask long").groupBy("word", "place").agg(F.bit_or("mask").alias("mask"))
    got = cells.toArrow()
    table = np.zeros((-(-len(langs) // BITS), positions), np.int64)
    table[got.column("word").to_numpy(), got.column("place").to_numpy()] = got.column("mask").to_numpy()
    counts.unpersist()
    return langs, table


def identify(df: DataFrame, langs: list[str], table: np.ndarray, id_col: str = "doc_id", text_col: str = "text", hashes: int = HASHES) -> DataFrame:
    """id, lang_pred, score of every row; no shuffle."""
    positions = table.shape[1]
    fill = [float(np.mean(table[i // BITS] >> (i % BITS) & 1)) ** hashes for i in range(len(langs))]
    narrow = table.astype(np.uint8) if len(langs) <= 8 else table
    shared = df.sparkSession.sparkContext.broadcast(narrow)

    def step(batches):
        letters, masks, wrong = letter_table(), shared.value, np.array(fill)
        for batch in batches:
            texts = batch.column(1).to_pylist()
            names, scores = [], []
            for a, b in text_runs(texts):
                grams, owner = trigrams([t or "" for t in texts[a:b]], letters)
                n = np.bincount(owner, minlength=b - a)
                hits = np.zeros((b - a, max(1, len(langs))))
                at = [places(grams, h, positions) for h in range(hashes)]
                for w in range(len(masks) if langs else 0):
                    found = masks[w][at[0]]
                    for p in at[1:]:
                        found = found & masks[w][p]
                    for i in range(w * BITS, min(len(langs), (w + 1) * BITS)):
                        hits[:, i] = np.bincount(owner, found >> (i - w * BITS) & 1, minlength=b - a)
                if langs:
                    hits = np.clip((hits - n[:, None] * wrong) / np.maximum(1 - wrong, 1e-9), 0, None)
                best = hits.argmax(axis=1)
                order = np.sort(hits, axis=1)
                top, second = order[:, -1], order[:, -2] if order.shape[1] > 1 else 0 * order[:, -1]
                score = np.where(top > 0, top / np.maximum(top + second, 1e-9), 0.0)
                names += [langs[i] if k and langs else "und" for i, k in zip(best, n)]
                scores.append(np.where((n > 0) & bool(langs), score, 0.0))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(np.concatenate(scores))], names=[id_col, "lang_pred", "score"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, text_col).mapInArrow(step, f"`{id_col}` {kind}, lang_pred string, score double")


def training_rows(df: DataFrame) -> DataFrame:
    return df.where((remainder(4) != 2) & F.col("lang").isNotNull())


def accepted(df: DataFrame, langs: list[str], table: np.ndarray, least: float = 0.52) -> DataFrame:
    """The rows whose text has letters and whose language stands out by ``least`` or more."""
    row = F.struct(*[F.col(c) for c in df.columns])
    got = identify(df.select(row.alias("_row"), "text"), langs, table, "_row")
    return got.where((F.col("lang_pred") != "und") & (F.col("score") >= least)).select("_row.*").select(*df.columns)


def op2_bitmask_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    langs, table = build_filter(training_rows(docs))
    got = identify(docs, langs, table)
    return got.select("doc_id", (remainder(4) == 2).alias("held_out"), "lang_pred", "score")
