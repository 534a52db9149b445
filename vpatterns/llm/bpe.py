"""BPE encoding and decoding by tree concatenation.

A text is cut at special tokens, normalised and split into runs as the tokenizer
file says. Short runs are encoded once per worker and cached. A long unsplit run
is cut in halves down to leaves; two encoded neighbours are joined by encoding a
window of tokens around the seam again, doubling it until its first and last
tokens are those the two sides had already. Every adjacent pair of the result then
is a pair of some valid encoding, and a sequence all of whose adjacent pairs are
valid is the encoding of its text, so the result equals one pass over the run.

Texts with an unsplit run above ``PARALLEL`` symbols go a way of their own: their long
runs are cut into pieces that tasks encode in parallel, and a text's pieces are joined at
their seams afterwards.

Defined cases: null and empty texts have no tokens and decode to the empty string;
repeated rows give repeated results; an empty table gives an empty table; columns
other than the id and the text are not read, so their names cannot clash.
"""

from __future__ import annotations

import json
import re

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.llm.common import documents

#: Text in which Python's and the tokenizer's character classes agree.
_PLAIN = re.compile(r"[^\t\n\r\x20-\x7e\xa1-\xff]")
_PLAIN_RUN = re.compile(
    r"'s|'t|'re|'ve|'m|'ll|'d|[a-zªµºß-öø-ÿ]+|[0-9²³¹¼½¾]|[^\sa-zªµºß-öø-ÿ0-9²³¹¼½¾]+"
)
#: Runs above so many symbols are encoded as a tree; its leaves have half as many at most.
LEAF = 32
#: Runs above so many symbols are encoded by several tasks, in pieces of so many.
PARALLEL, PIECE = 1 << 14, 1 << 12
#: Runs of each of a worker's two caches: when the newer is full it takes the place of the older.
CACHE = 100_000


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in a byte-level vocabulary."""
    direct = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table, spare = [""] * 256, 256
    for b in range(256):
        if b in direct:
            table[b] = chr(b)
        else:
            table[b], spare = chr(spare), spare + 1
    return table


class RunEncoder:
    """Encodes one run with merge ranks; long runs by joining encoded halves."""

    def __init__(self, model: dict, leaf: int = LEAF):
        pairs = (tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"])
        own = {s: s for s in model["vocab"]}  # one string for each symbol, in merges and vocabulary
        self.ranks = {(own.get(a, a), own.get(b, b)): i for i, (a, b) in enumerate(pairs)}
        self.suffix = model.get("end_of_word_suffix") or ""
        self.leaf = leaf
        self.bytes = byte_symbols()

    def symbols(self, run: str) -> list[str]:
        # a printable ASCII character stands for itself
        out = list(run) if run.isascii() and run.isprintable() else [self.bytes[b] for b in run.encode()]
        if out:
            out[-1] += self.suffix
        return out

    def merged(self, parts: list[str]) -> list[str]:
        rank, worst, parts = self.ranks.get, len(self.ranks), list(parts)
        keys = [rank(p, worst) for p in zip(parts, parts[1:])]
        while keys:
            best = min(keys)
            if best == worst:
                break
            i = keys.index(best)
            parts[i] += parts.pop(i + 1)
            # a merge only changes the pairs with its two neighbours
            del keys[i]
            if i < len(keys):
                keys[i] = rank((parts[i], parts[i + 1]), worst)
            if i:
                keys[i - 1] = rank((parts[i - 1], parts[i]), worst)
        return parts

    def pieces(self, token: str) -> list[str]:
        """A token's symbols; the suffix belongs to the last."""
        if self.suffix and token.endswith(self.suffix) and len(token) > len(self.suffix):
            body = list(token[: -len(self.suffix)])
            body[-1] += self.suffix
            return body
        return list(token)

    def joined(self, left: list[str], right: list[str]) -> list[str]:
        k = 1
        while True:
            a, b = left[-k:], right[:k]
            window = self.merged([s for t in a + b for s in self.pieces(t)])
            open_left = len(left) > k and window[0] != a[0]
            open_right = len(right) > k and window[-1] != b[-1]
            if not (open_left or open_right):
                return left[:-k] + window + right[k:]
            k *= 2

    def tree(self, symbols: list[str]) -> list[str]:
        """Leaves first, then neighbours joined level by level."""
        step = max(2, self.leaf // 2)
        level = [self.merged(symbols[i : i + step]) for i in range(0, len(symbols), step)]
        while len(level) > 1:
            pairs = [self.joined(*level[i : i + 2]) for i in range(0, len(level) - 1, 2)]
            level = pairs + level[len(level) & ~1 :]
        return level[0] if level else []

    def __call__(self, run: str) -> list[str]:
        symbols = self.symbols(run)
        return self.tree(symbols) if len(symbols) > self.leaf else self.merged(symbols)


class TextEncoder:
    """A whole tokenizer file: special tokens, normaliser, runs, ids, decoding."""

    def __init__(self, path: str, leaf: int = LEAF):
        from tokenizers import Tokenizer

        with open(path) as f:
            spec = json.load(f)
        # the library only normalises and cuts here, so it need not hold the vocabulary a second time
        self.library = Tokenizer.from_str(json.dumps(spec | {"model": spec["model"] | {"vocab": {}, "merges": []} | {k: None for k in ("unk_token",) if k in spec["model"]}, "added_tokens": []}))
        self.vocab = spec["model"]["vocab"]
        self.run = RunEncoder(spec["model"], leaf)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        names = sorted(map(re.escape, self.special), key=len, reverse=True)
        self.cut = re.compile("(" + "|".join(names) + ")") if names else None
        self.names = {i: t for t, i in (self.vocab | self.special).items()}
        self.cache: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}

    def runs(self, part: str) -> list[str]:
        if not _PLAIN.search(part):
            return _PLAIN_RUN.findall(part.lower())
        text = self.library.normalizer.normalize_str(part)
        back = {s: b for b, s in enumerate(self.run.bytes)}
        mapped = [piece for piece, _ in self.library.pre_tokenizer.pre_tokenize_str(text)]
        return [bytes(back[c] for c in m).decode() for m in mapped]

    def known(self, run: str) -> tuple[int, ...]:
        """Ids of a run that the newer cache does not hold."""
        ids = self.older.get(run) or tuple([self.vocab[t] for t in self.run(run)])
        if len(self.cache) >= CACHE:
            self.older = self.cache.copy()
            self.cache.clear()
        if len(run) <= 64:
            self.cache[run] = ids
        return ids

    def decoded(self, ids: list[int]) -> str:
        return " ".join(map(self.names.__getitem__, ids))

    def parts(self, text: str, most: int):
        """The text's special tokens and runs in order: (ids, decoded), or a run of more than ``most`` symbols itself.

        What lies between long runs comes as one entry; there is one at least.
        """
        ids, empty = [], True
        for part in self.cut.split(text) if self.cut and "<|" in text else [text]:
            if part in self.special:
                ids.append(self.special[part])
                continue
            for run in self.runs(part):
                if len(run) * 4 > most and len(run.encode()) > most:
                    if ids:
                        yield ids, self.decoded(ids)
                        ids = []
                    yield run
                    empty = False
                    continue
                ids.extend(self.cache.get(run) or self.known(run))
        if ids or empty:
            yield ids, self.decoded(ids)

    def __call__(self, text: str) -> tuple[list[int], str]:
        """(ids, decoded text) of one text."""
        ids = []
        parts = self.cut.split(text) if self.cut and "<|" in text else [text]
        cache = self.cache
        for part in parts:
            if part in self.special:
                ids.append(self.special[part])
                continue
            for run in self.runs(part):
                ids += cache.get(run) or self.known(run)
        return ids, self.decoded(ids)


def encode(df: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", leaf: int = LEAF, parallel: int = PARALLEL, piece: int = PIECE) -> DataFrame:
    """id, ids (array of int) and decoded text of every row, in one pass.

    Only texts with a run of more than ``parallel`` characters without a blank are shuffled.
    """
    rows = df.select(id_col, F.coalesce(text_col, F.lit("")).alias(text_col))
    # a byte level symbol is a byte: four a character at most
    longest = F.array_max(F.transform(F.split(text_col, r"\s+"), F.length))
    long = (F.length(text_col) * 4 > parallel) & (longest * 4 > parallel)
    short = _encode_rows(rows.where(~long), tokenizer, id_col, text_col, leaf)
    return short.unionByName(_encode_pieces(rows.where(long), tokenizer, id_col, text_col, leaf, parallel, piece))


def _encode_pieces(df: DataFrame, tokenizer: str, id_col: str, text_col: str, leaf: int, parallel: int, piece: int) -> DataFrame:
    """The same for texts with long runs: pieces of a run are encoded apart and joined at their seams."""
    kind = df.schema[id_col].dataType.simpleString()
    names = ["row", "no", "run", "last", "key", "ids", "decoded", "symbols"]

    def cut(batches):
        encoder, number = None, TaskContext.get().partitionId() << 33  # most tasks have no such text
        for batch in batches:
            encoder = encoder or TextEncoder(tokenizer, leaf)
            kinds = [pa.int64(), pa.int32(), pa.int32(), pa.bool_(), batch.schema.field(0).type, pa.list_(pa.int32()), pa.string(), pa.string()]
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                out = []
                for run, found in enumerate(encoder.parts(text or "", parallel)):
                    if isinstance(found, str):
                        raw = found.encode()
                        for at in range(0, len(raw), piece):
                            out.append((number, len(out), run, at + piece >= len(raw), key, None, None, "".join(encoder.run.bytes[b] for b in raw[at : at + piece])))
                    else:
                        out.append((number, len(out), run, False, key, *found, None))
                number += 1
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*out)) or [()] * 8, kinds)], names=names)

    def encoded(batches):
        encoder = None
        for batch in batches:
            encoder = encoder or TextEncoder(tokenizer, leaf)
            got = []
            for symbols, last in zip(batch.column(7).to_pylist(), batch.column(3).to_pylist()):
                some = None if symbols is None else list(symbols)
                if some and last:
                    some[-1] += encoder.run.suffix
                got.append(None if some is None else encoder.run.tree(some))
            yield pa.RecordBatch.from_arrays([*batch.columns[:7], pa.array(got, pa.list_(pa.string()))], names=[*names[:7], "tokens"])

    def joined(key, t):
        encoder = TextEncoder(tokenizer, leaf)
        t = t.sort_by("no")
        ids, decoded, open_, now = [], [], [], None

        def close():
            level = open_[:]
            open_.clear()
            while len(level) > 1:
                pairs = [encoder.run.joined(*level[i : i + 2]) for i in range(0, len(level) - 1, 2)]
                level = pairs + level[len(level) & ~1 :]
            for tokens in level:
                ids.extend(encoder.vocab[x] for x in tokens)
                decoded.append(" ".join(tokens))

        for run, some, text, tokens in zip(*(t.column(c).to_pylist() for c in ("run", "ids", "decoded", "tokens"))):
            if run != now:
                close()
            now = run
            if tokens is not None:
                open_.append(tokens)
            else:
                ids.extend(some)
                decoded.append(text)
        close()
        return pa.table([t.column("key").slice(0, 1), pa.array([ids], pa.list_(pa.int32())), pa.array([" ".join(decoded)], pa.string())], names=[id_col, "ids", "decoded"])

    rows = df.select(id_col, text_col).mapInArrow(cut, f"row long, no int, run int, last boolean, key {kind}, ids array<int>, decoded string, symbols string")
    pieces = rows.repartition("row", "no").mapInArrow(encoded, f"row long, no int, run int, last boolean, key {kind}, ids array<int>, decoded string, tokens array<string>")
    return pieces.groupBy("row").applyInArrow(joined, f"`{id_col}` {kind}, ids array<int>, decoded string")


def _encode_rows(df: DataFrame, tokenizer: str, id_col: str, text_col: str, leaf: int) -> DataFrame:
    def step(batches):
        encoder = TextEncoder(tokenizer, leaf)
        for batch in batches:
            keys, texts = batch.column(0), batch.column(1)
            for at in range(0, batch.num_rows, 256):
                got = [encoder(t or "") for t in texts[at : at + 256].to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [keys[at : at + 256], pa.array([g[0] for g in got], pa.list_(pa.int32())), pa.array([g[1] for g in got], pa.string())],
                    names=[id_col, "ids", "decoded"],
                )

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, text_col).mapInArrow(step, f"`{id_col}` {kind}, ids array<int>, decoded string")


def decode(df: DataFrame, tokenizer: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """id and decoded text of rows of ids: the tokens joined by a space, special ones kept."""

    def step(batches):
        with open(tokenizer) as f:
            spec = json.load(f)
        names = {i: t for t, i in spec["model"]["vocab"].items()} | {t["id"]: t["content"] for t in spec["added_tokens"]}
        for batch in batches:
            texts = [" ".join(names[i] for i in ids or [] if i in names) for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=[id_col, "decoded"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, ids_col).mapInArrow(step, f"`{id_col}` {kind}, decoded string")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op9_bpe_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = encode(documents(spark, sf_dir), default_tokenizer())
    return got.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join("ids", " "), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
