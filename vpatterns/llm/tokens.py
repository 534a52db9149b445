"""Token counts of sections: whole documents are encoded once, with offsets.

A text's sections are given as character spans. Tokens come from one encoding of the
whole text; each is attributed to a section by merging the two sorted lists of spans.
A token that crosses a boundary goes by an explicit rule: ``first`` (the section of its
first character), ``most`` (the section with most of its characters, the earlier on a
tie) or ``shared`` (every section gets the part of the token that its characters are).
Characters between sections belong to ``""``.

Defined cases: null and empty texts have no tokens and no rows in ``attribute``, one row
of zeros in the query; several tokens of one character (bytes) all have that character's
span; sections that overlap or run past the text are refused; repeated rows agree; other
columns are not read.
"""

from __future__ import annotations

import json
import re
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.llm.bpe import byte_symbols
from vpatterns.llm.common import documents

RULES = ("first", "most", "shared")
CACHE = 400_000
#: Text in which Python's and the tokenizer's character classes agree, and
#: the byte-level split for it.
_PLAIN = re.compile(r"[^\t\n\r\x20-\x7e\xa1-\xff]")
_RUN = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-zªµºÀ-ÖØ-öø-ÿ]+| ?[0-9²³¹¼½¾]+| ?[^\sA-Za-zªµºÀ-ÖØ-öø-ÿ0-9²³¹¼½¾]+|\s+(?!\S)|\s+")


class SpanEncoder:
    """Character spans of a whole text's tokens; runs are encoded once and cached.

    Texts with characters beyond the plain ones, and tokenizers with another split, go
    through the library as they are.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.library.encode_special_tokens = True
        with open(path) as f:
            spec = json.load(f)
        split = spec.get("pre_tokenizer") or {}
        self.runs = split.get("type") == "ByteLevel" and split.get("use_regex", True) and not split.get("add_prefix_space") and not spec.get("normalizer")
        self.bytes = byte_symbols()
        self.starts: dict[str, tuple[int, ...]] = {}
        self.ends: dict[str, tuple[int, ...]] = {}

    def add(self, run: str) -> None:
        if len(self.starts) >= CACHE:
            self.starts.clear()
            self.ends.clear()
        lead = run[0] == " "
        if run.isascii() and not run[lead : lead + 1].isspace() and len(run) > lead:
            found = self.library.model.tokenize("Ġ" + run[1:] if lead else run)  # the space's symbol has two bytes
            ends = tuple([t.offsets[1] - lead for t in found])
            self.starts[run], self.ends[run] = (0, *ends[:-1]), ends
            return
        raw = run.encode()
        spans = [t.offsets for t in self.library.model.tokenize("".join([self.bytes[b] for b in raw]))]
        if not run.isascii():  # offsets count bytes; every byte stands in one character
            # the library counts the bytes of the symbols, two for each beyond ASCII
            width = [len(self.bytes[b].encode()) for b in raw]
            at = np.repeat(np.arange(len(run)), [len(c.encode()) for c in run])
            place = np.repeat(np.arange(len(raw)), width)
            spans = [(int(at[place[a]]), int(at[place[b - 1]]) + 1) for a, b in spans]
        else:
            width = np.cumsum([0] + [len(self.bytes[b].encode()) for b in raw]).tolist()
            back = {w: i for i, w in enumerate(width)}
            spans = [(back[a], back[b]) for a, b in spans]
        self.starts[run], self.ends[run] = (tuple(x) for x in zip(*spans))

    def __call__(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        if not self.runs or _PLAIN.search(text):
            spans = np.array(self.library.encode(text, add_special_tokens=False).offsets, np.int64).reshape(-1, 2)
            return spans[:, 0], spans[:, 1]
        runs = _RUN.findall(text)
        starts, ends = self.starts, self.ends
        first = []
        for r in runs:
            if r not in starts:
                self.add(r)
            first.append(starts[r])
        try:
            last = [ends[r] for r in runs]
        except KeyError:  # the cache started anew within this text
            for r in dict.fromkeys(runs):
                self.add(r)
            last = [ends[r] for r in runs]
        n = np.fromiter(map(len, first), np.int64, len(runs))
        size = np.fromiter(map(len, runs), np.int64, len(runs))
        at = np.repeat(np.cumsum(size) - size, n)
        total = int(n.sum())
        return at + np.fromiter(chain.from_iterable(first), np.int64, total), at + np.fromiter(chain.from_iterable(last), np.int64, total)


def line_sections(text: str) -> list[tuple[str, int, int]]:
    """Sections of a plain text: its first line, its last line, and the body between them."""
    head = text.find("\n") + 1
    if not head:
        return [("head", 0, len(text))]
    tail = text.rstrip("\n").rfind("\n") + 1
    out = [("head", 0, head), ("body", head, tail), ("tail", max(head, tail), len(text))]
    return [s for s in out if s[1] < s[2]]


def allocate(starts: np.ndarray, ends: np.ndarray, sections: list[tuple[str, int, int]], rule: str, length: int) -> tuple[list[str], np.ndarray, int]:
    """(section names, tokens of each, tokens that cross a boundary) of one text."""
    if any(b < a for _, a, b in sections) or any(x[2] > y[1] for x, y in zip(sections, sections[1:])) or (sections and (sections[0][1] < 0 or sections[-1][2] > length)):
        raise ValueError("sections must be sorted, disjoint and inside the text")
    names, bounds, at = [], [], 0
    for name, a, b in sections:  # gaps become sections of no name
        if a > at:
            names.append("")
            bounds.append(at)
        names.append(name)
        bounds.append(a)
        at = b
    if at < length or not names:
        names.append("")
        bounds.append(at)
    edges = np.array([*bounds, max(length, at)])
    last = np.maximum(ends - 1, starts)
    first_at = np.clip(np.searchsorted(edges, starts, "right") - 1, 0, len(names) - 1)
    last_at = np.clip(np.searchsorted(edges, last, "right") - 1, 0, len(names) - 1)
    crossing = np.flatnonzero(first_at != last_at)
    if rule == "first" or not len(crossing):
        return names, np.bincount(first_at, minlength=len(names)).astype(float), len(crossing)
    whole = np.bincount(np.delete(first_at, crossing), minlength=len(names)).astype(float)
    for i in crossing:
        parts = [(min(ends[i], edges[k + 1]) - max(starts[i], edges[k]), k) for k in range(first_at[i], last_at[i] + 1)]
        if rule == "most":
            whole[max(parts, key=lambda p: (p[0], -p[1]))[1]] += 1
        else:
            for n, k in parts:
                whole[k] += n / (ends[i] - starts[i])
    return names, whole, len(crossing)


def attribute(df: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", sections=line_sections, rule: str = "most") -> DataFrame:
    """id, n_tokens, n_crossing and sections (name, tokens) of every row; no shuffle."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")

    def step(batches):
        encoder = SpanEncoder(tokenizer)
        kind = pa.list_(pa.struct([("name", pa.string()), ("tokens", pa.float64())]))
        for batch in batches:
            totals, crossed, each = [], [], []
            for text in batch.column(1).to_pylist():
                text = text or ""
                starts, ends = encoder(text)
                names, n, over = allocate(starts, ends, sections(text) if text else [], rule, len(text))
                totals.append(len(starts))
                crossed.append(over)
                each.append([{"name": a, "tokens": float(b)} for a, b in zip(names, n)] if text else [])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(totals, pa.int64()), pa.array(crossed, pa.int64()), pa.array(each, kind)], names=[id_col, "n_tokens", "n_crossing", "sections"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, text_col).mapInArrow(step, f"`{id_col}` {kind}, n_tokens long, n_crossing long, sections array<struct<name: string, tokens: double>>")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op6_offset_attribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = attribute(documents(spark, sf_dir), default_tokenizer())
    of = lambda name: F.aggregate(F.filter("sections", lambda s: s["name"] == name), F.lit(0.0), lambda a, s: a + s["tokens"]).cast("long")
    return got.select("doc_id", "n_tokens", "n_crossing", *[of(n).alias(f"{n}_tokens") for n in ("head", "body", "tail")])
