"""Closed patterns of a dense matrix counted by length; none is listed.

Where rows hold many of the variables there are billions of closed patterns, too many to make
one at a time. Variables are taken from the most frequent on. A choice of the first ones is
kept if it is frequent and closed among them: no larger pattern whose part there is another
one is lost, as closing only adds. The last ones, ``TABLE`` at most, are counted for many kept
choices at once in a table of all their masks: sums over supersets give supports, and what all
rows of a mask share tells whether one of the first variables would join it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Variables whose choices are dealt out to tasks, those that are chosen in one step, and those of a table.
DEAL, STEP, TABLE = 10, 8, 13
#: Choices counted in one table.
BATCH = 48

SCHEMA = "n_vars int, patterns long, least_support long, most_support long, total_support long"


def closed_choices(part: np.ndarray, pre: np.ndarray, w: np.ndarray, n: int, least: int) -> np.ndarray:
    """Masks of n variables that are frequent and closed among ``pre``, where rows hold ``part`` of the n.

    ``pre``: the same bits and those of earlier variables that are not in the pattern, above the n.
    """
    total = np.bincount(part, w, 1 << n)
    shared = np.full(1 << n, -1, np.int64)
    np.bitwise_and.at(shared, part, pre)
    for i in range(n):
        halves, both = total.reshape(-1, 2, 1 << i), shared.reshape(-1, 2, 1 << i)
        halves[:, 0] += halves[:, 1]
        both[:, 0] &= both[:, 1]
    return np.flatnonzero((total >= least) & (shared == np.arange(1 << n)))


class Tally:
    """Patterns, least, most and total support by length, from tables of the last ``low`` variables."""

    def __init__(self, low: int, least: int):
        self.low, self.least = low, least
        self.patterns, self.total, self.most = (np.zeros(65, np.int64) for _ in range(3))
        self.lowest = np.full(65, np.iinfo(np.int64).max)
        self.size = np.bitwise_count(np.arange(1 << low, dtype=np.uint32)).astype(np.uint8)
        self.waiting, self.lengths = [], []

    def add(self, low: np.ndarray, free: np.ndarray, w: np.ndarray, part: np.ndarray, choices: np.ndarray, length: int) -> None:
        """Choices of a node; ``free``: first variables of each row outside the node's pattern, and below ``STEP`` bits the part."""
        while len(choices):
            now, choices = choices[: BATCH - len(self.lengths)], choices[BATCH - len(self.lengths) :]
            row, at = np.nonzero((part[:, None] & now) == now)
            self.waiting.append((low[row], at + len(self.lengths), free[row] & ~now[at], w[row]))
            self.lengths += (np.bitwise_count(now) + length).tolist()
            if len(self.lengths) == BATCH:
                self.flush()

    def flush(self) -> None:
        if not self.lengths:
            return
        low, at, free, w = (np.concatenate(x) for x in zip(*self.waiting))
        b = len(self.lengths)
        cell = low * b + at
        kind = next(k for k in (np.int16, np.int32, np.int64) if np.bincount(at, w).max(initial=0) <= np.iinfo(k).max)
        total = np.zeros(b << self.low, kind)
        np.add.at(total, cell, w.astype(kind))
        wide = np.uint32 if not len(free) or int(free.max()) < 1 << 32 else np.uint64
        shared = np.full(b << self.low, np.iinfo(wide).max, wide)
        np.bitwise_and.at(shared, cell, free.astype(wide))
        for i in range(self.low):
            halves, both = total.reshape(-1, 2, b << i), shared.reshape(-1, 2, b << i)
            halves[:, 0] += halves[:, 1]
            both[:, 0] &= both[:, 1]
        keep = (shared == 0) & (total >= self.least)
        for i in range(self.low):
            halves, kept = total.reshape(-1, 2, b << i), keep.reshape(-1, 2, b << i)
            kept[:, 0] &= halves[:, 0] != halves[:, 1]
        found = np.flatnonzero(keep)
        s, n = total[found], (self.size[:, None] + np.array(self.lengths, np.uint8)).ravel()[found]
        self.patterns += np.bincount(n, minlength=65)
        self.total += np.bincount(n, s, 65).astype(np.int64)
        less, more = s < self.lowest[n], s > self.most[n]
        np.minimum.at(self.lowest, n[less], s[less])
        np.maximum.at(self.most, n[more], s[more])
        self.waiting, self.lengths = [], []

    def table(self) -> pa.Table:
        self.flush()
        n = np.flatnonzero(self.patterns)
        n = n[n > 0]  # not the empty pattern
        return pa.table({"n_vars": pa.array(n, pa.int32()), "patterns": self.patterns[n], "least_support": self.lowest[n], "most_support": self.most[n], "total_support": self.total[n]})


def count(masks: np.ndarray, w: np.ndarray, m: int, least: int, done: int, have: int, low: int) -> Tally:
    """All closed patterns whose part of the first ``done`` variables is ``have``, from the rows that hold it."""
    tally, first = Tally(low, least), m - low
    stack = [(masks, w, done, have)]
    while stack:
        masks, w, done, have = stack.pop()
        step = min(STEP, first - done)
        part = masks >> done & (1 << step) - 1
        # earlier variables outside the pattern stand above the step's
        pre = part | (masks & (1 << done) - 1 & ~have) << step
        choices = closed_choices(part, pre, w, step, least)
        if done + step == first:
            tally.add(masks >> first, pre, w, part, choices, have.bit_count())
            continue
        for c in map(int, choices):
            keep = part & c == c
            stack.append((masks[keep], w[keep], done + step, have | c << done))
    return tally


def closed_counts(rows: DataFrame, m: int, least: int) -> DataFrame:
    """Number and supports by length of the closed patterns of m variables, 62 at most, from distinct rows (mask, w).

    Variable 0 is the most frequent. The driver holds the rows' distinct parts of ``DEAL`` variables.
    """
    low = min(TABLE, m)
    deal = min(DEAL, m - low)
    part = F.col("mask").bitwiseAND((1 << deal) - 1)
    parts = rows.groupBy(part.alias("part")).agg(F.sum("w").alias("w")).toArrow()
    own = parts.column("part").to_numpy()
    choices = closed_choices(own, own, parts.column("w").to_numpy(), deal, least)
    asked = F.array(*(F.lit(int(c)).cast("long") for c in choices))
    each = rows.select("mask", "w", F.explode(F.filter(asked, lambda c: part.bitwiseAND(c) == c)).alias("choice"))

    def one(key, t):
        masks, w = t.column("mask").to_numpy(), t.column("w").to_numpy()
        return count(masks, w, m, least, deal, key[0].as_py(), low).table()

    found = each.repartition(max(1, len(choices)), "choice").groupBy("choice").applyInArrow(one, SCHEMA)
    return found.groupBy("n_vars").agg(F.sum("patterns").alias("patterns"), F.min("least_support").alias("least_support"), F.max("most_support").alias("most_support"), F.sum("total_support").alias("total_support"))
