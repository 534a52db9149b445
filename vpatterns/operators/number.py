"""How many closed patterns a dense matrix has, where not even their lengths are asked for.

A pattern is seen by the variables it leaves out. It is closed if each of them is missing from a
row that misses none but them, and its support is the weight of all such rows. Variables are put
out or into the pattern one at a time, each row keeping what it misses of the others. Once what
is out makes the pattern frequent and closed whatever happens to k variables, its 2**k
completions are counted at once; choices that cannot become both are left. So the work goes with
the number of rows that differ in what they add, not with the number of patterns.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators.tally import closed_choices

#: Variables whose choices are dealt out to tasks, and those up to which choices not known to be frequent are counted in a table.
DEAL, SMALL = 10, 11
#: Rows of choices that are taken up together, and how many of these; up to ``FEW`` rows all their unions are formed.
WIDTHS, BATCH, FEW = (6, 8, 9, 10, 16, 24, 32, 64), 512, 10


def union(x: np.ndarray) -> int:
    return int(np.bitwise_or.reduce(x, initial=0))


def lean(left: np.ndarray, adds: np.ndarray) -> np.ndarray:
    """What rows add beyond the smaller rows within them; rows stand on the last axis, the smallest first."""
    n = min(left.shape[-1], WIDTHS[-1])
    inner, outer = left[..., None, :n], left[..., :, None]
    within = ((outer & inner) == inner) & (np.arange(left.shape[-1])[:, None] > np.arange(n))
    return adds & ~np.bitwise_or.reduce(np.where(within, adds[..., None, :n], 0), axis=-1)


class Number:
    """Counts the closed patterns with a support of ``least`` or more.

    A choice has rows (``left``: undecided variables that the row misses, ``adds``: all it misses, ``w``), ``open_``: variables
    that are out and not yet missing from a row that fits, ``und``: undecided ones, ``good``: those of them that a row of their own covers.
    """

    def __init__(self, least: int):
        self.least, self.found = least, 0
        self.pools, self.waiting = {n: [] for n in WIDTHS}, dict.fromkeys(WIDTHS, 0)

    def count(self, left: np.ndarray, adds: np.ndarray, w: np.ndarray, open_: int, und: int) -> int:
        stack = [(left, adds, w, open_, und, 0, 0, 1)]
        while stack:
            self._one(stack, *stack.pop())
            self._drain(False)
        self._drain(True)
        return self.found

    def _one(self, stack, left, adds, w, open_, und, good, base, times) -> None:
        """A choice that may be infrequent (``w``, and ``base``: weight of rows that fit for sure) or has many rows."""
        ends = left == 0
        if ends.any():
            open_ &= ~union(adds[ends])
            if w is not None:
                base, w = base + int(w[ends].sum()), w[~ends]
            left, adds = left[~ends], adds[~ends]
        if w is not None:
            if base >= self.least:
                w = None
            elif base + int(w.sum()) < self.least:
                return
        good |= union(left[left & left - 1 == 0])
        if w is None:
            adds = adds & (open_ | und & ~good)
            left, adds = left[adds != 0], adds[adds != 0]
            order = np.argsort(np.bitwise_count(left), kind="stable")
            left = left[order]
            adds = lean(left, adds[order])
            left, adds = left[adds != 0], adds[adds != 0]
        held, used = union(adds), union(left)
        if open_ & ~held:
            return
        free = und & good & ~used
        und &= ~free & ~(und & ~good & ~held)
        good &= und
        times <<= free.bit_count()
        if not und:
            # nothing is open, as no row is left
            self.found += times if w is None else 0
            return
        if w is None and len(left) <= WIDTHS[-1]:
            rows = np.zeros((2, 1, WIDTHS[-1]), np.int64)
            rows[:, 0, : len(left)] = left, adds
            self._put(*rows, *(np.array([x], np.int64) for x in (open_, und, good, times)))
            return
        places = np.array([p for p in range(und.bit_length()) if und >> p & 1])
        if w is not None and len(places) <= SMALL:
            self.found += times * self._table(left, adds, w, open_, places, base)
            return
        bit = 1 << int(places[(left[:, None] >> places & 1).sum(0).argmax()])
        without, rest = left & bit == 0, und & ~bit
        stack.append((left[without], adds[without], None if w is None else w[without], open_, rest, good & ~bit, base, times))
        stack.append((left & ~bit, adds, w, open_ if good & bit else open_ | bit, rest, good & ~bit, base, times))

    def _table(self, left, adds, w, open_, places, base) -> int:
        k = len(places)
        cell = ((left[:, None] >> places & 1) << np.arange(k)).sum(1)
        total = np.bincount(cell, w, 1 << k).astype(np.int64)
        total[0] += base
        covered = np.zeros(1 << k, np.int64)
        np.bitwise_or.at(covered, cell, adds)
        asked = np.full(1, open_, np.int64)
        for i, p in enumerate(places):
            halves, both = total.reshape(-1, 2, 1 << i), covered.reshape(-1, 2, 1 << i)
            halves[:, 1] += halves[:, 0]
            both[:, 1] |= both[:, 0]
            asked = np.concatenate([asked, asked | 1 << p])
        return int(np.count_nonzero((asked & ~covered == 0) & (total >= self.least)))

    def _drain(self, last: bool) -> None:
        """Takes up choices in full batches, those with few rows first; at last all, then those with many rows first."""
        while True:
            n = next((n for n in WIDTHS if self.waiting[n] >= BATCH), 0) or (last and next((n for n in reversed(WIDTHS) if self.waiting[n]), 0))
            if not n:
                return
            taken, size = [], 0
            while self.pools[n] and size < BATCH:
                taken.append(self.pools[n].pop())
                size += len(taken[-1][0])
            self.waiting[n] -= size
            (self._few if n <= FEW else self._many)(*(np.concatenate(x) for x in zip(*taken)))

    def _few(self, left, adds, open_, und, good, times) -> None:
        """All completions of many frequent choices by the rows that fit.

        Good variables may be out at will, others only as rows ask. Completions that fit exactly the rows of
        a set are those that fit these at least, less those that fit more of them with the same others out.
        """
        b, n = left.shape
        out, covered = np.zeros((1, b), np.int64), np.zeros((1, b), np.int64)
        for i in range(n):
            out, covered = np.concatenate([out, out | left[:, i]]), np.concatenate([covered, covered | adds[:, i]])
        ways = np.left_shift(1, np.bitwise_count(good & ~out), dtype=np.int64)
        out &= und & ~good
        for i in range(n):
            halves, same = ways.reshape(-1, 2, b << i), out.reshape(-1, 2, b << i)
            halves[:, 0] -= np.where(same[:, 0] == same[:, 1], halves[:, 1], 0)
        self.found += int((np.where((open_ | out) & ~covered == 0, ways, 0).sum(axis=0) * times).sum())

    def _many(self, left, adds, open_, und, good, times) -> None:
        """One step of many frequent choices; rows that are no more have no bits."""
        open_ = open_ & ~np.bitwise_or.reduce(np.where(left == 0, adds, 0), axis=1)
        good = good | np.bitwise_or.reduce(np.where(left & left - 1 == 0, left, 0), axis=1)
        adds = np.where(left == 0, 0, adds & (open_ | und & ~good)[:, None])
        order = np.argsort(np.where(adds == 0, 64, np.bitwise_count(left)), axis=1, kind="stable")
        left, adds = np.take_along_axis(left, order, 1), np.take_along_axis(adds, order, 1)
        adds = lean(left, adds)
        left = np.where(adds == 0, 0, left)
        held, used = np.bitwise_or.reduce(adds, axis=1), np.bitwise_or.reduce(left, axis=1)
        free = und & good & ~used
        und = und & ~free & ~(und & ~good & ~held)
        times = times << np.bitwise_count(free).astype(np.int64)
        can = open_ & ~held == 0
        self.found += int(times[can & (und == 0)].sum())
        good = good & und
        rows = np.count_nonzero(adds, axis=1)
        on = can & (und != 0) & (rows <= FEW)
        self._put(*(x[on] for x in (left, adds, open_, und, good, times)))
        on = can & (rows > FEW)
        if not on.any():
            return
        left, adds, open_, und, good, times = (x[on] for x in (left, adds, open_, und, good, times))
        most, bit = np.zeros(len(und), np.int64), np.zeros(len(und), np.int64)
        every = union(und)
        for p in range(every.bit_length()):
            if every >> p & 1:
                n = np.count_nonzero(left & 1 << p, axis=1)
                more = n > most
                most[more], bit[more] = n[more], 1 << p
        at = bit[:, None]
        rest, stays = und & ~bit, good & ~bit
        self._put(np.where(left & at, 0, left), np.where(left & at, 0, adds), open_, rest, stays, times)
        self._put(left & ~at, adds, np.where(good & bit, open_, open_ | bit), rest, stays, times)

    def _put(self, left, adds, *others) -> None:
        """Into the pools by their number of rows."""
        rows, before = np.count_nonzero(adds, axis=1), -1
        for n in (n for n in WIDTHS if n <= left.shape[1]):
            own = (rows > before) & (rows <= n)
            before = n
            if own.any():
                order = np.argsort(adds[own] == 0, axis=1, kind="stable")[:, :n]
                self.pools[n].append((np.take_along_axis(left[own], order, 1), np.take_along_axis(adds[own], order, 1), *(x[own] for x in others)))
                self.waiting[n] += len(order)


def closed_number(rows: DataFrame, m: int, least: int) -> int:
    """Number of the closed patterns of m variables, 62 at most, from distinct rows (mask, w).

    Variable 0 is the most frequent. The driver holds the rows' distinct parts of ``DEAL`` variables.
    """
    deal, every = min(DEAL, m), (1 << m) - 1
    first = (1 << deal) - 1
    part = F.col("mask").bitwiseAND(first)
    parts = rows.groupBy(part.alias("part")).agg(F.sum("w").alias("w")).toArrow()
    own = parts.column("part").to_numpy()
    choices = closed_choices(own, own, parts.column("w").to_numpy(), deal, least)
    asked = F.array(*(F.lit(int(c)).cast("long") for c in choices)).cast("array<long>")
    each = rows.select("mask", "w", F.explode(F.filter(asked, lambda c: part.bitwiseAND(c) == c)).alias("choice"))

    def one(key, t):
        missing, have = every & ~t.column("mask").to_numpy(), key[0].as_py()
        w = t.column("w").to_numpy()
        n = Number(least).count(missing & ~first, missing, w, first & ~have, every & ~first)
        if not have and int(w.sum()) >= least and union(missing) == every:
            n -= 1  # the empty pattern
        return pa.table({"n": pa.array([n], pa.int64())})

    found = each.repartition(max(1, len(choices)), "choice").groupBy("choice").applyInArrow(one, "n long")
    return found.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
