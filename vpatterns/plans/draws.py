"""One draw of the experiment, run whole inside one task: group, mine, merge, measure.

A draw has few variables, so its rows are masks and their weights are summed over supersets
once: that table gives the support of every mask, whatever the number of rows was. The
workflow itself then runs on sets of masks: similarity, capped grouping, level-wise mining
of each group, sweeps over later groups with the strict threshold, closedness.
"""

from __future__ import annotations

import hashlib
import math
import time

import numpy as np

from vpatterns.operators.closed import superset_sums
from vpatterns.operators.clustering import fuse

#: Variables of a draw at most: the table of supports has 2**n entries of 8 bytes.
MOST = 24
STRATEGIES = ("similar", "dissimilar", "random")
REPEATS = 3


def digest(*parts) -> str:
    return hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()


def drawn(items: list[str], size: int, run: int, seed: int = 42) -> list[str]:
    """The draw's variables by name; the same as ``prepare.draw``."""
    return sorted(sorted(items, key=lambda x: (digest(seed, run, x), x))[:size])


def similarities(table: np.ndarray, n: int, n_obs: int) -> dict[tuple[int, int], float]:
    """Purity times concentration of each pair; presence has one joint level a pair."""
    out = {}
    for a in range(n):
        for b in range(a + 1, n):
            c = int(table[1 << a | 1 << b])
            if not c or n_obs <= 1:
                out[a, b] = 0.0
                continue
            p = c / n_obs
            out[a, b] = c / max(int(table[1 << a]), int(table[1 << b])) * (1 + p * math.log(p) / math.log(n_obs))
    return out


def groups_of(strategy: str, table: np.ndarray, names: list[str], n_obs: int, cap: int, linkage: str, seed: int = 42) -> list[list[int]]:
    n = len(names)
    if strategy == "random":
        order = sorted(range(n), key=lambda v: (digest(seed, names[v]), names[v]))
        parts = [sorted(order[i : i + cap]) for i in range(0, n, cap)]
    else:
        home, _ = fuse(similarities(table, n, n_obs), list(range(n)), cap, linkage, strategy)
        parts = [[v for v in range(n) if home[v] == c] for c in set(home.values())]
    return sorted(parts)


def frequent_sets(table: np.ndarray, members: list[int], least: int) -> np.ndarray:
    """Level by level: a set grows by a higher variable if all its subsets are frequent."""
    level = np.array([1 << v for v in members if table[1 << v] >= least], np.int64)
    found = [level]
    while len(level):
        made = [level[(level >> v) == 0] | (1 << v) for v in members if table[1 << v] >= least]
        made = np.concatenate(made) if made else level[:0]
        keep = np.ones(len(made), bool)
        for v in members:
            has = (made >> v & 1) == 1
            keep &= ~has | np.isin(made & ~(1 << v), level)
        level = made[keep]
        level = level[table[level] >= least]
        found.append(level)
    return np.concatenate(found)


def closed_in(table: np.ndarray, masks: np.ndarray, variables) -> np.ndarray:
    """Masks that no further one of the variables joins without losing a row."""
    keep = np.ones(len(masks), bool)
    for v in variables:
        keep &= ((masks >> v & 1) == 1) | (table[masks | (1 << v)] != table[masks])
    return masks[keep]


def merged(table: np.ndarray, local: list[np.ndarray], n: int, least: int) -> tuple[np.ndarray, dict]:
    """(closed patterns, work): from each group, sweep the later ones; a sweep combines what
    was there before it began. What a group starts is reduced to closed patterns.

    Work: pairs compared and kept, lengths of the row lists that the pairs would intersect,
    and comparisons for closedness if done pair by pair.
    """
    work = {"compared": 0, "kept": 0, "merge_rows": 0, "closed_compared": 0}
    final: list[np.ndarray] = []
    for i, current in enumerate(local):
        for more in local[i + 1 :]:
            work["compared"] += len(current) * len(more)
            work["merge_rows"] += int(table[current].sum()) * len(more) + int(table[more].sum()) * len(current)
            made = (current[:, None] | more[None, :]).reshape(-1)
            made = made[table[made] >= least]
            work["kept"] += len(made)
            current = np.concatenate([current, made])
        work["closed_compared"] += len(current) * (len(current) + sum(map(len, final)))
        final.append(closed_in(table, current, range(n)))
    return np.concatenate(final) if final else np.zeros(0, np.int64), work


def measured(masks: np.ndarray, w: np.ndarray, names: list[str], n_obs: int, least: int, cap: int, strategies=STRATEGIES, linkage: str = "average", repeats: int = REPEATS) -> list[tuple[str, str, float]]:
    """(strategy, metric, value) of one draw; seconds are the least of a few repeats."""
    n = len(names)
    if n > MOST:
        raise ValueError(f"a draw has {MOST} variables at most; mine more with operators.closed or plans.wide")
    table, out = superset_sums(masks, w, n), []
    for strategy in strategies:
        whole, merge = [], []
        for _ in range(repeats):
            began = time.perf_counter()
            groups = groups_of(strategy, table, names, n_obs, cap, linkage)
            local = [closed_in(table, frequent_sets(table, g, least), g) for g in groups]
            mined = time.perf_counter()
            final, work = merged(table, [x for x in local if len(x)], n, least)
            ended = time.perf_counter()
            whole.append(ended - began)
            merge.append(ended - mined)
        before = np.concatenate(local) if local else np.zeros(0, np.int64)
        values = {"whole_s": min(whole), "merge_s": min(merge), **work, "patterns": len(final), "local_patterns": len(before), "groups": len(groups)}
        if len(before):
            values["mean_support"] = float(table[before].mean())
            values["mean_length"] = float(np.bitwise_count(before).mean())
            values["extension_rate"] = 1 - float(np.isin(before, final).mean())
        out += [(strategy, k, float(v)) for k, v in values.items()]
    return out
