"""Choices of strategy from a matrix's profile; each choice only changes time, never results."""

from __future__ import annotations

from dataclasses import dataclass

from vpatterns.operators.clustering import DRIVER_LIMIT
from vpatterns.operators.prepare import MASK_BITS


@dataclass(frozen=True)
class Choice:
    workflow: str  # "masks" or "wide"
    similarity: str  # "signatures", "cells" or "gram"
    clustering: str  # "driver" or "distributed"
    merge: str  # "sequential", "tree" or "membership"


def choose(n_obs: int, n_vars: int, missing_pct: float, cap: int, n_levels: int = 1) -> Choice:
    """Masks as long as all variables fit one; few groups are swept, many merged as a tree.

    Dense rows of many levels are counted by Gram products: their pairs of cells would be
    the larger table. Beyond a mask only membership joins remain.
    """
    groups = -(-n_vars // max(1, cap))
    present = n_vars * (1 - missing_pct / 100)
    if n_vars > MASK_BITS:
        dense = present > 50 and n_vars * n_levels <= 10_000
        return Choice("wide", "gram" if dense else "cells", "driver" if n_vars <= DRIVER_LIMIT else "distributed", "membership")
    return Choice("masks", "signatures" if n_levels == 1 else "cells", "driver", "sequential" if groups <= 3 else "tree")
