"""One entry point for any matrix: its profile chooses the forms, which never change the result."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators import prepare
from vpatterns.plans import wide
from vpatterns.plans.pipeline import discover
from vpatterns.plans.planner import Choice, choose
from vpatterns.sources.workloads import Matrix


def planned(matrix: Matrix, cap: int) -> Choice:
    p = prepare.profile(matrix.cells, matrix.n_obs).first()
    return choose(matrix.n_obs, p["n_vars"], p["missing_pct"] or 0.0, cap)


def find(matrix: Matrix, min_sup: float, cap: int = 4, strategy: str = "similar", linkage: str = "average") -> DataFrame:
    """items (sorted), support of all closed frequent patterns of constant coherence over all variables."""
    cells = Matrix(prepare.cut(matrix.cells), matrix.n_obs)
    choice = planned(cells, cap)
    if choice.workflow == "wide":
        return wide.discover_wide(cells, min_sup, cap, strategy, linkage=linkage)
    variables = prepare.cut(prepare.numbered(cells.cells.select("item").distinct()))
    found = discover(cells, variables, min_sup, cap, strategy, choice.merge, linkage).patterns
    names = F.array(*[F.lit(r["item"]) for r in variables.orderBy("var_id").collect()])  # at most a mask's places
    return found.select(F.transform(prepare.bits("mask"), lambda i: F.get(names, i)).alias("items"), "support")
