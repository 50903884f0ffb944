"""Choosing how to answer a query by the predicted cost."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import scan, search
from ..operators.index import TwinIndex
from ..operators.metrics import predicted_cost


@dataclass(frozen=True)
class Choice:
    """The engine picked and what each would cost in unit operations."""

    engine: str
    costs: dict[str, float]

    def explain(self) -> str:
        return "\n".join(f"{'*' if e == self.engine else ' '} {e}: {c:.3g}" for e, c in sorted(self.costs.items(), key=lambda x: x[1]))


def plan(n: int, d: int, k: int, m: int = 10, p: int = 50, exact_needed: bool = False, survivors: float = 0.5, has_index: bool = True) -> Choice:
    """``exact``, ``index`` or ``bounded`` (exact through the index; ``survivors`` is the share of clusters that its bounds are expected to leave)."""
    costs = {"exact": predicted_cost("exact", n, d, layers=0, k=k)["time"] + n * d}
    if has_index:
        costs["bounded"] = survivors * (n * d + k * n) + m * d
        if not exact_needed:
            costs["index"] = predicted_cost("index", n, d, layers=0, k=k, m=m, p=p)["time"] + n * d / m
    return Choice(min(costs, key=costs.get), costs)


def answer(sigs: DataFrame, query_id: int, k: int, index: TwinIndex | None = None, exact_needed: bool = False) -> tuple[DataFrame, Choice]:
    """``u, rank, sim`` of one node by the engine that :func:`plan` picks, and the choice.

    Rows and dimensions are counted from ``sigs``; layers and clusters are those of ``index``.
    """
    n, d = sigs.agg(F.count("*"), F.max(F.size("sig"))).head()
    m, p = (len(index.layers.centroids[0]), len(index.layers.centroids)) if index else (1, 1)
    picked = plan(n, d or 1, k, m, p, exact_needed, has_index=index is not None)
    if picked.engine == "exact":
        return scan.exact_scan(sigs, query_id, k), picked
    run = search.bounded_exact if picked.engine == "bounded" else search.index_search
    return run(index, query_id, k), picked
