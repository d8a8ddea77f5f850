"""Which way a query is answered, decided before any plan is built."""

from __future__ import annotations

from dataclasses import dataclass
from math import comb

from waysite.operators.greedy import PlacementSpec
from waysite.operators.index import Index

#: Sets that an exact answer may try, and paths from which sketches pay.
FEW_SETS, MANY_PATHS = 200_000, 10_000_000


@dataclass(frozen=True)
class Strategy:
    name: str  # exact, greedy, index, index_sketch, arbitrary
    level: int | None = None


def choose_strategy(spec: PlacementSpec, tau: float, binary: bool, n_sites: int, n_paths: int, index: Index | None = None, exact: bool = False) -> Strategy:
    """Exact on request and small; without an index, or below its least tau, the plain greedy; at or above its largest
    tau any k sites; sketches for plain binary queries over very many paths; else the index."""
    plain = spec.budget is None and spec.quota is None and not spec.capacity and not spec.existing
    if exact:
        if plain and spec.k and comb(n_sites, spec.k) <= FEW_SETS:
            return Strategy("exact")
        raise ValueError("too large for an exact answer")
    if index is None or tau < index.levels[0].tau_lo:
        return Strategy("greedy")
    level = next((v.level for v in index.levels if v.tau_lo <= tau < v.tau_hi), None)
    if level is None:
        return Strategy("arbitrary")
    return Strategy("index_sketch" if plain and binary and n_paths >= MANY_PATHS else "index", level)
