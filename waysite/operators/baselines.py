"""Placements that the greedy is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waysite.operators.detours import cover as make_cover
from waysite.operators.detours import site_weights
from waysite.operators.greedy import Placement, PlacementSpec, greedy_place, prefix_utilities, seeded_order


def valued(cover: DataFrame, ids: list[int], n_paths: int) -> Placement:
    """A given list of sites as a placement: each step's gain on the cover, from one pass over its rows."""
    placed = Placement(n_paths=n_paths)
    before = 0
    for k, u in enumerate(prefix_utilities(cover, ids), 1):
        placed.steps.append((k, ids[k - 1], u - before, u))
        before = u
    return placed


def top_weight_place(cover: DataFrame, k: int, n_paths: int) -> Placement:
    """The most covered sites, overlap ignored."""
    rows = site_weights(cover).orderBy(F.col("weight").desc(), F.col("site_id").desc()).limit(k).collect()
    return valued(cover, [r["site_id"] for r in rows], n_paths)


def static_place(static_detours: DataFrame, cover: DataFrame, preference, k: int, n_paths: int) -> Placement:
    """Sites picked for users who stay at one node, valued on the real paths."""
    placed = greedy_place(make_cover(static_detours, preference), PlacementSpec(k=k), n_paths)
    return valued(cover, placed.sites, n_paths)


def arbitrary_place(sites: DataFrame, cover: DataFrame, k: int, n_paths: int) -> Placement:
    """Any k sites: enough where every site serves every path."""
    return valued(cover, [r["site_id"] for r in sites.orderBy("site_id").limit(k).collect()], n_paths)


def random_place(sites: DataFrame, cover: DataFrame, k: int, n_paths: int, seed: int = 1) -> Placement:
    rows = sites.orderBy(seeded_order(F.col("site_id"), seed)).limit(k).collect()
    return valued(cover, [r["site_id"] for r in rows], n_paths)
