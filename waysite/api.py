"""One place to ask from: a workload's relations as views, and placements and covers by their parameters."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from waysite.functions.preference import Preference, binary
from waysite.operators import detours as dt
from waysite.operators import exact as ex
from waysite.operators.greedy import Placement, PlacementSpec, greedy_place
from waysite.operators.index import Index, index_place
from waysite.operators.paths import path_arrays
from waysite.plans.planner import choose_strategy


@dataclass
class Workspace:
    """points(path_id, seq, node_id), sites(site_id[, cost, capacity]), edges, and stored detours or an index or both."""

    spark: SparkSession
    points: DataFrame
    sites: DataFrame
    edges: DataFrame
    detours: DataFrame | None = None
    index: Index | None = None
    _paths: int | None = field(default=None, repr=False)

    def n_paths(self) -> int:
        if self._paths is None:
            self._paths = self.points.select("path_id").distinct().count()
        return self._paths

    def cover_of(self, preference: Preference) -> DataFrame:
        """(path_id, site_id, metres, score): from the stored detours, or by searches made now."""
        if self.detours is not None:
            return dt.cover(self.detours, preference)
        return dt.cover_at_query(self.edges, self.points, self.sites, preference.tau, preference)

    def place_sites(self, tau: float, k: int | None = 5, preference: Preference | None = None, exact: bool = False, **limits) -> Placement:
        """The planner's way of answering: exact, greedy, index, index with sketches, or any k sites. limits: budget, quota,
        capacity, existing and mode as in PlacementSpec."""
        preference = preference or binary(tau)
        spec = PlacementSpec(k=k, **({"mode": "auto"} | limits))
        n_sites = self.sites.count() if exact else 0
        way = choose_strategy(spec, tau, preference.name == "binary", n_sites, self.n_paths(), self.index, exact)
        if way.name == "exact":
            return ex.optimal_placement(self.cover_of(preference), self.sites, k, self.n_paths())
        if way.name == "greedy":
            return greedy_place(self.cover_of(preference), spec, self.n_paths(), self.sites)
        outside = self.cover_of(preference) if way.level is None else None
        return index_place(self.index, spec, preference, self.n_paths(), outside, 30 if way.name == "index_sketch" else None, self.sites)

    def register(self, prefix: str = "") -> list[str]:
        """Temporary views of all relations; their names."""
        held = {"points": self.points, "sites": self.sites, "edges": self.edges, "detours": self.detours, "paths": path_arrays(self.points)}
        if self.index is not None:
            held |= {"cluster_members": self.index.member, "cluster_links": self.index.link, "cluster_paths": self.index.path, "clusters": self.index.clusters()}
        names = []
        for name, df in held.items():
            if df is not None:
                df.createOrReplaceTempView(prefix + name)
                names.append(prefix + name)
        return names
