"""The best k sites, on inputs small enough: by enumeration, by branch and bound, and as an integer program's rows."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waysite.operators.baselines import valued
from waysite.operators.bits import SiteBits, bit_sums, has_bit, site_bits
from waysite.operators.greedy import BIT_ROWS, Placement
from waysite.sources.tables import discard, materialize

#: Rows of the cover, paths of equal scores taken as one, on which branch and bound searches in one process (more are asked
#: through Spark), and sets that enumeration tries at most.
MOST_ROWS, MOST_SETS = 2_000_000, 5_000_000


def site_sets(sites: DataFrame, k: int) -> DataFrame:
    """All k-sets of sites as ascending columns s1..sk: a theta self-join, so for few sites only."""
    out = sites.select(F.col("site_id").alias("s1"))
    for i in range(2, k + 1):
        out = out.join(sites.select(F.col("site_id").alias(f"s{i}")), F.col(f"s{i - 1}") < F.col(f"s{i}"))
    return out


def enumerate_sets(cover: DataFrame, sites: DataFrame, k: int) -> DataFrame:
    """(members, utility) of every k-set."""
    n = sites.count()
    if comb(n, k) > MOST_SETS:
        raise ValueError(f"{comb(n, k)} sets are too many to try")
    sets = site_sets(sites, k).select(F.array(*(f"s{i}" for i in range(1, k + 1))).alias("members"))
    ids = np.sort(sites.select("site_id").toPandas()["site_id"].to_numpy()).astype(np.int64)
    best = grouped_rows(cover).mapInPandas(_set_utilities(ids, k), "members array<long>, utility long").groupBy("members").agg(F.sum("utility").alias("utility"))
    return sets.join(best, "members", "left").select("members", F.coalesce("utility", F.lit(0).cast("long")).alias("utility"))


def grouped_rows(cover: DataFrame) -> DataFrame:
    """(sites, scores, times): paths with equal scores everywhere as one, with their number."""
    each = cover.groupBy("path_id").agg(F.sort_array(F.collect_list(F.struct(F.col("site_id").cast("long").alias("site_id"), F.col("score").cast("long").alias("score")))).alias("row"))
    return each.groupBy("row").agg(F.count("*").alias("times")).select(F.col("row.site_id").alias("sites"), F.col("row.score").alias("scores"), "times")


def score_table(rows: pd.DataFrame, ids: np.ndarray) -> np.ndarray:
    """grouped_rows as scores, a line each and a column for each of the ascending ids; other sites are left out."""
    table = np.zeros((len(rows), len(ids)), np.int64)
    if len(rows):
        site, score = (np.concatenate(rows[c].to_list()) for c in ("sites", "scores"))
        line, known = np.repeat(np.arange(len(rows)), [len(x) for x in rows["sites"]]), np.isin(site, ids)
        table[line[known], np.searchsorted(ids, site[known])] = score[known]
    return table


def _set_utilities(ids: np.ndarray, k: int, at_once: int = 2_000):
    """What each k-set of the ids gets from a task's rows: a few sets and a few rows at a time."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sets = np.array(list(combinations(range(len(ids)), k)), np.int32).reshape(-1, k)
        total, any_rows = np.zeros(len(sets), np.int64), False
        for frame in frames:
            for a in range(0, len(frame), at_once):
                any_rows = True
                part = frame.iloc[a : a + at_once]
                table, times = np.ascontiguousarray(score_table(part, ids).T), part["times"].to_numpy()
                for b in range(0, len(sets), at_once):
                    best = table[sets[b : b + at_once, 0]]
                    for j in range(1, k):
                        np.maximum(best, table[sets[b : b + at_once, j]], out=best)
                    total[b : b + at_once] += best @ times
        if any_rows:
            for b in range(0, len(sets), 100_000):
                yield pd.DataFrame({"members": list(ids[sets[b : b + 100_000]]), "utility": total[b : b + 100_000]})

    return run


def optimal_placement(cover: DataFrame, sites: DataFrame, k: int, n_paths: int, method: str = "branch_bound") -> Placement:
    """The k sites of greatest utility; of equal ones the lexicographically smallest list."""
    if method == "enumerate":
        top = enumerate_sets(cover, sites, k).orderBy(F.col("utility").desc(), "members").first()
        return valued(cover, list(top["members"]) if top else [], n_paths)
    if method == "branch_bound":
        return valued(cover, branch_and_bound(cover, sites, k), n_paths)
    raise ValueError(f"unknown method {method}")


@dataclass(frozen=True)
class _Held:
    """Scores as a table of one process; a state is each line's best score so far."""

    table: np.ndarray
    times: np.ndarray

    def nothing(self) -> np.ndarray:
        return np.zeros(len(self.table), np.int64)

    def with_site(self, u: np.ndarray, i: int) -> np.ndarray:
        return np.maximum(u, self.table[:, i])

    def gains(self, u: np.ndarray, start: int) -> np.ndarray:
        return np.maximum(self.table[:, start:] - u[:, None], 0).T @ self.times


@dataclass(frozen=True)
class _Bits:
    """Different rows of bits and the sums of their scores; a state is the rows that no site so far covers."""

    ids: np.ndarray
    covering: np.ndarray  # the sites of the bits
    held: tuple[np.ndarray, np.ndarray]

    @staticmethod
    def of(cover: DataFrame, ids: np.ndarray) -> _Bits | None:
        bits: SiteBits | None = site_bits(cover) if cover.limit(BIT_ROWS + 1).count() > BIT_ROWS else None
        if bits is None:
            return None
        held = bits.merged()
        bits.discard()
        return None if held is None else _Bits(ids, bits.ids, held)

    def nothing(self) -> tuple[np.ndarray, np.ndarray]:
        return self.held

    def with_site(self, u: tuple[np.ndarray, np.ndarray], i: int) -> tuple[np.ndarray, np.ndarray]:
        at = np.flatnonzero(self.covering == self.ids[i])
        if not len(at):
            return u
        left = ~has_bit(u[0], int(at[0]))
        return u[0][left], u[1][left]

    def gains(self, u: tuple[np.ndarray, np.ndarray], start: int) -> np.ndarray:
        summed = dict(zip(self.covering.tolist(), bit_sums(*u, len(self.covering)).tolist(), strict=True))
        return np.array([summed.get(s, 0) for s in self.ids[start:].tolist()], np.int64)


@dataclass(frozen=True)
class _Asked:
    """Scores of any number, written; a state is the places of the sites so far, and gains are one job of Spark."""

    rows: DataFrame
    ids: np.ndarray

    def nothing(self) -> tuple[int, ...]:
        return ()

    def with_site(self, u: tuple[int, ...], i: int) -> tuple[int, ...]:
        return (*u, i)

    def gains(self, u: tuple[int, ...], start: int) -> np.ndarray:
        chosen = [int(self.ids[i]) for i in u]
        pairs = F.arrays_zip("sites", "scores")
        best = F.coalesce(F.array_max(F.transform(F.filter(pairs, lambda x: x["sites"].isin(chosen)), lambda x: x["scores"])), F.lit(0)) if chosen else F.lit(0)
        each = self.rows.select("times", best.cast("long").alias("u"), F.inline(pairs)).withColumnsRenamed({"sites": "site_id", "scores": "score"})
        summed = each.groupBy("site_id").agg(F.sum(F.col("times") * F.greatest(F.col("score") - F.col("u"), F.lit(0))).alias("gain")).toPandas()
        out, known = np.zeros(len(self.ids), np.int64), np.isin(summed["site_id"], self.ids)
        out[np.searchsorted(self.ids, summed["site_id"][known])] = summed["gain"][known]
        return out[start:]


def branch_and_bound(cover: DataFrame, sites: DataFrame, k: int) -> list[int]:
    """Depth first over sites in id order. The k - d best single gains bound what d chosen sites can still add, as
    gains never grow when sites are added. Large covers that can be bits of sites are searched as their different rows. Else
    paths with equal scores everywhere count once, with their number; up to MOST_ROWS
    rows the search is one process's, with more each of its gains is a job."""
    ids, rows = np.sort(sites.select("site_id").toPandas()["site_id"].to_numpy()), None
    scores = _Bits.of(cover, ids)
    if scores is None:
        rows = materialize(grouped_rows(cover), "exact-rows")
        if int(rows.agg(F.coalesce(F.sum(F.size("sites")), F.lit(0))).first()[0]) <= MOST_ROWS:
            taken = rows.toPandas()
            scores = _Held(score_table(taken, ids), taken["times"].to_numpy(np.int64))
        else:
            scores = _Asked(rows, ids)
    best_value, best_set = -1, ()

    def search(chosen: tuple[int, ...], u, value: int, start: int) -> None:
        nonlocal best_value, best_set
        left = k - len(chosen)
        if not left or start == len(ids):
            if value > best_value and not left:
                best_value, best_set = value, chosen
            return
        if len(ids) - start < left:
            return
        gains = scores.gains(u, start)
        order = np.sort(gains)[::-1]
        if value + order[:left].sum() <= best_value:
            return
        for i in range(start, len(ids) - left + 1):
            if value + gains[i - start] + order[: left - 1].sum() > best_value:
                search((*chosen, i), scores.with_site(u, i), value + int(gains[i - start]), i + 1)

    # A greedy start makes the bound bite early; a strictly better set replaces it, as does an equal smaller one below.
    u, start_set, value = scores.nothing(), [], 0
    for _ in range(min(k, len(ids))):
        gains = scores.gains(u, 0)
        gains[start_set] = -1
        i = int(np.argmax(gains))
        start_set.append(i)
        value += int(gains[i])
        u = scores.with_site(u, i)
    best_value = value - 1
    search((), scores.nothing(), 0, 0)
    if rows is not None:
        discard(rows)
    return [int(ids[i]) for i in (best_set or tuple(sorted(start_set)))]


def ilp_rows(cover: DataFrame, sites: DataFrame, k: int) -> DataFrame:
    """The integer program in rows (kind, name, variable, coefficient, bound).

    Variables: x<site> opens a site, y<path>_<site> serves a path there. Objective: scores of the y. Constraints:
    each y at most its x; a path's y at most 1 in sum; the x at most k in sum."""
    y = F.concat(F.lit("y"), F.col("path_id"), F.lit("_"), F.col("site_id"))
    x = F.concat(F.lit("x"), F.col("site_id"))
    row = lambda kind, name, variable, coefficient, bound: (F.lit(kind).alias("kind"), name.alias("name"), variable.alias("variable"), coefficient.cast("long").alias("coefficient"), bound.cast("long").alias("bound"))
    none = F.lit(None)
    objective = cover.select(*row("objective", F.lit("max"), y, F.col("score"), none))
    opened = cover.select(*row("open", F.concat(F.lit("o_"), y), y, F.lit(1), F.lit(0))).unionByName(cover.select(*row("open", F.concat(F.lit("o_"), y), x, F.lit(-1), F.lit(0))))
    once = cover.select(*row("once", F.concat(F.lit("p_"), F.col("path_id")), y, F.lit(1), F.lit(1)))
    count = sites.select(*row("count", F.lit("k"), x, F.lit(1), F.lit(k)))
    return objective.unionByName(opened).unionByName(once).unionByName(count)


def brute_force(scores: dict[tuple[int, int], int], ids: list[int], k: int) -> tuple[int, tuple[int, ...]]:
    """Plain enumeration in Python, for tests."""
    paths = {p for p, _ in scores}
    return max(((sum(max((scores.get((p, s), 0) for s in chosen), default=0) for p in paths), chosen) for chosen in combinations(sorted(ids), k)), key=lambda v: (v[0], [-s for s in v[1]]))
