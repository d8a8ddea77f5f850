"""Probabilistic counting sketches of covering sets, and the greedy that only reads sketches (binary preference)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from waysite.functions.preference import MICRO
from waysite.operators.baselines import valued
from waysite.operators.bits import site_bits, sketched_bits
from waysite.operators.greedy import Placement

#: The prime of the hash family (2^31 - 1) and the published bias constant of the estimator.
PRIME, BIAS = 2_147_483_647, 0.77351


def hash_pair(copy: int) -> tuple[int, int]:
    """The multiplier and offset of a copy's hash: powers of a primitive root of the prime, so all differ."""
    return pow(16807, 3 * copy + 5, PRIME), pow(16807, 7 * copy + 11, PRIME)


def hashed(ids: Column, copy: Column | int, f: int) -> Column:
    """h(id) = (a * id + b) mod PRIME for a copy, in whole numbers."""
    if isinstance(copy, int):
        a, b = (F.lit(v).cast("long") for v in hash_pair(copy))
    else:
        a = F.element_at(F.array(*(F.lit(hash_pair(c)[0]).cast("long") for c in range(f))), copy + 1)
        b = F.element_at(F.array(*(F.lit(hash_pair(c)[1]).cast("long") for c in range(f))), copy + 1)
    return F.pmod(a * F.pmod(ids.cast("long"), F.lit(PRIME)) + b, F.lit(PRIME))


def position(h: Column) -> Column:
    """Trailing zero bits of a positive hash (31 for zero): position i has probability 2^-(i+1)."""
    return F.when(h == 0, F.lit(31)).otherwise(F.bit_count(h.bitwiseAND(-h) - 1))


def fm_sketch(members: DataFrame, key: str, item: str, f: int) -> DataFrame:
    """members(key, item) -> (key, copy, word): f words a key. Words are ORed on the map side, so the shuffle carries
    at most keys * f words a task, whatever the number of members."""
    copies = members.select(key, item).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(f - 1))))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), position(hashed(F.col(item), F.col("copy"), f)).cast("int"))
    return copies.select(key, "copy", bit.alias("bit")).groupBy(key, "copy").agg(F.bit_or("bit").alias("word"))


def lowest_zero(word: Column) -> Column:
    return F.bit_count(F.bitwise_not(word).bitwiseAND(word + 1) - 1)


def highest_one(word: Column) -> Column:
    """Number of bits up to the last one set (0 for an empty word)."""
    return F.when(word == 0, F.lit(0)).otherwise(F.length(F.bin(word)))


def fm_estimate(sketches: DataFrame, key: str, rule: str = "first_zero") -> DataFrame:
    """(key, copy, word) -> (key, estimate), from the mean over the copies of the rule's bit position: first_zero with
    the published constant, or last_set (the last marked bit). Empty sets give 0."""
    place = lowest_zero(F.col("word")) if rule == "first_zero" else highest_one(F.col("word"))
    mean = F.sum(place).cast("double") / F.count("*")
    value = F.pow(F.lit(2.0), mean) / (BIAS if rule == "first_zero" else 1.0)
    return sketches.groupBy(key).agg(F.when(F.bit_or("word") == 0, 0.0).otherwise(value).alias("estimate"))


def fm_union(sketches: DataFrame, key: str) -> DataFrame:
    """(copy, word) of the union of all keys."""
    return sketches.groupBy("copy").agg(F.bit_or("word").alias("word"))


def estimates(words: np.ndarray) -> np.ndarray:
    """first_zero estimates of word rows (n, f)."""
    low = np.bitwise_count(words ^ (words + 1)).astype(np.int64) - 1  # the bits below the lowest zero
    value = 2.0 ** low.mean(1) / BIAS
    return np.where((words == 0).all(1), 0.0, value)


#: Unions that are estimated at once, though the step may end among them.
UNIONS_AT_ONCE = 256


def sketch_steps(words: np.ndarray, ids: np.ndarray, k: int, prune: bool) -> tuple[list[int], int]:
    """Greedy over sketches: each step takes the site whose union with what is open has the largest estimate. With
    prune, sites are tried by their own estimates and the step ends at the first that cannot beat the best gain.
    Returns the sites and the number of unions estimated."""
    own = estimates(words)
    order = np.lexsort((-ids, -own))
    base, chosen, tried = np.zeros(words.shape[1], np.int64), [], 0
    free = np.ones(len(ids), bool)
    now = 0.0
    while len(chosen) < min(k, len(ids)):
        best, left, at = None, order[free[order]], 0
        while at < len(left) and not (prune and best is not None and own[left[at]] < best[0]):
            some = left[at : at + UNIONS_AT_ONCE]
            for i, gain in zip(some.tolist(), (estimates(words[some] | base) - now).tolist(), strict=True):
                if prune and best is not None and own[i] < best[0]:
                    break
                tried += 1
                if best is None or (gain, own[i], ids[i]) > (best[0], own[best[1]], ids[best[1]]):
                    best = (gain, i)
            at += len(some)
        chosen.append(int(ids[best[1]]))
        free[best[1]] = False
        base = base | words[best[1]]
        now = float(estimates(base[None])[0])
    return chosen, tried


def sketch_words(cover: DataFrame, f: int, members: DataFrame | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Site ids and their words: n * f numbers, the only thing that reaches the driver. members(path_id, route): the paths of
    the cover are routes, and what is counted are their members; where the cover can be bits of sites these are ORed, else
    each route's words are made once for all its sites."""
    bits = None if members is None else site_bits(cover)
    if bits is not None:
        words = sketched_bits(bits, members, [hash_pair(c) for c in range(f)], PRIME)
        bits.discard()
        marked = words.any(1)
        return bits.ids[marked], words[marked]
    if members is None:
        found = fm_sketch(cover, "site_id", "path_id", f)
    else:
        words = fm_sketch(members, "route", "path_id", f)
        found = cover.select("site_id", F.col("path_id").alias("r")).join(words, F.col("r") == F.col("route")).groupBy("site_id", "copy").agg(F.bit_or("word").alias("word"))
    rows = found.toPandas().sort_values(["site_id", "copy"])
    ids = np.unique(rows["site_id"].to_numpy()) if len(rows) else np.zeros(0, np.int64)
    return ids, rows["word"].to_numpy(np.int64).reshape(len(ids), f)


def greedy_place_sketch(cover: DataFrame, k: int, n_paths: int, f: int = 30, prune: bool = True, members: DataFrame | None = None) -> Placement:
    """The sketch greedy on a binary cover; the picked sites are valued on the cover itself."""
    ids, words = sketch_words(cover, f, members)
    chosen, tried = sketch_steps(words, ids, k, prune) if len(ids) else ([], 0)
    placed = valued(cover, chosen, n_paths)
    placed.evaluations = tried
    return placed


def error_of(estimate: float, true: int) -> float:
    return abs(estimate - true) / max(true, 1)


def micro_percent(utility: int, n_paths: int) -> float:
    return utility / MICRO / n_paths * 100 if n_paths else 0.0
