"""Binary covers with one row a path: the sites that cover it as bits.

A path between far nodes is covered by every site near any of its ways, so on networks of thousands of nodes a cover of
pairs has thousands of rows a path. As bits a path takes an eighth of a byte a site, and gains, sketches and utilities
are sums and ORs over whole rows of bits."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.core.broadcast import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waysite.functions.preference import MICRO
from waysite.operators.detours import FAR, Matrix, route_arrays
from waysite.operators.distance import Roads
from waysite.operators.greedy import Placement
from waysite.operators.index import Index
from waysite.operators.sketch import PRIME, hash_pair, sketch_steps
from waysite.sources.tables import materialize

#: Nodes of a network whose distances still go to every worker: as 16-bit numbers 128 MB, and as much for the ways back.
MOST_PACKED_NODES = 8_000
#: Nodes that are searched for at once, and bits that are unpacked at once.
GOALS_AT_ONCE, BITS_AT_ONCE = 16, 1 << 23
NEVER = (1 << 16) - 1
#: Rows of paths, clusters and links that a task has at once.
MET_AT_ONCE = 4_000_000


@dataclass(frozen=True)
class PackedCover:
    """rows(path_id, bits): bit i, the first of a byte being its highest, tells whether ids[i] covers the path."""

    rows: DataFrame
    ids: np.ndarray
    weight: np.ndarray  # paths that each site covers

    @staticmethod
    def of(rows: DataFrame, ids: np.ndarray, name: str) -> PackedCover:
        """A cover that is written and counted."""
        return PackedCover.counted(materialize(rows, name), ids)

    @staticmethod
    def counted(rows: DataFrame, ids: np.ndarray) -> PackedCover:
        return PackedCover(rows, ids, _summed(rows, len(ids), lambda _, bits: bits))

    def n_rows(self) -> int:
        """Pairs of a path and a site that covers it."""
        return int(self.weight.sum())

    def of_paths(self, where) -> PackedCover:
        return PackedCover.counted(self.rows.where(where), self.ids)

    def of_sites(self, kept: np.ndarray) -> PackedCover:
        """The cover by the sites for which kept says so; the bits of others stay in the rows and count for nothing."""
        return replace(self, weight=np.where(kept, self.weight, 0))

    def place(self, k: int, n_paths: int, candidates: np.ndarray | None = None) -> Placement:
        """The greedy's k sites among the candidates (None: sites that cover any path), with its ties: larger gain,
        larger weight, larger id. After each pick only the paths newly served are taken off the gains. The first steps are
        those of any smaller k, and so are their seconds."""
        began = time.perf_counter()
        free = self.weight > 0 if candidates is None else np.isin(self.ids, candidates)
        gain, out, chosen = self.weight.copy(), Placement(n_paths=n_paths), []
        while len(chosen) < k and free.any():
            at = np.flatnonzero(free)
            best = int(at[np.lexsort((self.ids[at], self.weight[at], gain[at]))[-1]])
            now = int(gain[best])
            if now and len(chosen) + 1 < k:
                gain = gain - _summed(self.rows, len(self.ids), _newly(list(chosen), best))
            free[best] = False
            chosen.append(best)
            out.steps.append((len(chosen), int(self.ids[best]), now * MICRO, out.utility + now * MICRO))
            out.seconds.append(time.perf_counter() - began)
        return out

    def utilities(self, sites: list[int]) -> list[int]:
        """Total score of the paths over the first one, two, ... of the sites, from one pass."""
        at = [int(i) for i in np.searchsorted(self.ids, sites)]
        width = len(at)

        def first(_: np.ndarray, bits: np.ndarray) -> np.ndarray:
            held = np.stack([_bit(bits, i) for i in at], 1)
            return np.packbits(held & (np.cumsum(held, 1) == 1), axis=1)

        return [int(x) * MICRO for x in np.cumsum(_summed(self.rows, width, first))] if width else []

    def utility_of(self, sites: list[int]) -> int:
        found = self.utilities(sites)
        return found[-1] if found else 0

    def sketch_words(self, f: int) -> tuple[np.ndarray, np.ndarray]:
        """As sketch.sketch_words: for each copy and place of a bit, the rows of paths whose hash ends there are ORed."""
        size, pairs = -(-len(self.ids) // 8), [hash_pair(c) for c in range(f)]
        if not size:
            return self.ids, np.zeros((0, f), np.int64)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = np.zeros((f, 32, -(-size // 8)), np.uint64)
            for paths, bits in _arrays(batches, size):
                words = _as_words(bits)
                for c, (a, b) in enumerate(pairs):
                    h = (a * (paths % PRIME) + b) % PRIME
                    low = h & -h
                    place = np.where(h == 0, 31, np.log2(np.maximum(low, 1)).astype(np.int64))
                    for p in np.unique(place):
                        held[c, p] |= np.bitwise_or.reduce(words[place == p], axis=0)
            c, p = np.nonzero(held.any(2))
            yield pa.RecordBatch.from_arrays([pa.array(c * 32 + p, pa.int64()), pa.array([held[i, j].tobytes() for i, j in zip(c, p, strict=True)], pa.binary())], ["at", "bits"])

        words = np.zeros((len(self.ids), f), np.int64)
        for r in self.rows.mapInArrow(run, "at long, bits binary").collect():
            on = np.unpackbits(np.frombuffer(r["bits"], np.uint8)[:size])[: len(self.ids)].astype(np.int64)
            words[:, r["at"] // 32] |= on << (r["at"] % 32)
        covering = self.weight > 0
        return self.ids[covering], words[covering]

    def place_sketch(self, k: int, n_paths: int, f: int = 30, sketched: tuple[np.ndarray, np.ndarray] | None = None) -> Placement:
        """As sketch.greedy_place_sketch. sketched: the cover's sketch_words, where they are made already."""
        ids, words = self.sketch_words(f) if sketched is None else sketched
        chosen, tried = sketch_steps(words, ids, k, True) if len(ids) else ([], 0)
        out = Placement(n_paths=n_paths, evaluations=tried)
        for step, u in enumerate(self.utilities(chosen), 1):
            out.steps.append((step, chosen[step - 1], u - out.utility, u))
        return out


def _bit(bits: np.ndarray, i: int) -> np.ndarray:
    return (bits[:, i >> 3] >> (7 - (i & 7))) & 1 == 1


def _newly(before: list[int], site: int) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """The rows of paths that the site covers and none of those before does."""

    def rows(_: np.ndarray, bits: np.ndarray) -> np.ndarray:
        new = _bit(bits, site)
        for i in before:
            new &= ~_bit(bits, i)
        return bits[new]

    return rows


def _as_words(bits: np.ndarray) -> np.ndarray:
    wide = np.zeros((len(bits), -(-bits.shape[1] // 8) * 8), np.uint8)
    wide[:, : bits.shape[1]] = bits
    return wide.view(np.uint64)


def _arrays(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(path ids, bits as bytes of one row each) of each batch."""
    for batch in batches:
        if batch.num_rows:
            column = batch.column(1).cast(pa.large_binary())
            at = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
            yield batch.column(0).to_numpy(), np.frombuffer(column.buffers()[2], np.uint8)[at[0] : at[-1]].reshape(len(column), size)


def _summed(rows: DataFrame, width: int, chosen: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
    """Over all tasks, how many of the rows of bits that chosen(path ids, bits) gives have each of the first `width` bits."""
    from_bytes, at_once = -(-width // 8), 255
    if not width:
        return np.zeros(0, np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(from_bytes * 8, np.int64)
        for paths, bits in _each(batches):
            found = chosen(paths, bits)
            for a in range(0, len(found), at_once):  # sums of 255 bits fit a byte
                total += np.add.reduce(np.unpackbits(found[a : a + at_once], axis=1), axis=0, dtype=np.uint8)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

    parts = rows.select("path_id", "bits").mapInArrow(run, "sums binary").collect()
    return sum((np.frombuffer(r["sums"], np.int64)[:width] for r in parts), np.zeros(width, np.int64))


def _each(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    for batch in batches:
        if batch.num_rows:
            yield from _arrays(iter([batch]), len(batch.column(1)[0].as_buffer()))


# -- covers


@dataclass(frozen=True)
class Ways:
    """All distances of a network of up to MOST_PACKED_NODES nodes: there by where they start, home by where they end; 16 bits
    each where sums of two fit. far stands for no way."""

    ids: np.ndarray
    there: np.ndarray
    home: np.ndarray
    far: int
    most: int  # the largest threshold that is asked

    @staticmethod
    def of(edges: DataFrame, nodes: DataFrame, tau: int) -> Ways:
        ids = np.unique(nodes.select(F.col("node_id").cast("long")).limit(MOST_PACKED_NODES + 1).toArrow().column(0).to_numpy())
        if len(ids) > MOST_PACKED_NODES:
            raise ValueError("network too large for packed covers; use detours()")
        home = np.full((len(ids), len(ids)), FAR, np.int32)
        np.fill_diagonal(home, 0)
        for goal, roads, metres in whole_distances(edges):
            home[np.searchsorted(ids, goal), np.searchsorted(ids, roads)] = metres
        small = int(home.max(where=home < FAR, initial=0)) + tau < NEVER // 2
        far = NEVER // 2 if small else FAR
        home = np.minimum(home, far).astype(np.uint16 if small else np.int32)
        return Ways(ids, np.ascontiguousarray(home.T), home, far, tau)

    def within(self, nodes: np.ndarray, tau: int) -> np.ndarray:
        """Whether each node is within a detour tau of a path: over all pairs of the path's nodes. Nodes that the network
        doesn't have lead nowhere."""
        at = np.minimum(np.searchsorted(self.ids, nodes), max(len(self.ids) - 1, 0))
        at = at[self.ids[at] == nodes] if len(self.ids) else at[:0]
        out, home = self.there[at], self.home[at]
        found = np.zeros(len(self.ids), bool)
        limit = self.there[np.ix_(at, at)]
        for i in range(len(at)):
            back, most = home, limit[i]
            if (most == self.far).any():
                back, most = home[most < self.far], most[most < self.far]
            found |= (out[i] + back <= (most + most.dtype.type(tau))[:, None]).any(0)
        return found


def whole_distances(edges: DataFrame) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(node, ids of all nodes with roads, metres from each to the node or FAR): for blocks of nodes at once, until
    nothing gets shorter."""
    roads = Roads.of(edges)
    n = len(roads.ids)
    if not n:
        return
    spark = edges.sparkSession
    # Roads by where they end: what got nearer to a goal is handed on to the starts of the roads that lead there.
    start = np.repeat(np.arange(n, dtype=np.int32), np.diff(roads.start))
    by_end = np.argsort(roads.to, kind="stable")
    shared = spark.sparkContext.broadcast((n, np.searchsorted(roads.to[by_end], np.arange(n + 1)), start[by_end], roads.metres[by_end].astype(np.int32)))

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, first, start, metres = shared.value
        for batch in batches:
            for block in batch.column(0).to_pylist():
                goals = np.arange(block * GOALS_AT_ONCE, min(n, (block + 1) * GOALS_AT_ONCE))
                best = np.full((n, len(goals)), FAR, np.int32)  # from each node to the block's nodes
                best[goals, np.arange(len(goals))] = 0
                moved = goals
                while len(moved):
                    number = first[moved + 1] - first[moved]
                    road = np.repeat(first[moved] - np.cumsum(number) + number, number) + np.arange(int(number.sum()))
                    road, end = (x[order] for order in [np.argsort(start[road], kind="stable")] for x in (road, np.repeat(moved, number)))
                    if not len(road):
                        break
                    at = np.flatnonzero(np.r_[True, np.diff(start[road]) > 0])
                    nodes = start[road[at]]
                    found = np.minimum.reduceat(best[end] + metres[road][:, None], at, axis=0)
                    before = best[nodes]
                    best[nodes] = np.minimum(before, found)
                    moved = nodes[(found < before).any(1)]
                rows = np.minimum(best.T, FAR)
                fits = [r.max(where=r < FAR, initial=0) < NEVER for r in rows]
                packed = [np.where(r < FAR, r, NEVER).astype(np.uint16).tobytes() if ok else r.tobytes() for r, ok in zip(rows, fits, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(goals, pa.int64()), pa.array(packed, pa.binary())], ["place", "metres"])

    blocks = spark.range(0, -(-n // GOALS_AT_ONCE), 1, max(8, spark.sparkContext.defaultParallelism))
    for r in blocks.mapInArrow(search, "place long, metres binary").collect():
        raw = r["metres"]
        found = np.frombuffer(raw, np.int32) if len(raw) == 4 * n else np.frombuffer(raw, np.uint16).astype(np.int32)
        yield int(roads.ids[r["place"]]), roads.ids, np.where(found == NEVER, FAR, found) if len(raw) == 2 * n else found


def near_cover(points: DataFrame, shared: Broadcast, tau: int) -> PackedCover:
    """The binary cover of a threshold by every node of the network; shared: its Ways, broadcast."""
    ids = shared.value.ids
    if tau > shared.value.most:
        raise ValueError("the ways serve smaller thresholds only")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ways = shared.value
        for batch in batches:
            bits = [np.packbits(ways.within(np.asarray(nodes, np.int64), tau)).tobytes() for nodes in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(bits, pa.binary())], ["path_id", "bits"])

    routes = route_arrays(points).select(F.col("path_id").cast("long").alias("path_id"), F.col("nodes").cast("array<long>").alias("nodes"))
    return PackedCover.of(routes.mapInArrow(run, "path_id long, bits binary"), ids, "packed-near")


def estimated_cover(index: Index, level: int, tau: int) -> PackedCover:
    """The binary cover of a threshold by the representatives of a level, from the index's estimates: as
    index.estimated_cover. A path's clusters meet what each reaches with the metres left to it."""
    at = F.col("level") == level
    reps = index.clusters().where(at & F.col("rep").isNotNull()).select(F.col("cluster_id").alias("target"), F.col("rep").cast("long").alias("rep"), F.col("rep_metres").cast("long").alias("rep_metres"))
    links = index.link.where(at).select(F.col("cluster_id").alias("from"), F.col("nbr_id").alias("to"), F.col("metres").alias("between"))
    own = reps.select(F.col("target").alias("from"), F.col("target").alias("to"), F.lit(0).cast("long").alias("between"))
    routes = links.unionByName(own).join(reps, F.col("to") == F.col("target")).select(F.col("from").cast("long"), "rep", (F.col("between") + F.col("rep_metres")).cast("long").alias("rest")).where(F.col("rest") <= tau).toArrow()
    start, rep, rest = (routes.column(k).to_numpy() for k in range(3))
    ids, place = np.unique(rep, return_inverse=True)
    order = np.argsort(start, kind="stable")
    centres, first = np.unique(start[order], return_index=True)
    shared = index.path.sparkSession.sparkContext.broadcast((centres, np.append(first, len(order)), place[order].astype(np.int32), rest[order], len(ids)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centres, first, place, rest, n = shared.value
        for batch in batches:
            lists = batch.column(1)
            offsets = lists.offsets.to_numpy().astype(np.int64)
            inner = lists.values
            path = np.repeat(np.arange(len(lists)), np.diff(offsets))
            part = slice(offsets[0], offsets[-1])
            cluster, far = (inner.field(k).to_numpy()[part] for k in range(2))
            at = np.minimum(np.searchsorted(centres, cluster), max(len(centres) - 1, 0))
            known = centres[at] == cluster if len(centres) else np.zeros(len(at), bool)
            path, at, far = path[known], at[known], far[known]
            rows = max(1, BITS_AT_ONCE // max(n, 1))
            out = []
            for a in range(0, len(lists), rows):
                b = min(a + rows, len(lists))
                some = slice(*np.searchsorted(path, [a, b]))
                found = np.zeros((b - a, n), bool)
                lengths = first[at[some] + 1] - first[at[some]]
                for lo, hi in _chunks(lengths, MET_AT_ONCE):
                    number = lengths[lo:hi]
                    each = np.repeat(first[at[some][lo:hi]] - np.cumsum(number) + number, number) + np.arange(int(number.sum()))
                    ok = np.repeat(far[some][lo:hi], number) + rest[each] <= tau
                    found[np.repeat(path[some][lo:hi] - a, number)[ok], place[each[ok]]] = True
                out += [r.tobytes() for r in np.packbits(found, axis=1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["path_id", "bits"])

    held = index.path.where(at & (F.col("metres") <= tau)).groupBy(F.col("path_id").cast("long").alias("path_id")).agg(F.collect_list(F.struct(F.col("cluster_id").cast("long").alias("c"), F.col("metres").cast("long").alias("m"))).alias("own"))
    return PackedCover.of(held.mapInArrow(run, "path_id long, bits binary"), ids, "packed-estimated")


def _chunks(lengths: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Stretches whose lengths add up to about `most`."""
    total = np.cumsum(lengths)
    lo = 0
    while lo < len(lengths):
        hi = max(lo + 1, int(np.searchsorted(total, (total[lo - 1] if lo else 0) + most, "right")))
        yield lo, hi
        lo = hi
