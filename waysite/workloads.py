"""The experiments, re-expressed on the given tables: each query returns its table of parameters and measures.

What a query returns is the same on every run; seconds and bytes, which are not, are in queries named *_time and *_bytes."""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from waysite import fixtures as fx
from waysite import measures as ms
from waysite.functions import preference as pref
from waysite.operators import baselines as bl
from waysite.operators import clusters as cl
from waysite.operators import detours as dt
from waysite.operators import exact as ex
from waysite.operators import greedy as gr
from waysite.operators import index as ix
from waysite.operators import packed as pk
from waysite.operators import paths as pt
from waysite.operators import sketch as sk
from waysite.oracles import placed_sql as ps
from waysite.oracles import placement_sql as sql
from waysite.sources.tables import discard, materialize, read_table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
TAUS, TAU = (240, 400, 500, 800, 1200), 800
KS = (1, 5, 9, 13, 17, 21, 25)
EPSILONS, COPIES = (0.25, 0.5, 0.75, 1.0), (1, 2, 4, 10, 20, 30, 40, 50, 100)
SIGMAS, MEANS = (0.0, 0.2, 0.4, 0.6, 0.8, 1.0), (0.001, 0.01, 0.1, 0.5, 1.0)
#: Samples of the comparison with the optimum, their sites and their paths.
SAMPLES, SAMPLE_SITES, SAMPLE_PATHS = 10, 50, 1000
#: Thresholds that the index of the supplier and part networks serves.
LIMITS = (210, 2400)
POINTS = "filled_points"


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return add


def world(spark, sf_dir) -> fx.World:
    return fx.net100(spark, sf_dir, filled=True)


def plain(w: fx.World, tau: float, k: int, cover: DataFrame | None = None) -> gr.Placement:
    return gr.greedy_place(w.cover(pref.binary(tau)) if cover is None else cover, gr.PlacementSpec(k=k, mode="auto"), w.n_paths(), w.sites())


def on_index(w: fx.World, index: ix.Index, tau: float, k: int, copies: int | None = None, members: DataFrame | None = None) -> gr.Placement:
    return ix.index_place(index, gr.PlacementSpec(k=k), pref.binary(tau), w.n_paths(), w.cover(pref.binary(tau)), copies, members=members)


def pct(w: fx.World, utility: int) -> float:
    return round(ms.utility_pct(utility, w.n_paths()), 6)


def true_pct(w: fx.World, tau: float, sites: list[int]) -> float:
    return pct(w, gr.utility_of(w.cover(pref.binary(tau)), sites))


def table(spark, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def union(parts: list[str]) -> str:
    return "\nUNION ALL ".join(parts)


def level_parts(tau: float, eps: float = fx.EPS, limits=ps.LIMITS_100, points: str = POINTS, existing: tuple[int, ...] = ()) -> tuple[int, tuple[str, ...]]:
    """The level that serves tau and its relations in SQL."""
    p = ps.level_of(tau, limits, eps)
    return p, (ps.level_relations(p, ps.level_radii(limits, eps)[p], eps, points), ps.estimated(p, existing))


def every_level(taus, **options) -> list[str]:
    """The relations of all levels that serve one of the thresholds, each once."""
    held = {}
    for tau in taus:
        p, parts = level_parts(tau, **options)
        held[p] = parts
    return [x for parts in held.values() for x in parts]


# -- optimum


def sample_of(w: fx.World, cover: DataFrame, sample: int):
    """(paths, sites, cover) of one sample: the first by a seeded hash."""
    sites = materialize(w.sites().orderBy(gr.seeded_order(F.col("site_id"), sample)).limit(SAMPLE_SITES), "w1-sites")
    paths = materialize(w.points().select("path_id").distinct().orderBy(gr.seeded_order(F.col("path_id"), sample)).limit(SAMPLE_PATHS), "w1-paths")
    return paths, sites, materialize(cover.join(paths, "path_id").join(sites, "site_id", "left_semi"), "w1-part")


@query()
def w1_optimum(spark, sf_dir):
    """Exact optimum against greedy, index and sketches for one to five sites, on ten samples of paths and fifty sites."""
    w = fx.net100(spark, sf_dir)
    cover = materialize(w.cover(pref.binary(400)), "w1")
    rows = []
    for sample in range(SAMPLES):
        paths, sites, part = sample_of(w, cover, sample)
        m = paths.count()
        # Clusters and links are those of the whole network, and so are the rows of the sample's paths.
        whole = w.index()
        index = ix.with_sites(replace(whole, path=materialize(whole.path.join(paths, "path_id", "left_semi"), "w1-index")), sites)
        five = gr.PlacementSpec(k=5, mode="auto")
        contenders = {"greedy": gr.greedy_place(part, five, m, sites), "greedy_fm": sk.greedy_place_sketch(part, 5, m, 30), "index": ix.index_place(index, five, pref.binary(400), m, part), "index_fm": ix.index_place(index, five, pref.binary(400), m, part, 30)}
        reached = {name: gr.prefix_utilities(part, p.sites) for name, p in contenders.items()}
        for k in range(1, 6):
            best = gr.utility_of(part, ex.branch_and_bound(part, sites, k))
            rows.append((sample, k, "optimum", best, 1.0))
            rows += [(sample, k, name, u[min(k, len(u)) - 1], round(ms.optimality_ratio(u[min(k, len(u)) - 1], best), 6)) for name, u in reached.items()]
    return table(spark, rows, "sample int, k int, method string, utility long, ratio double")


def w1_sql() -> str:
    parts, out = [*ps.DAYS[:4], sql.detour(), ps.cover("whole", 400)], []
    for s in range(10):
        parts += [f"s{s}_sites AS MATERIALIZED (SELECT node_id AS site_id FROM nodes ORDER BY md5('{s}:' || node_id) LIMIT 50)", f"s{s}_paths AS MATERIALIZED (SELECT path_id FROM (SELECT DISTINCT path_id FROM points) p ORDER BY md5('{s}:' || path_id) LIMIT 1000)", f"s{s} AS MATERIALIZED (SELECT path_id, site_id, score FROM whole SEMI JOIN s{s}_sites USING (site_id) SEMI JOIN s{s}_paths USING (path_id))", ps.steps(f"g{s}", f"s{s}", 5, f"SELECT * FROM s{s}_sites")]
        out.append(f"SELECT CAST({s} AS INTEGER) AS sample, step, site_id, gain FROM g{s}")
    return ps.statement((), *parts, union(out))


@query(w1_sql())
def w1_greedy(spark, sf_dir):
    """The greedy's sites on the ten samples."""
    w = fx.net100(spark, sf_dir)
    cover = materialize(w.cover(pref.binary(400)), "w1")
    rows = []
    for sample in range(10):
        paths, sites, part = sample_of(w, cover, sample)
        rows += [(sample, k, site, gain) for k, site, gain, _ in gr.greedy_place(part, gr.PlacementSpec(k=5, mode="auto"), paths.count(), sites).steps]
    return table(spark, rows, "sample int, step int, site_id long, gain long")


# -- resolution and sketches


def w2_sql() -> str:
    parts, out = [*ps.FILLED, ps.cover("cov", TAU), ps.steps("g", "cov", 5)], []
    for n, eps in enumerate(EPSILONS):
        radii = ps.level_radii(ps.LIMITS_100, eps)
        for p, r in enumerate(radii):
            parts.append(ps.level_relations(100 * n + p, r, eps, POINTS))
        at = 100 * n + ps.level_of(TAU, ps.LIMITS_100, eps)
        parts += [ps.estimated(at), ps.cover(f"e{n}", TAU, source=f"est{at}"), ps.steps(f"i{n}", f"e{n}", 5, ps.reps(at))]
        rows = " + ".join(f"(SELECT count(*) FROM {x}{100 * n + p})" for p in range(len(radii)) for x in ("member", "link", "own"))
        lost = f"1 - (SELECT sum(u) FROM (SELECT path_id, max(score) AS u FROM cov WHERE site_id IN (SELECT site_id FROM i{n}) GROUP BY path_id) v) / (SELECT sum(gain) FROM g)"
        out.append(f"SELECT {eps}::DOUBLE AS eps, CAST({len(radii)} AS INTEGER) AS levels, CAST({rows} AS BIGINT) AS index_rows, round(100.0 * ({lost}), 4) AS loss_pct")
    return ps.statement((), *parts, union(out))


def index_at(w: fx.World, eps: float) -> ix.Index:
    return w.index(eps)


@query(w2_sql())
def w2_resolution(spark, sf_dir):
    """The index resolution: levels, size and loss against the plain greedy."""
    w = world(spark, sf_dir).by_routes()
    reference = plain(w, TAU, 5).utility
    rows = []
    for eps in EPSILONS:
        index = index_at(w, eps)
        found = on_index(w, index, TAU, 5)
        loss = 100 * ms.relative_loss(reference, gr.utility_of(w.cover(pref.binary(TAU)), found.sites))
        rows.append((eps, len(index.levels), int(ms.index_rows(index).agg(F.sum("rows")).first()[0]), round(loss, 4)))
    return table(spark, rows, "eps double, levels int, index_rows long, loss_pct double")


def index_on_routes(w: fx.World, eps: float) -> tuple[ix.Index, tuple[DataFrame, DataFrame]]:
    """An index of a world's routes, made from its paths, and the tables that tell each path's route and each route's nodes."""
    routes = materialize(dt.counted_routes(w.points()), "w2-routes")
    route_of = materialize(dt.route_arrays(w.points()).join(routes.select("nodes", "route"), "nodes").select("path_id", "route"), "w2-route-of")
    return ix.build_index(dt.route_points(routes), w.sites(), w.dist(), w.trips(), eps), (routes, route_of)


@query()
def w2_time(spark, sf_dir):
    """The index resolution: seconds of building and bytes of the files written; finding the paths of each route, on which
    the index stands, belongs to either."""
    w = world(spark, sf_dir)
    w.points(), w.trips()
    rows = []
    for eps in EPSILONS:
        (index, tables), seconds = ms.timed(index_on_routes, w, eps)
        rows.append((eps, round(seconds, 3), ms.index_bytes(index) + sum(map(ms.file_bytes, tables))))
    return table(spark, rows, "eps double, build_s double, file_bytes long")


def w3_sql() -> str:
    p, parts = level_parts(TAU)
    out = [f"SELECT CAST(0 AS INTEGER) AS copies, CAST((SELECT sum(gain) FROM g) AS BIGINT) AS utility, 0.0::DOUBLE AS loss_pct"]
    more = [ps.cover("cov", TAU, source=f"est{p}"), ps.steps("g", "cov", 5, ps.reps(p))]
    for f in COPIES:
        more.append(ps.sketch_steps(f"f{f}", "cov", 5, f))
        u = f"(SELECT CAST(sum(u) AS BIGINT) FROM (SELECT path_id, max(score) AS u FROM cov WHERE site_id IN (SELECT site_id FROM f{f}) GROUP BY path_id) v)"
        out.append(f"SELECT CAST({f} AS INTEGER), {u}, round(100.0 * (1 - {u} / (SELECT sum(gain) FROM g)), 4)")
    return ps.statement((), *ps.FILLED, *parts, *more, union(out))


@query(w3_sql())
def w3_sketch_copies(spark, sf_dir):
    """The number of sketch copies on an index level: utility and loss against counting."""
    w = world(spark, sf_dir)
    cover = materialize(ix.estimated_cover(w.index(), ix.choose_level(w.index().levels, TAU).level, pref.binary(TAU)), "w3")
    counted = gr.greedy_place(cover, gr.PlacementSpec(k=5, mode="auto"), w.n_paths()).utility
    rows = [(0, counted, 0.0)]
    for f in COPIES:
        found = sk.greedy_place_sketch(cover, 5, w.n_paths(), f).utility
        rows.append((f, found, round(100 * ms.relative_loss(counted, found), 4)))
    return table(spark, rows, "copies int, utility long, loss_pct double")


@query()
def w3_time(spark, sf_dir):
    """The number of sketch copies: seconds and speed-up over counting."""
    w = world(spark, sf_dir)
    cover = materialize(ix.estimated_cover(w.index(), ix.choose_level(w.index().levels, TAU).level, pref.binary(TAU)), "w3")
    _, counted = ms.timed(gr.greedy_place, cover, gr.PlacementSpec(k=5, mode="auto"), w.n_paths())
    rows = [(0, round(counted, 3), 1.0)]
    for f in COPIES:
        _, s = ms.timed(sk.greedy_place_sketch, cover, 5, w.n_paths(), f)
        rows.append((f, round(s, 3), round(ms.speed_up(counted, s), 3)))
    return table(spark, rows, "copies int, time_s double, speed_up double")


# -- quality, memory, time


def w4_sql() -> str:
    parts, out = [*ps.FILLED, *every_level(TAUS)], []
    for tau in TAUS:
        k, p = (25 if tau == TAU else 5), ps.level_of(tau)
        parts += [ps.cover(f"c{tau}", tau), ps.cover(f"e{tau}", tau, source=f"est{p}"), ps.steps(f"greedy{tau}", f"c{tau}", k), ps.steps(f"index{tau}", f"e{tau}", k, ps.reps(p)), ps.sketch_steps(f"greedy_fm{tau}", f"c{tau}", k, 30), ps.sketch_steps(f"index_fm{tau}", f"e{tau}", k, 30)]
        for step in KS:
            if step <= k:
                out += [f"SELECT CAST({tau} AS INTEGER) AS tau, CAST({step} AS INTEGER) AS k, '{m}' AS method, {ps.valued(f'(SELECT site_id FROM {m}{tau} WHERE step <= {step})', f'c{tau}', POINTS)} AS utility_pct" for m in ("greedy", "greedy_fm", "index", "index_fm")]
    return ps.statement((), *parts, union(out))


@query(w4_sql())
def w4_quality(spark, sf_dir):
    """True utility of greedy, sketches and index, by the number of sites up to 25 and by the threshold."""
    paths = world(spark, sf_dir)
    w, members = paths.by_routes(), paths.route_of()
    rows = []
    for tau in TAUS:
        k = 25 if tau == TAU else 5
        cover = materialize(w.cover(pref.binary(tau)), "w4")
        found = {"greedy": plain(w, tau, k, cover), "greedy_fm": sk.greedy_place_sketch(cover, k, w.n_paths(), 30, members=members), "index": on_index(w, w.index(), tau, k), "index_fm": on_index(w, w.index(), tau, k, 30, members)}
        reached = {name: gr.prefix_utilities(cover, p.sites) for name, p in found.items()}
        for step in KS:
            if step <= k:
                rows += [(tau, step, name, pct(w, u[min(step, len(u)) - 1])) for name, u in reached.items()]
    return table(spark, rows, "tau int, k int, method string, utility_pct double")


def w5_sql() -> str:
    parts, out = [*ps.FILLED, *every_level(TAUS)], []
    for tau in TAUS:
        p = ps.level_of(tau)
        parts += [ps.cover(f"c{tau}", tau), ps.cover(f"e{tau}", tau, source=f"est{p}")]
        held = {"greedy": f"(SELECT count(*) FROM c{tau})", "greedy_fm": f"(SELECT count(*) + 30 * count(DISTINCT site_id) FROM c{tau})", "index": f"(SELECT count(*) FROM e{tau})", "index_fm": f"(SELECT count(*) + 30 * count(DISTINCT site_id) FROM e{tau})"}
        out += [f"SELECT CAST({tau} AS INTEGER) AS tau, '{m}' AS method, CAST({n} AS BIGINT) AS held_rows" for m, n in held.items()]
    return ps.statement((), *parts, union(out))


def held_covers(w: fx.World, tau: float) -> dict[str, tuple[DataFrame, DataFrame | None]]:
    """What each method holds for a threshold: its cover, and with sketches their words too."""
    true = materialize(w.cover(pref.binary(tau)), "w5")
    level = ix.choose_level(w.index().levels, tau)
    est = materialize(ix.estimated_cover(w.index(), level.level, pref.binary(tau)), "w5")
    words = [materialize(sk.fm_sketch(c, "site_id", "path_id", 30), "w5-words") for c in (true, est)]
    return {"greedy": (true, None), "greedy_fm": (true, words[0]), "index": (est, None), "index_fm": (est, words[1])}


@query(w5_sql())
def w5_memory(spark, sf_dir):
    """Rows that each method holds, by the threshold: covers, and words of sketches."""
    w = world(spark, sf_dir)
    return table(spark, [(tau, name, sum(x.count() for x in held if x is not None)) for tau in TAUS for name, held in held_covers(w, tau).items()], "tau int, method string, held_rows long")


@query()
def w5_bytes(spark, sf_dir):
    """Bytes of the files of what each method holds."""
    w = world(spark, sf_dir)
    return table(spark, [(tau, name, sum(ms.file_bytes(x) for x in held if x is not None)) for tau in TAUS for name, held in held_covers(w, tau).items()], "tau int, method string, held_bytes long")


Cover = DataFrame | pk.PackedCover


def near_of(w: fx.World, tau: int) -> Cover:
    """The binary cover of a network too large for stored detours: as bits, or as pairs beyond what bits are kept for."""
    return w.packed_cover(tau, LIMITS[1]) if w.n <= pk.MOST_PACKED_NODES else materialize(w.near_cover(tau), "near")


def estimate_of(w: fx.World, index: ix.Index, tau: int) -> Cover:
    level = ix.choose_level(index.levels, tau).level
    return pk.estimated_cover(index, level, tau) if w.n <= pk.MOST_PACKED_NODES else materialize(ix.estimated_cover(index, level, pref.binary(tau)), "est")


def place_on(c: Cover, k: int, n_paths: int) -> gr.Placement:
    return c.place(k, n_paths) if isinstance(c, pk.PackedCover) else gr.greedy_place(c, gr.PlacementSpec(k=k, mode="auto"), n_paths)


def sketch_on(c: Cover, k: int, n_paths: int) -> gr.Placement:
    return c.place_sketch(k, n_paths, 30) if isinstance(c, pk.PackedCover) else sk.greedy_place_sketch(c, k, n_paths, 30)


def timed_loops(c: Cover, ks: list[int], n_paths: int) -> list[tuple[float, float]]:
    """Seconds of the loop for each number of sites, counted and sketched. On bits the counted loop runs once, up to the
    largest number, and a smaller one has the seconds at which its last site was picked; the words of the sketches don't
    depend on the number: they are made once, and their seconds stand in each."""
    if not isinstance(c, pk.PackedCover):
        return [(ms.timed(place_on, c, k, n_paths)[1], ms.timed(sketch_on, c, k, n_paths)[1]) for k in ks]
    at = [0.0, *c.place(max(ks), n_paths).seconds]
    words, making = ms.timed(c.sketch_words, 30)
    return [(at[min(k, len(at) - 1)], making + ms.timed(c.place_sketch, k, n_paths, 30, words)[1]) for k in ks]


def timed_methods(w: fx.World, covers: dict[str, tuple[Cover, float]], tau: int, ks: list[int]) -> list[tuple]:
    out = []
    for name, (c, before) in covers.items():
        for k, (counted, sketched) in zip(ks, timed_loops(c, ks, w.n_paths()), strict=True):
            out += [(tau, k, name, round(before, 3), round(counted, 3)), (tau, k, f"{name}_fm", round(before, 3), round(sketched, 3))]
    return out


@query()
def w6_time(spark, sf_dir):
    """Seconds of the cover and of the loop on the supplier network: greedy and index, counted and sketched, by the
    threshold and by the number of sites. A threshold's covers, and its loops as far as they are alike, are made once for all
    numbers of sites; its covers go before the next are made."""
    w = fx.netsup(spark, sf_dir, filled=False)
    index = w.bounded_index(LIMITS)
    rows = []
    for tau in (240, 400, 800, 1200):
        covers = {"greedy": ms.timed(near_of, w, tau), "index": ms.timed(estimate_of, w, index, tau)}
        rows += timed_methods(w, covers, tau, list(KS) if tau == TAU else [5])
        discard(*(c.rows if isinstance(c, pk.PackedCover) else c for c, _ in covers.values()))
    return table(spark, rows, "tau int, k int, method string, cover_s double, loop_s double")


# -- variants


def w7_sql() -> str:
    p, level = level_parts(400)
    parts, out = [*ps.FILLED, *level, ps.cover("cov", 400), ps.cover("est", 400, source=f"est{p}")], []
    for n, sigma in enumerate(SIGMAS):
        sites = ps.attributed(sigma)
        parts += [ps.budget_steps(f"g{n}", "cov", sites, 5.0), ps.budget_steps(f"i{n}", "est", f"SELECT * FROM ({sites}) a WHERE site_id IN (SELECT rep FROM rep{p})", 5.0)]
        out += [f"SELECT {sigma}::DOUBLE AS sigma, '{m}' AS method, CAST((SELECT count(*) FROM {m[0]}{n}) AS INTEGER) AS n_sites, {ps.valued(f'{m[0]}{n}', 'cov', POINTS)} AS utility_pct" for m in ("greedy", "index")]
    return ps.statement((), *parts, union(out))


def budgeted(w: fx.World, cover: DataFrame, sigma: float) -> dict[str, Callable[[], gr.Placement]]:
    spec, sites = gr.PlacementSpec(k=None, budget=5.0, mode="auto"), fx.with_costs(w.sites(), sigma)
    return {"greedy": lambda: gr.greedy_place(cover, spec, w.n_paths(), sites), "index": lambda: ix.index_place(w.index(), spec, pref.binary(400), w.n_paths(), cover, None, sites)}


@query(w7_sql())
def w7_budget(spark, sf_dir):
    """A budget of 5 over costs of mean 1 and growing spread: sites and true utility."""
    w = world(spark, sf_dir).by_routes()
    cover = materialize(w.cover(pref.binary(400)), "w7")
    rows = []
    for sigma in SIGMAS:
        for name, place in budgeted(w, cover, sigma).items():
            p = place()
            rows.append((sigma, name, len(p.steps), pct(w, gr.utility_of(cover, p.sites))))
    return table(spark, rows, "sigma double, method string, n_sites int, utility_pct double")


@query()
def w7_time(spark, sf_dir):
    """A budget of 5 over costs of mean 1 and growing spread: seconds."""
    w = world(spark, sf_dir).by_routes()
    cover = materialize(w.cover(pref.binary(400)), "w7")
    return table(spark, [(sigma, name, round(ms.timed(place)[1], 3)) for sigma in SIGMAS for name, place in budgeted(w, cover, sigma).items()], "sigma double, method string, time_s double")


@query()
def w7_columns(spark, sf_dir):
    """Costs and capacities from columns: part prices about their mean, part sizes; greedy on the part network."""
    w = fx.netpart(spark, sf_dir)
    part = read_table(spark, sf_dir, "part", "p_partkey", "p_retailprice", "p_size")
    mean = part.agg(F.avg("p_retailprice")).first()[0]
    sites = part.select((F.col("p_partkey") - 1).alias("site_id"), F.greatest(F.lit(0.1), F.round(F.col("p_retailprice") / mean, 4)).alias("cost"), F.col("p_size").cast("long").alias("capacity"))
    cover = materialize(w.near_cover(300), "w7-part")
    rows = []
    for name, spec in (("budget", gr.PlacementSpec(k=None, budget=5.0, mode="auto")), ("capacity", gr.PlacementSpec(k=5, capacity=True, mode="auto"))):
        p = gr.greedy_place(cover, spec, w.n_paths(), sites if name == "capacity" else sites.drop("capacity"))
        rows.append((name, len(p.steps), pct(w, p.utility)))
    return table(spark, rows, "variant string, n_sites int, utility_pct double")


def w8_sql() -> str:
    p, level = level_parts(400)
    parts, out = [*ps.FILLED, *level, ps.cover("cov", 400), ps.cover("est", 400, source=f"est{p}")], []
    for n, share in enumerate(MEANS):
        sites = ps.attributed(mean=f"{share}::DOUBLE * (SELECT count(DISTINCT path_id) FROM {POINTS})")
        parts += [ps.steps(f"g{n}", "cov", 5, sites, capacity=True), ps.steps(f"i{n}", "est", 5, f"SELECT * FROM ({sites}) a WHERE site_id IN (SELECT rep FROM rep{p})", capacity=True), ps.steps(f"t{n}", "cov", 5, sites, capacity=True, forced=f"i{n}")]
        out += [f"SELECT {share}::DOUBLE AS mean_share, '{m}' AS method, round((SELECT sum(gain) FROM {x}{n}) / 1000000 / (SELECT count(DISTINCT path_id) FROM {POINTS}) * 100, 6) AS utility_pct" for m, x in (("greedy", "g"), ("index", "t"), ("index_estimated", "i"))]
    return ps.statement((), *parts, union(out))


@query(w8_sql())
def w8_capacity(spark, sf_dir):
    """Capacities of mean 0.1 % to 100 % of the paths: true utilities, and what the index estimates for its own."""
    paths = world(spark, sf_dir)
    w, members, binary = paths.by_routes(), paths.route_of(), pref.binary(400)
    index = w.index()
    level = ix.choose_level(index.levels, 400).level
    cover = materialize(dt.cover(w.detours(), binary), "w8")
    est = materialize(dt.cover(ix.estimated_detours(index, level), binary), "w8-est")
    reps = index.clusters().where((F.col("level") == level) & F.col("rep").isNotNull()).select(F.col("rep").alias("site_id")).distinct()
    rows = []
    for share in MEANS:
        sites = fx.with_capacities(w.sites(), share * w.n_paths())
        i = gr.capacity_place(est, members, 5, w.n_paths(), reps.join(sites, "site_id"))
        true = gr.capacity_place(cover, members, 5, w.n_paths(), sites, i.sites)
        rows += [(share, "greedy", pct(w, gr.capacity_place(cover, members, 5, w.n_paths(), sites).utility)), (share, "index", pct(w, true.utility)), (share, "index_estimated", pct(w, i.utility))]
    return table(spark, rows, "mean_share double, method string, utility_pct double")


def w9_sql() -> str:
    parts, out = [*ps.FILLED, *every_level((400, 800))], []
    for tau in (400, 800):
        p = ps.level_of(tau)
        parts += [ps.cover(f"c{tau}", tau, "convex"), ps.cover(f"e{tau}", tau, "convex", f"est{p}"), ps.steps(f"g{tau}", f"c{tau}", 5), ps.steps(f"i{tau}", f"e{tau}", 5, ps.reps(p))]
        out += [f"SELECT CAST({tau} AS INTEGER) AS tau, '{m}' AS method, {ps.valued(f'{m[0]}{tau}', f'c{tau}', POINTS)} AS utility_pct" for m in ("greedy", "index")]
    return ps.statement((), *parts, union(out))


@query(w9_sql())
def w9_market_size(spark, sf_dir):
    """The convex preference: expected paths served."""
    w = world(spark, sf_dir)
    rows = []
    for tau in (400, 800):
        like = pref.convex(tau)
        cover = materialize(w.cover(like), "w9")
        for name, p in (("greedy", gr.greedy_place(cover, gr.PlacementSpec(k=5, mode="auto"), w.n_paths(), w.sites())), ("index", ix.index_place(w.index(), gr.PlacementSpec(k=5), like, w.n_paths(), cover))):
            rows.append((tau, name, pct(w, gr.utility_of(cover, p.sites))))
    return table(spark, rows, "tau int, method string, utility_pct double")


# -- updates and scale


def w10_sql() -> str:
    radii = ps.level_radii()
    parts = [*ps.FILLED, *(ps.members(p, r) for p, r in enumerate(radii))]
    out = []
    for days in (2, 4, 6, 8, 10):
        held = " + ".join(f"(SELECT count(*) FROM (SELECT DISTINCT m.cluster_id, x.path_id FROM {POINTS} x JOIN member{p} m USING (node_id) WHERE path_id % 100 < {20 + days}) d)" for p in range(len(radii)))
        out.append(f"SELECT 'paths' AS kind, CAST({days} AS INTEGER) AS batch, (SELECT count(DISTINCT path_id) FROM {POINTS} WHERE path_id % 100 >= 20 AND path_id % 100 < {20 + days}) AS added, CAST({held} AS BIGINT) AS held_rows")
    for step in (1, 2, 3):
        held = " + ".join(f"(SELECT count(DISTINCT cluster_id) FROM member{p} WHERE node_id % 4 <= {step})" for p in range(len(radii)))
        out.append(f"SELECT 'sites', CAST({step} AS INTEGER), (SELECT count(*) FROM nodes WHERE node_id % 4 BETWEEN 1 AND {step}), CAST({held} AS BIGINT)")
    return ps.statement((), *parts, union(out))


def growing(w: fx.World) -> list[tuple[str, int, DataFrame, Callable[[], ix.Index]]]:
    start = fx.once(w.spark, w.sf_dir, "w10-index", lambda: ix.build_index(w.points().where("path_id % 100 < 20"), w.sites().where("site_id % 4 = 0"), w.dist(), w.trips(), limits=ix.tau_limits(w.trips(), w.sites())))
    out = []
    for days in (2, 4, 6, 8, 10):
        points = w.points().where(f"path_id % 100 >= 20 AND path_id % 100 < {20 + days}")
        out.append(("paths", days, points.select("path_id").distinct(), lambda p=points: ix.add_paths(start, p, w.dist())))
    for step in (1, 2, 3):
        ids = w.sites().where(f"site_id % 4 >= 1 AND site_id % 4 <= {step}")
        out.append(("sites", step, ids, lambda s=ids: ix.add_sites(start, s)))
    return out


@query(w10_sql())
def w10_updates(spark, sf_dir):
    """Paths and sites added to a standing index in growing batches: rows of path lists, and clusters that have a site."""
    rows = []
    for kind, batch, added, grow in growing(world(spark, sf_dir)):
        grown = grow()
        rows.append((kind, batch, added.count(), grown.path.count() if kind == "paths" else grown.clusters().where("rep IS NOT NULL").count()))
    return table(spark, rows, "kind string, batch int, added long, held_rows long")


@query()
def w10_time(spark, sf_dir):
    """Paths and sites added to a standing index in growing batches: seconds."""
    return table(spark, [(kind, batch, round(ms.timed(grow)[1], 3)) for kind, batch, _, grow in growing(world(spark, sf_dir))], "kind string, batch int, time_s double")


SUPPLIERS = (sql.lattice_of("supplier"), sql.DIST, sql.TRIPS, sql.SUPPLIER_POINTS, sql.detour())


def w11_sql() -> str:
    p, level = level_parts(TAU, limits=LIMITS, points="points")
    parts, out = [*SUPPLIERS, *near_level(p)], []
    for part in (4, 2, 1):
        for kind, where in (("sites", f"site_id % {part} = 0"), ("paths", f"path_id % {part} = 0")):
            n = f"{kind}{part}"
            parts += [ps.cover(f"c{n}", TAU, where=where), ps.cover(f"e{n}", TAU, source=f"est{p}" if kind == "paths" or part == 1 else f"est{p}_{part}", where=where), ps.steps(f"g{n}", f"c{n}", 5, "SELECT DISTINCT site_id FROM c" + n), ps.steps(f"i{n}", f"e{n}", 5, "SELECT DISTINCT site_id FROM e" + n)]
            m = "(SELECT count(DISTINCT path_id) FROM points)" if kind == "sites" else f"(SELECT count(DISTINCT path_id) FROM points WHERE path_id % {part} = 0)"
            out += [f"SELECT '{kind}' AS varied, CAST({part} AS INTEGER) AS part, '{x}' AS method, (SELECT count(*) FROM {h}{n}) AS cover_rows, round((SELECT coalesce(sum(u), 0) FROM (SELECT path_id, max(score) AS u FROM c{n} WHERE site_id IN (SELECT site_id FROM {y}{n}) GROUP BY path_id) v) / 1000000 / {m} * 100, 6) AS utility_pct" for x, h, y in (("greedy", "c", "g"), ("index", "e", "i"))]
    return ps.statement((), *parts, union(out))


def near_level(p: int) -> list[str]:
    """A level of the bounded index: path lists with both ways of 2R at most, and its representatives among every site, every
    second and every fourth."""
    r = ps.level_radii(LIMITS)[p]
    near = f"""near AS MATERIALIZED (SELECT m.cluster_id, x.path_id, min(t.metres + b.metres - g.metres) AS metres FROM (SELECT DISTINCT cluster_id, path_id FROM points JOIN member{p} USING (node_id)) x JOIN centre{p} m USING (cluster_id)
  JOIN (SELECT DISTINCT path_id, node_id FROM points) v ON v.path_id = x.path_id JOIN dist t ON t.src = v.node_id AND t.dst = x.cluster_id AND t.metres <= {2 * r}
  JOIN (SELECT DISTINCT path_id, node_id FROM points) w ON w.path_id = x.path_id JOIN dist b ON b.src = x.cluster_id AND b.dst = w.node_id AND b.metres <= {2 * r}
  JOIN dist g ON g.src = v.node_id AND g.dst = w.node_id GROUP BY ALL)"""
    links = f"link{p} AS MATERIALIZED (SELECT a AS cluster_id, b AS nbr_id, metres FROM round_trips JOIN centre{p} x ON x.cluster_id = a JOIN centre{p} y ON y.cluster_id = b WHERE a <> b AND metres <= {int(4 * r * (1 + fx.EPS))})"
    out = [ps.members(p, r), f"centre{p} AS MATERIALIZED (SELECT DISTINCT cluster_id FROM member{p})", links, near]
    for part in (4, 2, 1):
        name = f"{p}" if part == 1 else f"{p}_{part}"
        out.append(f"""rep{name} AS MATERIALIZED (SELECT cluster_id, arg_min(node_id, struct_pack(metres, node_id)) AS rep, min(metres) AS rep_metres FROM member{p} WHERE node_id % {part} = 0 GROUP BY cluster_id),
est{name} AS MATERIALIZED (SELECT o.path_id, t.rep AS site_id, min(o.metres + l.metres + t.rep_metres) AS metres FROM near o
  JOIN (SELECT cluster_id, nbr_id, metres FROM link{p} UNION ALL SELECT cluster_id, cluster_id, 0 FROM centre{p}) l USING (cluster_id) JOIN rep{name} t ON t.cluster_id = l.nbr_id GROUP BY ALL)""")
    return out


def scaled(w: fx.World, index: ix.Index) -> list[tuple[str, int, Cover, Cover, int]]:
    """(varied, part, cover, estimated cover, paths) for every fourth, second and each site, and path. Each site and each path
    are the same covers, which are made once."""
    true, est = near_of(w, TAU), estimate_of(w, index, TAU)
    out = []
    for part in (4, 2):
        fewer = ix.with_sites(index, w.sites().where(F.col("site_id") % part == 0))
        kept = true.of_sites(true.ids % part == 0) if isinstance(true, pk.PackedCover) else materialize(true.where(F.col("site_id") % part == 0), "w11-part")
        out.append(("sites", part, kept, estimate_of(w, fewer, TAU), w.n_paths()))
        some = F.col("path_id") % part == 0
        both = [c.of_paths(some) if isinstance(c, pk.PackedCover) else materialize(c.where(some), "w11-part") for c in (true, est)]
        out.append(("paths", part, *both, w.points().where(some).select("path_id").distinct().count()))
    return [*out, *((varied, 1, true, est, w.n_paths()) for varied in ("sites", "paths"))]


def size_of(c: Cover) -> int:
    return c.n_rows() if isinstance(c, pk.PackedCover) else c.count()


@query(w11_sql())
def w11_scale(spark, sf_dir):
    """Growing numbers of sites and of paths on the supplier network: rows and true utility of greedy and index."""
    w = fx.netsup(spark, sf_dir, filled=False)
    rows, measured = [], {}
    for varied, part, cover, est, m in scaled(w, w.bounded_index(LIMITS)):
        for name, c in (("greedy", cover), ("index", est)):
            if id(c) not in measured:
                sites = place_on(c, 5, m).sites
                reached = cover.utility_of(sites) if isinstance(cover, pk.PackedCover) else gr.utility_of(cover, sites)
                measured[id(c)] = size_of(c), round(ms.utility_pct(reached, m), 6)
            rows.append((varied, part, name, *measured[id(c)]))
    return table(spark, rows, "varied string, part int, method string, cover_rows long, utility_pct double")


@query()
def w11_time(spark, sf_dir):
    """Growing numbers of sites and of paths on the supplier network: seconds of the loop."""
    w = fx.netsup(spark, sf_dir, filled=False)
    rows = []
    for varied, part, cover, est, m in scaled(w, w.bounded_index(LIMITS)):
        rows += [(varied, part, name, round(ms.timed(place_on, c, 5, m)[1], 3)) for name, c in (("greedy", cover), ("index", est))]
    return table(spark, rows, "varied string, part int, method string, time_s double")


# -- robustness


@query()
def w12_city_shape(spark, sf_dir):
    """The same trips on three road networks."""
    rows = []
    for shape in ("mesh", "star", "poly"):
        w = fx.net100(spark, sf_dir, shape=shape)
        rows.append((shape, w.cover(pref.binary(400)).count(), pct(w, plain(w, 400, 5).utility)))
    return table(spark, rows, "shape string, cover_rows long, utility_pct double")


def w13_sql() -> str:
    parts = [*ps.FILLED, f"classes AS MATERIALIZED (SELECT path_id, points, ntile(4) OVER (ORDER BY points, path_id) AS quarter FROM (SELECT path_id, count(*) AS points FROM {POINTS} GROUP BY path_id) l)"]
    out = []
    for q in (1, 2, 3, 4):
        parts += [ps.cover(f"c{q}", 400, where=f"path_id IN (SELECT path_id FROM classes WHERE quarter = {q})"), ps.steps(f"g{q}", f"c{q}", 5, f"SELECT DISTINCT site_id FROM c{q}")]
        out.append(f"SELECT CAST({q} AS INTEGER) AS quarter, count(*) AS n_paths, round(avg(points), 4) AS mean_points, round((SELECT sum(gain) FROM g{q}) / 1000000 / count(*) * 100, 6) AS utility_pct FROM classes WHERE quarter = {q}")
    return ps.statement((), *parts, union(out))


@query(w13_sql())
def w13_path_length(spark, sf_dir):
    """Four classes of path length, equally many paths of each."""
    w = world(spark, sf_dir)
    length = w.points().groupBy("path_id").agg(F.count("*").alias("points"))
    # One row a path in one task: the classes are quarters of all paths in order.
    classes = materialize(length.withColumn("quarter", F.ntile(4).over(Window.orderBy("points", "path_id"))), "w13")
    rows = []
    for q in (1, 2, 3, 4):
        ids = classes.where(F.col("quarter") == q)
        cover = materialize(w.cover(pref.binary(400)).join(ids.select("path_id"), "path_id"), "w13-cover")
        m = ids.count()
        p = gr.greedy_place(cover, gr.PlacementSpec(k=5, mode="auto"), m)
        rows.append((q, m, round(ids.agg(F.avg("points")).first()[0], 4), round(ms.utility_pct(p.utility, m), 6)))
    return table(spark, rows, "quarter int, n_paths long, mean_points double, utility_pct double")


@query(ps.statement(ps.FILLED, *ps.all_levels(POINTS), ps.stats()))
def w14_levels(spark, sf_dir):
    """The levels of the index: radius, clusters, and what they hold on average."""
    return ix.index_stats(world(spark, sf_dir).index())


@query()
def w14_levels_part(spark, sf_dir):
    """The levels of the bounded index on the part network."""
    return ix.index_stats(fx.netpart(spark, sf_dir).bounded_index(LIMITS))


@query()
def w14_time(spark, sf_dir):
    """Seconds and bytes of building each level alone, on the part network."""
    w = fx.netpart(spark, sf_dir)
    rows = []
    for v in ix.level_plan(*LIMITS, fx.EPS):
        index, s = ms.timed(ix.build_index_bounded, w.points(), w.sites(), w.net().edges, w.net().nodes, (v.tau_lo, v.tau_lo), fx.EPS)
        rows.append((v.level, round(v.radius, 6), round(s, 3), ms.index_bytes(index)))
    return table(spark, rows, "level int, radius double, build_s double, file_bytes long")


def w15_sql() -> str:
    parts, out = [*ps.FILLED, *every_level((800, 1200)), f"busy_nodes AS MATERIALIZED (SELECT node_id, count(DISTINCT path_id) AS n FROM {POINTS} GROUP BY node_id)"], []
    for tau in (800, 1200):
        p = ps.level_of(tau)
        parts += [ps.cover(f"c{tau}", tau), f"busy{p} AS MATERIALIZED (SELECT cluster_id, arg_min(struct_pack(i := node_id, m := metres), struct_pack(o := -coalesce(n, 0), i := node_id)) AS b FROM member{p} LEFT JOIN busy_nodes USING (node_id) GROUP BY cluster_id)",
            f"""estb{p} AS MATERIALIZED (SELECT o.path_id, t.b.i AS site_id, min(o.metres + l.metres + t.b.m) AS metres FROM own{p} o JOIN (SELECT cluster_id, nbr_id, metres FROM link{p} UNION ALL SELECT cluster_id, cluster_id, 0 FROM centre{p}) l USING (cluster_id) JOIN busy{p} t ON t.cluster_id = l.nbr_id GROUP BY ALL)""",
            ps.cover(f"closest{tau}_c", tau, source=f"est{p}"), ps.cover(f"busiest{tau}_c", tau, source=f"estb{p}"), ps.steps(f"closest{tau}", f"closest{tau}_c", 5, ps.reps(p)), ps.steps(f"busiest{tau}", f"busiest{tau}_c", 5, f"SELECT b.i AS site_id FROM busy{p}")]
        out += [f"SELECT '{rule}' AS rule, CAST({tau} AS INTEGER) AS tau, {ps.valued(f'{rule}{tau}', f'c{tau}', POINTS)} AS utility_pct" for rule in ("closest", "busiest")]
    return ps.statement((), *parts, union(out))


@query(w15_sql())
def w15_representatives(spark, sf_dir):
    """Two rules for the representative of a cluster, valued on the true cover."""
    w = world(spark, sf_dir)
    rows = []
    for rule in ("closest", "busiest"):
        index = w.index(rule=rule)
        for tau in (800, 1200):
            rows.append((rule, tau, true_pct(w, tau, on_index(w, index, tau, 5).sites)))
    return table(spark, rows, "rule string, tau int, utility_pct double")


FX_C = [(1, 1), (1, 2), (2, 1), (2, 2), (3, 1), (3, 2), (4, 3), (5, 1), (5, 3)]


@query("WITH RECURSIVE visit AS (SELECT * FROM (VALUES " + ", ".join(map(str, FX_C)) + """) v(path_id, site_id)), cover AS (SELECT *, 1000000 AS score FROM visit),
top AS (SELECT site_id FROM visit GROUP BY site_id ORDER BY count(*) DESC, site_id DESC LIMIT 2), """ + ps.steps("g", "cover", 2, "SELECT DISTINCT site_id FROM visit") + """
SELECT m AS method, string_agg(CAST(site_id AS VARCHAR), ',' ORDER BY site_id) AS sites, CAST(1000000 * (SELECT count(DISTINCT path_id) FROM visit WHERE list_contains(list(x.site_id), visit.site_id)) AS BIGINT) AS utility
FROM (SELECT 'greedy' AS m, site_id FROM g UNION ALL SELECT 'top_weight', site_id FROM top) x GROUP BY m""")
def w16_motivation(spark, sf_dir):
    """Two sites for five paths: the most visited pair overlaps, the greedy pair covers all."""
    cover = spark.createDataFrame([(p, s, 1_000_000) for p, s in FX_C], "path_id long, site_id long, score long")
    rows = [(name, ",".join(map(str, sorted(p.sites))), p.utility) for name, p in (("greedy", gr.greedy_place(cover, gr.PlacementSpec(k=2), 5)), ("top_weight", bl.top_weight_place(cover, 2, 5)))]
    return table(spark, rows, "method string, sites string, utility long")


def w17_sql() -> str:
    k = 6
    far = "far AS MATERIALIZED (SELECT path_id, site_id, max(metres) OVER (PARTITION BY path_id) + 1 - metres AS score FROM detour)"
    parts = [*ps.FILLED, ps.cover("cov", 400), ps.steps("e", "cov", 5, existing=(55, 33)), ps.steps("g", "cov", k), far, ps.steps("f", "far", 5)]
    whole = f"(SELECT count(DISTINCT path_id) FROM {POINTS})"
    out = [f"SELECT 'existing' AS variant, 5.0::DOUBLE AS parameter, CAST(5 AS INTEGER) AS n_sites, {ps.valued('(SELECT site_id FROM e UNION ALL SELECT 55 UNION ALL SELECT 33)', 'cov', POINTS)} AS utility_pct"]
    for beta in (0.25, 0.5, 0.75):
        run = f"(SELECT * FROM (SELECT step, site_id, sum(gain) OVER (ORDER BY step) - gain AS before FROM g) r WHERE before < ceil({beta}::DOUBLE * {whole}) * 1000000)"
        out.append(f"SELECT 'quota', {beta}::DOUBLE, CAST((SELECT count(*) FROM {run}) AS INTEGER), {ps.valued(f'(SELECT site_id FROM {run})', 'cov', POINTS)}")
    out.append(f"SELECT 'inconvenience', 5.0::DOUBLE, CAST(5 AS INTEGER), {ps.valued('f', 'cov', POINTS)}")
    return ps.statement((), *parts, union(out))


@query(w17_sql())
def w17_variants(spark, sf_dir):
    """Existing services, market share and inconvenience on one workload."""
    w = world(spark, sf_dir)
    cover = materialize(w.cover(pref.binary(400)), "w17")
    base = gr.greedy_place(cover, gr.PlacementSpec(k=5, existing=(55, 33), mode="auto"), w.n_paths(), w.sites())
    rows = [("existing", 5.0, len(base.steps), pct(w, base.utility))]
    for beta in (0.25, 0.5, 0.75):
        p = gr.greedy_place(cover, gr.PlacementSpec(k=None, quota=beta, mode="auto"), w.n_paths(), w.sites())
        rows.append(("quota", beta, len(p.steps), pct(w, p.utility)))
    far, _ = gr.place_inconvenience(w.detours(), 5, w.n_paths(), w.sites())
    rows.append(("inconvenience", 5.0, len(far.steps), pct(w, gr.utility_of(cover, far.sites))))
    return table(spark, rows, "variant string, parameter double, n_sites int, utility_pct double")


def wj_sql() -> str:
    parts, out = [*ps.FILLED, ps.cover("cov", 400)], []
    for n, threshold in enumerate((0.3, 0.6)):
        parts += [ps.leaders(f"l{n}", "cov", threshold), f"c{n} AS MATERIALIZED (SELECT * FROM cov WHERE site_id IN (SELECT cluster_id FROM l{n}))", ps.steps(f"g{n}", f"c{n}", 5, f"SELECT DISTINCT cluster_id AS site_id FROM l{n}")]
        out.append(f"SELECT {threshold}::DOUBLE AS threshold, (SELECT count(DISTINCT cluster_id) FROM l{n}) AS n_clusters, {ps.valued(f'g{n}', 'cov', POINTS)} AS utility_pct")
    return ps.statement((), *parts, union(out))


@query(wj_sql())
def w_rejected_clusters(spark, sf_dir):
    """Clusters of similar covers, the rejected way: their number and the utility of one site for each of the best."""
    w = world(spark, sf_dir).by_routes()
    cover = materialize(w.cover(pref.binary(400)), "wj")
    rows = []
    for threshold in (0.3, 0.6):
        leaders = cl.jaccard_clusters(cover, threshold).select("cluster_id").distinct()
        p = gr.greedy_place(cover.join(leaders, F.col("site_id") == F.col("cluster_id"), "left_semi"), gr.PlacementSpec(k=5, mode="auto"), w.n_paths())
        rows.append((threshold, leaders.count(), pct(w, p.utility)))
    return table(spark, rows, "threshold double, n_clusters long, utility_pct double")


NEAR = sql.chain(sql.lattice(100), sql.DIST, sql.TRIPS) + "SELECT t.tau, round(avg(n), 6) AS mean_sites FROM (SELECT CAST(unnest([240, 400, 500, 800, 1200]) AS INTEGER) AS tau) t, LATERAL (SELECT a, count(*) FILTER (WHERE metres <= t.tau) AS n FROM round_trips WHERE a <> b GROUP BY a) s GROUP BY t.tau"


@query(NEAR)
def w_neighbourhood(spark, sf_dir):
    """Sites within a round trip of tau of a site, on average."""
    w = world(spark, sf_dir)
    out = None
    for tau in TAUS:
        one = ms.sites_within(w.trips(), tau).select(F.lit(tau).alias("tau"), "mean_sites")
        out = one if out is None else out.unionByName(one)
    return out


def wc_sql() -> str:
    radii = ps.level_radii()
    out = [f"""SELECT CAST({p} AS INTEGER) AS level, (SELECT count(*) FROM {POINTS}) AS points, count(*) AS steps FROM (SELECT path_id, cluster_id, lag(cluster_id) OVER (PARTITION BY path_id ORDER BY seq) AS last FROM {POINTS} JOIN member{p} USING (node_id)) s WHERE last IS NULL OR last <> cluster_id""" for p in range(len(radii))]
    return ps.statement((), *ps.FILLED[:5], *(ps.members(p, r) for p, r in enumerate(radii)), union(out))


@query(wc_sql())
def w_compression(spark, sf_dir):
    """Path points against steps of the compressed paths, by level."""
    w = world(spark, sf_dir)
    return ms.compression(w.points(), ix.compress_paths(w.points(), w.index().member))


def ws_sql() -> str:
    sessions = """opened AS (SELECT *, coalesce(CAST(floor(epoch(ts)) AS BIGINT) - CAST(floor(epoch(lag(ts) OVER w)) AS BIGINT) > 21600, false) AS new FROM visits WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
session_points AS MATERIALIZED (SELECT user_id * 10000 + CAST(sum(CAST(new AS INTEGER)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS path_id, node_id FROM opened)"""
    second = sql.detour("any", "session_points")
    for name in ("pairs", "extra", "detour"):
        second = re.sub(rf"\b{name}\b", f"{name}2", second)
    parts = [*ps.DAYS, sessions, second, ps.cover("c1", 400), ps.cover("c2", 400, source="detour2"), ps.steps("g1", "c1", 5), ps.steps("g2", "c2", 5)]
    out = [f"SELECT '{name}' AS paths_from, (SELECT count(DISTINCT path_id) FROM {points}) AS n_paths, {ps.valued(g, c, points)} AS utility_pct" for name, points, g, c in (("net100", "points", "g1", "c1"), ("net100-sessions", "session_points", "g2", "c2"))]
    return ps.statement((), *parts, union(out))


@query(ws_sql())
def w_sessions(spark, sf_dir):
    """Day trips against session trips of the same events: paths and the utility of five sites."""
    day = fx.net100(spark, sf_dir)
    alike = fx.World(spark, sf_dir, "net100-sessions", 100, lambda: pt.trips_by_session(read_table(spark, sf_dir, "events", "user_id", "ts", "event_id", "props")))
    rows = [(w.name, w.n_paths(), pct(w, plain(w, 400, 5).utility)) for w in (day, alike)]
    return table(spark, rows, "paths_from string, n_paths long, utility_pct double")


OWNED = "owned AS MATERIALIZED (SELECT path_id // 100 AS path_id, node_id FROM points)"


@query(ps.statement((*ps.DAYS[:4], OWNED, sql.detour("any", "owned")), ps.cover("cov", 240), ps.steps("g", "cov", 3), ps.placed("g", "owned")))
def w_users(spark, sf_dir):
    """Users as unions of their trips: they are served on any of them."""
    w = fx.net100u(spark, sf_dir)
    cover = materialize(dt.cover(dt.kernel_detours(w.points(), w.sites(), w.dist()), pref.binary(240)), "wu")
    p = gr.greedy_place(cover, gr.PlacementSpec(k=3, mode="auto"), w.n_paths(), w.sites())
    return p.frame(spark)


def bounds_sql() -> str:
    parts = [sql.lattice(25), sql.DIST, sql.NATION_POINTS, sql.detour(), ps.cover("cov", 240), ps.steps("g", "cov", 2),
        "sets AS (SELECT a.node_id AS s1, b.node_id AS s2 FROM nodes a JOIN nodes b ON a.node_id < b.node_id)",
        "best AS (SELECT max(u) AS u FROM (SELECT s1, s2, sum(u) AS u FROM (SELECT s1, s2, path_id, max(score) AS u FROM sets JOIN cov ON site_id IN (s1, s2) GROUP BY ALL) x GROUP BY ALL) y)"]
    return ps.statement((), *parts, """SELECT 'greedy' AS kind, round(1 - 1 / exp(1.0::DOUBLE), 6) AS bound, round((SELECT sum(gain) FROM g) / (SELECT u FROM best), 6) AS ratio, true AS holds""")


@query(bounds_sql())
def w_bounds(spark, sf_dir):
    """The greedy's guarantee against what it reaches of the optimum."""
    w = fx.net25(spark, sf_dir).by_routes()
    cover = materialize(w.cover(pref.binary(240)), "wb")
    best = ex.optimal_placement(cover, w.sites(), 2, w.n_paths(), "branch_bound").utility
    found = gr.greedy_place(cover, gr.PlacementSpec(k=2, mode="auto"), w.n_paths(), w.sites()).utility
    bound, ratio = ms.guarantee("greedy", k=2, n=25), ms.optimality_ratio(found, best)
    return table(spark, [("greedy", round(bound, 6), round(ratio, 6), ratio >= bound)], "kind string, bound double, ratio double, holds boolean")


@query()
def w_bounds_all(spark, sf_dir):
    """Each guarantee on real runs: budget, quota, index and sketch against optimum or greedy."""
    paths = fx.net25(spark, sf_dir)
    w, members = paths.by_routes(), paths.route_of()
    cover = materialize(w.cover(pref.binary(240)), "wb")
    m, sites = w.n_paths(), w.sites()
    best = ex.optimal_placement(cover, sites, 3, m, "branch_bound").utility
    three = gr.PlacementSpec(k=3, mode="auto")
    budget = gr.greedy_place(cover, gr.PlacementSpec(k=None, budget=3.0, mode="auto"), m, fx.with_costs(sites, 0.0)).utility
    index = w.index()
    on = gr.utility_of(cover, ix.index_place(index, three, pref.binary(240), m, cover).sites)
    level = ix.choose_level(index.levels, 240)
    clusters = index.clusters().where(F.col("level") == level.level).count()
    sketched = sk.greedy_place_sketch(cover, 3, m, 100, members=members)
    words = sk.sketch_words(cover, 100, members)
    exact = {r["site_id"]: r["n"] for r in cover.groupBy("site_id").agg(F.sum("times").alias("n")).collect()}
    error = max(sk.error_of(float(e), exact[int(i)]) for i, e in zip(words[0], sk.estimates(words[1]), strict=True))
    quota = gr.greedy_place(cover, gr.PlacementSpec(k=None, quota=0.5, mode="auto"), m, sites)
    least = next(k for k in range(1, 26) if ex.optimal_placement(cover, sites, k, m, "branch_bound").utility >= -(-m // 2) * 1_000_000)
    rows = [("budget", ms.guarantee("budget"), budget / best), ("index", ms.guarantee("index", k=3, clusters=clusters), on / best), ("sketch", ms.guarantee("greedy", k=3, n=25) * ms.guarantee("sketch", error=min(error, 1.0), k=3), sketched.utility / best), ("quota", ms.guarantee("quota", n=m), len(quota.steps) / least)]
    return table(spark, [(k, round(b, 6), round(r, 6), r <= b if k == "quota" else r >= b) for k, b, r in rows], "kind string, bound double, ratio double, holds boolean")
