"""Quality rules by robust multivariate outliers: minimum covariance determinant per language and source.

Documents become vectors of transformed statistics that don't depend on their length. For each (lang, source), each
language and the corpus, concentration steps from four deterministic starts look for the three quarters of the documents
whose scatter has the least determinant; a reweighted estimate over all documents near it follows. Every step is an
aggregate over all documents, for all groups and starts at once. A group's estimate is drawn towards its language's, and
that towards the corpus', as if each had PRIOR documents more; no size of group is treated apart. Documents at a large
Mahalanobis distance from their group are rejected."""

from __future__ import annotations

from collections.abc import Iterator
from math import exp, gamma

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, materialize, named, pick, segments, slices, text_key, utf8_buffer, word_stream

SLICE = 2 << 20
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
FEATURES = ("f_length", "f_symbols", "f_dup", "f_repeat", "f_lines")
#: Least spread of each feature: its square is added to every scatter's diagonal, as most features are 0 in most texts
#: and a scatter could not be inverted else.
FLOORS = (0.06, 0.06, 0.2, 0.15, 0.35)
#: Share of a group's documents that the concentrated part holds, share of those that are near it, and share of normal
#: documents that the cutoff keeps.
COVERAGE, NEAR, KEPT = 0.75, 0.975, 0.999
#: Documents by whose weight an estimate is drawn towards the one above it.
PRIOR = 50
#: Steps end where no determinant falls by more than this (of its logarithm).
LEAST_FALL = 1e-6
STARTS = 4
#: Groups whose parameters are broadcast, and fitted by the driver, about 1 kB each; more are joined by a shuffle.
MOST_BROADCAST_UNITS = 50_000
#: Distances and features are counted in bins of this width (of the feature, or of log2 of the distance).
BIN = 1 / 256
SYMBOLS = b"#*$%&|<>"

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(SYMBOLS)] = True
_START = (np.arange(256) & 0xC0) != 0x80
_START[[0x20, 0x0A]] = False


def statistics(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """int64 (texts, 6) in the order of STATS, for texts given as UTF-8 bytes and offsets."""
    n = len(offsets) - 1
    out = np.zeros((n, len(STATS)), np.int64)
    if not n:
        return out
    stream = word_stream(raw, offsets, lower=False)
    ends = np.flatnonzero(stream == 0x0A)
    starts = np.concatenate([[0], ends[:-1] + 1])
    out[:, 1] = np.add.reduceat(_START[stream], starts, dtype=np.int64)
    out[:, 2] = np.add.reduceat(_SYMBOL[stream], starts, dtype=np.int64)
    array, is_end = segments(stream)
    coded = pc.dictionary_encode(array)
    word = np.asarray(coded.indices).astype(np.int64)
    doc = np.cumsum(is_end) - is_end
    word, doc = word[~is_end], doc[~is_end]
    out[:, 0] = np.bincount(doc, minlength=n)
    if len(word) > 2:
        inside = np.flatnonzero(doc[2:] == doc[:-2])
        size = len(coded.dictionary)
        _, pair = np.unique(word[:-1] * size + word[1:], return_inverse=True)
        _, triple = np.unique(pair[:-1][inside] * size + word[2:][inside], return_inverse=True)
        _, again, times = np.unique(triple * n + doc[inside], return_inverse=True, return_counts=True)
        found = inside[times[again] > 1]
        marked = np.zeros(len(word), bool)
        for k in range(3):
            marked[found + k] = True
        out[:, 4] = np.bincount(doc[marked], minlength=n)
    # Lines: every text closed by a line feed.
    text = np.full(len(raw) + n, 0x0A, np.uint8)
    text[np.arange(len(raw)) + np.repeat(np.arange(n), np.diff(offsets))] = raw
    cut = np.concatenate([[0], np.flatnonzero(text == 0x0A) + 1])
    lines = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(cut) - 1, [None, pa.py_buffer(cut.astype(np.int64)), pa.py_buffer(text)])
    blank = np.zeros(256, bool)
    blank[[0x20, *range(0x09, 0x0E)]] = True
    has_word = np.add.reduceat(~blank[text], cut[:-1], dtype=np.int64) > 0
    of = np.searchsorted(offsets[1:] + np.arange(1, n + 1), cut[:-1], side="right")
    coded = pc.dictionary_encode(lines)
    line, of = np.asarray(coded.indices).astype(np.int64)[has_word], of[has_word]
    out[:, 5] = np.bincount(of, minlength=n)
    key, times = np.unique(line * n + of, return_counts=True)
    out[:, 3] = np.bincount(key % n, weights=times - 1, minlength=n).astype(np.int64)
    return out


def text_statistics(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """docs -> (doc_id, lang, source, tkey, *STATS): whole texts; null counts as the empty text, which has zeros. tkey
    is xxhash64 of the text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", SLICE):
            found = statistics(*utf8_buffer(batch.column(4)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], *(pa.array(found[:, k]) for k in range(len(STATS)))], names=["doc_id", "lang", "source", "tkey", *STATS])

    chosen = pick(docs, doc_id=id_col, lang=lang_col, source=source_col, text=text_col).select("doc_id", "lang", "source", text_key(F.col("text")).alias("tkey"), "text")
    kind = chosen.schema["doc_id"].dataType.simpleString()
    return chosen.mapInArrow(run, f"doc_id {kind}, lang string, source string, tkey long, " + ", ".join(f"{s} long" for s in STATS))


def base_failed() -> Column:
    """Fewer than 50 words, or more than half of the words in repeated 3-word windows."""
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def with_features(stats: DataFrame) -> DataFrame:
    """Adds the transformed statistics; shares go through a square root, sizes through a logarithm."""
    words, lines = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("n_lines"), F.lit(1))
    share = lambda part, whole: F.sqrt(F.least(part / whole, F.lit(4.0)))
    return stats.withColumns({"f_length": F.log(F.greatest(F.col("word_chars"), F.lit(1)) / words), "f_symbols": share(F.col("n_symbols"), words), "f_dup": share(F.col("n_dup_lines"), lines), "f_repeat": share(F.col("n_repeat_words"), words), "f_lines": F.log(words / lines)})


def chi2_share(x: float, degrees: int) -> float:
    """The share of a chi-squared variable's values up to x."""
    term = total = 1 / gamma(degrees / 2 + 1)
    k = 0
    while term > 1e-17 * total:
        k += 1
        term *= x / 2 / (degrees / 2 + k)
        total += term
    return total * (x / 2) ** (degrees / 2) * exp(-x / 2)


def chi2_value(share: float, degrees: int) -> float:
    low, high = 0.0, 1000.0
    for _ in range(100):
        middle = (low + high) / 2
        low, high = (middle, high) if chi2_share(middle, degrees) < share else (low, middle)
    return low


def consistency(share: float) -> float:
    """What the scatter of the nearest `share` of normal documents has to be multiplied by to be that of all."""
    k = len(FEATURES)
    return share / chi2_share(chi2_value(share, k), k + 2)


#: Squared distance above which a document is rejected.
CUTOFF = chi2_value(KEPT, len(FEATURES))


def bin_quantile(rows: DataFrame, keys: list[str], value: Column, share: float) -> DataFrame:
    """(keys, bin): the first bin by which `share` of a group's rows are counted. Counts are pre-aggregated, so no
    task sees more of a group than its distinct bins."""
    counts = rows.groupBy(*keys, F.floor(value / BIN).alias("bin")).agg(F.count("*").alias("n"))
    ordered = Window.partitionBy(*keys).orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    summed = counts.withColumn("upto", F.sum("n").over(ordered)).withColumn("all", F.sum("n").over(Window.partitionBy(*keys)))
    return summed.where(F.col("upto") >= share * F.col("all")).groupBy(*keys).agg(F.min("bin").alias("bin"))


def distance(params: str = "p") -> Column:
    """Squared Mahalanobis distance of a row's features under params.mu and the packed inverse params.inv."""
    k = len(FEATURES)
    diff = [F.col(f) - F.col(f"{params}.mu")[i] for i, f in enumerate(FEATURES)]
    total, at = F.lit(0.0), 0
    for i in range(k):
        for j in range(i, k):
            total = total + (1 if i == j else 2) * F.col(f"{params}.inv")[at] * diff[i] * diff[j]
            at += 1
    return F.greatest(total, F.lit(0.0))


def log_distance() -> Column:
    return F.log2(F.col("d2") + 1e-9)


def with_params(rows: DataFrame, params: DataFrame, few: bool) -> DataFrame:
    """rows(unit, ...) with each row's params as struct p; units without params are left out."""
    named = params.select(F.col("unit").alias("of"), F.struct(*(c for c in params.columns if c != "unit")).alias("p"))
    return rows.join(F.broadcast(named) if few else named, F.col("unit") == F.col("of")).drop("of")


def packed(matrix: np.ndarray) -> list[float]:
    # Rounded, so that the order in which Spark adds doubles cannot show.
    return [float(f"{x:.9g}") for x in matrix[np.triu_indices(len(FEATURES))]]


def unpacked(values) -> np.ndarray:
    out = np.zeros((len(FEATURES), len(FEATURES)))
    out[np.triu_indices(len(FEATURES))] = values
    return out + np.triu(out, 1).T


def centred(n: float, sums, pairs) -> tuple[np.ndarray, np.ndarray]:
    """Mean and scatter of n rows from their sums and sums of products."""
    mu = np.array(sums) / n
    return mu, unpacked(pairs) / n - np.outer(mu, mu)


PARAMS = "unit string, start int, n double, mu array<double>, cov array<double>, inv array<double>, det double"


def param_rows(found: list[tuple]) -> pa.RecordBatch:
    """(unit, start, n, mu, scatter, determinant or None) -> rows of PARAMS; the scatter is completed by the floors."""
    out = []
    for unit, start, n, mu, cov, det in found:
        full = cov + np.diag(np.square(FLOORS))
        out.append((unit, start, float(n), [float(f"{x:.9g}") for x in mu], packed(full), packed(np.linalg.inv(full)), float(f"{np.linalg.slogdet(full)[1]:.9g}") if det is None else det))
    columns = list(zip(*out, strict=True)) if out else [[]] * 7
    vector = pa.list_(pa.float64())
    kinds = (pa.string(), pa.int32(), pa.float64(), vector, vector, vector, pa.float64())
    return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True)], names=["unit", "start", "n", "mu", "cov", "inv", "det"])


def mapped(rows: DataFrame, run, schema: str, few: bool) -> DataFrame:
    """run over rows of one a group or start: few of them (checked) in the driver, so that no Python worker is started for a
    handful of small matrices, more of them by the executors."""
    if not few:
        return rows.mapInArrow(run, schema)
    out = list(run(iter(rows.toArrow().to_batches())))
    return rows.sparkSession.createDataFrame(pa.Table.from_batches(out), schema) if out else rows.sparkSession.createDataFrame([], schema)


def product_sums(values: list[Column]) -> Column:
    return F.array(*(F.sum(a * b) for i, a in enumerate(values) for b in values[i:]))


def fitted(rows: DataFrame, few: bool) -> DataFrame:
    """rows(unit, start, features) -> PARAMS: mean and scatter of each unit's and start's rows."""
    columns = [F.col(f) for f in FEATURES]
    sums = rows.groupBy("unit", "start").agg(F.count("*").alias("n"), F.array(*(F.sum(f) for f in FEATURES)).alias("s"), product_sums(columns).alias("ss"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield param_rows([(unit, start, n, *centred(n, s, ss), None) for unit, start, n, s, ss in zip(*(c.to_pylist() for c in batch.columns), strict=True)])

    return mapped(sums, run, PARAMS, few)


def started(rows: DataFrame, few: bool) -> DataFrame:
    """PARAMS of four deterministic starts a unit: medians and median deviations; mean and scatter; scatter of directions
    from the median; scatter of hyperbolic tangents of the standardised features."""
    long = rows.select("unit", F.posexplode(F.array(*FEATURES)).alias("f", "x"))
    middle = bin_quantile(long, ["unit", "f"], F.col("x"), 0.5).select("unit", "f", ((F.col("bin") + 0.5) * BIN).alias("m"))
    vector = lambda df, value: df.groupBy("unit").agg(F.expr(f"transform(array_sort(collect_list(struct(f, {value}))), x -> x.{value})").alias(value))
    medians = materialize(vector(middle, "m"), "mcd-medians")
    off = with_params(rows, medians, few).select("unit", F.posexplode(F.array(*(F.abs(F.col(f) - F.col("p.m")[i]) for i, f in enumerate(FEATURES)))).alias("f", "x"))
    spread = bin_quantile(off, ["unit", "f"], F.col("x"), 0.5).select("unit", "f", (1.4826 * (F.col("bin") + 0.5) * BIN).alias("d"))
    scales = materialize(medians.join(vector(spread, "d"), "unit"), "mcd-scales")
    floor = F.array(*(F.lit(float(x)) for x in FLOORS))
    told = scales.select("unit", "m", F.zip_with("d", floor, lambda d, f: F.sqrt(d * d + f * f)).alias("s"))
    z = [F.col(f"z{i}") for i in range(len(FEATURES))]
    known = with_params(rows, told, few).withColumns({f"z{i}": (F.col(f) - F.col("p.m")[i]) / F.col("p.s")[i] for i, f in enumerate(FEATURES)})
    known = known.withColumn("r2", F.greatest(sum((c * c for c in z), F.lit(0.0)), F.lit(1e-18)))
    for i in range(len(FEATURES)):
        known = known.withColumn(f"h{i}", F.tanh(f"z{i}"))
    h = [F.col(f"h{i}") for i in range(len(FEATURES))]
    first = [F.col(f) for f in FEATURES]
    signs = F.array(*(F.sum(a * b / F.col("r2")) for i, a in enumerate(z) for b in z[i:]))
    sums = known.groupBy("unit").agg(F.first("p.m").alias("m"), F.first("p.s").alias("s"), F.count("*").alias("n"), F.array(*(F.sum(f) for f in FEATURES)).alias("s1"), product_sums(first).alias("s2"), signs.alias("u2"), F.array(*(F.sum(c) for c in h)).alias("h1"), product_sums(h).alias("h2"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for unit, m, s, n, s1, s2, u2, h1, h2 in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                m, both = np.array(m), np.outer(s, s)
                scatters = (np.diag(np.square(s)), centred(n, s1, s2)[1], both * unpacked(u2) / n * len(FEATURES), both * centred(n, h1, h2)[1])
                found += [(unit, k, n, np.array(s1) / n if k == 1 else m, c, float("inf")) for k, c in enumerate(scatters)]
            yield param_rows(found)

    out = materialize(mapped(sums, run, PARAMS, few), "mcd-start")
    discard(medians, scales)
    return out


def spread_over(rows: DataFrame, params: DataFrame, few: bool) -> DataFrame:
    """rows(unit, features) -> (unit, start, features, d2): a row for each start of its unit."""
    per_unit = params.groupBy("unit").agg(F.collect_list(F.struct("start", "mu", "inv")).alias("all"))  # STARTS entries at most
    every = with_params(rows, per_unit, few).select("unit", *FEATURES, F.explode("p.all").alias("p"))
    return every.select("unit", F.col("p.start").alias("start"), *FEATURES, distance().alias("d2"))


def nearest(measured: DataFrame, coverage: float, few: bool) -> DataFrame:
    """Of each unit's and start's rows the nearest ones that make up `coverage` of them."""
    last = bin_quantile(measured, ["unit", "start"], log_distance(), coverage).select(F.col("unit").alias("of"), F.col("start").alias("from"), F.col("bin").alias("last"))
    return measured.join(F.broadcast(last) if few else last, (F.col("unit") == F.col("of")) & (F.col("start") == F.col("from"))).where(F.floor(log_distance() / BIN) <= F.col("last"))


def estimate(rows: DataFrame, coverage: float = COVERAGE) -> DataFrame:
    """rows(unit, features) -> (unit, n, mu, cov): the minimum covariance determinant estimate of every unit.

    Concentration steps from every start go on while its determinant falls; a step that doesn't lower it is not taken.
    The start that ends with the least determinant counts (ties: the first). n, mu and cov are those of the documents
    within the NEAR quantile of it; both scatters are made consistent for normal documents."""
    few = rows.select("unit").distinct().count() <= MOST_BROADCAST_UNITS
    params = started(rows, few)
    active, settled = params, []
    while True:
        stepped = fitted(nearest(spread_over(rows, active, few), coverage, few), few)
        old = active.select(*(F.col(c).alias(f"old_{c}") for c in active.columns))
        both = materialize(stepped.join(old, (F.col("unit") == F.col("old_unit")) & (F.col("start") == F.col("old_start"))).withColumn("falls", F.col("det") < F.col("old_det") - LEAST_FALL), "mcd-step")
        settled.append(both.where("not falls").select(*(F.col(f"old_{c}").alias(c) for c in active.columns)))
        if not both.where("falls").limit(1).count():
            break
        active = both.where("falls").select(*active.columns)
    ended = settled[0]
    for part in settled[1:]:
        ended = ended.unionByName(part)
    best = ended.groupBy("unit").agg(F.min_by(F.struct("mu", "inv"), F.struct("det", "start")).alias("b"))
    raw = materialize(best.select("unit", F.lit(0).alias("start"), F.col("b.mu").alias("mu"), F.transform("b.inv", lambda x: x / consistency(coverage)).alias("inv")), "mcd-raw")
    close = fitted(spread_over(rows, raw, few).where(F.col("d2") <= chi2_value(NEAR, len(FEATURES))), few)
    # Some documents of every unit are near: the mean distance of its nearest ones is below 5.
    out = close.select("unit", "n", "mu", F.transform("cov", lambda x: x * consistency(NEAR)).alias("cov"))
    return materialize(out, "mcd-estimate")


def drawn_together(own: DataFrame, above: DataFrame, prior: float) -> DataFrame:
    """own(unit, up, n, mu, cov), above(unit, mu, cov): own as if `prior` documents of its unit `up` were added."""
    upper = above.select(F.col("unit").alias("u"), F.col("mu").alias("mu_up"), F.col("cov").alias("cov_up"))
    mix = lambda a, b: F.zip_with(a, b, lambda x, y: (F.col("n") * x + prior * y) / (F.col("n") + prior))
    return own.join(upper, F.col("up") == F.col("u")).select("unit", "n", mix("mu", "mu_up").alias("mu"), mix("cov", "cov_up").alias("cov"))


def inverted(params: DataFrame, few: bool) -> DataFrame:
    """(unit, mu, cov) -> (unit, mu, inv)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            inv = [packed(np.linalg.inv(unpacked(c))) for c in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(inv, pa.list_(pa.float64()))], names=["unit", "mu", "inv"])

    return mapped(params.select("unit", "mu", "cov"), run, "unit string, mu array<double>, inv array<double>", few)


def unit_name(*columns: str) -> Column:
    return F.concat_ws("/", F.lit(str(len(columns))), *(F.coalesce(F.concat(F.lit("="), F.hex(c)), F.lit("-")) for c in columns))


def group_params(passed: DataFrame, coverage: float = COVERAGE, prior: float = PRIOR) -> DataFrame:
    """passed(lang, source, features) -> (unit, mu, inv) of every (lang, source), by unit_name."""
    names = F.array(unit_name("lang", "source"), unit_name("lang"), unit_name())
    fed = materialize(passed.select(F.explode(names).alias("unit"), *FEATURES), "quality-features")
    found = estimate(fed, coverage)
    depth = F.substring("unit", 1, 1)
    corpus = found.where(depth == "0")
    lang = drawn_together(found.where(depth == "1").withColumn("up", unit_name()), corpus, prior)
    up = F.concat(F.lit("1"), F.expr("substring(substring_index(unit, '/', 2), 2)"))  # the group's name without its source
    few = found.count() <= MOST_BROADCAST_UNITS
    params = materialize(inverted(drawn_together(found.where(depth == "2").withColumn("up", up), lang, prior), few), "quality-params")
    discard(fed, found)
    return params


def judge(docs: DataFrame, *, cutoff: float = CUTOFF, coverage: float = COVERAGE, prior: float = PRIOR, **columns: str) -> DataFrame:
    """docs -> (doc_id, lang, source, tkey, *STATS, base_failed, distance, kept), a row for every input row.

    Documents that fail the base rules are rejected and take no part in the estimates. Null languages and sources are
    values of their own. Repeated rows count each. An empty table gives no rows; where no document passes the base
    rules there is nothing to estimate and all are rejected."""
    stats = materialize(text_statistics(docs, **columns), "quality-stats")
    passed = with_features(stats.where(~base_failed())).withColumn("unit", unit_name("lang", "source"))
    params = group_params(passed, coverage, prior)
    few = params.count() <= MOST_BROADCAST_UNITS
    measured = with_params(passed, params, few).withColumn("distance", F.round(distance(), 6))
    good = measured.select("doc_id", "lang", "source", "tkey", *STATS, F.lit(False).alias("base_failed"), "distance", (F.col("distance") <= cutoff).alias("kept"))
    bad = stats.where(base_failed()).select("doc_id", "lang", "source", "tkey", *STATS, F.lit(True).alias("base_failed"), F.lit(None).cast("double").alias("distance"), F.lit(False).alias("kept"))
    return good.unionByName(bad)


def keep_good(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source", **options) -> DataFrame:
    """docs without the rejected documents, all columns kept; rows that repeat stay or go together."""
    judged = judge(docs, id_col=id_col, text_col=text_col, lang_col=lang_col, source_col=source_col, **options)
    rejected = judged.where(~F.col("kept")).select(F.struct("doc_id", "lang", "source", "tkey").alias("gone")).distinct()
    here = F.struct(named(docs, id_col).alias("doc_id"), named(docs, lang_col).alias("lang"), named(docs, source_col).alias("source"), text_key(named(docs, text_col)).alias("tkey"))
    return docs.join(rejected, here == rejected["gone"], "left_anti")
