"""Headline queries of the placement engine at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from waysite import fixtures as fx  # noqa: E402
from waysite import measures as ms  # noqa: E402
from waysite.functions import preference as pref  # noqa: E402
from waysite.operators import detours as dt  # noqa: E402
from waysite.operators import greedy as gr  # noqa: E402
from waysite.operators import index as ix  # noqa: E402
from waysite.operators import sketch as sk  # noqa: E402
from waysite.sources.tables import materialize  # noqa: E402


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "8"))
    conf = {"spark.sql.shuffle.partitions": max(cpus, 8), "spark.sql.session.timeZone": "UTC", "spark.ui.enabled": "false", "spark.driver.memory": "8g", "spark.ui.showConsoleProgress": "false"}
    spark = SparkSession.builder.master(f"local[{cpus}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    measures: dict[str, float] = {}

    def timed(name, f):
        began = time.perf_counter()
        out = f()
        seconds[name] = round(time.perf_counter() - began, 3)
        return out

    w = fx.net100(spark, sf_dir, filled=True)
    timed("paths_filled", lambda: w.points().count())
    timed("distances", lambda: w.trips().count())
    timed("detours", lambda: w.detours().count())
    binary = pref.binary(800)
    cover = timed("cover_800", lambda: materialize(w.cover(binary), "bench"))
    plain = timed("greedy_k5", lambda: gr.greedy_place(cover, gr.PlacementSpec(k=5), w.n_paths(), w.sites()))
    delta = timed("greedy_delta_k5", lambda: gr.greedy_place(cover, gr.PlacementSpec(k=5, mode="delta"), w.n_paths(), w.sites()))
    index = timed("index_build", lambda: w.index())
    found = timed("index_query_k5", lambda: ix.index_place(index, gr.PlacementSpec(k=5, mode="delta"), binary, w.n_paths()))
    timed("index_fm_query_k5", lambda: ix.index_place(index, gr.PlacementSpec(k=5), binary, w.n_paths(), sketch_copies=30))
    fm = timed("greedy_fm_k5", lambda: sk.greedy_place_sketch(cover, 5, w.n_paths(), 30))
    timed("add_paths", lambda: ix.add_paths(index, w.points().where("path_id % 100 >= 25").withColumn("path_id", F.col("path_id") + 10**9), w.dist()))
    big = fx.netsup(spark, sf_dir, filled=False)
    reach = pref.binary(300)
    near = timed("netsup_cover_300", lambda: materialize(dt.cover(dt.kernel_detours(big.points(), big.sites(), big.dist(), 300), reach), "bench"))
    best = timed("netsup_greedy_k5", lambda: gr.greedy_place(near, gr.PlacementSpec(k=5, mode="delta"), big.n_paths()))
    far = timed("netsup_index_build", lambda: big.bounded_index((210, 2400)))
    on_far = timed("netsup_index_query_k5", lambda: ix.index_place(far, gr.PlacementSpec(k=5), reach, big.n_paths()))
    measures["netsup_index_loss_pct"] = round(100 * ms.relative_loss(best.utility, gr.utility_of(near, on_far.sites)), 4)
    assert plain.sites == delta.sites
    measures["greedy_pct"] = round(ms.utility_pct(plain.utility, w.n_paths()), 4)
    measures["index_loss_pct"] = round(100 * ms.relative_loss(plain.utility, gr.utility_of(cover, found.sites)), 4)
    measures["fm_loss_pct"] = round(100 * ms.relative_loss(plain.utility, fm.utility), 4)
    print(json.dumps({"metric": "placement_total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "measures": measures, "sf": Path(sf_dir).name.removeprefix("sf")}))


if __name__ == "__main__":
    main()
