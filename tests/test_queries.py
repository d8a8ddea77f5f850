"""Every query with SQL against DuckDB on the smallest tables; the others run and return rows."""

import pytest

import waysite.queries
import waysite.relational
import waysite.streaming.queries
import waysite.workloads
from tests.compare import database, same

PARTS = (waysite.queries, waysite.relational, waysite.streaming.queries, waysite.workloads)
WITH_SQL = [(p, n) for p in PARTS for n in p.ORACLES]
WITHOUT = [(p, n) for p in PARTS for n in p.QUERIES if n not in p.ORACLES and n != "w1_optimum"]


@pytest.fixture(scope="module")
def con(sf_dir):
    return database(sf_dir)


@pytest.mark.parametrize("part,name", WITH_SQL, ids=[n for _, n in WITH_SQL])
def test_equals_sql(spark, sf_dir, con, part, name):
    same(part.QUERIES[name](spark, sf_dir), con, part.ORACLES[name])


@pytest.mark.parametrize("part,name", WITHOUT, ids=[n for _, n in WITHOUT])
def test_runs(spark, sf_dir, part, name):
    assert part.QUERIES[name](spark, sf_dir).count() > 0


def test_optimum_samples(spark, sf_dir, monkeypatch):
    """Ten samples of fifty sites, each with every contender for one to five sites, none above the optimum; two are run here."""
    assert (waysite.workloads.SAMPLES, waysite.workloads.SAMPLE_SITES, waysite.workloads.SAMPLE_PATHS) == (10, 50, 1000)
    monkeypatch.setattr(waysite.workloads, "SAMPLES", 2)
    rows = waysite.workloads.QUERIES["w1_optimum"](spark, sf_dir).collect()
    assert sorted((r["sample"], r["k"], r["method"]) for r in rows) == [(s, k, m) for s in range(2) for k in range(1, 6) for m in ("greedy", "greedy_fm", "index", "index_fm", "optimum")]
    assert all(0 < r["ratio"] <= 1 for r in rows)
    assert all(r["ratio"] >= 1 - (1 - 1 / r["k"]) ** r["k"] for r in rows if r["method"] == "greedy")
