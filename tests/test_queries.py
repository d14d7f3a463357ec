"""Queries against their DuckDB twins on the small tables."""

import datetime
import glob
import os
from decimal import Decimal

import duckdb
import numpy as np
import pandas as pd
import pytest

from tidelabel.queries import catalog, experiments

CORE = [n for n in catalog.ORACLES if not n.startswith("stream_")]


def plain(v):
    """One form for values that both engines give in their own types."""
    if v is None or v is pd.NaT or v is pd.NA or (not hasattr(v, "__len__") and v != v):
        return None
    if hasattr(v, "__len__") and not isinstance(v, str):
        return tuple(plain(x) for x in v)
    if isinstance(v, (bool, np.bool_, str)):
        return v
    if isinstance(v, (datetime.date, pd.Timestamp)):
        return pd.Timestamp(v)
    return float(v) if isinstance(v, (int, float, Decimal, np.number)) else v


def flat(df: pd.DataFrame) -> list:
    return sorted(repr(tuple(map(plain, row))) for row in df[sorted(df.columns)].astype(object).itertuples(index=False, name=None))


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from read_parquet('{f}')")
    return con


@pytest.mark.parametrize("name", CORE)
def test_query_equals_its_twin(spark, sf_dir, duck, name):
    ours, twin = catalog.QUERIES[name](spark, sf_dir).toPandas(), duck.execute(catalog.ORACLES[name]).df()
    assert sorted(ours.columns) == sorted(twin.columns) and len(ours) == len(twin)
    assert flat(ours) == flat(twin)


@pytest.mark.parametrize("name", ["stream_tumbling", "stream_majority", "stream_interval_join"])
def test_streams_equal_their_batch_twins(spark, sf_dir, duck, name):
    ours, twin = catalog.QUERIES[name](spark, sf_dir).toPandas(), duck.execute(catalog.ORACLES[name]).df()
    assert sorted(ours.columns) == sorted(twin.columns) and flat(ours) == flat(twin)


def test_bucketed_tables_join_without_a_shuffle(spark, sf_dir):
    plan = catalog.QUERIES["io_bucketed_join"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan


@pytest.mark.parametrize("name", ["replay_round", "exp1_bilevel", "detector_b"])
def test_experiments_run(spark, sf_dir, name):
    assert experiments.QUERIES[name](spark, sf_dir).count() > 0


def test_workload_compares_all_methods(spark):
    rows = experiments.QUERIES["exp1_quality"](spark, "/root/testdata/sf0.01").collect()
    by = {(r.method, r.strategy, r.b, r.refresh): r for r in rows}
    budget, small = max(r.b for r in rows), min(r.b for r in rows)
    assert len(by) == len(rows) == 2 * 9 + 1 and all(r.n_cleaned == budget for r in rows)
    for b in (budget, small):
        # with two classes least confidence and entropy choose the same rows
        assert by["least_confidence", "HUMAN3", b, "retrain"].loss_after == by["entropy", "HUMAN3", b, "retrain"].loss_after
        ours = by["uplift", "SUGGEST", b, "retrain"]
        assert ours.loss_after < by["random", "HUMAN3", b, "retrain"].loss_after and ours.agreed >= 0.75 * budget and ours.votes == 0
    again = by["uplift", "SUGGEST", small, "replay"]
    assert abs(again.loss_after - by["uplift", "SUGGEST", small, "retrain"].loss_after) < 0.02


def test_methods_over_repeated_draws(spark, sf_dir):
    rows = {r.method: r for r in experiments.spread(spark, sf_dir, ("doc_quality",), 2).collect()}
    assert set(rows) == {"uplift", "deletion", "least_confidence", "random"}
    assert all(r.repeats == 2 and r.loss_spread > 0 for r in rows.values()) and rows["uplift"].loss_mean < rows["random"].loss_mean


def test_pruner_in_rounds_picks_as_full_scoring(spark, sf_dir):
    rows = experiments.QUERIES["exp2_select"](spark, sf_dir).collect()
    assert rows and all(r.same_picks for r in rows) and {r.workload for r in rows if r["last"]} == {"line_planted", "doc_quality", "vec_planted4"}
    assert min(r.n_candidates / r.n_pool for r in rows if r.method == "pruner") < 0.02
