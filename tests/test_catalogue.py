"""Every registered query runs, and those with SQL match it."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from veilgrid.plans import catalog, experiments

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Panels of ten runs; each is tested below with one run.
HEAVY = {n for n in catalog.QUERIES if n.startswith("sweep_")}


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def canonical(df):
    def text(v):
        if v is None or v is pd.NA or v is pd.NaT or (isinstance(v, float) and np.isnan(v)):
            return "NULL"
        return repr(round(float(v), 9) + 0.0) if isinstance(v, (float, np.floating)) else str(v)

    df = df[sorted(df.columns)].map(text)
    return df.sort_values(list(df.columns)).reset_index(drop=True)


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - HEAVY))
def test_query(spark, duck, sf, name):
    got = catalog.QUERIES[name](spark, sf).toPandas()
    assert len(set(got.columns)) == len(got.columns)
    if name in catalog.ORACLES:
        pd.testing.assert_frame_equal(canonical(got), canonical(duck.execute(catalog.ORACLES[name]).df()), check_dtype=False)
    else:
        assert len(got)


@pytest.mark.parametrize("panel", experiments.PANELS)
@pytest.mark.parametrize("name", experiments.STUDIED)
def test_panel(spark, sf, panel, name):
    """One run of every panel: a row a setting, distances that fit the grid, nothing moved on a single cell."""
    rows = experiments.run_panel(spark, sf, panel, name, runs=1).collect()
    assert len(rows) == len(experiments.PANELS[panel]()) and f"{panel}_{name}" in catalog.QUERIES
    for r in rows:
        assert 0 <= r.w2 <= 2**0.5 * r.d and r.runs == r.parts == (3 if experiments.STUDIED[name] else 1)
        assert r.d > 1 or r.w2 < 1e-6
        assert r.measure == ("exact" if panel in ("sweep_d", "sweep_eps", "sweep_eps_growth") else "sinkhorn")


def test_growing_subsets_are_as_large_as_privacy_allows():
    sizes = {(s["eps"], s["d"]): s["k"] for p in ("sweep_eps_growth", "sweep_d_large", "sweep_eps_large") for s in experiments.PANELS[p]() if s["method"] == "subset"}
    assert [sizes[e, 5] for e in (0.7, 1.4, 2.1, 2.8, 3.5)] == [12, 6, 3, 2, 1]
    assert {at: k for at, k in sizes.items() if at[0] >= 5 and k > 1} == {(5.0, 15): 2}  # elsewhere n / e^eps is one, or larger sets can't match


ASKED = ["area_low", "continuous_constants", "cost_table", "diagonal_share", "grid_constants", "info_best_radius"]
INHABITED = ["decay_channel", "disk_channel", "distance_loss", "distance_set", "exp_mech_channel"]


@pytest.mark.parametrize("name", [*ASKED, *INHABITED, "explain_report"])
def test_spark_reads_a_given_table(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).inputFiles()


@pytest.mark.parametrize("name", ASKED)
def test_odd_line_items_ask_as_in_sql(spark, duck, tmp_path, name):
    nan, inf = float("nan"), float("inf")
    rows = [(q, n) for q in (None, nan, inf, -inf, -3.0, 0.0, 0.4, 2.5, 17.0, 17.0, 50.0) for n in (None, -1, 0, 1, 4, 9)]
    spark.createDataFrame(rows, "l_quantity double, l_linenumber int").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    own = duck.cursor()
    own.execute(f"CREATE TEMP VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    got = catalog.QUERIES[name](spark, str(tmp_path)).toPandas()
    pd.testing.assert_frame_equal(canonical(got), canonical(own.execute(catalog.ORACLES[name]).df()), check_dtype=False)
    assert got.n.sum() == 15 * (2 if name == "grid_constants" else 1)


def test_channels_list_inhabited_cells_only(spark, duck, sf, tmp_path):
    for t, some in (("orders", "o_totalprice < 200000"), ("events", "value < 100"), ("lineitem", "l_extendedprice < 40000")):
        duck.execute(f"COPY (SELECT * FROM '{sf}/{t}.parquet' WHERE {some}) TO '{tmp_path}/{t}.parquet' (FORMAT parquet)")
    own = duck.cursor()
    for t in ("orders", "events", "lineitem"):
        own.execute(f"CREATE TEMP VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet'")
    for name in INHABITED:
        got = catalog.QUERIES[name](spark, str(tmp_path)).toPandas()
        pd.testing.assert_frame_equal(canonical(got), canonical(own.execute(catalog.ORACLES[name]).df()), check_dtype=False)
        assert name == "distance_loss" or set(zip(got.cx, got.cy)) < {(x, y) for x in range(8) for y in range(8)}
    row = catalog.QUERIES["explain_report"](spark, str(tmp_path)).first()
    assert row.reports == duck.execute(f"SELECT count(*) FROM '{tmp_path}/orders.parquet'").fetchall()[0][0] and not row.python


def test_entry_point(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries()) and e.entry(spark).count() == 25


def test_core_does_not_import_the_pipeline_operators():
    import subprocess
    import sys

    code = "import sys; from veilgrid.plans import catalog; import veilgrid.streaming.collect, veilgrid.sources.io; sys.exit(any(m.startswith('veilgrid.llm') for m in sys.modules))"
    assert subprocess.run([sys.executable, "-c", code], cwd=__file__.rsplit("/tests/", 1)[0]).returncode == 0
