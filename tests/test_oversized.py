"""Events over the capacity of a bin: their queries agree with the SQL, which keeps such sizes as they are."""

import duckdb
import numpy as np
import pandas as pd
import pytest

from packsum.operators import estimate, solvers
from packsum.params import Eps
from packsum.sources.tables import Items
from tests.test_entry import rows_of

NAMES = ["dyadic_fixed_level", "geometric_grouping_offline", "next_fit_fold", "octave_inequality", "octave_profile", "pack_report_events_bfd", "pack_report_events_ffd", "pack_report_events_lp", "pack_report_events_nfd", "properties_sequential"]


def agrees(spark, folder, name, values):
    import __spark_entry__ as entry

    n = len(values)
    ts = pd.Timestamp("2024-01-01") + pd.to_timedelta(np.arange(n), unit="min")
    path = str(folder / "events.parquet")
    pd.DataFrame({"event_id": np.arange(n), "ts": ts.astype("datetime64[us]"), "user_id": np.arange(n) % 7, "event_type": "x", "value": values, "props": ""}).to_parquet(path)
    con = duckdb.connect()
    con.sql(f"create view events as select * from '{path}'")
    got, want = entry.queries()[name](spark, str(folder)), con.sql(entry.oracle_sql()[name])
    assert rows_of(got.columns, [tuple(r) for r in got.collect()]) == rows_of(want.columns, want.fetchall())


@pytest.mark.parametrize("name", NAMES)
def test_events_over_a_bin(spark, tmp_path, name):
    values = np.random.default_rng(1).integers(0, 40_000, 700) / 100
    values[::9] = 520.16
    values[5::90] = 560.21
    agrees(spark, tmp_path, name, values)


@pytest.mark.parametrize("name", ["dyadic_fixed_level", "next_fit_fold", "octave_inequality", "octave_profile", "pack_report_events_bfd", "pack_report_events_ffd", "pack_report_events_lp", "pack_report_events_nfd"])
def test_events_over_several_bins(spark, tmp_path, name):
    values = np.random.default_rng(2).integers(0, 40_000, 700) / 100
    values[::50] = [500.0, 500.01, 1000.0, 1000.01, 1499.99, 2500.0, 2617.35, 999_999.0, 3_000_000.0, 600.0, 1200.0, 0.0, 510.0, 5000.0]
    agrees(spark, tmp_path, name, values)


@pytest.mark.parametrize("solver", ["ffd", "lp", "nfd", "bfd"])
@pytest.mark.parametrize("values", [[], [None, None], [700.0], [-3.0, None, 0.0, 1700.25]], ids=["none", "nulls", "one", "odd"])
def test_reports_of_odd_events(spark, tmp_path, solver, values):
    agrees(spark, tmp_path, f"pack_report_events_{solver}", np.array(values, float))


def test_a_large_item_fills_whole_bins_and_packs_its_last_piece(spark):
    items = Items(spark.createDataFrame([(1000,), (2000,), (2300,), (3050,), (700,), (40,)], "size_units long"), 1000, over=True)
    r = estimate.report(items, Eps(1, 5), estimate.rounded(items, Eps(1, 5))).first()
    assert (r["n_small"], r["n_big"], r["small_total"], r["big_total"], r["size_bound"]) == (1, 5, 40, 9050, 10)
    pieces = [1000, 1000, 300, 700]  # and 50 and 40, which are small; 1 + 2 + 3 bins are full
    assert r["rounded_bins"] == 6 + solvers.bins(solvers.solve_lp([(s, pieces.count(s)) for s in set(pieces)], 1000)[0])
    assert r["alg"] >= r["size_bound"]
