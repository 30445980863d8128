"""The entry module: names, twins, and a few queries against DuckDB; it must work without the training-data parts."""

import subprocess
import sys

import duckdb
import pytest

NAMES = "region nation customer supplier part orders lineitem events documents".split()


def rows_of(columns, rows):
    pick = sorted(range(len(columns)), key=lambda i: columns[i])
    flat = lambda v: tuple(map(flat, v)) if isinstance(v, (list, tuple)) else round(v, 6) if isinstance(v, float) else v
    return sorted((tuple(flat(r[i]) for i in pick) for r in rows), key=repr)


@pytest.mark.parametrize("name", ["round_octaves_exact", "round_simple_exact", "linear_grouping", "containers_prefix", "makespan_counters_twopass", "typed_small_sums", "rank_bounds_lookup", "packing_rollup", "merge_union_check"])
def test_twins(spark, tiny, name):
    import __spark_entry__ as entry

    con = duckdb.connect()
    for t in NAMES:
        con.sql(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    got = entry.queries()[name](spark, tiny)
    want = con.sql(entry.oracle_sql()[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert rows_of(got.columns, [tuple(r) for r in got.collect()]) == rows_of(want.columns, want.fetchall())


def test_every_twin_has_a_query():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 90


def test_flagship(spark):
    import __spark_entry__ as entry

    row = entry.entry(spark).first()
    assert row["alg"] >= row["size_bound"]


def test_without_the_training_data_parts(tmp_path):
    import shutil
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    shutil.copytree(root / "packsum", tmp_path / "packsum", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; assert len(e.queries()) > 80 and not [n for n in e.queries() if n.startswith('op') or n == 'pipeline']; print('fine')"
    out = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)}, timeout=120)
    assert out.stdout.strip() == "fine", out.stderr
