"""Makespan, containers, typed counters, vector packing and rank queries against exact results."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from packsum.operators import containers, makespan, properties, ranking, solvers, typed, vectors
from packsum.operators.estimate import PackHow
from packsum.params import Eps, container_gamma
from packsum.sources import tables

SIZES = "size_units long"


def sizes(spark, values):
    return spark.createDataFrame([(v,) for v in values], SIZES)


def vecs(spark, rows, cap=1000):
    return tables.Vectors(spark.createDataFrame([(i, list(v)) for i, v in enumerate(rows)], "job_id long, v array<long>"), len(rows[0]), cap)


def test_exponents_at_boundaries(spark):
    eps = Eps(1, 1)
    got = {r["size_units"]: r["exp_i"] for r in makespan.with_exponent(sizes(spark, [0, 1, 2, 3, 4, 5, 8, 9, 1024, 1025]), eps).collect()}
    assert got == {0: None, 1: -1, 2: 0, 3: 1, 4: 1, 5: 2, 8: 2, 9: 3, 1024: 9, 1025: 10}


def test_one_and_two_passes_agree(spark, tiny):
    df = tables.event_items(spark, tiny).df
    a = makespan.cut(makespan.counters(df, Eps(1, 5)), Eps(1, 5)).collect()
    b = makespan.summary_two_pass(df, Eps(1, 5)).collect()
    assert sorted(map(tuple, a), key=repr) == sorted(map(tuple, b), key=repr)


@pytest.mark.parametrize("order", ["up", "down", "random"])
def test_drift_of_the_small_total(order):
    rng = random.Random(3)
    data = [rng.randint(1, 10**6) for _ in range(2000)]
    data = sorted(data) if order == "up" else sorted(data, reverse=True) if order == "down" else data
    s = makespan.GeometricStream(Eps(1, 5))
    for p in data:
        s.add(p)
    exact = sum(p for p in data if s.exponent(p) < s.q - s.k)
    assert exact <= s.small <= 1.2 * exact + len(data)
    assert s.most <= s.k + 3


def test_makespan_within_its_factor(spark, tiny):
    for r in makespan.makespan_report(tables.document_items(spark, tiny).df, Eps(1, 10), [2, 8]).collect():
        assert r["valid"], r


def test_rank_by_packing_is_exact_without_rounding(spark):
    values = spark.createDataFrame([(v,) for v in (1, 5, 5, 7, 9, 12, 12, 15, 18, 20)], "x long")
    qs = [0, 1, 6, 12, 20, 25]
    exact = {r["q"]: r for r in ranking.rank_exact(values, "x", qs).collect()}
    got = {r["q"]: r["rank_estimate"] for r in ranking.rank_by_packing(spark, values, "x", qs, Eps(1, 5)).collect()}
    for q in qs:
        assert got[q] == exact[q]["rank"], q
        assert exact[q]["optimum"] == 20 + exact[q]["rank"]


def test_quantile_by_rank(spark):
    values = spark.range(1, 1001).select(F.col("id").alias("x"))
    assert abs(ranking.quantile_by_rank(spark, values, "x", 0.5, Eps(1, 10)) - 500) <= 0.4 * 1000 / 10 + 2


@pytest.mark.parametrize("rows", [10, 14, 61, 200])
def test_tight_instance(spark, rows):
    keys = spark.createDataFrame([(k * k * 97,) for k in range(rows)], "k long")
    for m, inv in ((2, 2), (2, 4), (3, 3)):
        v = tables.tight_instance(keys, "k", m, inv)
        jobs = sorted((r["job_id"], tuple(r["v"])) for r in v.df.collect())
        share = (rows - m) // (m * (m - 1) * inv)
        assert [j for j, _ in jobs] == [k * k * 97 for k in range(rows)] and v.cap == share * inv
        used = [x for _, x in jobs if any(x)]
        if share:
            assert sum(x[m] > 0 for x in used) == m and len(used) == m + m * (m - 1) * inv * share
        assert all(sum(x[k] for x in used) == m * v.cap for k in range(m + 1))
        if share and len(used) <= 14:
            assert containers.optimum_exact(used, m) == v.cap
        summary = containers.containers_grouped(v, "grp").collect()
        assert sum(r["n_jobs"] for r in summary) == rows and all(r["kind"] == "big" or r["norm"] <= share for r in summary)
        if share:
            assert containers.optimum_exact([tuple(r["vec"]) for r in summary], m) / v.cap >= 2 - 1 / m


def test_tight_queries_read_customers(spark, tmp_path):
    import __spark_entry__ as entry

    for n in (233,):
        path = str(tmp_path / str(n))
        spark.range(n).select((F.col("id") * 11 + 5).alias("c_custkey")).write.parquet(f"{path}/customer.parquet")
        assert entry.queries()["tight_instance"](spark, path).count() == n
        assert all(r["jobs"] == n and r["as_proved"] for r in entry.queries()["w11_tight_checked"](spark, path).collect())
        plain = entry.queries()["w11_tight"](spark, path)
        assert [r["summary_optimum"] for r in plain.filter("method = 'grouped'").collect()] == [1.5, 1.5, 5 / 3]


@pytest.mark.parametrize("order", ["up", "down", "random"])
@pytest.mark.parametrize("first_fit", [False, True])
def test_sequential_containers(order, first_fit):
    rng = np.random.default_rng(1)
    data = rng.integers(0, 1000, (1500, 3))
    key = {"up": data.max(axis=1), "down": -data.max(axis=1), "random": rng.random(len(data))}[order]
    gamma, m = container_gamma(Eps(1, 1), 3), 4
    s = containers.ContainerStream(m, gamma, 3, first_fit)
    for v in data[np.argsort(key)]:
        s.add(v)
    rows = s.rows()
    assert (np.array([r[1] for r in rows]).sum(axis=0) == data.sum(axis=0)).all()
    assert sum(r[3] for r in rows) == len(data)
    assert all(r[2] <= 2 * s.small + 2 for r in rows if r[0] == "container")
    assert all(r[2] > s.small for r in rows if r[0] == "big")
    assert len(rows) <= 3 * m / float(gamma) + 1


def test_container_variants_keep_all_load(spark, tiny):
    v = tables.document_vectors(spark, tiny)
    gamma = container_gamma(Eps(1, 1), 3)
    half = [tables.Vectors(v.df.filter(F.col("job_id") % 2 == k), 3, v.cap) for k in (0, 1)]
    built = {
        "prefix": (containers.containers_prefix(v, 4, gamma), 17),
        "parallel": (containers.containers_parallel(v, 4, gamma), 1),
        "merged": (containers.merge_containers(*(containers.containers_parallel(h, 4, gamma) for h in half), 3, 4, gamma), 1),
    }
    for name, (s, extra) in built.items():
        r = containers.container_report(s, v, 4, gamma, extra).first()
        assert r["capacity_ok"] and r["load_kept"] and r["space_ok"], (name, r)
    assert containers.placement(built["prefix"][0], 3, 4, gamma, 1.0).first()["within"]


def test_estimate_above_the_optimum(spark):
    rows = [(3, 1), (2, 2), (1, 3), (4, 4), (2, 1), (1, 1)]
    v = vecs(spark, rows)
    gamma = container_gamma(Eps(1, 2), 2)
    value, low = containers.makespan_estimate(containers.containers_prefix(v, 2, gamma), 2, 2, gamma, 0.5)
    assert low <= containers.optimum_exact(rows, 2) <= value


def test_typed_batch_and_stream(spark, tiny):
    v = tables.document_vectors(spark, tiny)
    r = typed.typed_report(v, Eps(1, 1)).first()
    assert r["within"] and r["jobs"] == v.df.count()
    assert typed.typed_drift(v, Eps(1, 1)).first()["within"]
    with pytest.raises(ValueError):
        typed.typed_summary(tables.Vectors(v.df, 8, v.cap), Eps(1, 4))


def test_relative_types(spark):
    rows = [(100, 50, 1), (8, 8, 8), (5, 0, 0)]
    got = {r["job_id"]: r["small_type"] for r in typed.with_types(vecs(spark, rows), Eps(1, 1)).collect()}
    assert got == {0: [0, 1, None], 1: [0, 0, 0], 2: [0, None, None]}


def test_vector_packing_is_valid(spark, tiny):
    r = vectors.vector_pack(tables.document_vectors(spark, tiny), Eps(1, 1), PackHow(solver="ffd")).first()
    s = vectors.vector_pack_split(tables.document_vectors(spark, tiny), Eps(1, 1), PackHow(solver="ffd")).first()
    assert r["alg"] >= r["vector_bound"] and s["alg"] >= s["vector_bound"]
    rng = random.Random(2)
    for _ in range(5):
        rows = [tuple(rng.randint(1, 10) for _ in range(2)) for _ in range(7)]
        assert solvers.solve_exact([(max(x), 1) for x in rows], 10) <= 2 * solvers.solve_exact_vectors(rows, 10)


def test_streams_equal_batch(spark, tiny):
    from packsum.functions.units import octave
    from packsum.streaming import summaries as streams

    items = tables.event_items(spark, tiny)
    whole = streams.rounded_in_batches(spark, streams.event_stream(spark, tiny), items.cap, Eps(1, 5))
    big = items.df.filter(octave(F.col("size_units"), items.cap, Eps(1, 5)) >= 0).count()
    assert whole.agg(F.sum("multiplicity")).first()[0] == big
    out = streams.run_to_end(spark, streams.windowed_octaves(streams.event_stream(spark, tiny), items.cap, Eps(1, 5)), "t", "append")
    last = out.agg(F.max("w.end")).first()[0]
    assert out.agg(F.sum("n")).first()[0] == items.df.filter(F.col("ts") < F.lit(last)).count()


def test_drained_streams_hold_all_rows(spark, tiny, tmp_path):
    from packsum.streaming import summaries as streams

    events = spark.read.parquet(f"{tiny}/events.parquet").limit(200).orderBy(F.desc("ts"))  # later files are hours behind
    rows = events.collect()
    for k in range(0, 200, 10):
        spark.createDataFrame(rows[k : k + 10], events.schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    batch = streams.windowed_exponents(spark.read.parquet(f"{tmp_path}/events.parquet").select(F.col("ts").cast("timestamp").alias("ts"), F.round(F.col("value") * 100).cast("long").alias("size_units")), Eps(1, 5))
    out = streams.run_to_end(spark, streams.windowed_exponents(streams.event_stream(spark, str(tmp_path)), Eps(1, 5)), "t")
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, batch.collect()))
    with pytest.warns(UserWarning, match="behind the watermark"):
        streams.run_to_end(spark, streams.windowed_exponents(streams.event_stream(spark, str(tmp_path)), Eps(1, 5)), "t", "append")


def test_plans_push_filters_and_stay_native(spark, tiny):
    from packsum.functions.units import is_big

    df = spark.read.parquet(f"{tiny}/documents.parquet").select("n_chars").filter(is_big(F.col("n_chars"), 33_047, Eps(1, 5)))
    text = df._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThan(n_chars" in text
    v = tables.line_vectors(spark, tiny)
    plan = containers.containers_prefix(v, 8, container_gamma(Eps(1, 2), 4), load=10**9)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Pandas" not in plan and "CartesianProduct" not in plan


def test_streams_go_on_after_a_restart(spark, tiny, tmp_path):
    from packsum.streaming import summaries as streams

    events = tables.read(spark, tiny, "events")
    folder, src = f"file://{tmp_path}/state", f"{tmp_path}/events.parquet"
    halves = [events.filter(F.col("event_id") % 3 == k).coalesce(1) for k in range(3)]
    cap, eps, seen = 50_000, Eps(1, 5), 0
    for k, part in enumerate(halves):  # three drains of one growing folder, as after a crash between batches
        part.write.mode("append").parquet(src)
        seen += part.count()
        whole = streams.rounded_in_batches(spark, streams.event_stream(spark, str(tmp_path)), cap, eps, folder)
        counted = streams.run_to_end(spark, streams.windowed_octaves(streams.event_stream(spark, str(tmp_path)), cap, eps), "t", folder=folder + "-windows")
        assert counted.agg(F.sum("n")).first()[0] == seen
        items = tables.event_items(spark, str(tmp_path))
        flags = properties.check_properties(items, eps, whole).first()
        assert flags["p1"] and flags["p2"] and flags["p3"] and flags["p4"], k
        assert streams.versions(spark, folder) == list(range(k + 1))
    again = streams.rounded_in_batches(spark, streams.event_stream(spark, str(tmp_path)), cap, eps, folder)
    assert sorted(again.collect()) == sorted(whole.collect())


def test_jobs_of_any_admitted_size_are_counted(spark):
    df = spark.createDataFrame([(1 << 60,), (10**17,), (10**15 + 1,), (1,), (0,)], "size_units long")
    rows = makespan.counters(df, Eps(1, 5)).collect()
    assert sum(r["n"] for r in rows) == 4 and all(r["exp_i"] is not None for r in rows)
