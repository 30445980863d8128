"""Experiment workloads over the given tables: one function a workload, one report table each."""

from __future__ import annotations

from fractions import Fraction
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from packsum.operators import containers, estimate, makespan, ranking, typed, vectors
from packsum.operators.estimate import PackHow
from packsum.params import Eps, container_gamma, lower_bound_comparison, lower_bound_randomised
from packsum.sources import tables

TARGETS = (Eps(1, 1), Eps(3, 5), Eps(3, 10), Eps(3, 20))


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), parts)


def _packed(items: tables.Items, name: str, targets: tuple[Eps, ...], how: PackHow = PackHow(), **options) -> DataFrame:
    parts = [estimate.pack(items, t, how, **options).withColumn("workload", F.lit(name)).withColumn("method", F.lit(f"{how.rounding}/{how.summary}/{how.solver}")) for t in targets]
    return estimate.with_guarantee(_union(parts))


def w01_quantity(spark: SparkSession, d: str) -> DataFrame:
    items = tables.quantity_items(spark, d)
    return _union([_packed(items, "quantity", TARGETS), _packed(items, "quantity", TARGETS[:2], PackHow(rounding="simple")), _packed(items, "quantity", TARGETS[:2], PackHow(summary="universe"), bits=6)])


def w02_price(spark: SparkSession, d: str) -> DataFrame:
    items = tables.price_items(spark, d)
    kinds = [_packed(items, "price", TARGETS[:3], PackHow(solver="ffd", summary=s)) for s in ("exact", "builtin", "random", "universe")]
    return _union([*kinds, _packed(items, "price", TARGETS[3:], PackHow(solver="ffd")), _packed(items, "price", TARGETS[1:2], PackHow(solver="lp")), _packed(items, "price", TARGETS[1:2], PackHow(solver="ffd", summary="sequential"))])


def w03_documents(spark: SparkSession, d: str) -> DataFrame:
    return _union([_packed(tables.document_items(spark, d), "documents", TARGETS), _packed(tables.document_items(spark, d, clean=True), "clean documents", TARGETS[:2]), _packed(tables.document_items(spark, d), "documents observed", TARGETS[:2], PackHow(small_cap="observed"))])


def w04_events(spark: SparkSession, d: str) -> DataFrame:
    items = tables.event_items(spark, d)
    return _union([_packed(items, "events", TARGETS, PackHow(solver="ffd")), *(_packed(items, "events", TARGETS[:2], PackHow(solver=k)) for k in ("bfd", "lp"))])


def w05_streams(spark: SparkSession, d: str) -> DataFrame:
    nation = _packed(tables.nation_items(spark, d), "nations", (Eps(3, 5),)).withColumnRenamed("n_name", "stream_key")
    role = _packed(tables.turn_items(spark, d), "roles", (Eps(3, 5),)).withColumnRenamed("role", "stream_key")
    pages = _packed(tables.page_items(spark, d), "pages", (Eps(3, 5),)).withColumn("stream_key", F.lit("all"))
    users = tables.event_items(spark, d)
    users = _packed(tables.Items(users.df.select(F.col("user_id").cast("string").alias("stream_key"), "size_units"), users.cap, ("stream_key",)), "users", (Eps(3, 5),), PackHow(solver="ffd"))
    docs = tables.document_items(spark, d)
    langs = tables.Items(tables.read(spark, d, "documents").select(F.coalesce("lang", F.lit("none")).alias("stream_key"), F.col("n_chars").cast("long").alias("size_units")), docs.cap, ("stream_key",))
    return _union([nation, role, pages, users, _packed(langs, "languages", (Eps(3, 5),))])


def w06_line_vectors(spark: SparkSession, d: str) -> DataFrame:
    v = tables.line_vectors(spark, d)
    cols = ["alg", "sigma", "words", "vector_bound", "dims", "vector_ratio"]
    return _union([vectors.vector_pack(v, Eps(1, 1), PackHow(solver="ffd")).select(F.lit("largest coordinate").alias("method"), *cols), vectors.vector_pack_split(v, Eps(1, 1), PackHow(solver="ffd")).select(F.lit("split").alias("method"), *cols)])


def w07_other_vectors(spark: SparkSession, d: str) -> DataFrame:
    cols = ["alg", "sigma", "words", "vector_bound", "dims", "vector_ratio"]
    parts = []
    for name, v in (("documents", tables.document_vectors(spark, d)), ("embeddings", tables.embedding_vectors(spark, d))):
        parts.append(vectors.vector_pack(v, Eps(1, 1), PackHow(solver="ffd")).select(F.lit(name).alias("workload"), F.lit("largest coordinate").alias("method"), *cols))
        parts.append(vectors.vector_pack_split(v, Eps(1, 1), PackHow(solver="ffd")).select(F.lit(name).alias("workload"), F.lit("split").alias("method"), *cols))
    return _union(parts)


def w08_ranks(spark: SparkSession, d: str) -> DataFrame:
    events = tables.event_jobs(spark, d)
    qs = [int(x) for x in events.approxQuantile("size_units", [k / 10 for k in range(1, 10)], 0.01)]
    return _union([ranking.rank_report(spark, events, "size_units", qs, e).withColumn("eps", F.lit(e.label)) for e in (Eps(1, 5), Eps(1, 10))])


def w09_makespan(spark: SparkSession, d: str) -> DataFrame:
    jobs = {"events": tables.event_jobs(spark, d), "documents": tables.document_items(spark, d).df, "orders": tables.read(spark, d, "orders").select(tables.units("o_totalprice", 100).alias("size_units"))}
    return _union([makespan.makespan_report(df, e, [2, 8, 32]).withColumn("workload", F.lit(name)) for name, df in jobs.items() for e in (Eps(1, 2), Eps(1, 5), Eps(1, 20))])


def w10_containers(spark: SparkSession, d: str, cases: tuple = ((8, Eps(1, 1)), (8, Eps(1, 2)))) -> DataFrame:
    parts = []
    for name, v in (("documents", tables.document_vectors(spark, d)), ("order lines", tables.line_vectors(spark, d))):
        for m, eps in cases:
            gamma = container_gamma(eps, v.dims)
            load = containers.load_bound(v, m)
            for method, s, extra in (("prefix", containers.containers_prefix(v, m, gamma, load=load), 17), ("parallel", containers.containers_parallel(v, m, gamma, load), 1)):
                s = s.persist()
                parts.append(containers.container_report(s, v, m, gamma, extra).crossJoin(containers.schedule_report(s, v, m, gamma, float(eps.fraction))).withColumn("workload", F.lit(name)).withColumn("method", F.lit(method)).withColumn("eps", F.lit(eps.label)))
    return _union(parts)


def w11_tight(spark: SparkSession, d: str) -> DataFrame:
    """The tight instance over all customers, through sequential containers and by its groups; the optimum of each summary
    beside what is proved of the container that groups the small jobs."""
    rows = []
    for m, inv in ((2, 2), (2, 4), (3, 3)):
        v = tables.tight_customers(spark, d, m, inv)
        own = tables.Vectors(v.df.select("job_id", "v"), v.dims, v.cap)
        for method, s in (("sequential", containers.containers_sequential(own, m, Fraction(1, inv))), ("grouped", containers.containers_grouped(v, "grp"))):
            summary = [(tuple(r["vec"]), r["n_jobs"]) for r in s.collect()]  # m big jobs, and at most (m - 1) * inv + 2 containers
            optimum = containers.optimum_exact([vec for vec, _ in summary], m, 16)
            rows.append((method, m, inv, sum(n for _, n in summary), optimum / max(1, v.cap), 2 - 1 / m))
    return spark.createDataFrame(rows, "method string, machines int, inv_gamma int, jobs long, summary_optimum double, proved_least double")


def w12_typed(spark: SparkSession, d: str) -> DataFrame:
    v = tables.document_vectors(spark, d)
    return _union([typed.typed_report(v, e).crossJoin(typed.typed_estimate(v, e, 8)).withColumn("eps", F.lit(e.label)) for e in (Eps(1, 1), Eps(1, 2))])


def w13_orders(spark: SparkSession, d: str) -> DataFrame:
    """Arrival orders: ascending, descending, by hash, by time."""
    v = tables.document_vectors(spark, d)
    m, eps = 8, Eps(1, 2)
    gamma = container_gamma(eps, v.dims)
    orders = {"ascending": F.array_max("v"), "descending": -F.array_max("v"), "hashed": F.xxhash64("job_id"), "identifier": F.col("job_id")}
    parts = []
    for name, place in orders.items():
        own = tables.Vectors(v.df.withColumn("place", place), v.dims, v.cap)
        s = containers.containers_sequential(own, m, gamma, "place")
        parts.append(containers.container_report(s.drop("most"), v, m, gamma, 1).withColumn("arrival", F.lit(name)))
    return _union(parts)


def w14_growth(spark: SparkSession, d: str) -> DataFrame:
    """Stored sizes against precision and input: a quarter, a half and all of the order lines, beside the proved bound of
    the exact grid (4 / eps and two ends for each octave) and the least that any comparison-based summary stores."""
    lines = tables.price_items(spark, d)
    parts = []
    for share in (4, 2, 1):
        items = tables.Items(lines.df.filter(F.pmod(F.xxhash64("size_units", F.lit(1)), F.lit(share)) == 0), lines.cap)
        for e in (Eps(1, 5), Eps(1, 10), Eps(1, 20)):
            inst = estimate.rounded(items, e, "octaves", "exact")
            n = items.df.count()
            parts.append(inst.agg(F.count_distinct("size_units").alias("sigma"), F.sum("multiplicity").cast("long").alias("n_big")).select("sigma", "n_big", F.lit(e.label).alias("eps"), F.lit(n).alias("n"), F.lit(lower_bound_comparison(e, n)).alias("least_stored"), F.lit(lower_bound_randomised(e, 1e-4)).alias("least_stored_random"), F.lit(share).alias("parts"), F.lit(e.octaves * (-(-8 * e.den // e.num) + 2)).alias("most_stored")))
    return _union(parts)


WORKLOADS = {
    "w01_quantity": w01_quantity, "w02_price": w02_price, "w03_documents": w03_documents, "w04_events": w04_events, "w05_streams": w05_streams, "w06_line_vectors": w06_line_vectors,
    "w07_other_vectors": w07_other_vectors, "w08_ranks": w08_ranks, "w09_makespan": w09_makespan, "w10_containers": w10_containers, "w11_tight": w11_tight, "w12_typed": w12_typed,
    "w13_orders": w13_orders, "w14_growth": w14_growth,
}
