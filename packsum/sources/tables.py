"""Tables as items, vectors and jobs in exact whole units, with validation and instance generators."""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from packsum.functions.ranks import with_position


@dataclass(frozen=True)
class Items:
    """Scalar items: ``df`` has ``size_units`` (and ``keys``); a bin holds ``cap`` units. over: some may be larger."""

    df: DataFrame
    cap: int
    keys: tuple[str, ...] = ()
    over: bool = False


@dataclass(frozen=True)
class Vectors:
    """Vector items or jobs: ``df`` has ``job_id`` and ``v``, whole units in an array of ``dims``; ``cap`` is 1."""

    df: DataFrame
    dims: int
    cap: int


def units(column: str, scale: int) -> Column:
    return F.round(F.col(column) * scale).cast("long")


def items(df: DataFrame, measure: Column, cap: int, keys: tuple[str, ...] = (), on_bad: str = "error", **columns: Column) -> Items:
    """Items of a measure in whole units. on_bad: what null, negative and oversized sizes do: error, drop, clamp or keep."""
    out = df.select(*keys, *(c.alias(n) for n, c in columns.items()), measure.cast("long").alias("size_units"))
    bad = F.col("size_units").isNull() | (F.col("size_units") < 0) | (F.col("size_units") > cap)
    if on_bad == "drop":
        out = out.filter(~bad)
    elif on_bad == "clamp":
        out = out.filter(F.col("size_units").isNotNull()).withColumn("size_units", F.least(F.greatest("size_units", F.lit(0)), F.lit(cap)).cast("long"))
    elif on_bad == "error":
        out = out.withColumn("size_units", F.when(bad, F.raise_error(F.lit("a size is null, negative or over the capacity")).cast("long")).otherwise(F.col("size_units")))
    elif on_bad != "keep":
        raise ValueError(on_bad)
    return Items(out, cap, keys, on_bad == "keep")


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def quantity_items(spark: SparkSession, sf_dir: str) -> Items:
    return items(read(spark, sf_dir, "lineitem"), units("l_quantity", 1), 50)


def price_items(spark: SparkSession, sf_dir: str) -> Items:
    return items(read(spark, sf_dir, "lineitem"), units("l_extendedprice", 100), 10_500_000)


def event_jobs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as jobs: sizes without an upper limit."""
    return items(read(spark, sf_dir, "events"), units("value", 100), 1 << 60, item_id=F.col("event_id"), user_id=F.col("user_id"), ts=F.col("ts").cast("timestamp")).df


def event_items(spark: SparkSession, sf_dir: str, on_bad: str = "clamp") -> Items:
    """Events as items: a bin holds 500.00, and the rare larger value fills one, or is kept as it is."""
    return items(read(spark, sf_dir, "events"), units("value", 100), 50_000, on_bad=on_bad, item_id=F.col("event_id"), user_id=F.col("user_id"), ts=F.col("ts").cast("timestamp"))


def document_items(spark: SparkSession, sf_dir: str, clean: bool = False) -> Items:
    """Documents by characters; the capacity is the longest. clean: only those labelled good and not toxic."""
    docs = read(spark, sf_dir, "documents")
    cap = docs.agg(F.max("n_chars")).first()[0]
    if clean:
        good = read(spark, sf_dir, "labels").filter("quality = 1 and toxic = 0")
        docs = docs.join(good, "doc_id", "left_semi")
    return items(docs, F.col("n_chars"), int(cap), item_id=F.col("doc_id"))


def page_items(spark: SparkSession, sf_dir: str) -> Items:
    pages = read(spark, sf_dir, "pages").select("page_id", F.length("html").alias("n"))
    return items(pages, F.col("n"), int(pages.agg(F.max("n")).first()[0]), item_id=F.col("page_id"))


def turn_items(spark: SparkSession, sf_dir: str) -> Items:
    turns = read(spark, sf_dir, "conversations").select("role", F.length("text").alias("n"))
    return items(turns, F.col("n"), int(turns.agg(F.max("n")).first()[0]), keys=("role",))


def nation_items(spark: SparkSession, sf_dir: str) -> Items:
    """Order lines by quantity, one stream for each nation."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customers = read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nations = read(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    named = customers.join(nations, F.col("c_nationkey") == F.col("n_nationkey"))
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(named, F.col("o_custkey") == F.col("c_custkey"))
    return items(joined, units("l_quantity", 1), 50, keys=("n_name",))


LINE_CAP = 10_500_000


def line_vectors(spark: SparkSession, sf_dir: str) -> Vectors:
    """Quantity, price, discount and tax of order lines, each over its maximum, on one common denominator."""
    df = read(spark, sf_dir, "lineitem")
    parts = [(units("l_quantity", 1), 50), (units("l_extendedprice", 100), LINE_CAP), (units("l_discount", 100), 10), (units("l_tax", 100), 8)]
    v = F.array(*(c * F.lit(LINE_CAP // top) for c, top in parts))
    ident = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate")
    return Vectors(df.select(ident.alias("job_id"), v.alias("v")), 4, LINE_CAP)


DOC_CAP = 1_000_000


def document_vectors(spark: SparkSession, sf_dir: str) -> Vectors:
    """Characters, words and lines of documents, each over its maximum, rounded up on a fixed denominator."""
    df = read(spark, sf_dir, "documents")
    raw = df.select("doc_id", F.col("n_chars").cast("long").alias("a"), F.size(F.split("text", " ")).cast("long").alias("b"), (F.length("text") - F.length(F.replace("text", F.lit("\n"), F.lit(""))) + 1).cast("long").alias("c"))
    top = raw.agg(*(F.max(x).alias(x) for x in "abc")).first()
    up = lambda x: F.expr(f"({x} * {DOC_CAP}L + {top[x] - 1}L) div {top[x]}L")
    return Vectors(raw.select(F.col("doc_id").alias("job_id"), F.array(*map(up, "abc")).alias("v")), 3, DOC_CAP)


def embedding_vectors(spark: SparkSession, sf_dir: str, dims: int = 64) -> Vectors:
    """Absolute embedding coordinates over the largest of each dimension, rounded up on a fixed denominator."""
    df = read(spark, sf_dir, "embeddings")
    tops = df.select(F.posexplode("embedding").alias("k", "x")).groupBy("k").agg(F.max(F.abs("x")).cast("double").alias("t"))
    table = {r["k"]: r["t"] for r in tops.collect()}  # one row a dimension
    top = F.array(*(F.lit(float(table[k])) for k in range(dims)))
    v = F.transform("embedding", lambda x, k: F.ceil(F.abs(x).cast("double") * DOC_CAP / F.get(top, k)).cast("long"))
    return Vectors(df.select(F.col("vec_id").alias("job_id"), F.transform(v, lambda x: F.least(x, F.lit(DOC_CAP).cast("long"))).alias("v")), dims, DOC_CAP)


def tight_instance(df: DataFrame, key: str, m: int, inv_gamma: int) -> Vectors:
    """Every row of a table as a job, such that containers lose a factor 2 - 1/m: (job_id, v, grp).

    In the order of the key, big job i of the first m is full in its own dimension i and in the last. Small jobs are one
    unit in one of the first m dimensions, by turns. ``share`` of them in each dimension are gamma, a full machine is
    inv_gamma shares, and group k has one share of each dimension, (m - 1) / gamma groups in all; so all of a group fits
    one container. Rows that fill no further share, fewer than m (m - 1) / gamma, are jobs of no size in a last group.
    """
    groups = (m - 1) * inv_gamma
    share = max(0, df.count() - m) // (m * groups)
    full = share * inv_gamma
    at = F.col("at")
    big, small = at < m, at < m + m * groups * share
    unit = [F.when(big & (at == j), full).when(~big & small & (at % m == j), 1).otherwise(0).cast("long") for j in range(m)]
    v = F.array(*unit, F.when(big, full).otherwise(0).cast("long"))
    grp = F.when(big, at - m).otherwise(F.expr(f"(at - {m}) div {max(1, m * share)}L") if share else F.lit(groups)).cast("long")
    jobs = with_position(df.select(F.col(key).cast("long").alias("job_id")), "job_id", "at")
    return Vectors(jobs.select("job_id", v.alias("v"), F.when(big | small, grp).otherwise(groups).alias("grp")), m + 1, full)


def tight_customers(spark: SparkSession, sf_dir: str, m: int, inv_gamma: int) -> Vectors:
    return tight_instance(read(spark, sf_dir, "customer"), "c_custkey", m, inv_gamma)


ITEM_SCHEMA = StructType([StructField("size_units", LongType(), False)])


def size_list(spark: SparkSession, sizes: list[Fraction | int], cap: int) -> Items:
    return Items(spark.createDataFrame([(int(s),) for s in sizes], ITEM_SCHEMA), cap)
