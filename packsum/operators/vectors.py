"""Vector packing by scalars: the largest coordinate, or a split by the largest coordinate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packsum.operators.estimate import PackHow, report, rounded
from packsum.params import Eps, packing_eps
from packsum.sources.tables import Items, Vectors


def linf_items(vectors: Vectors) -> Items:
    """A packing of the largest coordinates packs the vectors, and the optimum grows by d at most."""
    return Items(vectors.df.select(F.array_max("v").alias("size_units")), vectors.cap)


def split_items(vectors: Vectors) -> Items:
    """One stream for each dimension: vectors whose largest coordinate it is, ties to the lowest."""
    top = F.array_max("v")
    return Items(vectors.df.select((F.array_position("v", top).cast("int") - 1).alias("dim"), top.alias("size_units")), vectors.cap, ("dim",))


def vector_pack(vectors: Vectors, eps_target: Eps, how: PackHow = PackHow()) -> DataFrame:
    """Factor d + eps_target: scalars with precision eps_target / (3 d)."""
    eps = packing_eps(eps_target, vectors.dims)
    items = linf_items(vectors)
    return with_bounds(report(items, eps, rounded(items, eps, how.rounding, how.summary), how), vectors)


def vector_pack_split(vectors: Vectors, eps_target: Eps, how: PackHow = PackHow()) -> DataFrame:
    """Factor d (1 + eps_target): a scalar run for each dimension, bins added."""
    eps = packing_eps(eps_target)
    items = split_items(vectors)
    rows = report(items, eps, rounded(items, eps, how.rounding, how.summary), how)
    total = rows.agg(F.sum("alg").cast("long").alias("alg"), F.max("size_bound").cast("long").alias("largest_group_bound"), F.sum("sigma").cast("long").alias("sigma"), F.sum("words").cast("long").alias("words"))
    return with_bounds(total, vectors)


def vector_lower_bounds(vectors: Vectors) -> DataFrame:
    """Total of each dimension in bins, rounded up."""
    sums = vectors.df.agg(*(F.sum(F.get("v", F.lit(k))).cast("decimal(38,0)").alias(f"s{k}") for k in range(vectors.dims)))
    rows = F.explode(F.array(*(F.struct(F.lit(k).alias("dim"), F.col(f"s{k}").alias("total")) for k in range(vectors.dims))))
    return sums.select(rows.alias("r")).select("r.dim", F.col("r.total").cast("long").alias("total_units"), F.ceil(F.col("r.total") / vectors.cap).cast("long").alias("bins"))


def with_bounds(df: DataFrame, vectors: Vectors) -> DataFrame:
    bound = vector_lower_bounds(vectors).agg(F.max("bins").alias("vector_bound"))
    return df.crossJoin(F.broadcast(bound)).withColumn("dims", F.lit(vectors.dims)).withColumn("vector_ratio", F.col("alg") / F.greatest("vector_bound", F.lit(1)))
