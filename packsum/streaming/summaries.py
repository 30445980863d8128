"""Structured Streaming forms of the summaries."""

from __future__ import annotations

import warnings

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from packsum.functions.steps import fresh_path
from packsum.functions.units import exponent, octave
from packsum.operators.makespan import TOP
from packsum.operators.rounding import grid_steps, histogram, merge_rounded, steps_to_instance
from packsum.params import Eps, octave_step
from packsum.sources.tables import Items


def event_stream(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    """Events in whole units with an event-time watermark; a timestamp without zone is cast first."""
    path = f"{sf_dir}/events.parquet"
    reader = spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", 4)
    # A file source streams folders; a table that is one file is picked from its folder by name.
    raw = reader.parquet(path) if _is_folder(spark, path) else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), F.round(F.col("value") * 100).cast("long").alias("size_units")).withWatermark("ts", delay)


def _is_folder(spark: SparkSession, path: str) -> bool:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(hadoop).isDirectory()


def windowed_octaves(stream: DataFrame, cap: int, eps: Eps, width: str = "1 day") -> DataFrame:
    """Counts and totals by event-time window and octave: the state is a few rows for each open window."""
    own = stream.withColumn("size_units", F.least("size_units", F.lit(cap).cast("long"))).withColumn("group_j", octave(F.col("size_units"), cap, eps))
    return own.groupBy(F.window("ts", width).alias("w"), "group_j").agg(F.count(F.lit(1)).alias("n"), F.sum("size_units").alias("total"))


def windowed_exponents(stream: DataFrame, eps: Eps, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Geometric counters by window; any number of machines can be asked of them later."""
    own = stream.filter("size_units > 0").withColumn("exp_i", exponent(F.col("size_units"), eps, TOP))
    return own.groupBy(F.window("ts", width, slide).alias("w"), "exp_i").agg(F.count(F.lit(1)).alias("n"), F.sum("size_units").alias("total"))


def session_totals(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("size_units").alias("total"))


def run_to_end(spark: SparkSession, stream: DataFrame, name: str, mode: str = "complete", folder: str | None = None) -> DataFrame:
    """Drain what is there into versions of a table in the shared folder, and read the result.

    In complete mode each batch writes the whole result anew and the last version is read: windows still open are in
    it, and no row is late, for nothing is closed. In append mode only closed windows are returned; the rows that came
    behind the watermark, and are lost, are counted and reported by a warning. A folder of the caller's own makes the
    drain restartable: the next call goes on from its log and reads all its versions.
    """
    root = folder or fresh_path(spark, name)

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/v{batch_id}")

    query = stream.writeStream.foreachBatch(write).option("checkpointLocation", root + "-log").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    late = late_rows(query)
    if late:
        warnings.warn(f"{name}: {late} rows or partial sums came behind the watermark and are not in the result", stacklevel=2)
    there = versions(spark, root)
    if not there:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(f"{root}/v{k}" for k in (there[-1:] if mode == "complete" else there)))


def versions(spark: SparkSession, root: str) -> list[int]:
    """Numbers of the finished versions in a folder, in order."""
    path = spark._jvm.org.apache.hadoop.fs.Path(root)
    files = path.getFileSystem(spark._jsc.hadoopConfiguration())
    if not files.exists(path):
        return []
    names = [s.getPath() for s in files.listStatus(path)]
    done = [p.getName() for p in names if files.exists(spark._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS"))]
    return sorted(int(n[1:]) for n in done if n[1:].isdigit())


def late_rows(query: StreamingQuery) -> int:
    """Rows that stateful steps dropped behind the watermark, over the batches whose progress is kept."""
    return sum(int(s["numRowsDroppedByWatermark"]) for p in query.recentProgress for s in p["stateOperators"])


def rounded_in_batches(spark: SparkSession, stream: DataFrame, cap: int, eps: Eps, folder: str | None = None) -> DataFrame:
    """Rounded summary kept by micro-batch, in as many levels as the number of batches has binary digits.

    A batch is rounded with a quarter of the precision. Two summaries of one level become one of the next, rounded again;
    the shares of all levels sum to another quarter, and reading takes the last half, so the whole stays within eps and
    the state within a few rows for each octave and level. Version k is made of version k - 1 and batch k alone: a
    repeated batch writes the same table again, and a drain in a folder of the caller's own goes on after a restart.
    """
    root = folder or fresh_path(spark, "rounded")
    share = lambda part: octave_step("n_j", Eps(eps.num, part * eps.den))

    def merge(batch: DataFrame, batch_id: int) -> None:
        sizes = Items(batch.select(F.least("size_units", F.lit(cap).cast("long")).alias("size_units")), cap)
        carry, level = steps_to_instance(grid_steps(histogram(sizes, eps), share(4))), 0
        parts = []
        if batch_id:
            before = batch.sparkSession.read.parquet(f"{root}/v{batch_id - 1}")
            while batch_id >> level & 1:  # the levels in use are the binary digits of the number of earlier batches
                both = carry.unionByName(before.filter(F.col("level") == level).drop("level"))
                carry, level = merge_rounded(both, share(4 * (level + 1) * (level + 2))), level + 1
            parts.append(before.filter(F.col("level") > level))
        out = carry.withColumn("level", F.lit(level))
        for part in parts:
            out = out.unionByName(part)
        out.write.mode("overwrite").parquet(f"{root}/v{batch_id}")

    query = stream.select("size_units").writeStream.foreachBatch(merge).option("checkpointLocation", root + "-log").trigger(availableNow=True).start()
    query.awaitTermination()
    there = versions(spark, root)
    if not there:
        return spark.createDataFrame([], "group_j int, size_units long, multiplicity long")
    return merge_rounded(spark.read.parquet(f"{root}/v{there[-1]}").drop("level"), share(2))
