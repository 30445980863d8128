"""Operator 10: mixing sources to target weights by a multivariate-hypergeometric splitting tree.

The word stream of a source is its documents in a seeded order, laid end to end, as often as its target asks. The
stream is cut into blocks of words; a tree splits the exact block quotas of all sources among output shards, level by
level, with seeded hypergeometric draws, so that every shard holds a random sample without replacement of known
composition. A permutation of each source's blocks then hands disjoint blocks to the shards, which order them locally.

Only tables of one row a source, or one row a source and bucket, are summed globally; documents are summed inside
(source, bucket), so a source with a third of all rows is spread over all buckets. Defined results: a null text has
size 0 and is never taken; a null source is a source of its own, ordered last; the order of repeated rows is a tie that
cannot be seen in the result; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from packsum.llm.runtime import materialize
from packsum.llm.textexpr import word_array, word_count


@dataclass(frozen=True)
class MixPlan:
    weights: tuple[int, ...] = (5, 2, 1)
    total_percent: int = 150
    most_repeats: int = 2
    seed: int = 11
    buckets: int = 256
    block_words: int = 512  # at least; doubled until there are at most ``most_blocks``
    most_blocks: int = 500_000_000  # numpy draws exactly from populations below 10**9
    shards: int = 64


PLAN = MixPlan()


def order_key(plan: MixPlan, doc_id: Column) -> Column:
    """A seeded order that every engine reproduces: the first hexadecimal digits of an MD5."""
    return F.md5(F.concat_ws(":", F.lit(str(plan.seed)), F.coalesce(doc_id.cast("string"), F.lit(""))))


def sized(docs: DataFrame, plan: MixPlan = PLAN, doc_id: str = "doc_id", text: str = "text", source: str = "source", rid: str | None = None) -> DataFrame:
    return docs.select(
        F.col(doc_id).alias("doc_id"),
        F.col(source).alias("source"),
        word_count(F.col(text)).alias("size"),
        order_key(plan, F.col(doc_id)).alias("key"),
        (F.col(rid) if rid else F.monotonically_increasing_id()).alias("rid"),
    )


def source_targets(sizes: DataFrame, plan: MixPlan = PLAN) -> DataFrame:
    """One row a source: its words and its target.

    Resharing the excess by weight until none is above its limit ends where every target is the lesser of the limit
    and one common multiple of the weight; that multiple follows from sums in the order of limit over weight, and
    needs no loop. The windows here run over sources, never over documents.
    """
    per_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    in_order = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, plan.weights)), ((F.row_number().over(in_order) - 1) % len(plan.weights) + 1).cast("int"))
    table = per_source.withColumn("weight", weight.cast("double")).withColumn("limit", (F.col("source_size") * plan.most_repeats).cast("double"))
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    table = table.withColumn("total", F.sum("source_size").over(everything) * plan.total_percent / 100.0)
    by_ratio = Window.orderBy(F.col("limit") / F.col("weight"), F.col("source").asc_nulls_last())
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    table = (
        table.withColumn("limits_before", F.coalesce(F.sum("limit").over(before), F.lit(0.0)))
        .withColumn("weights_from", F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
        .withColumn("level", (F.col("total") - F.col("limits_before")) / F.col("weights_from"))
    )
    fits = F.col("level") <= F.col("limit") / F.col("weight")
    table = table.withColumn("common", F.min(F.when(fits, F.struct(F.col("limit") / F.col("weight"), F.col("level").alias("level")))).over(everything)["level"])
    target = F.when(F.col("common").isNull(), F.col("limit")).otherwise(F.least("limit", F.col("common") * F.col("weight")))
    return table.select("source", "source_size", "weight", target.alias("target"))


def placed(sizes: DataFrame, targets: DataFrame, plan: MixPlan = PLAN) -> DataFrame:
    """Documents with their source's target, and where their words begin in its stream (``begin``)."""
    bucket = (F.conv(F.substring("key", 1, 4), 16, 10).cast("long") * plan.buckets / 65536).cast("int")
    sizes = sizes.withColumn("bucket", bucket)
    sums = sizes.groupBy("source", "bucket").agg(F.sum("size").alias("words"))
    ahead = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("source", "bucket", F.coalesce(F.sum("words").over(ahead), F.lit(0)).alias("offset"))
    inside = Window.partitionBy("source", "bucket").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    local = sizes.withColumn("local", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    local, offsets, targets = local.alias("d"), offsets.alias("o"), targets.alias("t")
    joined = local.join(offsets, F.col("d.source").eqNullSafe(F.col("o.source")) & (F.col("d.bucket") == F.col("o.bucket"))).join(targets, F.col("d.source").eqNullSafe(F.col("t.source")))
    return joined.select(
        F.col("d.rid").alias("rid"), F.col("d.doc_id").alias("doc_id"), F.col("d.source").alias("source"), F.col("d.size").alias("size"), F.col("t.source_size").alias("source_size"),
        F.col("t.target").alias("target"), (F.col("o.offset") + F.col("d.local")).alias("begin"),
    )


def handed_out(sizes: DataFrame, plan: MixPlan = PLAN) -> tuple[DataFrame, DataFrame]:
    """Placed documents, and one row for each copy of which a shard's blocks hold words.

    A copy's words are what the blocks handed out hold of it. It belongs to the shard, and the place there, of the
    block that holds its first word, so that copies stay whole; ``begin`` orders the copies that begin in one block.
    """
    targets = materialize(source_targets(sizes, plan))
    rows = materialize(placed(sizes, targets, plan))
    lap = rows.filter("size > 0").withColumn("lap", F.explode(F.sequence(F.lit(0), F.lit(plan.most_repeats - 1))))
    lap = lap.withColumn("lo", F.col("lap") * F.col("source_size") + F.col("begin"))
    lap = lap.withColumn("hi", F.least(F.col("lo") + F.col("size"), F.floor(F.col("target") + 0.5))).filter("lo < hi")
    each = block_words(targets, plan)
    of_word = lambda w: F.floor(w / each).cast("long")
    touched = lap.select("rid", "lap", "size", "lo", "hi", F.col("source").alias("_source"), F.explode(F.sequence(of_word(F.col("lo")), of_word(F.col("hi") - 1))).alias("_block"))
    held = touched.join(owned_blocks(targets, plan), F.col("_source").eqNullSafe(F.col("source")) & (F.col("_block") == F.col("block")))
    words = F.least("hi", F.col("first_word") + F.col("n_words")) - F.greatest("lo", "first_word")
    head = F.min(F.struct("block", "shard", "place"))
    copies = held.groupBy("rid", "lap").agg(F.sum(words).alias("words"), F.first("size").alias("size"), F.first("lo").alias("begin"), head.alias("head"))
    return rows, copies.select("rid", "lap", "words", "size", "begin", "head.shard", "head.place", "head.block")


def mix(docs: DataFrame, plan: MixPlan = PLAN, **columns: str) -> DataFrame:
    """One row for each input row: its size, its source's size and target, and the words the mix takes of it."""
    rows, copies = handed_out(materialize(sized(docs, plan, **columns)), plan)  # texts are read once
    taken = copies.groupBy("rid").agg(F.sum("words").alias("taken"))
    return rows.join(taken, "rid", "left").select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))


def split_quotas(quotas: dict[str, int], shards: int, seed: int) -> np.ndarray:
    """Blocks of each source for each shard: halve the shards, draw the composition of the left half, recurse.

    The draw is multivariate hypergeometric, one source after another, so each leaf is distributed as a random
    sample without replacement, while all sums are exact. Work is shards times sources, whatever the data.
    """
    names = list(quotas)
    out = np.zeros((shards, len(names)), np.int64)
    total = sum(quotas.values())
    sizes = np.full(shards, total // max(shards, 1), np.int64)
    sizes[: total - int(sizes.sum())] += 1

    def part(lo: int, hi: int, have: np.ndarray) -> None:
        if hi - lo == 1:
            out[lo] = have
            return
        mid = (lo + hi) // 2
        rng = np.random.default_rng([seed, lo, hi])
        left, want = np.zeros_like(have), int(sizes[lo:mid].sum())
        rest = int(have.sum())
        for k, n in enumerate(have):
            n = int(n)
            rest -= n
            left[k] = int(rng.hypergeometric(n, rest, want)) if want else 0
            want -= int(left[k])
        part(lo, mid, left)
        part(mid, hi, have - left)

    part(0, shards, np.array([quotas[x] for x in names], np.int64))
    return out


def shard_blocks(docs: DataFrame, plan: MixPlan = PLAN, **columns: str) -> DataFrame:
    """The mixed stream as blocks: (shard, place, source, block, first word, words), disjoint and exhaustive."""
    return owned_blocks(source_targets(sized(docs, plan, **columns), plan), plan)


def block_words(targets: DataFrame, plan: MixPlan) -> int:
    total = targets.agg(F.sum(F.floor(F.col("target") + 0.5))).first()[0] or 0
    return plan.block_words << max(0, int(-(-total // plan.block_words) // plan.most_blocks).bit_length())


def owned_blocks(targets: DataFrame, plan: MixPlan = PLAN) -> DataFrame:
    """The blocks of all sources with their shards and places.

    Blocks of a source are ranked by a seeded permutation; the shard whose cumulated quota holds the rank owns the
    block. One row a source goes to the driver, for the tree.
    """
    words, each = F.floor(F.col("target") + 0.5), block_words(targets, plan)
    table = targets.select("source", words.alias("words"), F.ceil(words / each).cast("long").alias("blocks")).filter("blocks > 0")
    rows = sorted(table.collect(), key=lambda r: (r["source"] is None, r["source"]))
    spark = targets.sparkSession
    quotas = {r["source"]: r["blocks"] for r in rows}
    split = split_quotas(quotas, plan.shards, plan.seed) if quotas else np.zeros((plan.shards, 0), np.int64)
    bounds = split.cumsum(axis=0)
    lines = [(s, i, int(bounds[i, k] - split[i, k]), int(bounds[i, k])) for k, s in enumerate(quotas) for i in range(plan.shards) if split[i, k]]
    owners = spark.createDataFrame(lines, "source string, shard int, lo long, hi long")
    # A large source has many blocks: they are listed in runs of 4,096, which tasks then share.
    run = F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1, F.lit(4096).cast("long")))
    runs = table.withColumn("run", run).repartition("source", "run")
    blocks = runs.withColumn("block", F.explode(F.sequence("run", F.least(F.col("run") + 4096, "blocks") - 1))).drop("run")
    shuffled = F.xxhash64(F.lit(plan.seed), "source", "block")
    # Ranks in the permutation come from ranks inside buckets of the hash and the buckets' counts.
    blocks = blocks.withColumn("h", shuffled).withColumn("part", F.shiftrightunsigned("h", 54))
    counts = blocks.groupBy("source", "part").count()
    ahead = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(F.col("source").alias("cs"), F.col("part").alias("cp"), F.coalesce(F.sum("count").over(ahead), F.lit(0)).alias("ahead"))
    inside = Window.partitionBy("source", "part").orderBy("h", "block")
    ranked = blocks.withColumn("r", F.row_number().over(inside) - 1).join(counts, F.col("source").eqNullSafe(F.col("cs")) & (F.col("part") == F.col("cp")))
    ranked = ranked.withColumn("rank", F.col("r") + F.col("ahead"))
    o = owners.select(F.col("source").alias("os"), "shard", "lo", "hi")
    owned = ranked.join(F.broadcast(o) if len(lines) <= 50_000 else o, F.col("source").eqNullSafe(F.col("os")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    place = F.xxhash64(F.lit(plan.seed + 1), "source", "block")
    return owned.select("shard", place.alias("place"), "source", "block", (F.col("block") * each).alias("first_word"), F.least(F.lit(each), F.col("words") - F.col("block") * each).alias("n_words"))


def mixed_documents(docs: DataFrame, plan: MixPlan = PLAN) -> DataFrame:
    """The documents of the mix, with the columns of ``docs``: whole copies, and a last one cut where its quota ends.

    Partition i is shard i, in the order of its shuffled blocks.
    """
    keyed = materialize(docs.withColumn("_mix_rid", F.monotonically_increasing_id()))
    _, copies = handed_out(materialize(sized(keyed, plan, rid="_mix_rid")), plan)
    copies = copies.select(*(F.col(c).alias(f"_m_{c}") for c in copies.columns))
    out = keyed.join(copies, F.col("_mix_rid") == F.col("_m_rid"))
    out = out.repartitionById(plan.shards, F.col("_m_shard")).sortWithinPartitions("_m_place", "_m_block", "_m_begin")
    first = F.concat_ws(" ", F.slice(word_array(F.col("text")), F.lit(1), F.col("_m_words").cast("int")))
    out = out.withColumn("text", F.when(F.col("_m_words") == F.col("_m_size"), F.col("text")).otherwise(first))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def oracle(plan: MixPlan = PLAN) -> str:
    """The same over DuckDB's view ``documents``."""
    weights = ", ".join(map(str, plan.weights))
    laps = " + ".join(f"greatest(0, least(s.size, floor(t.target + 0.5)::BIGINT - {lap} * t.source_size - s.begin_at))" for lap in range(plan.most_repeats))
    return rf"""
WITH s0 AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
    md5('{plan.seed}:' || coalesce(doc_id::VARCHAR, '')) AS key FROM documents),
s AS (SELECT *, coalesce(sum(size) OVER (PARTITION BY source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS begin_at FROM s0),
p AS (SELECT source, sum(size)::BIGINT AS source_size FROM s0 GROUP BY source),
w AS (SELECT *, [{weights}][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % {len(plan.weights)} + 1]::DOUBLE AS weight, (source_size * {plan.most_repeats})::DOUBLE AS top,
    sum(source_size) OVER () * {plan.total_percent} / 100.0::DOUBLE AS total FROM p),
l AS (SELECT *, (total - coalesce(sum(top) OVER b, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER b, 0)) AS level FROM w
    WINDOW b AS (ORDER BY top / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
c AS (SELECT arg_min(level, top / weight) FILTER (level <= top / weight) AS common FROM l),
t AS (SELECT l.source, l.source_size, CASE WHEN common IS NULL THEN top ELSE least(top, common * weight) END::DOUBLE AS target FROM l, c)
SELECT s.doc_id, s.size, t.source_size, t.target, ({laps})::BIGINT AS taken FROM s JOIN t ON s.source IS NOT DISTINCT FROM t.source"""
