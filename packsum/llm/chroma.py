"""Operator 4: chroma audio fingerprints.

Audio is cut into overlapping frames; spectral energy is folded into twelve pitch classes. Sixteen box filters over the
image of pitch classes by time, evaluated from its integral image, give two bits each: one 32-bit integer for each
frame. Recordings are aligned by the histogram of offsets at which windows of their integers agree, and judged by bit
errors at the best offset.

Noisy copies seldom share a whole integer, so the index has keys of bits drawn from a window of integers, in several
tables. Which bits are steady is fitted on a bounded sample of classes (``Chroma.sample``); every recording is indexed.
Keys lengthen with the logarithm of the number of classes, so that chance meetings stay in proportion to the rows, and
tables become more with them, to hold the recall. A sketch of other bits of the same window screens what a key lets
meet; whole fingerprints join only the pairs that are left. Of a group of noisy copies only a central leader stands in
the index; the others are reached through it, so that a query meets the group in a few windows and not in all of them.

The tables hold no audio, so the query renders each embedding as a melody, a documented stand-in for a media column.
Recordings with equal fingerprints are one class; searches compare classes. Defined results: null or empty audio has an
empty fingerprint, which matches nothing but its own class; repeated rows share a class; rows without an identifier
are found by their class but are no queries; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from packsum.llm import wordhash
from packsum.llm.runtime import materialize

FINGERPRINTS = "rec_id long, codes array<int>"


@dataclass(frozen=True)
class Chroma:
    rate: int = 4096
    frame: int = 1024
    hop: int = 512
    low_hz: float = 60.0
    high_hz: float = 1900.0
    widest: int = 8
    query_modulus: int = 20
    most_errors: float = 0.2
    least_overlap: int = 16
    window: int = 16  # integers that a key draws its bits from
    steady: int = 12  # bits of an integer that keys draw from
    sample: int = 2048  # classes that the steady bits are fitted on
    sketch_errors: int = 12  # of 64 bits; steady bits differ in some 9 between copies at the bound
    salts: int = 16  # parts of a leader's followers
    seed: int = 7


def filters(how: Chroma) -> list[tuple[int, int, int, int]]:
    """(pattern, first pitch class, pitch classes, frames) of the sixteen filters, by rule."""
    out = []
    for k in range(16):
        height = (3, 6, 9, 4)[k % 4]  # all twelve classes sum to one: a filter of that height would tell nothing
        out.append((k % 6, (5 * k) % (13 - height), height, (2, 4, how.widest, 6)[(k // 4 + k) % 4]))
    return out


def chromagram(pcm: np.ndarray, how: Chroma) -> np.ndarray:
    """(recordings, frames, 12) energies, each frame scaled to sum one. pcm: (recordings, samples)."""
    n = (pcm.shape[1] - how.frame) // how.hop + 1
    if n <= 0:
        return np.zeros((len(pcm), 0, 12))
    at = np.arange(how.frame) + how.hop * np.arange(n)[:, None]
    power = np.abs(np.fft.rfft(pcm[:, at].astype(np.float32) * np.hanning(how.frame).astype(np.float32), axis=2)) ** 2
    hz = np.fft.rfftfreq(how.frame, 1 / how.rate)
    used = (hz >= how.low_hz) & (hz <= how.high_hz)
    pitch = np.zeros((len(hz), 12), np.float32)
    pitch[np.flatnonzero(used), np.round(12 * np.log2(hz[used] / 440.0)).astype(int) % 12] = 1
    chroma = power @ pitch
    return chroma / np.maximum(chroma.sum(axis=2, keepdims=True), 1e-9)


def codes(chroma: np.ndarray, how: Chroma) -> np.ndarray:
    """Packed integers of each frame that has the widest filter's frames after it."""
    r, t, _ = chroma.shape
    n = t - how.widest + 1
    if n <= 0:
        return np.zeros((r, 0), np.int32)
    image = np.zeros((r, t + 1, 13))
    image[:, 1:, 1:] = chroma.cumsum(axis=1).cumsum(axis=2)
    box = lambda a, b, lo, hi: image[:, b : b + n, hi] - image[:, a : a + n, hi] - image[:, b : b + n, lo] + image[:, a : a + n, lo]
    out = np.zeros((r, n), np.uint32)
    for kind, y, h, w in filters(how):
        whole, mid_t, mid_p = box(0, w, y, y + h), w // 2, y + h // 2
        if kind == 0:
            x, other = whole, np.full_like(whole, w * h / 12)
        elif kind == 1:
            x = box(0, w, y, mid_p)
            other = whole - x
        elif kind == 2:
            x = box(0, mid_t, y, y + h)
            other = whole - x
        elif kind == 3:
            x = box(0, mid_t, y, mid_p) + box(mid_t, w, mid_p, y + h)
            other = whole - x
        elif kind == 4:
            x = box(0, w, y + h // 3, y + h - h // 3) * 2
            other = whole
        else:
            x = box(w // 4, w - w // 4, y, y + h) * 2
            other = whole
        value = np.log1p(x) - np.log1p(other)
        level = (value > -0.12).astype(np.uint32) + (value > 0) + (value > 0.12)
        out = (out << np.uint32(2)) | (level ^ (level >> np.uint32(1)))  # neighbouring levels differ in one bit
    return out.view(np.int32)


def fingerprints(audio: DataFrame, how: Chroma = Chroma(), rec_id: str = "rec_id", pcm: str = "pcm") -> DataFrame:
    """(rec_id, codes) of recordings in a binary column of 16-bit little-endian mono samples."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 32):
                batch = whole.slice(lo, 32)
                waves = [np.frombuffer((x or b"")[: len(x or b"") // 2 * 2], "<i2") for x in batch.column("pcm").to_pylist()]
                out: list = [None] * len(waves)
                for length in {len(w) for w in waves}:  # recordings of one length are one array
                    at = [i for i, w in enumerate(waves) if len(w) == length]
                    for i, row in zip(at, codes(chromagram(np.stack([waves[i] for i in at]), how), how), strict=True):
                        out[i] = row.tolist()
                yield pa.RecordBatch.from_arrays([batch.column("rec_id"), pa.array(out, pa.list_(pa.int32()))], names=["rec_id", "codes"])

    return audio.select(F.col(rec_id).cast("long").alias("rec_id"), F.col(pcm).alias("pcm")).mapInArrow(run, FINGERPRINTS)


def rendered(vectors: np.ndarray, how: Chroma) -> np.ndarray:
    """A note for each coordinate: two octaves from low to high value, with one overtone; 16-bit samples."""
    spread = np.maximum(np.sqrt((vectors**2).mean(axis=1, keepdims=True)), 1e-9)
    note = np.round(12 * (np.clip(vectors / (2.5 * spread), -1, 1) + 1))
    hz = 110.0 * 2 ** (note / 12)
    phase = 2 * np.pi * hz[:, :, None] * (np.arange(how.hop) / how.rate)
    wave = 0.6 * np.sin(phase) + 0.25 * np.sin(2 * phase)
    return (wave.reshape(len(vectors), -1) * 20_000).astype("<i2")


def melody_audio(embeddings: DataFrame, how: Chroma = Chroma()) -> DataFrame:
    """(rec_id, pcm): the stand-in media column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 32):
                batch = whole.slice(lo, 32)
                out = []
                for v in batch.column("embedding").to_pylist():
                    x = np.nan_to_num(np.array([0.0 if c is None else c for c in v or []], float))
                    out.append(rendered(x[None, :], how)[0].tobytes() if len(x) else None)
                yield pa.RecordBatch.from_arrays([batch.column("rec_id"), pa.array(out, pa.binary())], names=["rec_id", "pcm"])

    return embeddings.select(F.col("vec_id").cast("long").alias("rec_id"), "embedding").mapInArrow(run, "rec_id long, pcm binary")


def steady_bits(sample: np.ndarray, how: Chroma) -> list[int]:
    """Bits that differ least in near copies, against what chance would give; from near copies within the sample where it
    has some, otherwise the most even bits. sample: (recordings, integers), all of one length."""
    x = np.ascontiguousarray(sample).view(np.uint32)
    if not x.size:
        return list(range(how.steady))
    bits = np.unpackbits(x.view(np.uint8).reshape(*x.shape, 4), axis=2, bitorder="little").reshape(*x.shape, 32).astype(np.float32)
    share = bits.mean(axis=(0, 1))
    chance = 2 * share * (1 - share)
    flat = bits.reshape(len(x), -1) * 2 - 1
    wrong = np.triu((1 - flat @ flat.T / flat.shape[1]) / 2 + np.eye(len(x)), 1)
    a, b = np.nonzero((wrong > 0) & (wrong <= 1.25 * how.most_errors))
    flips = (bits[a] != bits[b]).mean(axis=(0, 1)) if len(a) >= 20 else np.zeros(32)
    return np.lexsort((np.arange(32), -chance, flips / np.maximum(chance, 1e-3) + 9.0 * (chance < 0.1)))[: how.steady].tolist()


def key_plan(classes: int, bits: list[int], how: Chroma) -> tuple[list[list[tuple[int, int]]], list[tuple[int, int]]]:
    """(bits of each table's keys, bits of the sketch) as (integer in the window, bit)."""
    rng = np.random.default_rng(how.seed)
    all_bits = [(s, k) for s in range(how.window) for k in bits]
    length = min(math.ceil(1.5 * math.log2(max(classes, 2) + 254)), len(all_bits))
    tables = max(2, math.ceil(4 * 1.15 ** (length - 24)))
    draw = lambda n: sorted(all_bits[i] for i in rng.permutation(len(all_bits))[:n])
    return [draw(length) for _ in range(tables)], draw(64)


def window_keys(flat: np.ndarray, plan: list[tuple[int, int]], window: int) -> np.ndarray:
    """One 64-bit key for every window of a run of integers."""
    n = len(flat) - window + 1
    out = np.zeros(n, np.uint64)
    for s in sorted({s for s, _ in plan}):
        mask = np.uint32(sum(1 << k for t, k in plan if t == s))
        out = wordhash.mix(out * wordhash.STEP + (flat[s : s + n] & mask).astype(np.uint64) + np.uint64(s + 1))
    return out


def window_sketch(flat: np.ndarray, plan: list[tuple[int, int]], window: int) -> np.ndarray:
    n = len(flat) - window + 1
    out = np.zeros(n, np.uint64)
    for i, (s, k) in enumerate(plan):
        out |= ((flat[s : s + n] >> np.uint32(k)) & np.uint32(1)).astype(np.uint64) << np.uint64(i)
    return out


def postings(classes: DataFrame, plan: tuple, how: Chroma, side: str) -> DataFrame:
    """(class, place, key, sketch) of all windows. Windows that repeat the key of the one before are left out: a held note
    counts where it begins, which aligns as well."""
    tables, sketch = plan
    names = [f"{side}_id", f"{side}_at", "code", f"{side}_sketch"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 1024):
                batch = whole.slice(lo, 1024)
                lists = batch.column("codes")
                size = lists.value_lengths().to_numpy(zero_copy_only=False)
                flat = lists.flatten().to_numpy().view(np.uint32)
                if len(flat) < how.window:
                    continue
                own, start = np.repeat(np.arange(len(size)), size), np.concatenate([[0], np.cumsum(size)])[:-1]
                n = len(flat) - how.window + 1
                inside = own[:n] == own[how.window - 1 :]
                marks, ids = window_sketch(flat, sketch, how.window).view(np.int64), batch.column("class_id").to_numpy(zero_copy_only=False)
                for t, table in enumerate(tables):
                    key = wordhash.mix(window_keys(flat, table, how.window) + np.uint64(t))
                    new = inside.copy()
                    new[1:] &= (key[1:] != key[:-1]) | (own[1:n] != own[: n - 1])
                    at = np.flatnonzero(new)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[own[at]], pa.int64()), pa.array((at - start[own[at]]).astype(np.int32)), pa.array(key[at].view(np.int64)), pa.array(marks[at])], names=names)

    return classes.select("class_id", "codes").mapInArrow(run, f"{names[0]} long, {names[1]} int, code long, {names[3]} long")


def judged(pairs: DataFrame, known: DataFrame) -> DataFrame:
    """(q_id, r_id, offset, overlap, errors) of pairs: bits that differ where both have integers at the offset."""
    side = lambda p: known.select(F.col("class_id").alias(f"{p}_id"), F.col("codes").alias(f"{p}_codes"))
    both = pairs.select("q_id", "r_id", "offset").join(side("q"), "q_id").join(side("r"), "r_id")
    overlap = F.greatest(F.lit(0), F.least(F.size("q_codes"), F.size("r_codes") - F.col("offset")) - F.greatest(F.lit(0), -F.col("offset")))
    first = F.greatest(F.lit(0), -F.col("offset"))
    a, b = F.slice("q_codes", first + 1, overlap), F.slice("r_codes", first + F.col("offset") + 1, overlap)
    errors = F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y).bitwiseAND(F.lit(0xFFFFFFFF)))), F.lit(0), lambda t, x: t + x)
    return both.select("q_id", "r_id", "offset", overlap.alias("overlap"), errors.alias("errors"))


def followers(known: DataFrame, plan: tuple, how: Chroma) -> DataFrame:
    """(f_id, leader, f_errors): classes that lie within the bound of a leader of the same length, at offset 0.

    A class's weight is the number of its meetings under the first two tables' keys; of the classes that it meets it takes
    the heaviest, which is central in a group of noisy copies. Leaders follow nobody: a class whose choice follows another
    stays by itself, as does one whose choice is out of the bound. Work is in proportion to the windows: each key gives its
    count and its heaviest class, never its pairs.
    """
    marks = materialize(postings(known, (plan[0][:2], plan[1]), how, "r").select("r_id", "code").distinct())
    met = marks.groupBy("code").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    weight = marks.join(met, "code").groupBy("r_id").agg(F.sum(F.col("n") - 1).alias("weight"))
    weighed = materialize(marks.join(weight, "r_id"))
    heaviest = weighed.groupBy("code").agg(F.max(F.struct("weight", (-F.col("r_id")).alias("minus"))).alias("top"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    chosen = weighed.join(heaviest, "code").groupBy("r_id").agg((-F.max("top")["minus"]).alias("leader")).filter(F.col("leader") != F.col("r_id"))
    length = known.select("class_id", F.size("codes").alias("n"))
    near = judged(chosen.select(F.col("r_id").alias("q_id"), F.col("leader").alias("r_id"), F.lit(0).alias("offset")), known)
    near = near.join(length.toDF("q_id", "q_n"), "q_id").join(length.toDF("r_id", "r_n"), "r_id")
    near = materialize(near.filter((F.col("q_n") == F.col("r_n")) & (F.col("errors") <= how.most_errors * 32 * F.col("q_n"))).select(F.col("q_id").alias("f_id"), F.col("r_id").alias("leader"), F.col("errors").alias("f_errors")))
    return materialize(near.join(near.select(F.col("f_id").alias("leader")), "leader", "left_anti").select("f_id", "leader", "f_errors"))


def search(prints: DataFrame, how: Chroma = Chroma()) -> DataFrame:
    """One row for each recording: its class, and for queries the classes that align with it.

    Queries are recordings whose identifier the modulus divides. Candidates share a key of a window; the offset that most
    shared keys have in common is the alignment. Classes meet once, whatever their sizes. Noisy copies are met through
    their leader: only leaders and classes by themselves are looked up by keys, and a query that meets a leader is judged
    with its followers at the same offset, but for those that the triangle inequality rules out.
    """
    rows = materialize(prints.withColumn("h", F.xxhash64("codes")))
    asks = F.max(F.coalesce((F.col("rec_id") % how.query_modulus == 0).cast("int"), F.lit(0)))
    classes = materialize(rows.groupBy("h").agg(F.min("rec_id").alias("class_id"), F.count(F.lit(1)).alias("n_class"), F.first("codes").alias("codes"), asks.alias("asks")))
    known = classes.filter((F.size("codes") >= how.window) & F.col("class_id").isNotNull())
    usual = known.groupBy(F.size("codes").alias("n")).agg(F.count(F.lit(1)).alias("c")).orderBy(F.desc("c"), "n").first()
    total = known.count()
    length = usual["n"] if usual else 0
    taken = known.filter(F.size("codes") == length).select("h", "codes").orderBy("h").limit(how.sample).toArrow()["codes"]  # of bounded number
    plan = key_plan(total, steady_bits(np.array(taken.to_pylist(), np.int32).reshape(len(taken), length), how), how)
    led = followers(known, plan, how)
    queries = known.filter("asks = 1")
    heads = known.join(led.select(F.col("f_id").alias("class_id")), "class_id", "left_anti")
    alike = F.bit_count(F.col("q_sketch").bitwiseXOR(F.col("r_sketch"))) <= how.sketch_errors
    met = postings(queries, plan, how, "q").alias("q").join(postings(heads, plan, how, "r").alias("r"), (F.col("q.code") == F.col("r.code")) & (F.col("q_id") != F.col("r_id")) & alike)
    votes = met.groupBy("q_id", "r_id", (F.col("r_at") - F.col("q_at")).alias("offset")).agg(F.count(F.lit(1)).alias("votes"))
    asking = queries.select(F.col("class_id").alias("q_id"))
    own = led.select(F.col("f_id").alias("q_id"), F.col("leader").alias("r_id"), F.lit(0).alias("offset"), F.lit(0).cast("long").alias("votes")).join(asking, "q_id", "left_semi")
    best = votes.unionByName(own).groupBy("q_id", "r_id").agg(F.max(F.struct("votes", -F.abs("offset"), "offset"))["offset"].alias("offset"))
    direct = materialize(judged(best, known))
    most = how.most_errors * 32 * F.col("overlap")
    itself = asking.select("q_id", F.col("q_id").alias("r_id"), F.lit(0).alias("offset"), F.lit(None).cast("int").alias("overlap"), F.lit(None).cast("int").alias("errors"))
    reach = direct.filter(F.col("overlap") >= how.least_overlap).unionByName(itself).join(led.select(F.col("leader").alias("r_id")).distinct(), "r_id", "left_semi")
    reach = reach.withColumnRenamed("r_id", "leader").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(how.salts - 1))))
    salted = led.withColumn("salt", F.pmod(F.xxhash64("f_id"), F.lit(how.salts)).cast("int"))
    within = F.col("errors").isNull() | (F.col("errors") - F.col("f_errors") <= most)
    through = reach.join(salted, ["leader", "salt"]).filter(within & (F.col("f_id") != F.col("q_id"))).select("q_id", F.col("f_id").alias("r_id"), "offset")
    every = direct.unionByName(judged(through, known))
    links = every.filter((F.col("overlap") >= how.least_overlap) & (F.col("errors") <= most)).withColumn("bit_errors", F.col("errors") / (32.0 * F.greatest(F.lit(1), F.col("overlap"))))
    found = materialize(links.groupBy(F.col("q_id").alias("class_id")).agg(F.sort_array(F.collect_list(F.struct(F.col("r_id").alias("class_id"), "offset", F.round("bit_errors", 6).alias("bit_errors")))).alias("matches")))
    out = rows.join(classes.select("h", "class_id", "n_class"), "h").join(found, "class_id", "left")
    query = F.coalesce(F.col("rec_id") % how.query_modulus == 0, F.lit(False))
    return out.select(F.col("rec_id").alias("vec_id"), "class_id", "n_class", F.size("codes").cast("long").alias("n_codes"), query.alias("is_query"), F.when(query, F.coalesce("matches", F.array().cast("array<struct<class_id:bigint,offset:int,bit_errors:double>>"))).alias("matches"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(fingerprints(melody_audio(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))))
