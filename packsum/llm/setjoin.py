"""Operator 9: exact Jaccard join of shingle sets, with skipping over related sets, and its components.

Equal sets are one class. Classes are indexed by the first shingles of a global order in which rare and long shingles
lead; an index list is kept in blocks of like set size, so a probe skips all blocks but its own and the next. In each
block the most central class leads. Every other entry is compared with the leaders of its block and of the block below,
and these answers settle most of the rest: entries linked to one leader are one component, with no comparison among them, and by the triangle inequality of the Jaccard distance an entry far from a leader has no link to anything
near that leader. Only pairs that the leaders' answers leave open are compared. No link is lost, and a large family of
near copies costs comparisons in proportion to its size.

Symmetric differences have a lower bound from parity sketches, which screens pairs before whole sets are compared.
Shingles and classes are known by 64-bit fingerprints. Defined results: null and empty texts have empty sets and are
their own components; repeated rows share a class; rows without an identifier link by equal sets alone; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from packsum.llm import wordhash
from packsum.llm.graph import components
from packsum.llm.runtime import materialize, pieces
from packsum.llm.tokens import spread

SETS = "doc_id long, n long, cid long"
POSTINGS = "token long, band int, n int, pos int, cid long"
FRAMES = "cid long, n long, sketch array<long>"
MEMBERS = "cid long, members binary"


@dataclass(frozen=True)
class Join:
    """Documents link when ``100 * intersection >= percent * union``."""

    shingle: int = 3
    percent: int = 90
    counter_bits: int = 22
    sketch_longs: int = 32

    def band(self, n: np.ndarray) -> np.ndarray:
        """Set sizes whose ratio allows a link are in one band or in neighbouring ones."""
        return np.floor(np.log(np.maximum(n, 1)) / np.log(100 / self.percent) + 1e-9).astype(np.int32)

    def prefix(self, n: np.ndarray) -> np.ndarray:
        return n - -(-self.percent * n // 100) + 1


@dataclass
class Sets:
    """Distinct shingles of each document of a batch, in order of document and fingerprint."""

    doc: np.ndarray
    code: np.ndarray
    length: np.ndarray  # bytes of the shingle's words
    size: np.ndarray  # of each document
    cid: np.ndarray


def shingle_sets(texts: pa.Array, width: int) -> Sets:
    w = wordhash.words(texts, lower=True)
    n_docs = len(w.first) - 1
    per_doc = np.diff(w.first)
    byte = np.concatenate([[0], np.cumsum(w.end - w.start)])
    count = np.maximum(per_doc - width + 1, 0)
    start = spread(w.first[:-1], count)
    code = wordhash.runs(w.code, width)[start] if len(start) else np.empty(0, np.uint64)
    doc = np.repeat(np.arange(n_docs), count)
    length = byte[start + width] - byte[start] if len(start) else np.empty(0, np.int64)
    for m in range(1, width):  # shorter documents are one shingle
        few = np.flatnonzero(per_doc == m)
        if len(few):
            first = w.first[:-1][few]
            whole = np.zeros(len(few), np.uint64)
            for k in range(m):
                whole = whole * wordhash.STEP + w.code[first + k]
            doc, code, length = np.append(doc, few), np.append(code, wordhash.mix(whole + np.uint64(m))), np.append(length, byte[first + m] - byte[first])
    order = np.lexsort((code, doc))
    doc, code, length = doc[order], code[order], length[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (code[1:] != code[:-1])
    doc, code, length = doc[new], code[new], length[new]
    size = np.bincount(doc, minlength=n_docs)
    total = np.concatenate([[np.uint64(0)], np.cumsum(wordhash.mix(code + wordhash.MIX_A), dtype=np.uint64)])
    bound = np.concatenate([[0], np.cumsum(size)])
    cid = wordhash.mix((total[bound[1:]] - total[bound[:-1]]) + size.astype(np.uint64) * wordhash.STEP)
    return Sets(doc, code, length, size, cid)


def classes_of(docs: DataFrame, how: Join) -> DataFrame:
    """(doc_id, set size, class) of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, "text"):
            s = shingle_sets(batch.column("text"), how.shingle)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(s.size), pa.array(wordhash.signed(s.cid))], names=["doc_id", "n", "cid"])

    return docs.mapInArrow(run, SETS)


def commonness(docs: DataFrame, how: Join) -> np.ndarray:
    """A class of document frequency for each counter of a table of fixed size: 0 where a shingle looks rare."""
    size, block = 1 << how.counter_bits, 1 << max(0, how.counter_bits - 10)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = np.zeros(size, np.uint16)
        for batch in pieces(batches, "text"):
            s = shingle_sets(batch.column("text"), how.shingle)
            seen, n = np.unique(s.code >> np.uint64(64 - how.counter_bits), return_counts=True)
            table[seen] = np.minimum(table[seen].astype(np.int64) + n, 65535).astype(np.uint16)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(size // block)), pa.array([table[k : k + block].tobytes() for k in range(0, size, block)], pa.binary())], names=["block", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, raw in zip(batch.column("block").to_pylist(), batch.column("counts").to_pylist(), strict=True):
                part = np.frombuffer(raw, np.uint16).astype(np.int64)
                sums[k] = sums[k] + part if k in sums else part
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array([v.tobytes() for v in sums.values()], pa.binary())], names=["block", "counts"])

    kind = "block long, counts binary"
    rows = docs.select("text").mapInArrow(count, kind).repartition("block").mapInArrow(add, kind).collect()  # 1,024 blocks of fixed size, whatever the data
    parts = {r["block"]: np.frombuffer(r["counts"], np.int64) for r in rows}
    mean = max(1.0, sum(int(p.sum()) for p in parts.values()) / size)
    out = np.zeros(size, np.uint8)
    for k, part in parts.items():  # block by block, so that the driver holds no second copy of the table
        out[k * block : (k + 1) * block] = np.clip(np.floor(2 * np.log2(np.maximum(part / mean, 1.0))), 0, 63)
    return out


def postings(docs: DataFrame, common: np.ndarray, how: Join) -> DataFrame:
    """The first shingles of each class, once for each task that meets the class."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met = np.empty(0, np.uint64)
        for batch in pieces(batches, "text"):
            s = shingle_sets(batch.column("text"), how.shingle)
            _, first = np.unique(s.cid, return_index=True)
            fresh = np.zeros(len(s.cid), bool)
            fresh[first] = True
            fresh &= ~np.isin(s.cid, met) & (s.size > 0)
            met = np.concatenate([met, s.cid[fresh]])
            keep = fresh[s.doc]
            doc, code = s.doc[keep], s.code[keep]
            rank = (common[(code >> np.uint64(64 - how.counter_bits)).astype(np.int64)].astype(np.uint64) << np.uint64(58)) | ((np.uint64(127) - np.minimum(s.length[keep], 127).astype(np.uint64)) << np.uint64(51)) | (code >> np.uint64(13))
            order = np.lexsort((rank, doc))
            doc, code = doc[order], code[order]
            begin = np.searchsorted(doc, np.arange(len(s.size)))
            pos = np.arange(len(doc)) - begin[doc]
            lead = pos < how.prefix(s.size)[doc]
            doc, code, pos = doc[lead], code[lead], pos[lead]
            n = s.size[doc]
            yield pa.RecordBatch.from_arrays(
                [pa.array(wordhash.signed(code)), pa.array(how.band(n)), pa.array(n.astype(np.int32)), pa.array(pos.astype(np.int32)), pa.array(wordhash.signed(s.cid[doc]))], names=["token", "band", "n", "pos", "cid"]
            )

    return docs.select("text").mapInArrow(run, POSTINGS)


def frames(docs: DataFrame, how: Join) -> DataFrame:
    """Size and parity sketch of each class: bit k is the parity of members that hash to k."""
    bits = 64 * how.sketch_longs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, "text"):
            s = shingle_sets(batch.column("text"), how.shingle)
            _, first = np.unique(s.cid, return_index=True)
            first = first[s.size[first] > 0]
            cell = s.doc * bits + (wordhash.mix(s.code ^ wordhash.MIX_B) % np.uint64(bits)).astype(np.int64)
            parity = np.zeros(len(s.size) * bits, np.uint8)
            seen, n = np.unique(cell, return_counts=True)
            parity[seen] = n & 1
            packed = np.packbits(parity.reshape(-1, bits), axis=1).view(np.int64)[first]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(first) + 1, dtype=np.int32) * how.sketch_longs), pa.array(packed.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(wordhash.signed(s.cid[first])), pa.array(s.size[first]), lists], names=["cid", "n", "sketch"])

    return docs.select("text").mapInArrow(run, FRAMES)


def members(docs: DataFrame, how: Join) -> DataFrame:
    """Whole sets of the given texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, "text"):
            s = shingle_sets(batch.column("text"), how.shingle)
            bound = np.concatenate([[0], np.cumsum(s.size)])
            view = memoryview(s.code).cast("B")
            yield pa.RecordBatch.from_arrays([pa.array(wordhash.signed(s.cid)), pa.array([bytes(view[8 * a : 8 * b]) for a, b in zip(bound[:-1].tolist(), bound[1:].tolist(), strict=True)], pa.binary())], names=["cid", "members"])

    return docs.select("text").mapInArrow(run, MEMBERS)


def linked(common: Column, n1: Column, n2: Column, percent: int) -> Column:
    return 100 * common >= percent * (n1 + n2 - common)


def screened(pairs: DataFrame, own: DataFrame, how: Join) -> DataFrame:
    """Pairs whose distance may be within twice the limit; what this drops is also far for the triangle inequality."""
    frame = lambda p: own.select(F.col("cid").alias(p), F.col("n").alias(f"n{p}"), F.col("sketch").alias(f"s{p}"))
    differ = F.aggregate(F.zip_with("sa", "sb", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda t, x: t + x)
    limit = 2 * (100 - how.percent)  # percent of distance: difference over union, union at least half the sum of both and the difference
    possible = 200 * differ <= limit * (F.col("na") + F.col("nb") + differ)
    return pairs.join(frame("a"), "a").join(frame("b"), "b").filter(possible).select("a", "b", "na", "nb")


def needed_sets(pairs: DataFrame, reps: DataFrame, docs: DataFrame, how: Join) -> DataFrame:
    cids = pairs.select(F.col("a").alias("cid")).unionByName(pairs.select(F.col("b").alias("cid"))).distinct()
    ids = cids.join(reps, "cid").select(F.col("rep").alias("rep_id"))
    return members(docs.join(ids, F.col("doc_id") == F.col("rep_id"), "left_semi"), how).dropDuplicates(["cid"])


def jaccard_components(docs: DataFrame, how: Join = Join(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each input row: its set size, and the least document reachable by links."""
    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    rows = materialize(classes_of(own, how))
    reps = rows.filter("n > 0").groupBy("cid").agg(F.min("doc_id").alias("rep"))
    frame = materialize(frames(own, how).dropDuplicates(["cid"]))
    index = postings(own, commonness(own, how), how)
    # Lists of one class end here; the others keep their entries.
    shared = index.groupBy("token").agg(F.min("cid").alias("lo"), F.max("cid").alias("hi")).filter("lo <> hi").select(F.col("token").alias("t"))
    entries = materialize(index.join(shared, F.col("token") == F.col("t"), "left_semi").distinct())
    views = led(entries)
    star = materialize(views.filter("cid <> lead").select(F.least("cid", "lead").alias("a"), F.greatest("cid", "lead").alias("b")).distinct())
    near = materialize(screened(star, frame, how))
    sets = materialize(needed_sets(near, reps, own, how))
    known = materialize(compared_sets(near, sets))
    links = known.filter(linked(F.col("common"), F.col("na"), F.col("nb"), how.percent)).select("a", "b")
    label = components(links)
    rest = open_pairs(views, known, label, how)
    rest = materialize(rest.join(star, ["a", "b"], "left_anti"))
    more = materialize(screened(rest, frame, how))
    more_sets = needed_sets(more, reps, own, how)
    found = compared_sets(more, more_sets).filter(linked(F.col("common"), F.col("na"), F.col("nb"), how.percent)).select("a", "b")
    label = components(links.unionByName(found))
    class_rep = reps.join(label.withColumnRenamed("node", "cid"), "cid", "left").withColumn("group", F.coalesce("label", "cid"))
    least = class_rep.groupBy("group").agg(F.min("rep").alias("component"))
    table = class_rep.join(least, "group").select(F.col("cid").alias("c"), "component")
    out = rows.join(table, (F.col("cid") == F.col("c")) & (F.col("n") > 0), "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "doc_id").alias("component_id"))


def led(entries: DataFrame) -> DataFrame:
    """Entries beside the leaders of their block and of the block below.

    The leader of a block is its most central class: the one whose lists are longest in all, which in a family of near
    copies is the copy with the fewest changes of its own.
    """
    size = entries.groupBy("token").agg(F.count(F.lit(1)).alias("size"))
    central = entries.select("token", "cid").join(size, "token").groupBy("cid").agg(F.sum("size").alias("score"))
    leaders = entries.select("token", "band", "cid").join(central, "cid").groupBy("token", "band").agg(F.max(F.struct("score", "cid"))["cid"].alias("lead"))
    lists = leaders.groupBy(F.col("token").alias("t")).agg(F.collect_list(F.struct("band", "lead")).alias("leads"))  # one a band
    views = entries.join(lists, F.col("token") == F.col("t")).withColumn("l", F.explode(F.expr("filter(leads, x -> x.band in (band, band - 1))")))
    return materialize(views.select("token", F.col("l.band").alias("lead_band"), F.col("l.lead").alias("lead"), (F.col("l.band") == F.col("band")).alias("own"), "band", "n", "pos", "cid"))


def compared_sets(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Pairs with the size of their intersection."""
    side = lambda p: sets.select(F.col("cid").alias(p), F.col("members").alias(f"m{p}"))

    def overlap(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [len(np.intersect1d(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), assume_unique=True)) for x, y in zip(batch.column("ma"), batch.column("mb"), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("a", "b", "na", "nb")] + [pa.array(out, pa.int64())], names=["a", "b", "na", "nb", "common"])

    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "na", "nb", "ma", "mb")
    return both.mapInArrow(overlap, "a long, b long, na long, nb long, common long")


def open_pairs(views: DataFrame, known: DataFrame, label: DataFrame, how: Join) -> DataFrame:
    """Pairs in one list that the leaders' answers leave open: other components, sizes and places that allow a link."""
    gap = 1 - how.percent / 100
    distance = 1 - F.col("common") / (F.col("na") + F.col("nb") - F.col("common"))
    answers = known.select(F.col("a").alias("ka"), F.col("b").alias("kb"), distance.alias("d"))
    v = views.withColumn("ka", F.least("cid", "lead")).withColumn("kb", F.greatest("cid", "lead")).join(answers, ["ka", "kb"], "left")
    v = v.withColumn("d", F.when(F.col("cid") == F.col("lead"), 0.0).otherwise(F.col("d")))  # null: screened, so over twice the limit
    v = v.join(label.select(F.col("node").alias("cid"), F.col("label")), "cid", "left").withColumn("label", F.coalesce("label", "cid"))
    key = ["token", "lead_band"]
    mixed = v.groupBy(*key).agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo <> hi").select(*key)
    v = materialize(v.join(mixed, key).select(*key, "own", "n", "pos", "cid", "label", "d"))
    free, close = F.col("d").isNull() | (F.col("d") > gap + 1e-9), F.col("d") <= 2 * gap + 1e-9
    left = lambda df: df.select(*key, *(F.col(c).alias(f"x_{c}") for c in ("own", "n", "pos", "cid", "label", "d")))
    right = lambda df: df.select(*key, *(F.col(c).alias(f"y_{c}") for c in ("own", "n", "pos", "cid", "label", "d")))
    sizes = (100 * F.least("x_n", "y_n") >= how.percent * F.greatest("x_n", "y_n")) & (F.col("x_own") | F.col("y_own"))
    rest = 1 + F.least(F.col("x_n") - F.col("x_pos") - 1, F.col("y_n") - F.col("y_pos") - 1)
    enough = rest * (100 + how.percent) >= how.percent * (F.col("x_n") + F.col("y_n"))
    triangle = F.coalesce(F.abs(F.col("x_d") - F.col("y_d")) <= gap + 1e-9, F.lit(True))
    may = sizes & enough & triangle & (F.col("x_label") != F.col("y_label"))
    among = left(v.filter(free)).join(right(v.filter(free)), key).filter(may & (F.col("x_cid") < F.col("y_cid")))
    across = left(v.filter(free & close)).join(right(v.filter(~free)), key).filter(may)
    both = among.select("x_cid", "y_cid").unionByName(across.select("x_cid", "y_cid"))
    return both.select(F.least("x_cid", "y_cid").alias("a"), F.greatest("x_cid", "y_cid").alias("b")).distinct()


def keep_one(docs: DataFrame, how: Join = Join()) -> DataFrame:
    """One document of each component stays: the least identifier, and one row of it. Rows without one all stay."""
    decided = jaccard_components(docs, how).filter(F.col("doc_id") == F.col("component_id")).select(F.col("doc_id").alias("_kept")).distinct()
    kept = docs.join(decided, F.col("doc_id") == F.col("_kept"), "left_semi").dropDuplicates(["doc_id"])
    return kept.unionByName(docs.filter(F.col("doc_id").isNull()))


def oracle(how: Join = Join()) -> str:
    """The same over DuckDB's view ``documents``."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return rf"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
p AS (SELECT doc_id, unnest(ws) AS a, generate_subscripts(ws, 1) AS i FROM w),
q AS (SELECT doc_id, i, a, lead(a) OVER o AS b, lead(a, 2) OVER o AS c FROM p WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
s AS (SELECT DISTINCT doc_id, a || ' ' || b || ' ' || c AS t FROM q WHERE c IS NOT NULL
  UNION ALL SELECT doc_id, array_to_string(ws, ' ') FROM w WHERE len(ws) IN (1, 2)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (SELECT x.doc_id AS u, y.doc_id AS v, count(*) AS c FROM s x JOIN s y ON x.t = y.t AND x.doc_id < y.doc_id GROUP BY 1, 2),
l AS (SELECT u, v FROM o JOIN n a ON a.doc_id = u JOIN n b ON b.doc_id = v WHERE 100 * c >= {how.percent} * (a.n + b.n - c)),
e AS (SELECT u, v FROM l UNION ALL SELECT v, u FROM l),
r AS (SELECT doc_id AS u, doc_id AS v FROM documents UNION SELECT r.u, e.v FROM r JOIN e ON r.v = e.u)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.component_id FROM w LEFT JOIN n ON n.doc_id = w.doc_id
JOIN (SELECT u, min(v) AS component_id FROM r GROUP BY u) m ON m.u = w.doc_id"""
