"""Operator 2: a hashed maximum-entropy language model with a class-factored softmax.

Every training word is an outcome. Words are put into classes of at most ``fanout`` members, classes into classes, and
so on to one root, lightest first, so that a common word is a few steps away and a rare one some more. The probability
of a word is the product of one softmax for each class on its way. Each softmax adds, to the log share of its members'
corpus counts, the hashed weights of the last word, the last two words, and the word before the last (a skip). Weights
of zero therefore give exactly the unigram model, and the probabilities of all words and of "a word not in training"
sum to one.

The commonest words have places of their own. The others share places by their fingerprint, about ``share`` to a place
(more only when there are over ``share * most_places`` of them), and a place is shared out by corpus counts. What the
driver and a task hold is bounded by ``frequent``, ``most_places`` and ``most_bits``; up to those bounds it grows with
the training text. Counts of all words stay a table, and words without a place of their own meet it in a join.

Training is distributed: in each round every task goes through its share of all training texts by adaptive gradient
steps, at every class on the way of every token, and hands back the weights it touched with their sums of squared
gradients; the next weights are the means weighted by those sums. Scoring works on numpy batches of (token, class on
its way) rows, which are sparse: no token touches a class that its word is not in.

Defined results: a null or empty text is the end token alone; with no training text both scores are 0; repeated rows
score alike, each in its own row; rows without an identifier are scored and belong to the training side; extra columns
are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from packsum.llm import wordhash
from packsum.llm.runtime import held_out, materialize, pieces

END = np.uint64(0x5DEECE66D1234567)
START = np.uint64(0x2545F4914F6CDD1D)
FEATURES = 3
#: Tokens of one gradient step, and of one batch of scores.
BATCH = 4096
#: Bytes of text that are cut into words at a time; a longer text is a slice of its own.
SLICE = 1_000_000
#: Weight rows that travel together between tasks.
BLOCK = 1024


@dataclass(frozen=True)
class Maxent:
    fanout: int = 16
    frequent: int = 131_072
    share: int = 16
    most_places: int = 65_536
    tokens_per_weight: int = 1
    least_bits: int = 16
    most_bits: int = 22
    rounds: int = 1
    rate: float = 0.3
    every: int = 1
    settled: float = 50.0
    tokens_per_task: int = 256_000_000


@dataclass
class Model:
    """Leaves: one for each frequent word, by fingerprint, then the shared places, then the unknown word."""

    code: np.ndarray
    index: np.ndarray  # buckets of the fingerprints
    count: np.ndarray
    place_bits: int  # -1: no shared places
    place_mass: np.ndarray
    way: np.ndarray  # bounds of each leaf's classes in the next two
    way_node: np.ndarray
    way_member: np.ndarray
    prior: np.ndarray  # log shares of a class's members
    weights: np.ndarray
    energy: np.ndarray  # sums of squared gradients by row of weights
    tokens: int
    types: int

    @property
    def leaves(self) -> int:
        return len(self.code) + len(self.place_mass) + 1

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update({k: built_in(v) if isinstance(v, np.ndarray) else v for k, v in state.items()})


def built_in(x: np.ndarray) -> np.ndarray:
    """The same array with numpy's own type object. Arrays out of a pickle have a copy of it, and so has all that is
    computed from them; ``np.add.at`` then takes a path some ten times slower."""
    return x.view(np.dtype(x.dtype.str))


def token_codes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Fingerprints of the tokens of all texts in turn, an end after each, and n + 1 bounds."""
    w = wordhash.words(texts, lower=True)
    code = np.insert(w.code, w.first[1:], END)
    return code, w.first + np.arange(len(w.first))


def word_counts(docs: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, "text", SLICE):
            code, n = np.unique(token_codes(batch.column("text"))[0], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(wordhash.signed(code)), pa.array(n)], names=["code", "c"])

    return docs.select("text").mapInArrow(run, "code long, c long").groupBy("code").agg(F.sum("c").alias("c"))


def buckets(table: np.ndarray) -> np.ndarray:
    """Bounds, in a sorted table of fingerprints, of those that begin with the same bits: about two buckets an entry."""
    bits = max(int(len(table)).bit_length(), 1)
    return np.searchsorted(table, np.arange(1 << bits, dtype=np.uint64) << np.uint64(64 - bits)).astype(np.int32)


def lookup(code: np.ndarray, table: np.ndarray, index: np.ndarray) -> np.ndarray:
    """Place of each code in a sorted table, or -1."""
    out = np.full(len(code), -1)
    if not len(table):
        return out
    bucket = (code >> np.uint64(64 - int(len(index)).bit_length() + 1)).astype(np.int64)
    at, end = index[bucket], np.append(index[1:], np.int32(len(table)))[bucket]
    left, want = np.arange(len(code)), code
    while True:
        live = at < end
        left, want, at, end = left[live], want[live], at[live], end[live]
        if not len(left):
            return out
        hit = table[at] == want
        out[left[hit]] = at[hit]
        miss = ~hit
        left, want, at, end = left[miss], want[miss], at[miss] + 1, end[miss]


def class_tree(mass: np.ndarray, fanout: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(parent, branch, prior); inner nodes come after the leaves, and are numbered from 0 as parents. The lightest ``fanout`` trees become one until one is left."""
    n = len(mass)
    inner = max(0, -(-(n - 1) // (fanout - 1)))
    parent, branch = np.full(n + inner, -1, np.int64), np.zeros(n + inner, np.int64)
    prior = np.full((max(inner, 1), fanout), -1e9, np.float32)
    order = np.argsort(mass, kind="stable")
    total = np.concatenate([mass, np.zeros(inner)])
    leaf = made = 0
    for node in range(inner):
        many = n - (inner - 1) * (fanout - 1) if node == 0 else fanout  # the first class takes what the others leave over
        members = []
        for _ in range(many):
            if made < node and (leaf == n or total[n + made] < mass[order[leaf]]):
                members.append(n + made)
                made += 1
            else:
                members.append(order[leaf])
                leaf += 1
        total[n + node] = total[members].sum()
        parent[members], branch[members] = node, np.arange(many)
        prior[node, :many] = np.log(total[members] / total[n + node])
    return parent, branch, prior


def leaf_of(code: np.ndarray, model: Model) -> tuple[np.ndarray, np.ndarray]:
    """Leaf of each token, and whether its word has one of its own."""
    at = lookup(code, model.code, model.index)
    own = at >= 0
    if model.place_bits < 0:
        shared = np.full(len(code), model.leaves - 1)
    else:
        shared = len(model.code) + ((code >> np.uint64(1)) >> np.uint64(63 - model.place_bits)).astype(np.int64)
    return np.where(own, at, shared), own


def contexts(code: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """(features, tokens): last word, last two words, word before the last, as mixed 64-bit values."""
    last, before = np.empty_like(code), np.empty_like(code)
    last[1:], before[2:] = code[:-1], code[:-2]
    last[bounds[:-1]] = START
    before[bounds[:-1]] = START
    second = bounds[:-1] + 1
    before[second[second < bounds[1:]]] = START
    return np.stack([wordhash.mix(last ^ wordhash.MIX_A), wordhash.mix(last * wordhash.STEP + before), wordhash.mix(before ^ wordhash.MIX_B)])


def paths(parent: np.ndarray, branch: np.ndarray, leaves: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bounds by leaf, classes, members): the classes on every leaf's way to the root."""
    leaf, at, steps = np.arange(leaves), np.arange(leaves), []
    while len(at):
        live = parent[at] >= 0
        leaf, at = leaf[live], at[live]
        steps.append((leaf, parent[at], branch[at]))
        at = leaves + parent[at]
    leaf, node, member = (np.concatenate(x) for x in zip(*steps, strict=True))
    order = np.argsort(leaf, kind="stable")
    return np.concatenate([[0], np.cumsum(np.bincount(leaf, minlength=leaves))]), node[order].astype(np.int32), member[order].astype(np.int8)


def ways(leaf: np.ndarray, model: Model, every: int = 1, first: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(token, class, member) for the classes on the tokens' ways, or every so many of them."""
    begin = model.way[leaf]
    ends = np.cumsum(model.way[leaf + 1] - begin)
    at = np.arange(first, ends[-1] if len(ends) else 0, every)
    token = np.repeat(np.arange(len(leaf)), model.way[leaf + 1] - begin) if every == 1 else np.searchsorted(ends, at, side="right")
    place = model.way[leaf[token] + 1] - (ends[token] - at)
    return token, model.way_node[place], model.way_member[place]


def softmax(context: np.ndarray, leaf: np.ndarray, model: Model, every: int = 1, first: int = 0) -> tuple[np.ndarray, ...]:
    """(token, member, weight rows, odds of all members, their sum) for the classes on the ways, or every so many of them."""
    token, node, member = ways(leaf, model, every, first)
    bits = int(len(model.weights)).bit_length() - 1
    salt = wordhash.mix(node.astype(np.uint64) + np.uint64(1))
    rows = [(((context[f, token] ^ salt) * wordhash.STEP) >> np.uint64(64 - bits)).astype(np.int64) for f in range(FEATURES)]
    z = np.take(model.prior, node, axis=0)
    for r in rows:
        z += np.take(model.weights, r, axis=0)
    np.exp(z, out=z)  # weights are bounded, so no member needs to be taken off first
    return token, member, rows, z, z @ np.ones(z.shape[1], np.float32)


def log_shares(context: np.ndarray, leaf: np.ndarray, model: Model) -> np.ndarray:
    """Natural log probability of each token's leaf."""
    out = np.zeros(len(leaf))
    for lo in range(0, len(leaf), BATCH):
        token, member, _, odds, total = softmax(context[:, lo : lo + BATCH], leaf[lo : lo + BATCH], model)
        log_p = np.log(odds[np.arange(len(odds)), member] / total)
        out[lo : lo + BATCH] = np.bincount(token, weights=log_p, minlength=len(out[lo : lo + BATCH]))
    return out


def gradient_steps(code: np.ndarray, bounds: np.ndarray, model: Model, how: Maxent) -> None:
    """Adaptive steps through all tokens in turn; changes ``weights`` and ``energy``.

    A step goes through every class on the ways of its tokens; ``every`` over 1 would leave classes out.
    """
    context, leaf = contexts(code, bounds), leaf_of(code, model)[0]
    fanout = model.weights.shape[1]
    pair = np.complex64 if fanout % 2 == 0 else np.float32  # two weights are added at a time, each to its own
    flat, ones = model.weights.reshape(-1).view(pair), np.ones(fanout, np.float32)
    wide = np.arange(fanout * np.dtype(np.float32).itemsize // flat.itemsize)
    for lo in range(0, len(code), BATCH):
        _, member, rows, step, total = softmax(context[:, lo : lo + BATCH], leaf[lo : lo + BATCH], model, how.every, lo // BATCH % how.every)
        step *= (-1 / total)[:, None]
        step[np.arange(len(step)), member] += 1
        square = (step * step) @ ones
        for r in rows:  # a row that several tokens share moves by the sum of their steps
            np.add.at(model.energy, r, square)
        for r in rows:
            own = step * (np.float32(how.rate) / np.sqrt(np.take(model.energy, r) + np.float32(1e-6)))[:, None]
            np.add.at(flat, (r[:, None] * len(wide) + wide).ravel(), own.ravel().view(pair))


TOUCHED = "block int, row array<int>, energy array<float>, weight array<float>"


def one_round(docs: DataFrame, model: Model, how: Maxent) -> None:
    """All tasks start from the same weights; a row's moves are averaged by their sums of squared gradients.

    Many tasks that each met a context a few times have all stopped short of where one task that met it every time would
    be, by the root of their number; the mean of such rows, known by a small sum, is lengthened by as much.
    """
    rows, fanout = model.weights.shape
    start = (model.weights, model.energy) if model.energy.any() else None  # untrained weights are not sent
    fixed = Model(**{**vars(model), "weights": np.empty((0, fanout), np.float32), "energy": np.empty(0, np.float32)})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, energy = map(built_in, start or (np.zeros((rows, fanout), np.float32), np.zeros(rows, np.float32)))
        local = Model(**{**vars(fixed), "weights": weights.copy(), "energy": energy.copy()})
        for batch in pieces(batches, "text", SLICE):
            gradient_steps(*token_codes(batch.column("text")), local, how)
        gain = local.energy - energy
        for lo in range(0, len(gain), BLOCK):
            hit = np.flatnonzero(gain[lo : lo + BLOCK] > 0)
            if len(hit):
                parts = [hit.astype(np.int32), gain[lo + hit], (local.weights[lo + hit] - weights[lo + hit]).ravel()]
                yield pa.RecordBatch.from_arrays([pa.array([lo // BLOCK], pa.int32()), *(pa.array([x]) for x in parts)], names=[f.split()[0] for f in TOUCHED.split(", ")])

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for batch in batches:
            for k, block in enumerate(batch.column("block").to_pylist()):
                row, energy, weight = (batch.column(c)[k].values.to_numpy() for c in ("row", "energy", "weight"))
                e, root, w = sums.setdefault(block, (np.zeros(BLOCK), np.zeros(BLOCK), np.zeros((BLOCK, fanout))))
                e[row] += energy
                root[row] += np.sqrt(energy)
                w[row] += weight.reshape(-1, fanout) * energy[:, None].astype(float)
        for block, (e, root, w) in sums.items():
            hit = np.flatnonzero(e)
            longer = 1 + (root[hit] / np.sqrt(e[hit]) - 1) / (1 + e[hit] / how.settled)
            parts = [hit.astype(np.int32), e[hit].astype(np.float32), (w[hit] * (longer / e[hit])[:, None]).astype(np.float32).ravel()]
            yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), *(pa.array([x]) for x in parts)], names=[f.split()[0] for f in TOUCHED.split(", ")])

    out = docs.select("text").mapInArrow(run, TOUCHED).repartition("block").mapInArrow(total, TOUCHED).toArrow()  # one row a block, of weights of a bounded number
    for block, row, energy, weight in zip(*(out[c] for c in out.column_names), strict=True):
        at = block.as_py() * BLOCK + row.values.to_numpy()
        model.weights[at] += weight.values.to_numpy().reshape(-1, fanout)
        model.energy[at] += energy.values.to_numpy()


def place_bits(types: int, how: Maxent) -> int:
    """log2 of the number of shared places, or -1 where every word has a place of its own."""
    rare = types - how.frequent
    return -1 if rare <= 0 else min(max(rare // how.share, 1), how.most_places).bit_length() - 1


def weight_bits(tokens: int, how: Maxent) -> int:
    return min(max(int(tokens // how.tokens_per_weight).bit_length(), how.least_bits), how.most_bits)


def untrained(code: np.ndarray, c: np.ndarray, place_mass: np.ndarray, bits: int, tokens: int, types: int, how: Maxent) -> Model:
    """The unigram model: frequent words sorted by fingerprint, masses of the shared places, one unit for the unknown word."""
    mass = np.concatenate([c + 1.0, np.maximum(place_mass, 1e-3), [1.0]])
    rows = (1 << weight_bits(tokens, how)) // how.fanout
    parent, branch, prior = class_tree(mass, how.fanout)
    return Model(code, buckets(code), c, bits, place_mass, *paths(parent, branch, len(mass)), prior, np.zeros((rows, how.fanout), np.float32), np.zeros(rows, np.float32), tokens, types)


def train(docs: DataFrame, how: Maxent = Maxent()) -> tuple[Model, DataFrame]:
    """The model, and the counts of all training words. docs: column ``text``."""
    counts = materialize(word_counts(docs))
    tokens, types = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("code")).first()
    bits = place_bits(types, how)
    top = counts.orderBy(F.desc("c"), "code").limit(how.frequent).toArrow()  # a table of bounded size
    code, c = top["code"].to_numpy().view(np.uint64), top["c"].to_numpy()
    place_mass = np.zeros(1 << bits if bits >= 0 else 0)
    if bits >= 0:
        at = F.shiftrightunsigned(F.shiftrightunsigned("code", 1), 63 - bits)
        sums = counts.groupBy(at.alias("place")).agg(F.sum(F.col("c") + 1).alias("mass")).toArrow()  # most_places rows at most
        place_mass[sums["place"].to_numpy()] = sums["mass"].to_numpy()
        np.subtract.at(place_mass, ((code >> np.uint64(1)) >> np.uint64(63 - bits)).astype(np.int64), c + 1.0)
    order = np.argsort(code)
    model = untrained(code[order], c[order], place_mass, bits, tokens, types, how)
    if tokens:
        tasks = max(docs.sparkSession.sparkContext.defaultParallelism, tokens // how.tokens_per_task)
        for _ in range(how.rounds):
            one_round(docs.coalesce(int(tasks)), model, how)
    return model, counts


SCORED = "rid long, doc_id long, held_out boolean, n_tokens long, n_known long, known_log double, model_log double, rare array<long>, extra array<double>"


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """Per row: what the model says of its tokens, taking words without a place of their own for unknown; and for each of
    those its fingerprint, and what would be added to the score if it is known, less the log of its count plus one."""

    model = Model(**{**vars(model), "energy": np.empty(0, np.float32)})  # not needed here, so not sent

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        log_place = np.log(np.maximum(model.place_mass, 1e-3))
        for batch in pieces(batches, "text", SLICE):
            code, bounds = token_codes(batch.column("text"))
            context = contexts(code, bounds)
            leaf, own = leaf_of(code, model)
            rare = np.flatnonzero(~own)
            log_p = log_shares(context, np.where(own, leaf, model.leaves - 1), model)
            extra = np.zeros(len(rare))
            if model.place_bits >= 0:
                extra = log_shares(context[:, rare], leaf[rare], model) - log_place[leaf[rare] - len(model.code)] - log_p[rare]
            log_c = np.zeros(len(code))
            log_c[own] = np.log10(model.count[leaf[own]] + 1.0)
            total = lambda x: np.add.reduceat(x, bounds[:-1]) if len(bounds) > 1 else np.empty(0)
            cuts = np.concatenate([[0], np.cumsum(total((~own).astype(np.int64)))]).astype(np.int32)
            lists = [pa.ListArray.from_arrays(pa.array(cuts), pa.array(x)) for x in (wordhash.signed(code[rare]), extra / np.log(10))]
            columns = [np.diff(bounds), total(own.astype(np.int64)), total(log_c), total(log_p / np.log(10))]
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("rid", "doc_id", "held_out")] + [pa.array(c) for c in columns] + lists, names=[f.split()[0] for f in SCORED.split(", ")])

    return docs.mapInArrow(run, SCORED)


def language_model(docs: DataFrame, how: Maxent = Maxent(), doc_id: str = "doc_id", text: str = "text", out: Column | None = None) -> DataFrame:
    """Train on the rows that are not held out; score every row by the unigram base and by the model."""
    mark = held_out(7, 2, doc_id) if out is None else out
    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), mark.alias("held_out"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    model, counts = train(own.filter(~F.col("held_out")), how)
    part = materialize(scored(own.withColumn("rid", F.monotonically_increasing_id()), model))
    words = part.select("rid", F.explode(F.arrays_zip("rare", "extra")).alias("x")).select("rid", F.col("x.rare").alias("code"), F.col("x.extra").alias("extra"))
    log_c = F.log10(F.col("c") + 1)
    rare = words.join(counts, "code").groupBy(F.col("rid").alias("r")).agg(F.sum(log_c).alias("rare_log"), F.count("c").alias("rare_known"), F.sum(log_c + F.col("extra")).alias("gain"))
    both = part.drop("rare", "extra").join(rare, F.col("rid") == F.col("r"), "left")
    rare_log, gain = F.coalesce("rare_log", F.lit(0.0)), F.coalesce("gain", F.lit(0.0))
    return both.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("rare_known", F.lit(0))).alias("n_known"), F.lit(int(model.tokens)).cast("long").alias("train_tokens"),
        (F.col("known_log") + rare_log - F.col("n_tokens") * float(np.log10(model.tokens + model.types + 1))).alias("base_score"), (F.col("model_log") + gain).alias("score"),
    )
