"""Operator 1: toxicity by weak supervision.

Voters are lexicon words and word-beginning patterns, found by counts over labelled training rows, beside a few style
patterns. A generative label model estimates each voter's accuracy by expectation maximisation, and the correlation of voters given the hidden label; correlated voters share their evidence. A linear
classifier over term features then learns from the posterior labels of the model, and scores every text.

The fit uses a bounded sample of labelled rows (``Training.documents``); scoring covers every whole text. Defined
results: a null or empty text gets the score of a document without any known term; with no training labels the seed
lexicon alone votes; repeated rows score alike; documents without a label are scored too; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from packsum.llm.runtime import held_out, pieces

SCORES = "doc_id long, held_out boolean, score double, predicted int"
# Common English insults, voters also where no labels exist.
SEED_LEXICON = ("idiot", "moron", "stupid", "loser", "scum", "trash", "pathetic", "worthless", "disgusting", "clown")
EDGES = ".,!?;:|\"'()[]{}*#$%&<>-_«»¡¿"
PREFIXES = (4, 5, 6)


@dataclass(frozen=True)
class Training:
    """Bounds of the fit."""

    documents: int = 16_000
    most_features: int = 4_000
    least_documents: int = 4
    voter_precision: float = 0.9
    most_voters: int = 300
    seed: int = 3
    threshold: float = 0.3


@dataclass
class Model:
    terms: list[str]
    weights: np.ndarray
    bias: float
    prior: float
    accuracies: np.ndarray
    correlations: np.ndarray


def bag(texts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Distinct lower-case words of a batch, the index of each word in turn, and its document."""
    lists = pc.ascii_split_whitespace(pc.fill_null(texts, ""))
    doc = np.repeat(np.arange(len(texts)), pc.list_value_length(lists).to_numpy())
    coded = pc.dictionary_encode(lists.flatten())
    words = pc.utf8_trim(pc.utf8_lower(coded.dictionary), characters=EDGES)
    return words, coded.indices.to_numpy(), doc


def term_columns(words: pa.Array) -> list[pa.Array]:
    """The features of each distinct word: itself, and its first characters as a pattern."""
    size = pc.utf8_length(words)
    out = [pc.if_else(pc.greater_equal(size, 3), pc.binary_join_element_wise("=", words, ""), pa.scalar(None, pa.string()))]
    for n in PREFIXES:
        out.append(pc.if_else(pc.greater_equal(size, n), pc.binary_join_element_wise("^", pc.utf8_slice_codeunits(words, 0, n), ""), pa.scalar(None, pa.string())))
    return out


def features(texts: pa.Array, terms: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(document, term) pairs that occur, each once; texts are looked at whole."""
    words, index, doc = bag(texts)
    pairs = []
    for column in term_columns(words):
        found = pc.fill_null(pc.index_in(column, value_set=terms), -1).to_numpy(zero_copy_only=False)
        at = found[index]
        hit = at >= 0
        pairs.append(doc[hit].astype(np.int64) * len(terms) + at[hit])
    flat = np.unique(np.concatenate(pairs))
    return flat // max(len(terms), 1), flat % max(len(terms), 1)


def term_counts(sample: DataFrame) -> DataFrame:
    """Labelled documents, and toxic ones among them, that hold each term."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, "text"):
            words, index, doc = bag(batch.column("text"))
            toxic = batch.column("toxic").to_numpy(zero_copy_only=False).astype(np.int64)
            for column in term_columns(words):
                coded = pc.dictionary_encode(column)
                code = pc.fill_null(coded.indices, -1).to_numpy(zero_copy_only=False)[index]
                ok = code >= 0
                flat = np.unique(code[ok].astype(np.int64) * batch.num_rows + doc[ok])
                term, d = flat // batch.num_rows, flat % batch.num_rows
                n = np.bincount(term, minlength=len(coded.dictionary))
                t = np.bincount(term, weights=toxic[d], minlength=len(coded.dictionary)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([coded.dictionary, pa.array(n), pa.array(t)], names=["term", "n", "t"])

    return sample.mapInArrow(run, "term string, n long, t long").groupBy("term").agg(F.sum("n").alias("n"), F.sum("t").alias("t"))


def term_matrix(sample: DataFrame, terms: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, term) pairs of the bounded sample, and its labels."""
    names = pa.array(terms, pa.string())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, "text"):
            d, t = features(batch.column("text"), names)
            cuts = np.searchsorted(d, np.arange(batch.num_rows + 1)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("toxic").cast(pa.int32()), pa.ListArray.from_arrays(pa.array(cuts), pa.array(t.astype(np.int32)))], names=["toxic", "terms"])

    got = sample.select("text", "toxic").mapInArrow(run, "toxic int, terms array<int>").toArrow()
    if not got.num_rows:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    lists = got["terms"].combine_chunks()
    return np.repeat(np.arange(got.num_rows), pc.list_value_length(lists).to_numpy()), lists.flatten().to_numpy().astype(np.int64), got["toxic"].to_numpy().astype(float)


def label_model(votes: np.ndarray, prior: float, rounds: int = 25) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Posterior of the hidden label, accuracy of each voter, and correlations of voters given the label.

    A voter says toxic or abstains; silence is no evidence, since lexicons of different languages rarely meet in one
    document. Each vote moves the log odds from the prior to the voter's accuracy, which is assumed no worse than a
    coin's. A voter that is correlated with others given the label counts for the inverse of one plus its
    correlations, so that several faces of one fact count once. Documents on which all abstain share the part of the
    prior that the votes leave.
    """
    n, v = votes.shape
    logit = lambda p: np.log(p / (1 - p))
    accuracy, corr, share = np.full(v, 0.85), np.zeros((v, v)), votes / 1.0
    spoken, fired = votes.any(axis=1), votes.sum(axis=0)
    post = np.full(n, prior)
    for k in range(rounds):
        z = logit(prior) + share @ (logit(accuracy) - logit(prior))
        post = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        rest = (prior * n - post[spoken].sum()) / max(1, n - spoken.sum())
        post[~spoken] = np.clip(rest, 0.001, prior)
        accuracy = np.clip((post @ votes + 1.7) / (fired + 2.0), 0.5, 0.995)
        if k % 8 == 4:
            toxic_rate, clean_rate = (post @ votes) / post.sum(), ((1 - post) @ votes) / (1 - post).sum()
            centred = votes - (post[:, None] * toxic_rate + (1 - post)[:, None] * clean_rate)
            cov = centred.T @ centred / max(n, 1)
            sd = np.sqrt(np.maximum(np.diag(cov), 1e-9))
            corr = np.clip(cov / sd[:, None] / sd[None, :], -1, 1)
            strong = np.where(corr > 0.25, corr, 0.0)
            np.fill_diagonal(strong, 0.0)
            share = votes / (1 + votes @ strong)
    return post, accuracy, corr


def fit_linear(row: np.ndarray, term: np.ndarray, y: np.ndarray, size: int, steps: int = 400) -> tuple[np.ndarray, float]:
    """Logistic regression on soft labels: full-batch Adam on sparse pairs, with a light ridge."""
    w, b = np.zeros(size), float(np.log((y.mean() + 1e-4) / (1 - y.mean() + 1e-4)))
    m, v = np.zeros(size + 1), np.zeros(size + 1)
    n = len(y)
    for step in range(1, steps + 1):
        z = np.bincount(row, weights=w[term], minlength=n) + b
        d = (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y) / n
        g = np.append(np.bincount(term, weights=d[row], minlength=size) + 2e-5 * w, d.sum())
        m = 0.9 * m + 0.1 * g
        v = 0.99 * v + 0.01 * g * g
        move = 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        w -= move[:-1]
        b -= move[-1]
    return w, b


def wilson(hits: int, n: int, z: float = 1.0) -> float:
    """Lower confidence bound of a share."""
    p = hits / n
    return (p + z * z / (2 * n) - z * ((p * (1 - p) + z * z / (4 * n)) / n) ** 0.5) / (1 + z * z / n)


def train(docs: DataFrame, labels: DataFrame, how: Training = Training(), doc_id: str = "doc_id", text: str = "text") -> Model:
    """Labels of held-out rows are never read."""
    known = labels.select(F.col("doc_id").alias("_id"), F.col("toxic").cast("int").alias("toxic")).filter(F.col("toxic").isNotNull() & ~held_out(4, 2, "_id"))
    total = known.count()
    rate = min(1.0, how.documents / max(total, 1))
    known = known.filter(F.pmod(F.xxhash64(F.lit(how.seed), "_id"), F.lit(1_000_000)) < int(rate * 1_000_000)).dropDuplicates(["_id"])
    sample = docs.select(F.col(doc_id).alias("_d"), F.coalesce(F.col(text), F.lit("")).alias("text")).join(known, F.col("_d") == F.col("_id")).select("text", "toxic")
    sample = sample.persist()
    seeds = ["=" + w for w in SEED_LEXICON]
    n_docs = sample.count()
    if not n_docs:
        weights = np.full(len(seeds), 4.0)
        return Model(seeds, weights, -4.0, 0.02, np.full(len(seeds), 0.9), np.eye(len(seeds)))
    prior = float(np.clip(sample.agg(F.avg("toxic")).first()[0], 0.002, 0.5))
    smooth = (F.col("t") + 0.5 * prior) / (F.col("n") + 0.5)
    odds = (F.col("t") + 0.5 * prior) / (F.col("n") - F.col("t") + 0.5 * (1 - prior))
    told = term_counts(sample).filter((F.col("n") >= how.least_documents) & (F.col("t") >= 2) & (odds > 3 * prior / (1 - prior)))
    rows = told.select("term", "n", "t", smooth.alias("p")).orderBy(F.desc(F.col("t") * F.col("p")), "term").limit(how.most_features).collect()
    terms = list(dict.fromkeys([r["term"] for r in rows] + seeds))
    row, term, gold = term_matrix(sample, terms)
    sample.unpersist()
    del gold  # the classifier learns from the label model alone
    strong = {r["term"] for r in rows if wilson(r["t"], r["n"]) >= how.voter_precision} | set(seeds)
    voters = [i for i, t in enumerate(terms) if t in strong][: how.most_voters]
    at = np.full(len(terms), -1)
    at[voters] = np.arange(len(voters))
    votes = np.zeros((n_docs, len(voters)), np.float32)
    hit = at[term] >= 0
    votes[row[hit], at[term[hit]]] = 1
    post, accuracy, corr = label_model(votes, prior)
    weights, bias = fit_linear(row, term, post, len(terms))
    return Model(terms, weights, bias, prior, accuracy, corr)


def score(docs: DataFrame, model: Model, threshold: float = 0.3, doc_id: str = "doc_id", text: str = "text", mark: Column | None = None) -> DataFrame:
    keep = np.abs(model.weights) > 0.02
    names, weights, bias = [t for t, k in zip(model.terms, keep, strict=True) if k], model.weights[keep], model.bias

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        terms = pa.array(names, pa.string())
        for batch in pieces(batches, "text", 12_000_000):
            d, t = features(batch.column("text"), terms)
            z = bias + np.bincount(d, weights=weights[t], minlength=batch.num_rows)
            p = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(p), pa.array((p >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), (F.lit(False) if mark is None else mark).alias("held_out"), F.col(text).alias("text"))
    return own.mapInArrow(run, SCORES)


def toxicity(docs: DataFrame, labels: DataFrame, how: Training = Training(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    return score(docs, train(docs, labels, how, doc_id, text), how.threshold, doc_id, text, held_out(4, 2, doc_id))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def keep_clean(docs: DataFrame, labels: DataFrame, how: Training = Training()) -> DataFrame:
    """Rows of ``docs``, with their columns, that are not predicted toxic."""
    model = train(docs, labels, how)
    keep = np.abs(model.weights) > 0.02
    names, weights, bias, threshold = [t for t, k in zip(model.terms, keep, strict=True) if k], model.weights[keep], model.bias, how.threshold

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        terms = pa.array(names, pa.string())
        for batch in pieces(batches, "text", 12_000_000):
            d, t = features(batch.column("text"), terms)
            z = bias + np.bincount(d, weights=weights[t], minlength=batch.num_rows)
            yield batch.filter(pa.array(1 / (1 + np.exp(-np.clip(z, -40, 40))) < threshold))

    return docs.mapInArrow(run, docs.schema)
