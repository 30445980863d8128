"""Operator 5: language by a byte convolutional network with multi-width filters, max pooling and a softmax.

The network is trained in numpy on a bounded, documented sample of labelled windows. Scoring covers every byte of every
text: texts are cut into fixed-length windows that overlap by the widest filter less one, so no filter position is
missed. A filter's response to a byte pair is a table look-up, so convolution is a few gathers for each byte. A
document's probabilities are the mean over its windows, each weighted by its bytes.

Defined results: a null text, or one with no letter, is ``und`` with score 0; with no labelled row at all every
document is ``und``; repeated rows are predicted alike; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from packsum.llm.runtime import held_out, pieces
from packsum.llm.wordhash import text_bytes

PREDICTIONS = "doc_id long, held_out boolean, lang_pred string, score double"
PAD = 0x20


@dataclass(frozen=True)
class Training:
    """Bounds of the fit: documents a language, windows a document, and the schedule."""

    documents_per_language: int = 600
    windows_per_document: int = 3
    window: int = 128
    dimensions: int = 8
    filters: int = 8
    widths: tuple[int, ...] = (2, 3, 4)
    steps: int = 700
    batch: int = 64
    rate: float = 0.01
    seed: int = 5


@dataclass
class Network:
    languages: list[str]
    window: int
    widths: tuple[int, ...]
    embedding: np.ndarray = None
    kernels: list[np.ndarray] = field(default_factory=list)  # (width, dimensions, filters)
    biases: list[np.ndarray] = field(default_factory=list)
    dense: np.ndarray = None
    dense_bias: np.ndarray = None


def labelled_windows(docs: DataFrame, how: Training, doc_id: str, text: str, lang: str, learn: Column) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """A bounded sample of training windows: of each language, the documents least by a seeded hash, so that reruns learn
    from the same. Counts by language set the rate of what is ranked, so no language is missed."""
    known = docs.filter(learn & F.col(lang).isNotNull() & F.col(text).isNotNull())
    counts = {r[0]: r[1] for r in known.groupBy(F.col(lang)).count().collect()}
    if not counts:
        return np.empty((0, how.window), np.uint8), np.empty(0, np.int64), []
    languages = sorted(counts)
    rate = F.create_map(*(x for k, n in counts.items() for x in (F.lit(k), F.lit(min(1.0, (2 * how.documents_per_language + 50) / n)))))
    spot = F.pmod(F.xxhash64(F.lit(how.seed), F.col(doc_id), F.col(text)), F.lit(1_000_000)) / 1_000_000
    least = Window.partitionBy(F.col(lang)).orderBy("_spot", F.col(doc_id), F.col(text))
    chosen = known.withColumn("_spot", spot).filter(F.col("_spot") < F.element_at(rate, F.col(lang)))
    chosen = chosen.withColumn("_place", F.row_number().over(least)).filter(F.col("_place") <= how.documents_per_language)
    span = how.window * 2
    cuts = [F.substring(F.col(text), (F.pmod(F.xxhash64(F.lit(k), F.col(text)), F.greatest(F.length(text) - how.window, F.lit(1))) + 1).cast("int"), F.lit(span)) for k in range(how.windows_per_document)]
    rows = chosen.select(F.col(lang).alias("lang"), F.array(*cuts).alias("cuts"), "_place").orderBy("lang", "_place").collect()  # at most documents_per_language rows a language
    x, y = [], []
    for r in rows:
        for cut in r["cuts"]:
            raw = cut.encode()[: how.window]
            if raw:
                x.append(np.frombuffer(raw.ljust(how.window, b" "), np.uint8))
                y.append(languages.index(r["lang"]))
    return np.array(x, np.uint8).reshape(-1, how.window), np.array(y, np.int64), languages


def train(x: np.ndarray, y: np.ndarray, languages: list[str], how: Training = Training()) -> Network:
    """Adam on the cross entropy; gradients pass the pooling only where a filter had its maximum."""
    rng = np.random.default_rng(how.seed)
    net = Network(languages, how.window, how.widths)
    net.embedding = rng.normal(0, 0.5, (256, how.dimensions)).astype(np.float32)
    for w in how.widths:
        net.kernels.append(rng.normal(0, (2 / (w * how.dimensions)) ** 0.5, (w, how.dimensions, how.filters)).astype(np.float32))
        net.biases.append(np.zeros(how.filters, np.float32))
    net.dense = rng.normal(0, 0.1, (how.filters * len(how.widths), len(languages))).astype(np.float32)
    net.dense_bias = np.zeros(len(languages), np.float32)
    if not len(x):
        return net
    share = np.bincount(y, minlength=len(languages)).astype(float)
    pick = (1 / share[y]) / (1 / share[y]).sum()
    parameters = [net.embedding, net.dense, net.dense_bias, *net.kernels, *net.biases]
    moments = [(np.zeros_like(p), np.zeros_like(p)) for p in parameters]
    for step in range(1, how.steps + 1):
        rows = rng.choice(len(x), how.batch, p=pick)
        grads = _gradients(net, x[rows], y[rows])
        rate = how.rate * min(1.0, 2 * (1 - step / (how.steps + 1)))
        for p, g, (m, v) in zip(parameters, grads, moments, strict=True):
            m *= 0.9
            m += 0.1 * g
            v *= 0.99
            v += 0.01 * g * g
            p -= (rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
    return net


def _gradients(net: Network, x: np.ndarray, y: np.ndarray) -> list[np.ndarray]:
    n, row = len(x), np.arange(len(x))[:, None]
    emb = net.embedding[x]
    tops, peaks = [], []
    for kernel, bias in zip(net.kernels, net.biases, strict=True):
        w = len(kernel)
        out = sum(emb[:, k : emb.shape[1] - w + 1 + k] @ kernel[k] for k in range(w)) + bias
        at = out.argmax(axis=1)
        peaks.append(at)
        tops.append(np.maximum(np.take_along_axis(out, at[:, None], 1)[:, 0], 0))
    hidden = np.concatenate(tops, axis=1)
    p = softmax(hidden @ net.dense + net.dense_bias)
    p[np.arange(n), y] -= 1
    p /= n
    g_dense, g_bias = hidden.T @ p, p.sum(axis=0)
    back = (p @ net.dense.T) * (hidden > 0)
    g_emb, g_kernels, g_biases = np.zeros_like(net.embedding), [], []
    f = net.kernels[0].shape[2]
    for i, kernel in enumerate(net.kernels):
        b = back[:, i * f : (i + 1) * f]
        g_k = np.zeros_like(kernel)
        for k in range(len(kernel)):
            seen = x[row, peaks[i] + k]
            g_k[k] = np.einsum("nfd,nf->df", net.embedding[seen], b)
            np.add.at(g_emb, seen, b[:, :, None] * kernel[k].T[None])
        g_kernels.append(g_k)
        g_biases.append(b.sum(axis=0))
    return [g_emb, g_dense, g_bias, *g_kernels, *g_biases]


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


class Scorer:
    """The network with its filters as tables over byte pairs."""

    def __init__(self, net: Network, window: int = 256):
        self.net, self.window, self.widest = net, window, max(net.widths)
        self.pairs: list[list[tuple[int, np.ndarray]]] = []
        for kernel in net.kernels:
            single = [net.embedding @ k for k in kernel]
            own = []
            for k in range(0, len(kernel) - 1, 2):
                own.append((k, (single[k][:, None, :] + single[k + 1][None, :, :]).reshape(65536, -1)))
            if len(kernel) % 2:
                own.append((len(kernel) - 1, single[-1]))
            self.pairs.append(own)

    def windows(self, windows: np.ndarray) -> np.ndarray:
        """Probabilities of rows of bytes."""
        wide = windows.astype(np.int32)
        pair = (wide[:, :-1] << 8) | wide[:, 1:]
        tops = []
        for kernel, bias, own in zip(self.net.kernels, self.net.biases, self.pairs, strict=True):
            n = windows.shape[1] - len(kernel) + 1
            out = None
            for k, table in own:
                got = table.take((pair if len(table) == 65536 else wide)[:, k : k + n], axis=0)
                out = got if out is None else np.add(out, got, out=out)
            tops.append(np.maximum(out.max(axis=1) + bias, 0))
        return softmax(np.concatenate(tops, axis=1) @ self.net.dense + self.net.dense_bias)

    def texts(self, column: pa.Array) -> np.ndarray:
        """Mean probabilities of each text over windows that cover all of it."""
        data, bounds = text_bytes(column)
        size = np.diff(bounds)
        stride = self.window - self.widest + 1
        count = np.maximum(1, -(-(size - self.widest + 1) // stride))
        row = np.repeat(np.arange(len(size)), count)
        first = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
        start = bounds[:-1][row] + first * stride
        length = np.clip(bounds[1:][row] - start, 0, self.window)
        padded = np.concatenate([data, np.full(self.window, PAD, np.uint8)])
        total = np.zeros((len(size), len(self.net.languages)))
        for lo in range(0, len(row), 1024):
            s, n = start[lo : lo + 1024], length[lo : lo + 1024]
            block = padded[s[:, None] + np.arange(self.window)]
            block[np.arange(self.window) >= n[:, None]] = PAD
            np.add.at(total, row[lo : lo + 1024], self.windows(block) * (n / np.maximum(size[row[lo : lo + 1024]], 1))[:, None])
        return total / np.maximum(total.sum(axis=1, keepdims=True), 1e-12)


def predict(docs: DataFrame, net: Network, doc_id: str = "doc_id", text: str = "text", mark: Column | None = None) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(net)
        for batch in pieces(batches, "text", 2_000_000):
            texts = batch.column("text")
            letters = pc.fill_null(pc.match_substring_regex(texts, r"\p{L}"), False).to_numpy(zero_copy_only=False)
            if net.languages:
                p = scorer.texts(texts)
                best = p.argmax(axis=1)
                names = np.array(net.languages, object)[best]
                score = p[np.arange(len(p)), best]
            else:
                names, score, letters = np.full(len(texts), "und", object), np.zeros(len(texts)), np.zeros(len(texts), bool)
            names = np.where(letters, names, "und")
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(names, pa.string()), pa.array(np.where(letters, np.clip(score, 0, 1), 0.0))], names=["doc_id", "held_out", "lang_pred", "score"])

    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), (F.lit(False) if mark is None else mark).alias("held_out"), F.col(text).alias("text"))
    return own.mapInArrow(run, PREDICTIONS)


def identify(docs: DataFrame, how: Training = Training(), doc_id: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """Train on rows whose crc32 leaves no remainder 1 of 3, then predict every row."""
    out = held_out(3, 1, doc_id)
    net = train(*labelled_windows(docs, how, doc_id, text, lang, ~out), how)
    return predict(docs, net, doc_id, text, out)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(spark.read.parquet(f"{sf_dir}/documents.parquet"))
