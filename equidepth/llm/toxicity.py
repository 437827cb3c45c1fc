"""Toxicity by subword-bag embeddings under a linear softmax.

A word's vector is the mean of the vectors of its character n-grams (with word ends marked) and of the
word itself, all hashed into one table; a passage's vector is the mean of its words' vectors; a linear
softmax over two classes scores it. Table and softmax are trained jointly by gradient descent in
numpy, so an unseen misspelling is scored through the n-grams it shares with words seen. A text's score
is that of its highest run of `passage` words, at whatever word it starts (a text of fewer words is one passage), so a
few words in a long text are not averaged away; training looks at each text's highest passage too. Two numbers
fitted on the training texts turn that height into a probability.

Because both the mean and the softmax are linear, a word adds one number to its passage's height:
scoring ships one float for each gram that tells the classes apart and remembers words' numbers.

Training reads at most `rows` labelled texts of at most `chars` characters together (a bounded, documented sample,
chosen by a hash of doc_id), never those held out; scoring reads every whole text. Labels, language, source and
doc_id are no inputs.

Nulls: a null text is scored like an empty one (by the bias alone); null labels are no labels; a
null doc_id hashes like an empty string. Very long texts are scored whole, one at a time; a very long token gives its grams one by one
and is not remembered. Ties: of equally high passages the first counts; a doc_id labelled twice has its greater label, and of two texts of a
labelled doc_id the lesser is learned from. Repeated rows each get their score. clean_documents renames the input's columns while it
works, so none can clash; score_texts returns the keys asked for. Empty tables give empty results. Without any label, or with one
class only, every score is the share of toxic labels (0 without any).
"""

from __future__ import annotations

import itertools
import zlib
from array import array
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import text_or_empty

EDGES = ".,;:!?\"'()[]{}<>«»“”‘’…|-–—*_#$%&~"


@dataclass(frozen=True)
class ToxicSpec:
    """Sizes of the model and of its training; rows and chars bound the labelled texts it reads."""

    rows: int = 6000
    chars: int = 30_000_000
    least: int = 3
    most: int = 8
    buckets: int = 1 << 18
    dim: int = 8
    passage: int = 64
    epochs: int = 6
    batch: int = 64
    rate: float = 0.02
    penalty: float = 1e-5
    gain: float = 64.0
    z: float = 4.0
    min_docs: int = 5
    seed: int = 7
    threshold: float = 0.3


def grams(word: str, spec: ToxicSpec) -> Iterator[str]:
    """A word itself, and its n-grams between word ends, one by one."""
    marked = f"<{word}>"
    end = len(marked) + 1
    yield "=" + word
    for n in range(spec.least, spec.most + 1):
        for i in range(end - n):
            yield marked[i : i + n]


def gram_count(word: str, spec: ToxicSpec) -> int:
    """How many grams() gives."""
    return 1 + sum(max(0, len(word) + 3 - n) for n in range(spec.least, spec.most + 1))


def entry_of(gram: str, spec: ToxicSpec) -> int:
    """The table entry of a gram."""
    return zlib.crc32(gram.encode("utf-8", "surrogatepass")) % spec.buckets


def bare(token: str) -> str:
    return token.strip(EDGES) or token


@dataclass
class ToxicModel:
    """The grams whose vectors are not 0, each with its vector times the softmax's difference; bias; the two fitted numbers."""

    spec: ToxicSpec
    heights: dict[str, float]
    bias: float
    slope: float
    offset: float

    def word_height(self, token: str) -> float:
        word = bare(token)
        return sum(map(self.heights.get, grams(word, self.spec), itertools.repeat(0.0))) / gram_count(word, self.spec)

    def scores(self, texts: Iterable[str], memo: "WordHeights") -> np.ndarray:
        top = np.array([top_passage(np.fromiter(map(memo.__getitem__, w), np.float64, len(w)), self.spec.passage)[0] for w in (t.lower().split() for t in texts)])
        z = np.clip(self.slope * (top + self.bias) + self.offset, -40, 40)
        return 1.0 / (1.0 + np.exp(-z))


class WordHeights(dict):
    """Remembered word heights, in two generations of `most` words; longer tokens are not remembered."""

    def __init__(self, model: ToxicModel, most: int = 150_000, longest: int = 64):
        super().__init__()
        self.model, self.most, self.longest, self.old = model, most, longest, {}

    def __missing__(self, token: str) -> float:
        if len(token) > self.longest:
            return self.model.word_height(token)
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        value = self.old.get(token)
        self[token] = value = self.model.word_height(token) if value is None else value
        return value


def top_passage(heights: np.ndarray, length: int) -> tuple[float, int]:
    """(mean, start) of the highest run of `length` words; fewer words are one run."""
    n = len(heights)
    if n == 0:
        return 0.0, 0
    if n <= length:
        return float(heights.mean()), 0
    sums = np.concatenate([[0.0], np.cumsum(heights)])
    runs = sums[length:] - sums[:-length]
    best = int(runs.argmax())
    return float(runs[best] / length), best


def telling_entries(docs: list[np.ndarray], y: np.ndarray, flat: np.ndarray, first: np.ndarray, sizes: np.ndarray, spec: ToxicSpec) -> np.ndarray:
    """Table entries that differ between the classes in the share of texts that hold them, by `z` standard errors."""
    holders = np.zeros((2, spec.buckets))
    for d, label in zip(docs, y, strict=True):
        w = np.unique(d)
        if len(w):
            holders[int(label), np.unique(flat[_runs(first[w], sizes[w])])] += 1
    n = np.array([max(1.0, float((y == c).sum())) for c in (0, 1)])
    share = holders.sum(axis=0) / n.sum()
    spread = np.sqrt(share * (1 - share) * (1 / n).sum()) + 1e-12
    return (np.abs(holders[1] / n[1] - holders[0] / n[0]) >= spec.z * spread) & (holders.sum(axis=0) >= spec.min_docs)


def _runs(first: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """first[0], first[0] + 1, ... (sizes[0] of them), first[1], ..."""
    return np.repeat(first - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())


def train(texts: list[str], labels: list[int], spec: ToxicSpec = ToxicSpec()) -> ToxicModel:
    """Adam over mini-batches of the texts' highest passages; the first round takes whole texts.

    Entries that do not tell the classes apart (telling_entries) keep the vector 0.
    """
    y = np.asarray(labels, np.int64)
    share = float(y.mean()) if len(y) else 0.0
    if len(set(labels)) < 2:
        z = np.log(max(share, 1e-9) / max(1 - share, 1e-9))
        return ToxicModel(spec, {}, 0.0, 0.0, float(z))
    vocabulary: dict[str, int] = {}
    docs = [np.array([vocabulary.setdefault(bare(w), len(vocabulary)) for w in t.lower().split()], np.int32) for t in texts]
    entries, counts = array("i"), array("i")
    for w in vocabulary:
        entries.extend(entry_of(g, spec) for g in grams(w, spec))
        counts.append(gram_count(w, spec))
    total = np.array(counts or [1], np.int64)  # a word's mean is over all its entries, zero vectors too
    flat = np.array(entries or [0], np.int32)
    first = np.concatenate([[0], np.cumsum(total)[:-1]])
    del entries, counts
    active = telling_entries(docs, y, flat, first, total, spec)
    keep = active[flat]
    sizes = np.add.reduceat(keep.astype(np.int64), first)
    flat = (np.cumsum(active) - 1).astype(np.int32)[flat[keep]]
    del keep
    first = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    n = int(active.sum())
    rng = np.random.default_rng(spec.seed)
    size = n * spec.dim
    theta = np.concatenate([rng.normal(0, 0.1, size), rng.normal(0, 0.3, spec.dim * 2), [0.0, np.log(share / (1 - share))]])
    m, v, step = np.zeros_like(theta), np.zeros_like(theta), 0

    def heights_of_words() -> np.ndarray:
        soft = theta[size : size + 2 * spec.dim].reshape(spec.dim, 2)
        entry = spec.gain * (theta[:size].reshape(n, spec.dim) @ (soft[:, 1] - soft[:, 0]))
        return np.bincount(np.repeat(np.arange(len(sizes)), sizes), entry[flat], len(sizes)) / total if n else np.zeros(len(sizes))

    bags = docs
    for epoch in range(spec.epochs):
        if epoch:
            high = heights_of_words()
            bags = [d[(s := top_passage(high[d], spec.passage)[1]) : s + spec.passage + spec.passage // 2] for d in docs]
        for at in np.array_split(rng.permutation(len(docs)), max(1, len(docs) // spec.batch)):
            table, soft, b = theta[:size].reshape(n, spec.dim), theta[size : size + 2 * spec.dim].reshape(spec.dim, 2), theta[-2:]
            lens = np.array([len(bags[i]) for i in at])
            words = np.concatenate([bags[i] for i in at])
            count = sizes[words]
            entry = flat[_runs(first[words], count)] if count.sum() else np.zeros(0, np.int64)
            owner = np.repeat(np.repeat(np.arange(len(at)), lens), count)
            weight = np.repeat(spec.gain / (total[words] * np.repeat(np.maximum(lens, 1), lens)), count)
            cell = owner * n + entry
            used, place = np.unique(cell, return_inverse=True)
            amount = np.bincount(place, weight, len(used))
            who, what = used // max(n, 1), used % max(n, 1)
            vector = np.zeros((len(at), spec.dim))
            np.add.at(vector, who, table[what] * amount[:, None])
            logit = vector @ soft + b
            p = np.exp(logit - logit.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            p[np.arange(len(at)), y[at]] -= 1.0
            p /= len(at)
            grad = spec.penalty * theta
            grad[-2:] = p.sum(axis=0)
            grad[size : size + 2 * spec.dim] += (vector.T @ p).ravel()
            np.add.at(grad[:size].reshape(n, spec.dim), what, (p @ soft.T)[who] * amount[:, None])
            step += 1
            m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
            theta = theta - spec.rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    high = heights_of_words()
    soft = theta[size : size + 2 * spec.dim].reshape(spec.dim, 2)
    by_entry = np.zeros(spec.buckets)
    by_entry[active] = spec.gain * (theta[:size].reshape(n, spec.dim) @ (soft[:, 1] - soft[:, 0]))
    heights = {g: float(by_entry[e]) for w, k in zip(vocabulary, sizes, strict=False) if k for g in grams(w, spec) if active[e := entry_of(g, spec)]}
    bias = float(theta[-1] - theta[-2])
    tops = np.array([top_passage(high[d], spec.passage)[0] if len(d) else 0.0 for d in docs]) + bias
    slope, offset = fit_line(tops, y.astype(np.float64))
    return ToxicModel(spec, heights, bias, slope, offset)


def fit_line(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Logistic regression on one number by Newton steps, lightly held towards 0."""
    scale = float(np.abs(x).mean()) or 1.0
    z = np.stack([x / scale, np.ones_like(x)], axis=1)
    beta = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(z @ beta, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + 1e-2 * np.eye(2), z.T @ (p - y) + 1e-2 * beta)
        beta -= np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-6:
            break
    return float(max(beta[0], 0.0) / scale), float(beta[1])


def held_out(key: Column) -> Column:
    """Rows whose crc32 of the id as text leaves 2 modulo 4."""
    return F.pmod(F.crc32(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), F.lit(4)) == 2


def labelled_texts(docs: DataFrame, labels: DataFrame, rows: int, chars: int) -> tuple[list[str], list[int]]:
    """At most `rows` labelled texts of at most `chars` characters together, outside the held-out rows, chosen and ordered by a hash of doc_id."""
    marks = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    chosen = marks.withColumn("_h", F.xxhash64("doc_id")).orderBy("_h", "doc_id").limit(rows)
    met = docs.select("doc_id", text_or_empty("text").alias("text")).join(F.broadcast(chosen), "doc_id")
    sizes = sorted(tuple(r) for r in met.groupBy("_h", "doc_id").agg(F.max(F.char_length("text")).alias("n")).collect())  # at most `rows`
    total, last = 0, len(sizes)
    for i, (_, _, n) in enumerate(sizes):
        total += n
        if total > chars:
            last = i
            break
    if last == 0:
        return [], []
    if last < len(sizes):
        met = met.filter((F.col("_h") < sizes[last][0]) | (F.col("_h") == sizes[last][0]) & (F.col("doc_id") < sizes[last][1]))
    got = met.groupBy("doc_id", "_h", "toxic").agg(F.min("text").alias("text")).select("_h", "doc_id", "text", "toxic").collect()
    got.sort(key=lambda r: (r[0], r[1]))
    return [r[2] for r in got], [int(r[3] > 0) for r in got]


def _scored(batches: Iterator[pa.RecordBatch], model: ToxicModel) -> Iterator[pa.RecordBatch]:
    memo = WordHeights(model)
    for batch in batches:
        scores = model.scores((x.as_py() for x in batch.column(batch.num_columns - 1)), memo)
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(scores, pa.float64())], names=[*batch.schema.names[:-1], "score"])


def score_texts(docs: DataFrame, model: ToxicModel, *, keys: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """(*keys, score) of every row."""
    slim = docs.select(*keys, text_or_empty(text).alias("_body"))
    schema = ", ".join(f"`{n}` {t}" for n, t in slim.select(*keys).dtypes) + ", score double"
    return slim.mapInArrow(lambda it: _scored(it, model), schema)


def fit(docs: DataFrame, labels: DataFrame, spec: ToxicSpec = ToxicSpec()) -> ToxicModel:
    return train(*labelled_texts(docs, labels, spec.rows, spec.chars), spec)


def clean_documents(docs: DataFrame, labels: DataFrame, spec: ToxicSpec = ToxicSpec()) -> DataFrame:
    """docs without those scored at the threshold or above."""
    model = fit(docs, labels, spec)
    named = docs.toDF(*[f"c{i}" for i in range(len(docs.columns))])  # no clash with the score's name
    body = f"c{docs.columns.index('text')}"
    kept = score_texts(named, model, keys=tuple(named.columns), text=body).filter(F.col("score") < spec.threshold).drop("score")
    return kept.toDF(*docs.columns)


def op10_query(spark, sf_dir: str) -> DataFrame:
    """The toxicity score of every document."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    spec = ToxicSpec()
    scored = score_texts(docs, fit(docs, labels, spec), keys=("doc_id",))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= spec.threshold).cast("int").alias("predicted"))
