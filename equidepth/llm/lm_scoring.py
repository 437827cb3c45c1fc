"""Masked pseudo-likelihood: every token predicted from both sides, log-probabilities summed.

The network: a window of `side` tokens on each side of the masked one; each offset has an embedding
table of its own whose vectors add up, with a bias, to a hidden layer under tanh; the output is a
two-level softmax (class, then unit within its class), so a prediction costs two short softmaxes and the
probabilities over the units still sum to one. A text's score is the sum of log P(token | window)
over all its tokens; a text's edges are a unit of their own.

Vocabulary: all lower-case tokens of the whole corpus. The `words` most frequent ones are units. Every other token has a
slot (by its last letters and its hash; the number of slots grows with the distinct tokens up to `slots`), and a slot's mean
count per token over the corpus puts it in a band; band and last letters make its unit. Its probability is the unit's
times its slot's mean count over the unit's total count: its share in the unit, so probabilities over all tokens of the
corpus sum to one. Where more tokens than slots exist, tokens of a slot share its mean. A token that the corpus
lacks (scoring other texts) counts as half a token in an empty slot. Classes are runs of the frequency order of about equal mass.

Training covers the corpus: every position of every text is a target in one of the rounds (a position's round
is its place in its text modulo `rounds`). Encoded texts are dealt to shards by a hash of key and tokens, about
`shard_tokens` to a shard, and lie in a shard in the order of that hash, so what is learned depends on the rows alone and not on
how the table is partitioned. Each round every shard starts from the shared parameters, runs mini-batch Adagrad
over its positions in numpy, and returns its parameters cut in blocks; blocks are averaged over shards, weighed by
positions, in whole numbers (so their order does not matter) after a shuffle by block. What a task or the driver
receives does not grow with the corpus, but for the table of slots up to its bound; what is gathered in all does.

Nulls: null and empty texts have no tokens, score 0 and mean null; a null key hashes like any value. Very long texts are one
row of two bytes a token, learned from and scored in pieces. Ties in frequency go by the token. Repeated rows each
get their score and lie in one shard. Columns of the input other than key and text are not read; a key column may have any
name but n_tokens, log_likelihood and mean_log_prob. An empty table gives an empty result. A corpus without tokens
scores with the untrained network.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import chunks_by_length, materialize, text_or_empty

CHARS = 400_000
POSITIONS = 16_384  # scored at once


@dataclass(frozen=True)
class LmSpec:
    """Vocabulary, network and training sizes."""

    words: int = 3967
    bands: int = 8
    kinds: int = 16
    slots: int = 1 << 22
    classes: int = 64
    side: int = 2
    hidden: int = 16
    rounds: int = 4
    batch: int = 16_384
    rate: float = 0.2
    shard_tokens: int = 2_000_000
    blocks: int = 64
    seed: int = 11

    @property
    def size(self) -> int:
        """Units: the words, those of the other tokens, and the edge."""
        return self.words + self.bands * self.kinds + 1

    @property
    def offsets(self) -> list[int]:
        return [d for d in range(-self.side, self.side + 1) if d]


class Codes(dict):
    """A token's code: a word's id, or `words` plus its slot; emptied beyond `most` tokens."""

    def __init__(self, ids: dict[str, int], spec: LmSpec, slots: int, most: int = 300_000):
        super().__init__()
        self.ids, self.words, self.kinds, self.each, self.most = ids, spec.words, spec.kinds, slots // spec.kinds, most

    def __missing__(self, token: str) -> int:
        if len(self) >= self.most:
            self.clear()
        code = self.ids.get(token)
        if code is None:
            kind = zlib.crc32(token[-2:].encode()) % self.kinds
            code = self.words + kind * self.each + zlib.crc32(token.encode()) % self.each
        self[token] = code
        return code


@dataclass
class Vocabulary:
    """Word ids by frequency; mean count per token of each slot; counts of all units; first unit of each class, class of each unit."""

    ids: dict[str, int]
    means: np.ndarray
    mass: np.ndarray
    start: np.ndarray
    spec: LmSpec

    def __post_init__(self):
        s = self.spec
        self.of = (np.searchsorted(self.start, np.arange(s.size), side="right") - 1).astype(np.uint8 if s.classes <= 256 else np.uint16)
        self.memo = Codes(self.ids, s, len(self.means))
        self.unit = unit_of(self.means, s).astype(np.uint16)
        self.share = (np.log(np.maximum(self.means, 0.5)) - np.log(np.maximum(self.mass, 1.0))[self.unit]).astype(np.float32)

    def units(self) -> "Vocabulary":
        """What the network needs: no words and no slots."""
        return Vocabulary({}, np.zeros(self.spec.kinds, np.float32), self.mass, self.start, self.spec)

    def encode(self, text: str) -> tuple[np.ndarray, float]:
        """(units, sum of the log shares of its tokens in their units)."""
        tokens = text.lower().split()
        codes = np.fromiter(map(self.memo.__getitem__, tokens), np.int64, len(tokens))
        rare = codes >= self.spec.words
        slots = codes[rare] - self.spec.words
        codes[rare] = self.unit[slots]
        return codes.astype(np.uint16), float(self.share[slots].sum())


def unit_of(means: np.ndarray, spec: LmSpec) -> np.ndarray:
    """The unit of each slot: its band (doublings of its mean count) and the kind its place stands for."""
    band = np.clip(np.rint(np.log2(np.maximum(means, 1.0))), 0, spec.bands - 1).astype(np.int64)
    kind = np.arange(len(means)) // max(1, len(means) // spec.kinds)
    return spec.words + band * spec.kinds + np.minimum(kind, spec.kinds - 1)


def make_vocabulary(counts: list[tuple[str, int]], slots: np.ndarray, totals: np.ndarray, tokens: np.ndarray, size: int, spec: LmSpec) -> Vocabulary:
    """counts: the most frequent tokens, falling; of each filled slot its count and its number of tokens; size: number of slots."""
    ids = {w: i for i, (w, _) in enumerate(counts[: spec.words])}
    means = np.zeros(size)
    means[slots] = totals / np.maximum(tokens, 1)
    mass = np.zeros(spec.size)
    mass[: len(ids)] = [n for _, n in counts[: spec.words]]
    np.add.at(mass, unit_of(means, spec)[slots], totals)
    root = np.sqrt(mass + 1e-9)
    level = np.cumsum(root) / root.sum()
    cuts = [0]
    for c in range(1, spec.classes):
        cuts.append(max(cuts[-1] + 1, int(np.searchsorted(level, c / spec.classes))))
    cuts = np.minimum(np.array(cuts), spec.size - spec.classes + np.arange(spec.classes))
    return Vocabulary(ids, means.astype(np.float32), mass, cuts, spec)


def _exp(logits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(exponentials, in place; their sums by row). Logits are sums of a few bounded terms; 60 bounds what a float32 can hold."""
    np.exp(np.minimum(logits, 60, out=logits), out=logits)
    return logits, logits @ np.ones(logits.shape[1], logits.dtype)


class Network:
    """Parameters in one flat float32 array: offset tables, hidden bias, class weights and bias, unit weights and bias.

    Untrained, it gives every unit its share in the corpus (plus one) whatever stands around it.
    """

    def __init__(self, vocabulary: Vocabulary, flat: np.ndarray | None = None):
        s = self.spec = vocabulary.spec
        self.v = vocabulary
        shapes = {"tables": (len(s.offsets), s.size, s.hidden), "bias": (s.hidden,), "cls": (s.hidden, s.classes), "cls_b": (s.classes,), "tok": (s.size, s.hidden), "tok_b": (s.size,)}
        total = sum(int(np.prod(x)) for x in shapes.values())
        fresh = flat is None
        if fresh:
            flat = np.random.default_rng(s.seed).normal(0, 0.1, total).astype(np.float32)
        self.flat, at = flat, 0
        for name, shape in shapes.items():
            n = int(np.prod(shape))
            setattr(self, name, flat[at : at + n].reshape(shape))
            at += n
        if fresh:
            mass = vocabulary.mass + 1.0
            by_class = np.add.reduceat(mass, vocabulary.start)
            self.cls_b[:] = np.log(by_class / by_class.sum())
            self.tok_b[:] = np.log(mass / by_class[vocabulary.of])

    def hidden_of(self, context: np.ndarray) -> np.ndarray:
        """(n, offsets) ids to (n, hidden)."""
        ids = context.T.astype(np.intp)
        h = self.tables[0].take(ids[0], axis=0)
        for k in range(1, len(ids)):
            h += self.tables[k].take(ids[k], axis=0)
        h += self.bias
        return np.tanh(h, out=h)

    def _by_class(self, target: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[tuple[int, int, slice]]]:
        """(order of the rows by class, their classes in it, (first unit, unit after the last, rows in it) of each class that any target is of)."""
        cls = self.v.of[target]
        order = np.argsort(cls, kind="stable")
        cls = cls[order]
        bounds = np.searchsorted(cls, np.arange(self.spec.classes + 1))
        ends = np.append(self.v.start[1:], self.spec.size)
        return order, cls, [(int(self.v.start[c]), int(ends[c]), slice(int(bounds[c]), int(bounds[c + 1]))) for c in np.flatnonzero(np.diff(bounds)).tolist()]

    def log_prob(self, context: np.ndarray, target: np.ndarray) -> np.ndarray:
        """log P(unit | context), one for each row."""
        order, cls, parts = self._by_class(target)
        h, target, every = self.hidden_of(context[order]), target[order], np.arange(len(target))
        z = h @ self.cls
        z += self.cls_b
        got = z[every, cls]
        got -= np.log(_exp(z)[1])
        for low, high, rows in parts:
            y = h[rows] @ self.tok[low:high].T
            y += self.tok_b[low:high]
            got[rows] += y[every[: len(y)], target[rows] - low]
            got[rows] -= np.log(_exp(y)[1])
        out = np.empty_like(got)
        out[order] = got
        return out

    def learn(self, context: np.ndarray, target: np.ndarray, seen: "Network") -> None:
        """One Adagrad step on a batch; seen: sums of squared gradients, shaped like the parameters."""
        order, cls, parts = self._by_class(target)
        context, target, every, n = context[order], target[order], np.arange(len(target)), np.float32(len(target))
        h = self.hidden_of(context)
        p = h @ self.cls
        p += self.cls_b
        p, total = _exp(p)
        p /= total[:, None]
        p[every, cls] -= 1
        g_h = p @ self.cls.T
        steps = [("cls", slice(None), h.T @ p), ("cls_b", slice(None), p.sum(axis=0))]
        for low, high, rows in parts:
            w, x = self.tok[low:high], h[rows]
            q = x @ w.T
            q += self.tok_b[low:high]
            q, total = _exp(q)
            q /= total[:, None]
            q[every[: len(q)], target[rows] - low] -= 1
            g_h[rows] += q @ w
            steps += [("tok", slice(low, high), q.T @ x), ("tok_b", slice(low, high), q.sum(axis=0))]
        h *= h
        np.subtract(1, h, out=h)
        g_h *= h
        steps.append(("bias", slice(None), g_h.sum(axis=0)))
        for name, at, g in steps:
            self._step(getattr(self, name), getattr(seen, name), at, g / n)
        for k in range(context.shape[1]):
            ids = context[:, k]
            order = np.argsort(ids, kind="stable")
            ids = ids[order]
            first = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
            self._step(self.tables[k], seen.tables[k], ids[first], np.add.reduceat(g_h.take(order, axis=0), first, axis=0) / n)

    def _step(self, values: np.ndarray, seen: np.ndarray, at, g: np.ndarray) -> None:
        total = seen[at] + g * g
        seen[at] = total
        values[at] -= np.float32(self.spec.rate) * g / np.sqrt(total)


def windows(texts: list[np.ndarray], spec: LmSpec) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(context, target, text) of every token of encoded texts."""
    edge = spec.size - 1
    sizes = np.array([len(t) for t in texts], np.int64)
    flat = np.full(int(sizes.sum()) + spec.side * (len(texts) + 1), edge, np.uint16)
    owner = np.repeat(np.arange(len(texts)), sizes)
    at = np.arange(len(owner)) + spec.side * (owner + 1)
    if not len(at):
        return np.zeros((0, len(spec.offsets)), np.uint16), np.zeros(0, np.uint16), owner
    flat[at] = np.concatenate(texts)
    return np.stack([flat[at + d] for d in spec.offsets], axis=1), flat[at], owner


def pieces_of(text: np.ndarray, spec: LmSpec, size: int = POSITIONS) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
    """(context, target, place of the first) of a text's positions, `size` at a time."""
    edge = np.full(spec.side, spec.size - 1, np.uint16)
    for start in range(0, len(text), size):
        own = np.arange(start, min(start + size, len(text)))
        low, high = max(0, start - spec.side), own[-1] + 1 + spec.side
        around = np.concatenate([edge[: spec.side - (start - low)], text[low:high], edge[: max(0, high - len(text))]])
        yield np.stack([around[own - start + spec.side + d] for d in spec.offsets], axis=1), text[own], start


def _groups(texts: list[np.ndarray], spec: LmSpec) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(context, target, text, place in the text) of all positions, about POSITIONS at a time."""
    for start, end in chunks_by_length([len(t) for t in texts], POSITIONS):
        if end - start == 1 and len(texts[start]) > POSITIONS:
            for context, target, first in pieces_of(texts[start], spec):
                yield context, target, np.full(len(target), start), first + np.arange(len(target))
            continue
        context, target, owner = windows(texts[start:end], spec)
        if len(target):
            yield context, target, owner + start, np.arange(len(target)) - np.searchsorted(owner, owner)


def _ids(column) -> list[np.ndarray]:
    return [np.frombuffer(x.as_buffer(), np.uint16) if x.as_buffer() is not None and x.as_buffer().size else np.zeros(0, np.uint16) for x in column]


def _encoded(batches: Iterator[pa.RecordBatch], vocabulary: Vocabulary) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, sizes, shares = [], [], []
        for text in batch.column(batch.num_columns - 1):
            units, share = vocabulary.encode(text.as_py())
            ids.append(units.tobytes())
            sizes.append(len(units))
            shares.append(share)
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(sizes, pa.int64()), pa.array(shares, pa.float64()), pa.array(ids, pa.binary())], names=[*batch.schema.names[:-1], "n_tokens", "_share", "_ids"])


def _trained(batches: Iterator[pa.RecordBatch], flat: np.ndarray, vocabulary: Vocabulary, turn: int) -> Iterator[pa.RecordBatch]:
    """The parameters after a shard's positions of one round, in blocks, with how many positions those were."""
    spec = vocabulary.spec
    net, seen, count = Network(vocabulary, flat.copy()), Network(vocabulary, np.full(flat.shape, 1e-8, np.float32)), 0
    rng = np.random.default_rng(spec.seed + turn)
    pool_c, pool_t, held = [], [], 0

    def learn():
        nonlocal pool_c, pool_t, held
        context, target = np.concatenate(pool_c), np.concatenate(pool_t)
        order = rng.permutation(len(target))
        for rows in np.array_split(order, -(-len(order) // spec.batch)):
            net.learn(context[rows], target[rows], seen)
        pool_c, pool_t, held = [], [], 0

    for batch in batches:
        for context, target, _, place in _groups(_ids(batch.column(0)), spec):
            take = place % spec.rounds == turn
            pool_c.append(context[take])
            pool_t.append(target[take])
            held += int(take.sum())
            count += int(take.sum())
            if held >= 32 * spec.batch:
                learn()
    if held:
        learn()
    if count:
        parts = [p.tobytes() for p in np.array_split(net.flat, spec.blocks)]
        yield pa.RecordBatch.from_arrays([pa.array(range(spec.blocks), pa.int32()), pa.array([count] * spec.blocks, pa.int64()), pa.array(parts, pa.binary())], names=["block", "n", "part"])


def _averaged(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The mean of a block's parts; sums of whole numbers (24 bits after the point, weights in thousands of positions)."""
    total, weight, block = None, 0, key[0].as_py()
    for batch in batches:
        for n, part in zip(batch.column("n").to_pylist(), batch.column("part").to_pylist(), strict=True):
            w = max(1, n // 1000)
            x = np.rint(np.frombuffer(part, np.float32).astype(np.float64) * (1 << 24)).astype(np.int64) * w
            total, weight = x if total is None else total + x, weight + w
    yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([(total / weight / (1 << 24)).astype(np.float32).tobytes()], pa.binary())], names=["block", "part"])


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Token counts of a partition, sent on whenever they fill the table."""
    counts: Counter[str] = Counter()

    def flush() -> pa.RecordBatch:
        out = pa.RecordBatch.from_arrays([pa.array(counts.keys(), pa.string()), pa.array(counts.values(), pa.int64())], names=["token", "n"])
        counts.clear()
        return out

    for batch in batches:
        for text in batch.column(0):
            counts.update(text.as_py().lower().split())
            if len(counts) > 300_000:
                yield flush()
    yield flush()


def corpus_vocabulary(docs: DataFrame, spec: LmSpec, text: str = "text") -> tuple[Vocabulary, int]:
    """(vocabulary, number of tokens): all tokens are counted; the most frequent ones and the table of slots come to the driver."""
    spark = docs.sparkSession
    partial = docs.select(text_or_empty(text).alias("body")).mapInArrow(_counted, "token string, n bigint")
    counts = materialize(partial.groupBy("token").agg(F.sum("n").alias("n")), "lm-counts")
    total, distinct = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    top = [(r[0], r[1]) for r in counts.orderBy(F.desc("n"), "token").limit(spec.words).collect()]
    size = min(spec.slots, max(1 << 10, 1 << distinct.bit_length()))
    each = size // spec.kinds
    named = F.broadcast(spark.createDataFrame([(w,) for w, _ in top], "token string"))  # at most `words` rows
    rest = counts.join(named, "token", "left_anti")
    code = F.encode("token", "UTF-8")
    place = F.crc32(F.encode(F.right("token", F.lit(2)), "UTF-8")) % spec.kinds * each + F.crc32(code) % each
    table = rest.groupBy(place.cast("int").alias("slot")).agg(F.sum("n").alias("n"), F.count("*").cast("int").alias("tokens")).toArrow()  # at most `slots` rows
    slots, totals, tokens = (table.column(c).to_numpy() for c in ("slot", "n", "tokens"))
    return make_vocabulary(top, slots, totals.astype(np.float64), tokens, size, spec), total


def encoded(docs: DataFrame, vocabulary: Vocabulary, *, keys: tuple[str, ...] = (), text: str = "text") -> DataFrame:
    """(*keys, n_tokens, _share, _ids) of every row."""
    slim = docs.select(*keys, text_or_empty(text).alias("_body"))
    schema = ", ".join([*(f"`{n}` {t}" for n, t in slim.select(*keys).dtypes), "n_tokens bigint", "_share double", "_ids binary"])
    return slim.mapInArrow(lambda it: _encoded(it, vocabulary), schema)


def fit(docs: DataFrame, spec: LmSpec = LmSpec(), *, keys: tuple[str, ...] = ("doc_id",), text: str = "text") -> tuple[Network, DataFrame]:
    """(the network trained on all of docs, docs encoded: what score() takes)."""
    vocabulary, total = corpus_vocabulary(docs, spec, text)
    net = Network(vocabulary)
    shards = max(1, -(-total // spec.shard_tokens))
    rows = encoded(docs, vocabulary, keys=keys, text=text).withColumn("_place", F.xxhash64(*keys, "_ids"))
    dealt = rows.repartitionById(shards, F.pmod("_place", F.lit(shards)).cast("int")).sortWithinPartitions("_place")
    dealt = dealt.checkpoint()  # one partition for each shard, read again in each round
    bodies = dealt.select("_ids")
    units = vocabulary.units()
    for r in range(spec.rounds):
        flat = net.flat
        parts = bodies.mapInArrow(lambda it, flat=flat, turn=r: _trained(it, flat, units, turn), "block int, n bigint, part binary")
        mean = parts.groupBy("block").applyInArrow(_averaged, "block int, part binary").collect()
        if mean:
            net = Network(vocabulary, np.concatenate([np.frombuffer(p, np.float32) for _, p in sorted((m[0], bytes(m[1])) for m in mean)]))
    return net, dealt.drop("_place")


def _scores(batches: Iterator[pa.RecordBatch], flat: np.ndarray, vocabulary: Vocabulary) -> Iterator[pa.RecordBatch]:
    net = Network(vocabulary, flat)
    for batch in batches:
        total = batch.column(batch.num_columns - 2).to_numpy(zero_copy_only=False).astype(np.float64)
        for context, target, owner, _ in _groups(_ids(batch.column(batch.num_columns - 1)), vocabulary.spec):
            total = total + np.bincount(owner, net.log_prob(context, target), len(total))
        yield pa.RecordBatch.from_arrays([*batch.columns[:-2], pa.array(total, pa.float64())], names=[*batch.schema.names[:-2], "log_likelihood"])


def score(rows: DataFrame, net: Network) -> DataFrame:
    """(*keys, n_tokens, log_likelihood, mean_log_prob) of every row of encoded texts."""
    flat, vocabulary = net.flat, net.v.units()
    schema = ", ".join([*(f"`{n}` {t}" for n, t in rows.drop("_share", "_ids").dtypes), "log_likelihood double"])
    found = rows.mapInArrow(lambda it: _scores(it, flat, vocabulary), schema)
    return found.withColumn("mean_log_prob", F.when(F.col("n_tokens") > 0, F.col("log_likelihood") / F.col("n_tokens")))


def op2_query(spark, sf_dir: str) -> DataFrame:
    """The pseudo-likelihood of every document under a network trained on all of them."""
    net, rows = fit(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return score(rows, net)
