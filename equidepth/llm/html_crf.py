"""Main text of web pages by a linear-chain conditional random field over leaf blocks.

A page is a chain of leaf blocks (html_blocks); each block is article or not. Features of a block are its
ancestors' tags, the words of their class, id and role, its tag, and the shape of its text (length,
links, punctuation, place). The chain's transitions differ by whether two neighbours share a parent. The
field is trained by maximum likelihood in numpy on generated labelled pages (html_pages) and decoded by
Viterbi; the blocks labelled article, in page order, are the text.

Scale: pages are read once, map-side, whole; nothing is shuffled. The model is a few thousand floats.

Nulls: a null or empty page has an empty text; a null id keeps its row. Pages of any length and nesting are decoded whole, one
at a time, in time and memory that follow their length. Ties between labellings go to "not article". Repeated rows each
get their text. Empty tables give empty results. extract() keeps the other columns of the input, whatever their names, but
replaces one named main_text.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .html_blocks import Block, Node, blocks_of
from .html_pages import PageMaker

FEATURES = 1 << 13


@dataclass(frozen=True)
class CrfSpec:
    """Labelled pages to generate, steps of training, weight of the squared penalty."""

    pages: int = 700
    steps: int = 160
    penalty: float = 2e-3
    seed: int = 3


def _at(name: str) -> int:
    return zlib.crc32(name.encode("utf-8", "surrogatepass")) % FEATURES


def own_features(node: Node) -> list[str]:
    """Of a block's last tag and those nearest above it."""
    above = node.parent.tag if node.parent is not None and node.parent.tag else ""
    return [f"leaf={node.tag}", f"above={above}>{node.tag}" if above else f"above={node.tag}", *(f"near={n}" for n in node.near), f"holder={node.holder}", f"holder={node.holder},leaf={node.tag}"]


def fresh_features(node: Node) -> list[str]:
    """Of the tag and words that come in with a node; a block has those of all nodes above it."""
    tags, names = node.fresh
    return [*(f"in={t}" for t in tags), *(f"name={n}" for n in names)]


def path_features(node: Node) -> list[str]:
    """Of a block's ancestors."""
    return [*own_features(node), *(f for n in node.up() for f in fresh_features(n))]


def _bucket(n: float, bounds: tuple) -> int:
    return sum(n >= b for b in bounds)


def text_features(block: Block, place: int, total: int) -> tuple[str, ...]:
    """Of a block's text and place."""
    t = block.text
    n = len(t)
    size = _bucket(n, (8, 20, 40, 80, 160, 320, 640))
    links = _bucket(block.link_chars / n, (0.01, 0.25, 0.6, 0.95))
    ends = t[-1] in ".!?…:\"'”»*%#$&"
    low = t[:200].lower()
    cue = "c" if "©" in low or "copyright" in low or "rights reserved" in low else "k" if "cookie" in low else "s" if low.startswith(("subscribe", "sign up", "search", "advert", "sponsor", "reply", "related", "most read")) else ""
    return (f"size={size}", f"links={links}", f"ends={ends},size={size}", f"cue={cue}", f"bar={'|' in t or '·' in t}", f"place={_bucket(place / total, (0.1, 0.5, 0.9))}", f"edge={'f' if place == 0 else 'l' if place == total - 1 else ''}")


def parent_of(node: Node) -> Node:
    return node.parent if node.tag in ("p", "h1", "h2", "h3", "h4", "li", "td", "pre", "figcaption", "blockquote") else node


@dataclass
class CrfModel:
    """weights: article over not, a float for each feature. moves[s]: scores from label to label; s: same parent."""

    weights: np.ndarray
    start: np.ndarray
    moves: np.ndarray

    def _height(self, node: Node, memo: dict) -> float:
        """The weight of what comes in with a node and with all above it."""
        missing = []
        for n in node.up():
            if (n,) in memo:
                break
            missing.append(n)
        for n in reversed(missing):
            own = fresh_features(n)
            memo[n,] = memo.get((n.parent,), 0.0) + (float(self.weights[[_at(f) for f in own]].sum()) if own else 0.0)
        return memo.get((node,), 0.0)

    def decode(self, blocks: list[Block], memo: dict) -> list[int]:
        """Viterbi. memo: what was found for paths and features so far."""
        n = len(blocks)
        if not n:
            return []
        w, moves = self.weights, self.moves.tolist()
        back, s0, s1, before = [], float(self.start[0]), float(self.start[1]), None
        for i, b in enumerate(blocks):
            lift = memo.get(b.path)
            if lift is None:
                lift = memo[b.path] = self._height(b.path, memo) + float(w[[_at(f) for f in own_features(b.path)]].sum())
            for f in text_features(b, i, n):
                x = memo.get(f)
                if x is None:
                    x = memo[f] = float(w[_at(f)])
                lift += x
            parent = parent_of(b.path)
            if i:
                m = moves[parent is before]
                a0, a1, b0, b1 = s0 + m[0][0], s1 + m[1][0], s0 + m[0][1], s1 + m[1][1]
                back.append((a1 > a0, b1 > b0))
                s0, s1 = max(a0, a1), max(b0, b1)
            s1 += lift
            before = parent
        label = int(s1 > s0)
        labels = [label]
        for step in reversed(back):
            label = int(step[label])
            labels.append(label)
        return labels[::-1]

    def text(self, html: str | None, memo: dict) -> str:
        if len(memo) > 100_000:  # the tree of paths goes with it
            memo.clear()
        blocks = blocks_of(html, memo.setdefault("tree", Node("", (), None)))
        return "\n".join(b.text for b, y in zip(blocks, self.decode(blocks, memo), strict=True) if y)


def labelled(spec: CrfSpec) -> list[tuple[list[Block], list[int]]]:
    """Generated pages as blocks with labels; pages whose blocks are not read as written are an error."""
    out = []
    for k in range(spec.pages):
        html, marks = PageMaker(spec.seed * 1_000_003 + k).page()
        blocks = blocks_of(html)
        if len(blocks) != len(marks):
            raise ValueError("a generated page is read otherwise than written")
        if blocks:
            out.append((blocks, [y for _, y in marks]))
    return out


@lru_cache(maxsize=4)
def train(spec: CrfSpec = CrfSpec()) -> CrfModel:
    """Maximum likelihood by Adam over all pages at once: pages are padded, forward and backward run over them together."""
    data = labelled(spec)
    P, T = len(data), max(len(b) for b, _ in data)
    real, gold, same = np.zeros((P, T), bool), np.zeros((P, T), int), np.zeros((P, T), int)
    entries, owners = [], []
    for p, (blocks, ys) in enumerate(data):
        for i, b in enumerate(blocks):
            found = {_at(f) for f in (*path_features(b.path), *text_features(b, i, len(blocks)))}
            entries += found
            owners += [p * T + i] * len(found)
            real[p, i], gold[p, i] = True, ys[i]
            same[p, i] = i > 0 and parent_of(b.path) is parent_of(blocks[i - 1].path)
    entry, owner = np.array(entries), np.array(owners)
    theta = np.zeros(FEATURES + 2 + 8)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    total = real.sum()
    for step in range(1, spec.steps + 1):
        w, start, moves = theta[:FEATURES], theta[FEATURES : FEATURES + 2], theta[FEATURES + 2 :].reshape(2, 2, 2)
        lift = np.bincount(owner, w[entry], P * T).reshape(P, T)
        emit = np.stack([np.zeros_like(lift), lift], axis=2)
        alpha, beta = np.zeros((P, T, 2)), np.zeros((P, T, 2))
        alpha[:, 0] = start + emit[:, 0]
        for t in range(1, T):
            nxt = np.logaddexp.reduce(alpha[:, t - 1, :, None] + moves[same[:, t]], axis=1) + emit[:, t]
            alpha[:, t] = np.where(real[:, t, None], nxt, alpha[:, t - 1])
        z = np.logaddexp.reduce(alpha[:, -1], axis=1)
        for t in range(T - 2, -1, -1):
            prv = np.logaddexp.reduce(moves[same[:, t + 1]] + (emit[:, t + 1] + beta[:, t + 1])[:, None, :], axis=2)
            beta[:, t] = np.where(real[:, t + 1, None], prv, beta[:, t + 1])
        mass = np.exp(alpha + beta - z[:, None, None]) * real[:, :, None]
        grad = np.zeros_like(theta)
        grad[:FEATURES] = np.bincount(entry, ((gold == 1) * real - mass[:, :, 1]).ravel()[owner], FEATURES)
        grad[FEATURES : FEATURES + 2] = np.bincount(gold[:, 0], minlength=2) - mass[:, 0].sum(axis=0)
        pair = np.exp(alpha[:, :-1, :, None] + moves[same[:, 1:]] + (emit[:, 1:] + beta[:, 1:])[:, :, None, :] - z[:, None, None, None]) * real[:, 1:, None, None]
        for s in (0, 1):
            on = (same[:, 1:] == s) & real[:, 1:]
            count = np.bincount((gold[:, :-1] * 2 + gold[:, 1:])[on], minlength=4)
            grad[FEATURES + 2 + 4 * s : FEATURES + 6 + 4 * s] = count - pair[on].sum(axis=0).ravel()
        grad = grad / total - spec.penalty * theta / 100
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta = theta + 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-9)
    return CrfModel(theta[:FEATURES].copy(), theta[FEATURES : FEATURES + 2].copy(), theta[FEATURES + 2 :].reshape(2, 2, 2).copy())


def _texts(batches: Iterator[pa.RecordBatch], model: CrfModel) -> Iterator[pa.RecordBatch]:
    memo: dict = {}
    for batch in batches:
        texts = [model.text(h.as_py(), memo) for h in batch.column(batch.num_columns - 1)]
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(texts, pa.string())], names=[*batch.schema.names[:-1], "main_text"])


def extract(pages: DataFrame, *, html: str = "html", spec: CrfSpec = CrfSpec()) -> DataFrame:
    """pages without the html, with main_text."""
    model = train(spec)
    rest = [c for c in pages.columns if c not in (html, "main_text")]
    schema = ", ".join([*(f"`{n}` {t}" for n, t in pages.select(*rest).dtypes), "main_text string"])
    return pages.select(*rest, html).mapInArrow(lambda it: _texts(it, model), schema)


def op3_query(spark, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    found = extract(pages)
    return found.select("page_id", "url", F.col("main_text").alias("text"), F.char_length("main_text").cast("long").alias("n_chars"))
