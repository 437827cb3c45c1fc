"""A hierarchy of linear models that estimates P(X <= x), monotone by construction.

The root picks a leaf, the leaf's line estimates the quantile, and each leaf is held inside its own band of
the sample's distribution. Root and leaves rise with x and bands follow each other without overlap, so
the estimate never falls as x rises, whatever the sample was.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


#: Codes beyond this in size tie; squares of differences stay finite.
FAR = 1e150
#: Most leaves below a tree of comparisons; more are found by halving an array, so generated code stays small and is not compiled anew for each model.
TREE = 8


def _literal(values: np.ndarray) -> Column:
    """A constant array of doubles; the optimizer folds it to one literal."""
    return F.split(F.lit(",".join(repr(float(v)) for v in values)), ",").cast("array<double>")


def _line(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[float, float, float]:
    """(slope, centre, intercept) of a weighted least-squares line; never falling."""
    total = w.sum()
    x0 = float(x[0])
    dx = x - x0
    with np.errstate(over="ignore", invalid="ignore"):
        mx, my = float((w * dx).sum() / total), float((w * y).sum() / total)
        var = float((w * (dx - mx) ** 2).sum())
        cov = float((w * (dx - mx) * (y - my)).sum())
        slope = cov / var if var > 0 and np.isfinite(var) and np.isfinite(cov) else 0.0
    if not np.isfinite(slope) or slope < 0 or not np.isfinite(mx):
        slope, mx = 0.0, 0.0
    return slope, x0, my - slope * mx


@dataclass(frozen=True)
class CdfModel:
    """root: "linear", "quantile" or "recursive". Leaf arrays hold slope, centre, intercept, band and sample size."""

    root: str
    slope: np.ndarray
    centre: np.ndarray
    intercept: np.ndarray
    low: np.ndarray
    high: np.ndarray
    count: np.ndarray
    top: tuple[float, float, float] = (0.0, 0.0, 0.0)
    borders: np.ndarray | None = None
    middle: np.ndarray | None = None  # of the recursive root: slope, centre, intercept, first and last leaf by row
    clamp: bool = True
    heaviest: float = 0.0  # share of the sample's most frequent code

    @property
    def leaves(self) -> int:
        return len(self.slope)

    @property
    def bytes(self) -> int:
        parts = [self.slope, self.centre, self.intercept, self.low, self.high, self.borders, self.middle]
        return sum(p.nbytes for p in parts if p is not None)

    # ---- on numpy arrays -------------------------------------------------------------------------

    def leaf_np(self, x: np.ndarray) -> np.ndarray:
        x = np.clip(np.asarray(x, np.float64), -FAR, FAR)
        if self.root == "quantile":
            return np.searchsorted(self.borders, x, side="right")
        a, c, b = self.top
        guess = a * (x - c) + b
        if self.root == "linear":
            return np.clip(np.floor(guess * self.leaves), 0, self.leaves - 1).astype(np.int64)
        k = self.middle.shape[1]
        mid = np.clip(np.floor(guess * k), 0, k - 1).astype(np.int64)
        s, m, i, first, last = self.middle[:, mid]
        return np.clip(np.floor((s * (x - m) + i) * self.leaves), first, last).astype(np.int64)

    def cdf_np(self, x: np.ndarray) -> np.ndarray:
        x = np.clip(np.asarray(x, np.float64), -FAR, FAR)
        j = self.leaf_np(x)
        y = self.slope[j] * (x - self.centre[j]) + self.intercept[j]
        if self.clamp:
            y = np.clip(y, self.low[j], self.high[j])
        return np.clip(y, 0.0, 1.0)

    def pid_np(self, x: np.ndarray, f: int) -> np.ndarray:
        return np.minimum(f - 1, np.floor(self.cdf_np(x) * f)).astype(np.int64)

    # ---- as expressions ---------------------------------------------------------------------------

    def leaf(self, x: Column) -> Column:
        def clip(v: Column, low, high) -> Column:
            return F.least(F.greatest(v, low), high)

        if self.root == "quantile":
            return _tree(x, self.borders) if self.leaves <= TREE else _search(x, self.borders)
        a, c, b = self.top
        guess = F.lit(a) * (x - F.lit(c)) + F.lit(b)
        n = F.lit(float(self.leaves))
        if self.root == "linear":
            return clip(F.floor(guess * n).cast("double"), F.lit(0.0), n - 1).cast("int")
        k = self.middle.shape[1]
        mid = clip(F.floor(guess * k).cast("double"), F.lit(0.0), F.lit(float(k - 1))).cast("int") + 1
        s, m, i, first, last = (F.element_at(_literal(row), mid) for row in self.middle)
        return clip(F.floor((s * (x - m) + i) * n).cast("double"), first, last).cast("int")

    def cdf(self, x: Column) -> Column:
        """Estimated quantile of a code column; null stays null."""
        x = x.cast("double")
        if self.root == "quantile" and self.leaves <= TREE:  # each end of the tree is its leaf's line: x is the only shared part
            return F.when(x.isNotNull(), _tree(x, self.borders, self._leaf_line))
        at = self.leaf(x) + 1
        y = F.element_at(_literal(self.slope), at) * (x - F.element_at(_literal(self.centre), at)) + F.element_at(_literal(self.intercept), at)
        if self.clamp:
            y = F.greatest(F.element_at(_literal(self.low), at), F.least(F.element_at(_literal(self.high), at), y))
        return F.when(x.isNotNull(), F.greatest(F.lit(0.0), F.least(F.lit(1.0), y)))

    def _leaf_line(self, x: Column, j: int) -> Column:
        y = F.lit(float(self.slope[j])) * (x - F.lit(float(self.centre[j]))) + F.lit(float(self.intercept[j]))
        if self.clamp:
            y = F.greatest(F.lit(float(self.low[j])), F.least(F.lit(float(self.high[j])), y))
        return F.greatest(F.lit(0.0), F.least(F.lit(1.0), y))

    def pid(self, x: Column, f: int) -> Column:
        """Slice of a code column, 0 to f - 1; null stays null."""
        return F.when(x.isNotNull(), F.least(F.lit(f - 1), F.floor(self.cdf(x) * f).cast("int")))

    def slice_start(self, p: int, f: int) -> float:
        """The least code whose slice is p or later; infinity where there is none. Slices rise with codes, so halving finds it."""
        low, high = _rank(-FAR), _rank(FAR)
        if self.pid_np(np.array([FAR]), f)[0] < p:
            return float("inf")
        while low < high:
            mid = (low + high) // 2
            if self.pid_np(np.array([_unrank(mid)]), f)[0] >= p:
                high = mid
            else:
                low = mid + 1
        x = _unrank(low)
        return float("-inf") if x <= -FAR else x

    def position(self, x: Column, rows: int) -> Column:
        """Estimated 0-based rank among `rows` rows: the model as an order-preserving hash."""
        return F.floor(self.cdf(x) * F.lit(float(max(rows - 1, 0)))).cast("long")

    def to_df(self, spark: SparkSession) -> DataFrame:
        """The leaves as a table."""
        rows = [(j, *(float(a[j]) for a in (self.slope, self.intercept, self.low, self.high, self.centre)), int(self.count[j])) for j in range(self.leaves)]
        return spark.createDataFrame(rows, "leaf int, slope double, intercept double, lo double, hi double, centre double, n long")


def _rank(x: float) -> int:
    """Doubles as integers of the same order."""
    raw = int(np.array([x], np.float64).view(np.int64)[0])
    return raw if raw >= 0 else -(raw & 0x7FFFFFFFFFFFFFFF)


def _unrank(k: int) -> float:
    raw = k if k >= 0 else -k - (1 << 63)
    return float(np.array([raw], np.int64).view(np.float64)[0])


def _tree(x: Column, borders: np.ndarray, end=None) -> Column:
    """A balanced tree of comparisons, generated code without a loop: the number of borders at or below x, or end(x, it)."""

    def below(low: int, high: int) -> Column:
        if low == high:
            return end(x, low) if end else F.lit(low)
        mid = (low + high) // 2
        return F.when(x < F.lit(float(borders[mid])), below(low, mid)).otherwise(below(mid + 1, high))

    return below(0, len(borders))


def _search(x: Column, borders: np.ndarray) -> Column:
    """The number of borders at or below x, by halving a constant array."""
    array = _literal(borders)
    steps = F.array(*[F.lit(1 << s) for s in reversed(range(len(borders).bit_length()))])
    return F.aggregate(steps, F.lit(0), lambda at, h: at + F.when(F.coalesce(F.get(array, at + h - 1) <= x, F.lit(False)), h).otherwise(0))


def train_cdf(sample: np.ndarray, leaves: int = 64, root: str = "linear", *, middle: int = 8, clamp: bool = True) -> CdfModel:
    """Fit the hierarchy on a sample of codes.

    root "linear": a least-squares line over the whole sample; "quantile": borders at the sample's quantiles, so
    leaves get equal parts of it whatever the skew; "recursive": a layer of `middle` lines between.
    clamp=False leaves out the bands (and with them the guarantee).
    """
    sample = np.asarray(sample, np.float64)
    sample = np.clip(sample[~np.isnan(sample)], -FAR, FAR)
    if not len(sample):
        zero = np.zeros(1)
        return CdfModel("linear", zero, zero, zero, zero, zero, np.zeros(1, np.int64))
    x, n = np.unique(sample, return_counts=True)
    y = np.cumsum(n) / n.sum()
    w = n.astype(np.float64)
    top, borders, mids = _line(x, y, w), None, None
    if root == "quantile":
        picks = x[np.searchsorted(y, np.arange(1, leaves) / leaves, side="left").clip(0, len(x) - 1)]
        borders = np.unique(picks)
        leaves = len(borders) + 1
    elif root == "recursive":
        guess = top[0] * (x - top[1]) + top[2]
        of = np.clip(np.floor(guess * middle), 0, middle - 1).astype(int)
        mids, floor = np.zeros((5, middle)), 0
        for k in range(middle):
            own = of == k
            if own.any():
                mids[:3, k] = _line(x[own], y[own], w[own])
                last = int(np.clip(np.floor(y[own][-1] * leaves), floor, leaves - 1))
            else:
                mids[:3, k] = (0.0, 0.0, floor / leaves)
                last = floor
            mids[3:, k] = (floor, last)
            floor = last
    elif root != "linear":
        raise ValueError(f"no root {root}")
    model = CdfModel(root, *(np.zeros(leaves) for _ in range(5)), np.zeros(leaves, np.int64), top, borders, mids, clamp, float(n.max() / n.sum()))
    of = model.leaf_np(x)
    bounds = np.searchsorted(of, np.arange(leaves + 1))
    reached = 0.0
    for j in range(leaves):
        a, b = bounds[j], bounds[j + 1]
        model.low[j] = reached
        if b > a:
            model.slope[j], model.centre[j], model.intercept[j] = _line(x[a:b], y[a:b], w[a:b])
            reached = float(y[b - 1])
            model.count[j] = int(n[a:b].sum())
        else:
            model.intercept[j] = reached
        model.high[j] = reached
    return model


def train_cdf_sql(sample: DataFrame, leaves: int = 64) -> DataFrame:
    """The linear-root fit in SQL: (leaf, n, slope, intercept, lo, hi) of the leaves that the sample reaches.

    sample: one column `code`. cume_dist comes from counts by value, summed inside slices and over the slices before them, so no window
    runs over all codes.
    """
    from .extsort import PID, model_sort

    counts = sample.groupBy("code").agg(F.count("*").alias("n"))
    sliced = model_sort(counts, ["code"])
    sums = sorted((r[0], r[1]) for r in sliced.sliced.groupBy(PID).agg(F.sum("n")).collect())  # a row for each slice
    least, total, starts = counts.agg(F.min("code")).first()[0], 0, []
    for p, n in sums:
        starts.append((p, total))
        total += n
    starts = F.broadcast(counts.sparkSession.createDataFrame(starts, f"{PID} int, _before long"))  # a row for each slice
    inside = F.sum("n").over(sliced.window().rowsBetween(Window.unboundedPreceding, Window.currentRow))
    targets = sliced.exchanged.withColumn("_in", inside).join(starts, PID).select("code", "n", ((F.col("_before") + F.col("_in")) / F.lit(float(max(total, 1)))).alias("y"))
    w = F.col("n").cast("double")
    moved = targets.withColumn("x", F.col("code") - F.lit(least))
    sums = moved.agg(F.sum(w).alias("w"), F.sum(w * F.col("x")).alias("wx"), F.sum(w * F.col("y")).alias("wy"), F.sum(w * F.col("x") * F.col("x")).alias("wxx"), F.sum(w * F.col("x") * F.col("y")).alias("wxy"))
    a = (F.col("w") * F.col("wxy") - F.col("wx") * F.col("wy")) / (F.col("w") * F.col("wxx") - F.col("wx") * F.col("wx"))
    root = sums.select(a.alias("a"), ((F.col("wy") - a * F.col("wx")) / F.col("w")).alias("b"))
    leaf = F.greatest(F.lit(0), F.least(F.lit(leaves - 1), F.floor((F.col("a") * F.col("x") + F.col("b")) * leaves)))
    placed = moved.crossJoin(F.broadcast(root)).withColumn("leaf", leaf.cast("int"))  # one row
    v = F.col("n").cast("double")
    fitted = placed.groupBy("leaf").agg(
        F.sum("n").alias("n"), F.sum(v * F.col("x")).alias("wx"), F.sum(v * F.col("y")).alias("wy"), F.sum(v * F.col("x") * F.col("x")).alias("wxx"),
        F.sum(v * F.col("x") * F.col("y")).alias("wxy"), F.count("*").alias("k"), F.max("y").alias("hi"),
    )
    m = F.col("n").cast("double")
    slope = F.when(F.col("k") > 1, (m * F.col("wxy") - F.col("wx") * F.col("wy")) / (m * F.col("wxx") - F.col("wx") * F.col("wx"))).otherwise(F.lit(0.0))
    fitted = fitted.withColumn("slope", F.greatest(slope, F.lit(0.0))).withColumn("intercept", (F.col("wy") - F.col("slope") * F.col("wx")) / m)
    return fitted.withColumn("lo", F.coalesce(F.lag("hi").over(Window.orderBy("leaf")), F.lit(0.0))).select("leaf", "n", "slope", "intercept", "lo", "hi")


@dataclass(frozen=True)
class RefinedModel:
    """A model on codes, and below each code that is heavier than a slice a model on its keys' next bytes.

    A heavy code's band of the distribution is cut by the finer model, which may be refined in turn.
    """

    base: CdfModel
    finer: dict[float, tuple[float, float, "CdfModel | RefinedModel"]]

    @property
    def bytes(self) -> int:
        return self.base.bytes + sum(m.bytes for _, _, m in self.finer.values())

    @property
    def depth(self) -> int:
        """Levels of codes that it looks at."""
        return 1 + max(m.depth if isinstance(m, RefinedModel) else 1 for _, _, m in self.finer.values())

    @property
    def heaviest(self) -> float:
        return self.base.heaviest

    def cdf(self, *codes: Column) -> Column:
        """codes: of the first bytes, of the next, and so on."""
        out = self.base.cdf(codes[0])
        for v, (low, high, m) in self.finer.items():
            inner = m.cdf(*codes[1:]) if isinstance(m, RefinedModel) else m.cdf(codes[1])
            out = F.when(codes[0] == F.lit(v), F.lit(low) + F.coalesce(inner, F.lit(1.0)) * F.lit(high - low)).otherwise(out)
        return out

    def pid(self, f: int, *codes: Column) -> Column:
        return F.when(codes[0].isNotNull(), F.least(F.lit(f - 1), F.floor(self.cdf(*codes) * f).cast("int")))


def refine_heavy(samples: np.ndarray, f: int, leaves: int = 64, most: int = 64) -> "CdfModel | RefinedModel":
    """samples: one column for each level of codes of the same sampled keys. At most `most` codes a level are refined."""
    codes = samples[:, 0]
    model = train_cdf(codes, leaves, "quantile")
    if samples.shape[1] == 1 or not len(codes):
        return model
    values, counts = np.unique(codes, return_counts=True)
    ends = np.cumsum(counts) / len(codes)
    heavy = [i for i in np.argsort(-counts)[:most] if counts[i] > len(codes) / f and np.isfinite(values[i])]
    finer = {}
    for i in heavy:
        rest = samples[codes == values[i]][:, 1:]
        if len(np.unique(rest[:, 0])) > 1 or rest.shape[1] > 1:
            # never below what smaller codes reach, never above what larger ones start from
            low = float(model.cdf_np(values[i - 1 : i])[0]) if i else 0.0
            high = float(model.cdf_np(values[i + 1 : i + 2])[0]) if i + 1 < len(values) else 1.0
            finer[float(values[i])] = (max(low, float(ends[i] - counts[i] / len(codes))) if i else 0.0, max(low, min(high, float(ends[i]))), refine_heavy(rest, own := max(2, int(f * counts[i] / len(codes))), max(8, min(leaves, 4 * own)), most))
    return RefinedModel(model, finer) if finer else model
