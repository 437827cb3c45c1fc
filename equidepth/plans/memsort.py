"""In-memory routines for the rows of one slice or run, as orders of positions; and the model's own.

All return the permutation that sorts. Spark's in-slice sort, which spills, is the default everywhere; these
are for comparison and must have their rows in memory.
"""

from __future__ import annotations

import numpy as np

from .cdf_model import CdfModel, train_cdf


def insertion_order(keys) -> np.ndarray:
    order = list(range(len(keys)))
    for i in range(1, len(order)):
        x, j = order[i], i - 1
        while j >= 0 and keys[order[j]] > keys[x]:
            order[j + 1] = order[j]
            j -= 1
        order[j + 1] = x
    return np.array(order, np.int64)


def natural_order(keys: np.ndarray, least: int = 32) -> np.ndarray:
    """Runs as they lie (falling ones turned), short ones filled up by insertion, then merged in pairs."""
    n, runs, at = len(keys), [], 0
    while at < n:
        end = at + 1
        if end < n and keys[end] < keys[at]:
            while end < n and keys[end] < keys[end - 1]:
                end += 1
            run = np.arange(end - 1, at - 1, -1)
        else:
            while end < n and not keys[end] < keys[end - 1]:
                end += 1
            run = np.arange(at, end)
        if end - at < least and end < n:
            end = min(n, at + least)
            part = np.concatenate([run, np.arange(at + len(run), end)])
            run = part[insertion_order([keys[i] for i in part])]
        runs.append(run)
        at = end
    while len(runs) > 1:
        runs = [_merge(keys, runs[i], runs[i + 1]) if i + 1 < len(runs) else runs[i] for i in range(0, len(runs), 2)]
    return runs[0].astype(np.int64) if runs else np.zeros(0, np.int64)


def _merge(keys: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Stable merge of two sorted orders by where b's keys fall among a's."""
    at = np.searchsorted(keys[a], keys[b], side="right") + np.arange(len(b))
    out = np.empty(len(a) + len(b), np.int64)
    mask = np.ones(len(out), bool)
    out[at] = b
    mask[at] = False
    out[mask] = a
    return out


def radix_order(codes: np.ndarray, bits: int = 8) -> np.ndarray:
    """Least digit first over the order-preserving bits of 64-bit floats."""
    raw = np.asarray(codes, np.float64).view(np.uint64)
    sign = raw >> np.uint64(63)
    turned = np.where(sign == 1, ~raw, raw | np.uint64(1 << 63))
    order = np.arange(len(turned))
    for shift in range(0, 64, bits):
        digit = (turned[order] >> np.uint64(shift)) & np.uint64((1 << bits) - 1)
        order = order[np.argsort(digit, kind="stable")]
    return order


def touch_up(keys, order: np.ndarray) -> tuple[np.ndarray, int]:
    """Insertion pass by whole keys over a nearly sorted order; also the number of single steps that it took."""
    out, moves = order.tolist(), 0
    for i in range(1, len(out)):
        x, j = out[i], i - 1
        while j >= 0 and keys[out[j]] > keys[x]:
            out[j + 1] = out[j]
            j -= 1
            moves += 1
        out[j + 1] = x
    return np.array(out, np.int64), moves


def model_order(codes: np.ndarray, keys=None, *, model: CdfModel | None = None, bucket: int = 64) -> tuple[np.ndarray, int]:
    """Predict each row's place, deal rows into buckets by counting, order buckets by code, touch up by whole keys.

    Buckets of one code are left as they are (early stop on duplicates). Returns the order and the touch-up's steps.
    """
    codes = np.asarray(codes, np.float64)
    n = len(codes)
    if n == 0:
        return np.zeros(0, np.int64), 0
    if model is None:
        sample = codes if n <= 2000 else codes[np.linspace(0, n - 1, 2000).astype(int)]
        model = train_cdf(sample, 256, "linear")
    f = max(1, n // bucket)
    at = model.pid_np(codes, f)
    order = np.argsort(at, kind="stable")
    bounds = np.searchsorted(at[order], np.arange(f + 1))
    for j in range(f):
        a, b = bounds[j], bounds[j + 1]
        if b - a > 1:
            part = codes[order[a:b]]
            if part.min() != part.max():
                order[a:b] = order[a:b][np.argsort(part, kind="stable")]
    return touch_up(keys, order) if keys is not None else (order, 0)


def quick_order(keys: np.ndarray) -> np.ndarray:
    """Three-way partitions around the middle of three, on a stack."""
    out, stack = [], [np.arange(len(keys))]
    while stack:
        part = stack.pop()
        if len(part) <= 1:
            out.append(part)
            continue
        k = keys[part]
        pivot = sorted([k[0], k[len(k) // 2], k[-1]])[1]
        low, same, high = part[k < pivot], part[k == pivot], part[k > pivot]
        if not len(low) and not len(high):
            out.append(same)
            continue
        stack += [high, low] if not len(same) else [high, same, low]
        if len(same) == len(part):
            out.append(stack.pop())
    return np.concatenate(out).astype(np.int64) if out else np.zeros(0, np.int64)


def intro_order(keys: np.ndarray) -> np.ndarray:
    """The library's introspective sort."""
    return np.argsort(keys, kind="quicksort")


def merge_order(keys: np.ndarray) -> np.ndarray:
    return np.argsort(keys, kind="stable")


ROUTINES = ("model", "quick", "merge", "intro", "natural", "insertion", "radix")


def memory_order(codes: np.ndarray, routine: str) -> np.ndarray:
    """The order of codes by a named routine."""
    codes = np.asarray(codes, np.float64)
    if routine == "model":
        return model_order(codes)[0]
    found = {"quick": quick_order, "merge": merge_order, "intro": intro_order, "natural": natural_order, "insertion": insertion_order, "radix": radix_order}
    return found[routine](codes)
