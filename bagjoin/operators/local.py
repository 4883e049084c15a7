"""Sum-product on sparse numpy listings: what runs inside one task for trees of small bags."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np


@dataclass
class Listing:
    """Rows of codes with weights; absent rows weigh zero."""

    vars: tuple[str, ...]
    codes: np.ndarray  # rows x vars
    w: np.ndarray

    def key(self, on: tuple[str, ...]) -> np.ndarray:
        return self.codes[:, [self.vars.index(v) for v in on]]


def _ids(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Equal numbers for equal rows of two code tables."""
    if a.shape[1] == 0:
        return np.zeros(len(a), np.int64), np.zeros(len(b), np.int64)
    both = np.concatenate([a, b])
    span = both.max(axis=0, initial=0).astype(object) + 1
    if math.prod(int(s) for s in span) < 2**62:
        place, key = 1, np.zeros(len(both), np.int64)
        for j in range(both.shape[1] - 1, -1, -1):
            key += both[:, j] * place
            place *= int(span[j])
    else:
        key = np.unique(both, axis=0, return_inverse=True)[1].reshape(-1)
    return key[: len(a)], key[len(a) :]


class RowLimitError(ValueError):
    """A product would have more rows than a task may hold."""


def times(a: Listing, b: Listing, limit: float = math.inf) -> Listing:
    """Weighted natural join; its rows are counted before any is made."""
    on = tuple(v for v in a.vars if v in b.vars)
    x, y = _ids(a.key(on), b.key(on))
    order = np.argsort(y, kind="stable")
    lo, hi = np.searchsorted(y[order], x, "left"), np.searchsorted(y[order], x, "right")
    n = hi - lo
    if n.sum() > limit:
        raise RowLimitError(f"a product has {int(n.sum())} rows, over {limit:g}")
    left = np.repeat(np.arange(len(x)), n)
    right = order[np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)]
    more = [j for j, v in enumerate(b.vars) if v not in a.vars]
    codes = np.concatenate([a.codes[left], b.codes[right][:, more]], axis=1)
    return Listing(a.vars + tuple(b.vars[j] for j in more), codes, a.w[left] * b.w[right])


def onto(a: Listing, vars: tuple[str, ...]) -> Listing:
    sub = a.key(vars)
    if not len(vars):
        return Listing((), np.zeros((1, 0), np.int64), np.array([a.w.sum()]))
    if not len(sub):
        return Listing(vars, sub, a.w)
    key, _ = _ids(sub, sub[:0])
    _, first, group = np.unique(key, return_index=True, return_inverse=True)
    return Listing(vars, sub[first], np.bincount(group.reshape(-1), weights=a.w, minlength=len(first)))


def product(listings: list[Listing], limit: float = math.inf) -> Listing:
    """Fold, always next with a listing that shares variables, the smallest first."""
    left = sorted(listings, key=lambda f: len(f.w))
    out = left.pop(0)
    while left:
        i = min(range(len(left)), key=lambda j: (not set(left[j].vars) & set(out.vars), len(left[j].w)))
        out = times(out, left.pop(i), limit)
    return out


def calibrate(chi: list[tuple[str, ...]], parent: list[int], inputs: list[list[Listing]], root: int, limit: float = math.inf) -> tuple[dict[int, Listing], float]:
    """Bag beliefs of one tree, each summing to one, and log Z; messages are scaled to sum to one.

    More than ``limit`` rows in all bags together raise RowLimitError before they are made.
    """
    kids: list[list[int]] = [[] for _ in chi]
    for b, p in enumerate(parent):
        if p >= 0:
            kids[p].append(b)
    order, todo = [], [root]
    while todo:
        b = todo.pop()
        order.append(b)
        todo += kids[b]
    beliefs: dict[int, Listing] = {}
    up: dict[int, Listing] = {}
    log_z, held = 0.0, 0

    def normal(f: Listing) -> tuple[Listing, float]:
        s = f.w.sum()
        if not s > 0:
            raise ZeroDivisionError("no assignment has a positive weight")
        return Listing(f.vars, f.codes, f.w / s), math.log(s)

    for b in reversed(order):
        beliefs[b], s = normal(product([*inputs[b], *[up[k] for k in kids[b]]], limit - held))
        held += len(beliefs[b].w)
        log_z += s
        if parent[b] >= 0:
            own = set(beliefs[b].vars)
            sep = tuple(v for v in chi[b] if v in set(chi[parent[b]]) and v in own)
            up[b] = onto(beliefs[b], sep)
    for b in order:
        for k in kids[b]:
            down = onto(beliefs[b], up[k].vars)
            x, y = _ids(down.codes, up[k].codes)
            at = np.argsort(y)
            old = up[k].w[at][np.searchsorted(y[at], x)]
            beliefs[k], _ = normal(times(beliefs[k], Listing(down.vars, down.codes, down.w / old)))
    return beliefs, log_z
