"""Classifiers on samples of bounded size, as arrays in one task: trees, forests, AdaBoost.M1 and linear models.

The utility experiments train many classifiers on samples of a stated size each. A sample is one group of an applyInPandas, so all of
an experiment's classifiers are trained side by side in one job; learners.py has those that are trained on whole tables.
"""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass

import numpy as np


def generator(*key) -> np.random.Generator:
    """Random numbers that hang on the key alone."""
    return np.random.Generator(np.random.Philox(key=int.from_bytes(hashlib.sha256("|".join(map(str, key)).encode()).digest()[:16], "little")))


@dataclass
class Tree:
    feature: np.ndarray  # -1: a leaf
    cut: np.ndarray  # codes up to it go left
    left: np.ndarray
    right: np.ndarray
    share: np.ndarray  # of each class

    def shares(self, x: np.ndarray) -> np.ndarray:
        node = np.zeros(len(x), np.int64)
        while True:
            f = self.feature[node]
            go = np.flatnonzero(f >= 0)
            if not len(go):
                return self.share[node]
            at = node[go]
            node[go] = np.where(x[go, f[go]] <= self.cut[at], self.left[at], self.right[at])


def grow(x: np.ndarray, y: np.ndarray, weight: np.ndarray, cards: list[int], classes: int, depth: int, rng=None, tried: int | None = None) -> Tree:
    """A tree by Gini impurity, level by level from histograms of codes; tried: features drawn for each node (all)."""
    n, m = x.shape
    feature, cut, left, right, share = [-1], [0], [0], [0], [np.zeros(classes)]
    node, at = np.zeros(n, np.int64), np.arange(n)  # rows whose node may still be split
    active = [0]
    for level in range(depth + 1):
        k = len(active)
        if not k:
            break
        total = np.bincount(node * classes + y[at], weight[at], k * classes).reshape(k, classes)
        whole = np.maximum(total.sum(1), 1e-300)
        for j, a in enumerate(active):
            share[a] = total[j] / whole[j]
        # nodes of one class are leaves, and their rows go
        mixed = total.max(1) < whole * (1 - 1e-12)
        if level == depth or not mixed.any():
            break
        if not mixed.all():
            number = np.where(mixed, np.cumsum(mixed) - 1, -1)[node]
            at, node, active, total, whole = at[number >= 0], number[number >= 0], [a for a, x in zip(active, mixed, strict=True) if x], total[mixed], whole[mixed]
            k = len(active)
        base = (total**2).sum(1) / whole
        best, which, where = base + 1e-9 * (1 + base), np.full(k, -1), np.zeros(k, np.int64)
        allowed = np.ones((k, m), bool) if tried is None else rng.random((k, m)).argsort(1).argsort(1) < tried
        for f in range(m):
            h = np.bincount((node * cards[f] + x[at, f]) * classes + y[at], weight[at], k * cards[f] * classes).reshape(k, cards[f], classes)
            low = h.cumsum(1)[:, :-1]
            if not low.shape[1]:
                continue
            high = total[:, None] - low
            a, b = low.sum(2), high.sum(2)
            score = np.where((a > 1e-12) & (b > 1e-12), (low**2).sum(2) / np.maximum(a, 1e-300) + (high**2).sum(2) / np.maximum(b, 1e-300), -1.0)
            top = score.argmax(1)
            value = score[np.arange(k), top]
            better = allowed[:, f] & (value > best)
            best[better], which[better], where[better] = value[better], f, top[better]
        fresh, number = [], np.full(2 * k, -1)
        for j in np.flatnonzero(which >= 0):
            a = active[j]
            feature[a], cut[a], left[a], right[a] = int(which[j]), int(where[j]), len(feature), len(feature) + 1
            for side in (0, 1):
                number[2 * j + side] = len(fresh)
                fresh.append(len(feature))
                for grown, v in ((feature, -1), (cut, 0), (left, 0), (right, 0), (share, None)):
                    grown.append(np.zeros(classes) if v is None else v)
        goes = which[node] >= 0
        at, node = at[goes], node[goes]
        node = number[2 * node + (x[at, which[node]] > where[node])]
        active = fresh
    return Tree(*(np.array(v) for v in (feature, cut, left, right)), np.array(share))


def tree(x, y, cards, classes, rng, depth: int = 10):
    t = grow(x, y, np.ones(len(y)), cards, classes, depth)
    return lambda z: t.shares(z).argmax(1)


def forest(x, y, cards, classes, rng, trees: int = 50, depth: int = 10):
    """Trees on bootstrap samples, each node looking at the square root of the features; their shares are averaged."""
    tried = max(1, math.isqrt(x.shape[1]))
    grown = [grow(x, y, np.bincount(rng.integers(0, len(y), len(y)), minlength=len(y)).astype(float), cards, classes, depth, rng, tried) for _ in range(trees)]
    return lambda z: sum(t.shares(z) for t in grown).argmax(1)


def adaboost(x, y, cards, classes, rng, rounds: int = 20, depth: int = 3):
    """AdaBoost.M1: rows that a round's tree gets right lose weight by e / (1 - e), trees vote with ln((1 - e) / e), and an error e of one half ends it."""
    weight, grown = np.full(len(y), 1 / len(y)), []
    for _ in range(rounds):
        t = grow(x, y, weight, cards, classes, depth)
        right = t.shares(x).argmax(1) == y
        e = float(weight[~right].sum())
        if e >= 0.5:
            break
        beta = max(e, 1e-10) / (1 - max(e, 1e-10))
        grown.append((t, -math.log(beta)))
        if e <= 1e-10:
            break
        weight = np.where(right, weight * beta, weight)
        weight /= weight.sum()
    if not grown:
        most = int(np.bincount(y, minlength=classes).argmax())
        return lambda z: np.full(len(z), most)

    def vote(z):
        total = np.zeros((len(z), classes))
        for t, v in grown:
            total[np.arange(len(z)), t.shares(z).argmax(1)] += v
        return total.argmax(1)

    return vote


MAKERS = {"tree": tree, "rf": forest, "adaboost": adaboost}


def trained(kind: str, rows, schema, target: str, salt: str = "classifier"):
    """A function from rows (pandas) to predicted codes of the target."""
    names = [n for n in schema.names if n != target]
    codes = lambda r: r[names].to_numpy(np.int64)
    cards = [schema.attributes[schema.index(n)].card for n in names]
    model = MAKERS[kind](codes(rows), rows[target].to_numpy(np.int64), cards, schema.attributes[schema.index(target)].card, generator(salt, kind))
    return lambda r: model(codes(r))
