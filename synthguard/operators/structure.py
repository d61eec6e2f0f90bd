"""Learning the dependency graph from correlations: greedy search under acyclicity and cost; driver work on an m x m matrix."""

from __future__ import annotations

from itertools import combinations, product

import numpy as np
from pyspark.sql import DataFrame

from synthguard.operators.info import correlations, entropy_sets, merit, with_noise
from synthguard.plans.schema import Graph, Schema, topological


def config_cost(parents, schema: Schema) -> int:
    """Configurations of a parent set, by bucketized cardinalities."""
    cost = 1
    for p in parents:
        cost *= schema.attributes[p].buckets
    return cost


def _reaches(parents, start: int, goal: int) -> bool:
    """Is goal an ancestor of start, or start itself?"""
    todo, seen = [start], set()
    while todo:
        x = todo.pop()
        if x == goal:
            return True
        if x not in seen:
            seen.add(x)
            todo += parents[x]
    return False


def learn_structure(c: np.ndarray, schema: Schema, maxcost: int = 1000, min_gain: float = 0.0) -> Graph:
    """Attributes in declared order; each takes the parent that raises its merit most, until none raises it by more than
    min_gain, closes no cycle and stays within maxcost. Ties go to the lowest index."""
    m = len(schema)
    parents: list[tuple[int, ...]] = [()] * m
    for i in range(m):
        score = 0.0
        while True:
            best = None
            for j in range(m):
                if j == i or j in parents[i] or _reaches(parents, j, i) or config_cost((*parents[i], j), schema) > maxcost:
                    continue
                s = merit(i, (*parents[i], j), c)
                if s > score + min_gain and (best is None or s > best[0]):
                    best = (s, j)
            if best is None:
                break
            score, parents[i] = best[0], (*parents[i], best[1])
    return Graph(tuple(parents), topological(parents))


def exhaustive_structure(c: np.ndarray, schema: Schema, maxcost: int = 1000) -> tuple[Graph, float]:
    """The acyclic graph of the largest total merit; for 5 attributes at most."""
    m = len(schema)
    if m > 5:
        raise ValueError("exhaustive search is for 5 attributes at most")
    options = [[s for k in range(m) for s in combinations([j for j in range(m) if j != i], k) if config_cost(s, schema) <= maxcost] for i in range(m)]
    best, top = None, -1.0
    for choice in product(*options):
        total = sum(merit(i, s, c) for i, s in enumerate(choice))
        if total > top + 1e-12:
            try:
                best, top = Graph(tuple(choice), topological(list(choice))), total
            except ValueError:
                continue
    return best, top


def rank_by_gain(values: dict, m: int, i: int) -> list[tuple[int, float]]:
    """Attributes by information gain about x_i, largest first: it sees no redundancy between them."""
    gains = [(j, values["x", i, -1] + values["b", j, -1] - values["xb", i, j]) for j in range(m) if j != i]
    return sorted(gains, key=lambda g: (-g[1], g[0]))


def learn(df: DataFrame, schema: Schema, maxcost: int = 1000, min_gain: float = 0.0, eps_entropy: float | None = None, eps_size: float = 0.01, salt: str = "structure") -> Graph:
    """The graph of a table, with differential privacy where eps_entropy is given."""
    values, n = entropy_sets(df, schema)
    if eps_entropy is not None:
        values = with_noise(values, n, eps_entropy, eps_size, salt)
    return learn_structure(correlations(values, len(schema)), schema, maxcost, min_gain)


def agreement(a: Graph, b: Graph) -> dict[str, int]:
    """Edges kept, reversed, lost and added from a to b."""
    x, y = set(a.edges), set(b.edges)
    turned = {(p, c) for c, p in x} & y - x
    return {"kept": len(x & y), "reversed": len(turned), "lost": len(x - y) - len(turned), "added": len(y - x) - len(turned)}
