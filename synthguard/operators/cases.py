"""Candidates of several sets for the same seeds, tested and drawn in one scan.

A candidate keeps its seed's leading attributes, so how many seeds could have given it is told by the seed alone: the counts of a
seed's prefixes are joined to it once, and each of its candidates is tested by them before anything is drawn.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from synthguard.functions.noise import laplace_value
from synthguard.operators.distance import Counter
from synthguard.operators.params import Tables, config_numbers
from synthguard.plans.schema import Graph, Schema


@dataclass(frozen=True)
class Case:
    """A set of candidates: omega is drawn from omegas; tested by a threshold k with Laplace(1/eps0) noise, or not at all (k None)."""

    name: str
    graph: Graph
    tables: Tables
    omegas: tuple[int, ...]
    k: int | None = None
    eps0: float = 1.0

    @cached_property
    def guides(self) -> list[np.ndarray]:
        return list(map(guides, self.tables.cum))


def keys(digests: pa.Array) -> np.ndarray:
    """Two 64-bit numbers of each hex text of 32 digits."""
    return np.frombuffer(bytes.fromhex("".join(digests.to_pylist())), ">u8").astype(np.uint64).reshape(-1, 2)


def _mixed(z: np.ndarray) -> np.ndarray:
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def numbers(key: np.ndarray, lane: int) -> np.ndarray:
    """In (0, 1): the number of that lane for each key; the key is a hash of the seed's, so a lost task draws it again."""
    step = np.uint64((lane + 1) * 0x9E3779B97F4A7C15 % 2**64)
    return ((_mixed(_mixed(key[:, 0] + step) ^ key[:, 1]) >> np.uint64(12)) + 0.5) / float(1 << 52)


#: Cells of (0, 1) from which the search for a number's place in a distribution begins.
GUIDES = 128


def guides(cum: np.ndarray) -> np.ndarray:
    """For each distribution and cell, how many of its sums lie at or below the cell's start."""
    starts = np.arange(GUIDES) / GUIDES
    return np.array([np.searchsorted(c, starts, "right") for c in cum]).astype(np.int32)


def placed(cum: np.ndarray, guide: np.ndarray, c: np.ndarray, u: np.ndarray) -> np.ndarray:
    """For each number u, how many sums of distribution c lie at or below it, the last place at most."""
    last, at = cum.shape[1] - 1, guide[c, (u * GUIDES).astype(np.int64)].astype(np.int64)
    np.minimum(at, last, out=at)
    todo = np.flatnonzero((cum[c, at] <= u) & (at < last))
    while len(todo):
        at[todo] += 1
        todo = todo[(cum[c[todo], at[todo]] <= u[todo]) & (at[todo] < last)]
    return at


def passed(case: Case, plausible: np.ndarray, ids, salt: str) -> np.ndarray:
    """Places of the candidates (named by case and seed) that pass, with the thresholds of deniability.randomized(): their noise is made only where it
    may decide, as it never exceeds 52 ln 2 / eps0."""
    far = 52 * math.log(2) / case.eps0 + 1e-6
    ok = plausible > case.k + far
    for at in np.flatnonzero(np.abs(plausible - case.k) <= far):
        ok[at] = plausible[at] >= case.k + laplace_value(1 / case.eps0, salt, f"{case.name}|{ids[int(at)]}", "threshold")
    return np.flatnonzero(ok)


def draw(schema: Schema, cases: list[Case], x: list[np.ndarray], key: np.ndarray, counts: np.ndarray, ids, salt: str) -> Iterator[tuple[Case, np.ndarray, list[np.ndarray]]]:
    """Each case with the seeds (by place) whose candidates pass, and those candidates' codes. x: an array for each attribute; counts[:, d]: how many
    seeds share a seed's first d attributes."""
    m = len(schema)
    for at, case in enumerate(cases):
        lane = at * (m + 1)
        omegas = np.array(case.omegas)
        w = omegas[np.minimum((numbers(key, lane) * len(omegas)).astype(np.int64), len(omegas) - 1)]
        go = np.arange(len(key))
        if case.k is not None:
            go = passed(case, counts[go, m - w], ids, salt)
        y, w, own = [v[go] for v in x], w[go], key[go]
        for place in range(m - int(omegas.max()), m):
            i = case.graph.order[place]
            anew = np.flatnonzero(w >= m - place)
            c = config_numbers(schema, case.graph.parents[i], [v[anew] for v in y])
            u = numbers(own[anew], lane + 1 + i)
            y[i][anew] = placed(case.tables.cum[i], case.guides[i], c, u)
        yield case, go, y


def with_counts(seeds: DataFrame, all_seeds: DataFrame, order: list[str], depths) -> DataFrame:
    """seeds with _n: at each of depths how many of all_seeds share their first attributes of order (elsewhere 0).

    All seeds are grouped by their deepest prefix; the shorter ones are sums over those groups."""
    deepest = max(depths)
    names, wanted = order[:deepest], set(depths)
    zero = F.lit(0).cast("long")
    if not deepest:
        return seeds.crossJoin(F.broadcast(all_seeds.agg(F.array(F.count("*")).alias("_n"))))
    level = all_seeds.groupBy(*names).agg(F.count("*").alias(f"_n{deepest}"))
    for d in sorted(wanted - {0, deepest}, reverse=True):
        level = level.withColumn(f"_n{d}", F.sum(f"_n{deepest}").over(Window.partitionBy(*names[:d])))
    if 0 in wanted:
        level = level.crossJoin(F.broadcast(all_seeds.agg(F.count("*").alias("_n0"))))
    told = level.select(*names, F.array(*[F.col(f"_n{d}") if d in wanted else zero for d in range(deepest + 1)]).alias("_n"))
    return seeds.join(told, names)


def _joined(batches, rows: int = 16_000):
    """Batches of about that many rows: arrays of a few thousand are short for the work on each."""
    some, n = [], 0
    for b in batches:
        some.append(b)
        n += b.num_rows
        if n >= rows:
            yield pa.concat_batches(some)
            some, n = [], 0
    if n:
        yield pa.concat_batches(some)


def _batches(schema: Schema, cases: list[Case], batches, salt: str):
    for b in _joined(batches):
        if b.num_rows:
            x = [b.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in schema.names]
            counts = b.column("_n").flatten().to_numpy().reshape(b.num_rows, -1)
            yield b, draw(schema, cases, x, keys(b.column("_key")), counts, b.column("rk"), salt)


def _keyed(seeds: DataFrame, schema: Schema, salt: str) -> DataFrame:
    return seeds.select("rk", *schema.names, F.substring(F.sha2(F.concat_ws("|", F.lit(salt), "rk"), 256), 1, 32).alias("_key"), "_n")


def candidates(seeds: DataFrame, schema: Schema, cases: list[Case], salt: str) -> DataFrame:
    """kind, rk (the seed's) and the attributes of every candidate that passes; seeds as with_counts() gives them."""
    held = seeds.sparkSession.sparkContext.broadcast(cases)

    def run(batches):
        for b, drawn in _batches(schema, held.value, batches, salt):
            for case, go, y in drawn:
                yield pa.RecordBatch.from_arrays([pa.array([case.name] * len(go), pa.string()), b.column("rk").take(pa.array(go)), *(pa.array(v.astype(np.int32)) for v in y)], names=["kind", "rk", *schema.names])

    return _keyed(seeds, schema, salt).mapInArrow(run, "kind string, rk string, " + ", ".join(f"`{n}` int" for n in schema.names))


def histograms(seeds: DataFrame, schema: Schema, cases: list[Case], sets, salt: str) -> DataFrame:
    """_kind, s, at, n: how often each cell of each of sets (pairs of attributes, or one twice) occurs among the candidates of each
    case that pass, as distance.counted() counts rows; candidates are counted where they are drawn."""
    held = seeds.sparkSession.sparkContext.broadcast(cases)

    def run(batches):
        seen = Counter(schema, sets)
        for _, drawn in _batches(schema, held.value, batches, salt):
            for case, _, y in drawn:
                seen.add(case.name, y)
        yield from seen.batches()

    return _keyed(seeds, schema, salt).mapInArrow(run, Counter.FORM).groupBy("_kind", "s", "at").agg(F.sum("n").alias("n"))
