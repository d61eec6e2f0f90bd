"""Statistical (total variation) distance of the distributions of attributes and pairs, and its summary."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from synthguard.plans.schema import Schema


class Counter:
    """Counts of single attributes and pairs, for each kind of rows: fixed arrays, however many rows are added."""

    FORM = "_kind string, s int, at long, n long"

    def __init__(self, schema: Schema, sets):
        self.cards, self.sets, self.totals = [a.card for a in schema.attributes], sets, {}

    def add(self, kind: str, x: list[np.ndarray]) -> None:
        cards = self.cards
        total = self.totals.setdefault(kind, [np.zeros(cards[i] * (cards[j] if i != j else 1), np.int64) for i, j in self.sets])
        for t, (i, j) in zip(total, self.sets, strict=True):
            t += np.bincount(x[i] * cards[j] + x[j] if i != j else x[i], minlength=len(t))

    def batches(self):
        for kind, total in self.totals.items():
            for s, t in enumerate(total):
                at = np.flatnonzero(t)
                yield pa.RecordBatch.from_arrays([pa.array([kind] * len(at), pa.string()), pa.array(np.full(len(at), s, np.int32)), pa.array(at), pa.array(t[at])], names=["_kind", "s", "at", "n"])


def sets_of(schema: Schema, pairs: bool) -> list[tuple[int, int]]:
    m = range(len(schema))
    return list(combinations(m, 2)) if pairs else [(i, i) for i in m]


def counted(df: DataFrame, schema: Schema, sets, by: str | None = None) -> DataFrame:
    """_kind, s, at, n: how often each cell of each of sets occurs (for each value of by, a column of few values): one scan."""
    names = schema.names

    def count(batches):
        seen = Counter(schema, sets)
        for b in batches:
            kinds = b.column("_kind").dictionary_encode()
            code, x = kinds.indices.to_numpy(), [b.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in names]
            for c, kind in enumerate(kinds.dictionary.to_pylist()):
                at = code == c
                seen.add(kind, x if at.all() else [v[at] for v in x])
        yield from seen.batches()

    kind = F.lit("") if by is None else F.col(by).cast("string")
    return df.select(kind.alias("_kind"), *names).mapInArrow(count, Counter.FORM).groupBy("_kind", "s", "at").agg(F.sum("n").alias("n"))


def distributions(df: DataFrame, schema: Schema, pairs: bool = False, by: str | None = None) -> DataFrame:
    """attrs, value, p of every attribute or pair (for each value of by, a column of few values): one scan, fixed arrays in each task."""
    sets = sets_of(schema, pairs)
    label = F.element_at(F.array(*[F.lit(schema.names[i] if i == j else f"{schema.names[i]},{schema.names[j]}") for i, j in sets]), F.col("s") + 1)
    found = counted(df, schema, sets, by).select("_kind", label.alias("attrs"), F.col("at").alias("value"), "n")
    totals = found.groupBy("_kind", "attrs").agg(F.sum("n").alias("_all"))  # a row for each attribute or pair
    told = found.join(F.broadcast(totals), ["_kind", "attrs"])
    return told.select(*([F.col("_kind").alias(by)] if by else []), "attrs", "value", (F.col("n") / F.col("_all")).alias("p"))


def tv_distance(a: DataFrame, b: DataFrame, schema: Schema, pairs: bool = False, by: str | None = None) -> DataFrame:
    """attrs, distance (for each value of by in b): half the sum of absolute differences; values that one side lacks count there as 0."""
    x, y = distributions(a, schema, pairs), distributions(b, schema, pairs, by).withColumnRenamed("p", "q")
    if by:
        x = x.crossJoin(F.broadcast(y.select(by).distinct()))  # a row for each kind
    keys = [*([by] if by else []), "attrs"]
    both = x.join(y, [*keys, "value"], "full")
    return both.groupBy(*keys).agg((0.5 * F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0))))).alias("distance"))


def boxplot(distances: DataFrame, by: list[str] = ()) -> DataFrame:
    """low, q1, median, q3, high of the distances (for each value of by)."""
    q = F.percentile("distance", F.array(*[F.lit(x) for x in (0.0, 0.25, 0.5, 0.75, 1.0)]))
    return distances.groupBy(*by).agg(q.alias("_q")).select(*by, *[F.col("_q")[i].alias(n) for i, n in enumerate(("low", "q1", "median", "q3", "high"))])


def boxes(found: DataFrame, sets, base: str) -> dict[str, dict[bool, list[float]]]:
    """By kind, for single attributes (False) and pairs (True): low, q1, median, q3, high of the distances to the kind base; found: _kind, s, at, n.
    A number for each value that occurs goes to the driver, as many as the domains have at most, however many rows were counted."""
    counts: dict[str, list[dict]] = {}
    for r in found.collect():
        counts.setdefault(r["_kind"], [{} for _ in sets])[r["s"]][r["at"]] = r["n"]
    share = lambda one: dict(zip(one, np.array(list(one.values())) / sum(one.values()), strict=True))
    shares = {kind: list(map(share, own)) for kind, own in counts.items()}
    real, out = shares.pop(base, [{} for _ in sets]), {}
    for kind, own in shares.items():
        far = [0.5 * sum(abs(a.get(v, 0.0) - b.get(v, 0.0)) for v in a.keys() | b.keys()) for a, b in zip(real, own, strict=True)]
        for pairs in (False, True):
            some = [d for d, (i, j) in zip(far, sets, strict=True) if (i != j) == pairs]
            out.setdefault(kind, {})[pairs] = [float(v) for v in np.percentile(some, (0, 25, 50, 75, 100))]
    return out
