"""Preparation: cleaning, profiles, bucketizing, keyed splits, seeds."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from synthguard.functions.noise import uniform
from synthguard.plans.schema import Schema

#: Shares of the rows: structure, parameters, seeds, test, other reals.
SHARES = (("T", 0.1875), ("P", 0.1875), ("S", 0.49), ("test", 0.07), ("other", 0.065))
SALT = "split"


def valid(schema: Schema) -> Column:
    return reduce(lambda a, b: a & b, [F.col(a.name).isNotNull() & F.col(a.name).between(0, a.card - 1) for a in schema.attributes])


def clean(df: DataFrame, schema: Schema) -> DataFrame:
    """Rows all of whose values lie in their domains."""
    return df.where(valid(schema))


def profile(df: DataFrame, schema: Schema) -> DataFrame:
    """rows, clean_rows, unique_records, attributes, possible_records (text: it may pass 64 bits)."""
    ok = valid(schema)
    return df.agg(F.count("*").alias("n_rows"), F.count_if(ok).alias("clean_rows"), F.count_distinct(F.when(ok, F.struct(*schema.names))).alias("unique_records")).withColumns(
        {"attributes": F.lit(len(schema)).cast("long"), "possible_records": F.lit(str(schema.possible_records()))}
    )


def bucket(schema: Schema, name: str) -> Column:
    """The bucket of an attribute's value, as parents are seen."""
    a = schema.attributes[schema.index(name)]
    if a.bucket_of == tuple(range(a.card)):
        return F.col(name)
    width = a.bucket_of.count(0)
    if a.bucket_of == tuple(v // width for v in range(a.card)):
        return F.floor(F.col(name) / width).cast("int")
    return F.element_at(F.array(*[F.lit(b) for b in a.bucket_of]), F.col(name) + 1)


def bucketize(df: DataFrame, schema: Schema) -> DataFrame:
    return df.select("rk", *[bucket(schema, n).alias(n) for n in schema.names])


def split(df: DataFrame, shares=SHARES, salt: str = SALT) -> DataFrame:
    """df with `split`, by a keyed uniform number: no shuffle, disjoint, the same in any layout. The salt must stay secret."""
    u = uniform(salt, "rk")
    edge, out = 1.0, None
    for name, share in reversed(shares):
        edge -= share
        out = F.lit(name) if out is None else F.when(u >= edge + share - 1e-15, out).otherwise(F.lit(name))
    return df.withColumn("split", out)


def part(df: DataFrame, which: str, shares=SHARES, salt: str = SALT) -> DataFrame:
    """The rows of one split, by range predicates on the keyed number."""
    low = 0.0
    for name, share in shares:
        if name == which:
            u = uniform(salt, "rk")
            return df.where((u >= low) & (u < low + share)) if low + share < 1 - 1e-12 else df.where(u >= low)
        low += share
    raise ValueError(f"no split {which}")


def number_of(which: str, shares=SHARES) -> int:
    return [name for name, _ in shares].index(which)


def dealt(shares=SHARES, salt: str = SALT) -> Column:
    """The number of a row's split, as part() deals it; the keyed number is made once for all of them."""
    u = uniform(salt, "rk")
    # a sum in place of nested conditions: what all its terms hold is computed once, in compiled code
    return reduce(lambda a, b: a + b, [(u >= edge).cast("byte") for edge in np.cumsum([share for _, share in shares])[:-1].tolist()])


def ranked(df: DataFrame, n: int, in_cell: int = 10_000, most_cells: int = 100_000) -> tuple[DataFrame, np.ndarray]:
    """df with a cell by the hash of its key (_c) and a rank in it (_r, from 0), and the number of rows of each cell.

    Both hang on the rows alone, so they are the same however a plan deals its rows to partitions. n: about how many rows
    there are; cells hold about in_cell rows, and at most most_cells numbers go to the driver."""
    cells = int(min(max(1, n // in_cell), most_cells))
    marked = df.withColumn("_c", F.pmod(F.xxhash64("rk"), F.lit(cells)))
    sizes = np.zeros(cells, np.int64)
    for r in marked.groupBy("_c").count().collect():
        sizes[r["_c"]] = r["count"]
    order = Window.partitionBy("_c").orderBy("rk", *[c for c in df.columns if c != "rk"])
    return marked.withColumn("_r", (F.row_number().over(order) - 1).cast("long")), sizes


def sample_seeds(seeds: DataFrame, n: int, salt: str, how: str = "rank") -> DataFrame:
    """Seeds, each drawn uniformly and on its own: rows of seeds with cand_id.

    rank: exactly n draws with replacement, each a hashed rank joined to the rows' own ranks. poisson: every row comes a hashed
    Poisson number of times with mean n / rows; it needs no ranks and no join, but its draws are not exactly n.
    """
    spark = seeds.sparkSession
    total = seeds.count()
    if how == "rank":
        held, sizes = ranked(seeds, total)
        ends = np.cumsum(sizes)
        if not ends[-1]:
            raise ValueError("there are no seeds")
        known = spark.sparkContext.broadcast(ends)

        @F.pandas_udf("struct<_c: long, _r: long>")
        def place(u: pd.Series) -> pd.DataFrame:
            e = known.value
            rank = np.minimum(np.floor(u.to_numpy() * e[-1]).astype(np.int64), e[-1] - 1)
            cell = np.searchsorted(e, rank, "right")
            return pd.DataFrame({"_c": cell, "_r": rank - np.where(cell > 0, e[cell - 1], 0)})

        draws = spark.range(n).select(F.col("id").cast("string").alias("cand_id"), place(uniform(salt, F.col("id"))).alias("_at")).select("cand_id", "_at.*")
        return draws.join(held, ["_c", "_r"]).drop("_c", "_r")
    if how == "poisson":
        mean = n / max(1, total)
        if mean > 500:
            raise ValueError("more than 500 draws a row: draw by rank")
        u = uniform(salt, "rk")
        # the inverse of the Poisson distribution, summed up to where the tail is below 2**-52
        terms, p, reached = [], math.exp(-mean), 0.0
        k = 0
        while reached + p < 1 - 2**-52 and k < 2000:
            reached += p
            k += 1
            terms.append(reached)
            p *= mean / k
        # bound once: a hash in the lambda would be made for each term
        times = F.transform(F.array(u), lambda v: F.size(F.filter(F.array(*[F.lit(t) for t in terms]), lambda t: t <= v)))[0] if terms else F.lit(0)
        return seeds.withColumn("_n", times).where("_n > 0").withColumn("_k", F.explode(F.sequence(F.lit(1), "_n"))).withColumn("cand_id", F.concat_ws("#", "rk", "_k")).drop("_n", "_k")
    raise ValueError("how is rank or poisson")
