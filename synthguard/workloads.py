"""The experiment workloads on the given tables, each a query with DuckDB SQL for the same rows where SQL can express it."""

from __future__ import annotations

import math
from contextlib import contextmanager
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.functions.noise import laplace_sql, uniform, uniform_sql
from synthguard.functions.scalar import gamma_bucket, pass_probability
from synthguard.operators import bounded, deniability, distance, info, learners, params, predict, prep, release, structure, synth
from synthguard.operators.cases import Case, candidates, histograms, with_counts
from synthguard.plans.budget import calibrate, compose, entropy_sensitivity, release_epsilon
from synthguard.plans.schema import DeniabilityParams, Graph, Schema
from synthguard.sources.tables import CONVERSATION, DOCUMENT, EVENT, ORDERLINE, View, read_table, wide_view
from synthguard.streaming.drift import daily_drift

OL = ORDERLINE.schema
ORDER = ("reg", "nat", "seg", "op", "rf", "ls", "disc", "qty", "pband", "uband", "netc")
_PARENTS = {"nat": ("reg",), "uband": ("qty", "pband"), "netc": ("pband", "disc")}
#: The fixed graph of the exact checks, which does not depend on the learner.
FIXED = Graph(tuple(tuple(OL.index(p) for p in _PARENTS.get(a.name, ())) for a in OL.attributes), tuple(OL.index(n) for n in ORDER))
RANDOM = ((9, 10, 11), (5, 6, 7, 8, 9, 10, 11))
SALT = "release"


# --- shared pieces


def micro(spark: SparkSession, sf_dir: str, view: View = ORDERLINE) -> DataFrame:
    return prep.clean(view.build(spark, sf_dir), view.schema)


def split_of(spark: SparkSession, sf_dir: str, which: str, view: View = ORDERLINE, split: str = prep.SALT) -> DataFrame:
    return prep.part(micro(spark, sf_dir, view), which, salt=split)


def fixed_model(spark: SparkSession, sf_dir: str) -> synth.Model:
    return synth.from_tables(spark, OL, FIXED, params.learn_tables(params.counts_by_set(split_of(spark, sf_dir, "P"), OL, [FIXED]), OL, FIXED))


def learned_graphs(t: DataFrame, schema: Schema, cases: dict[str, float | None], min_gain: float = 0.02) -> dict[str, Graph]:
    """By salt: the graph of t without noise, or with noise of its own that keeps to that epsilon; one scan for all."""
    values, n = info.entropy_sets(t, schema)
    noisy = lambda salt, eps: values if eps is None else info.with_noise(values, n, calibrate(eps, len(schema), 2.0**-30)[0], 0.01, f"{salt}-structure")
    return {salt: structure.learn_structure(info.correlations(noisy(salt, eps), len(schema)), schema, min_gain=min_gain) for salt, eps in cases.items()}


def learned_tables(p: DataFrame, schema: Schema, graphs: dict[str, Graph], cases: dict[str, float | None]) -> dict[str, params.Tables]:
    """By salt: the graph's tables, private and drawn from their posterior where there is an epsilon; one scan for all."""
    counted, out = params.counts_by_set(p, schema, list(graphs.values())), {}
    for salt, eps in cases.items():
        noise = {} if eps is None else {"estimator": "sampled", "eps": calibrate(eps, len(schema), 2.0**-30)[1], "salt": f"{salt}-parameters"}
        out[salt] = params.learn_tables(counted, schema, graphs[salt], **noise)
    return out


def learned_model(spark: SparkSession, sf_dir: str, eps: float | None = None, salt: str = "model", min_gain: float = 0.02, view: View = ORDERLINE, split: str = prep.SALT) -> synth.Model:
    """Structure from T and parameters from P; with eps, both private and the parameters drawn from their posterior."""
    schema, t, p = view.schema, split_of(spark, sf_dir, "T", view, split), split_of(spark, sf_dir, "P", view, split)
    graphs = learned_graphs(t, schema, {salt: eps}, min_gain)
    return synth.from_tables(spark, schema, graphs[salt], learned_tables(p, schema, graphs, {salt: eps})[salt])


def _seeds(spark: SparkSession, sf_dir: str, view: View = ORDERLINE, split: str = prep.SALT) -> DataFrame:
    """Every row of S once, as its own candidate's seed."""
    return split_of(spark, sf_dir, "S", view, split).withColumn("cand_id", F.col("rk"))


def _values(df: DataFrame, schema: Schema) -> DataFrame:
    """attr, value, n: how often each value stands in each column."""
    return df.select(F.explode(F.array(*[F.struct(F.lit(n).alias("attr"), F.col(n).cast("int").alias("value")) for n in schema.names])).alias("x")).select("x.*").groupBy("attr", "value").agg(F.count("*").alias("n"))


# --- SQL pieces


def _v(view: View = ORDERLINE) -> str:
    ok = " AND ".join(f"{a.name} BETWEEN 0 AND {a.card - 1}" for a in view.schema.attributes)
    return f"v AS MATERIALIZED (SELECT *, {uniform_sql(repr(prep.SALT + '|') + ' || rk')} AS u FROM ({view.sql}) WHERE {ok})"


def _part(which: str) -> str:
    low = 0.0
    for name, share in prep.SHARES:
        if name == which:
            return f"{which.lower()}_ AS (SELECT * FROM v WHERE u >= {low!r}" + (f" AND u < {low + share!r})" if low + share < 1 - 1e-12 else ")")
        low += share
    raise ValueError(which)


def _b(schema: Schema, name: str) -> str:
    a = schema.attributes[schema.index(name)]
    return name if a.bucket_of == tuple(range(a.card)) else f"({name} // {a.bucket_of.count(0)})"


def _config(schema: Schema, graph: Graph, i: int) -> str:
    out = "0"
    for p in graph.parents[i]:
        a = schema.attributes[p]
        out = f"({out} * {a.buckets} + {_b(schema, a.name)})"
    return f"{out}::BIGINT"


def _entropy_sql(source: str, schema: Schema) -> str:
    """role, i, j, h of every set."""
    sets = [("x", i, -1, n) for i, n in enumerate(schema.names)] + [("b", i, -1, _b(schema, n)) for i, n in enumerate(schema.names)]
    sets += [("xb", i, j, f"{x}, {_b(schema, y)}") for i, x in enumerate(schema.names) for j, y in enumerate(schema.names) if i != j]
    one = "SELECT '{0}' AS role, {1} AS i, {2} AS j, log2(sum(c)) - sum(c * log2(c)) / sum(c) AS h FROM (SELECT count(*) AS c FROM {4} GROUP BY {3})"
    return " UNION ALL ".join(one.format(*s, source) for s in sets)


def _cells_sql(source: str, schema: Schema, graph: Graph) -> str:
    """attr, config, value, n of every cell."""
    found = " UNION ALL ".join(f"SELECT {i} AS attr, {_config(schema, graph, i)} AS config, {n} AS value, count(*) AS n FROM {source} GROUP BY ALL" for i, n in enumerate(schema.names))
    every = " UNION ALL ".join(f"SELECT {i} AS attr, c.range AS config, w.range::INTEGER AS value FROM range({structure.config_cost(graph.parents[i], schema)}) c, range({a.card}) w" for i, a in enumerate(schema.attributes))
    return f"SELECT e.attr, e.config, e.value, coalesce(f.n, 0)::DOUBLE AS n FROM ({every}) e LEFT JOIN ({found}) f ON e.attr = f.attr AND e.config = f.config AND e.value = f.value"


def _probs_sql(cells: str, alpha: float = 1.0) -> str:
    return f"SELECT attr, config, value, (n + {alpha}) / sum(n + {alpha}) OVER (PARTITION BY attr, config) AS p FROM ({cells})"


def _lists_sql(cells: str) -> str:
    return f"SELECT attr, config, list(p ORDER BY value) AS probs, list(s ORDER BY value) AS cum FROM (SELECT *, sum(p) OVER (PARTITION BY attr, config ORDER BY value) AS s FROM ({_probs_sql(cells)})) GROUP BY attr, config"


def _synth_sql(source: str, tables: str, schema: Schema, graph: Graph, omega: int, salt: str) -> str:
    """CTEs y0, y1, ...: source with its last omega attributes drawn anew, keyed by rk. Returns (text, name of the last)."""
    text, last = [f"y0 AS (SELECT * FROM {source})"], "y0"
    for k, i in enumerate(graph.order[len(schema) - omega :], 1):
        a = schema.attributes[i]
        u = uniform_sql(f"'{salt}|' || rk || '|{a.name}'")
        text.append(f"y{k} AS (SELECT y.* REPLACE (least(len(list_filter(t.cum, lambda c: c <= y.uu)), {a.card - 1})::INTEGER AS {a.name}) FROM (SELECT *, {u} AS uu, {_config(schema, graph, i)} AS cc FROM (SELECT * EXCLUDE (uu, cc) FROM (SELECT 0 AS uu, 0 AS cc, z.* FROM {last} z)) ) y JOIN {tables} t ON t.attr = {i} AND t.config = y.cc)")
        # helper columns leave before the next step
        text[-1] = text[-1].replace(f"SELECT * EXCLUDE (uu, cc) FROM (SELECT 0 AS uu, 0 AS cc, z.* FROM {last} z)", f"SELECT rk, {', '.join(schema.names)} FROM {last}")
        last = f"y{k}"
    return ", ".join(text), last


def _values_sql(source: str, schema: Schema) -> str:
    return " UNION ALL ".join(f"SELECT '{n}' AS attr, {n}::INTEGER AS value, count(*)::BIGINT AS n FROM {source} GROUP BY {n}" for n in schema.names)


# --- data


def attribute_profile(spark, sf_dir):
    seen = distance.distributions(micro(spark, sf_dir), OL).groupBy("attrs").agg(F.min("value").cast("int").alias("lowest"), F.max("value").cast("int").alias("highest"), F.count("*").alias("distinct_values"))
    known = spark.createDataFrame([(a.name, a.kind, a.card, a.buckets) for a in OL.attributes], "attrs string, kind string, card long, buckets long")
    return known.join(seen, "attrs").withColumnRenamed("attrs", "attr")


def _attribute_profile_sql():
    return f"WITH {_v()} " + " UNION ALL ".join(
        f"SELECT '{a.name}' AS attr, '{a.kind}' AS kind, {a.card}::BIGINT AS card, {a.buckets}::BIGINT AS buckets, min({a.name})::INTEGER AS lowest, max({a.name})::INTEGER AS highest, count(DISTINCT {a.name})::BIGINT AS distinct_values FROM v" for a in OL.attributes
    )


def _profile_sql(view: View) -> str:
    s = view.schema
    return f"SELECT (SELECT count(*) FROM ({view.sql}))::BIGINT AS n_rows, count(*)::BIGINT AS clean_rows, count(DISTINCT ({', '.join(s.names)}))::BIGINT AS unique_records, {len(s)}::BIGINT AS attributes, '{s.possible_records()}' AS possible_records FROM v"


def clean_counts(spark, sf_dir):
    out = None
    for view in (ORDERLINE, DOCUMENT, EVENT, CONVERSATION):
        one = prep.profile(view.build(spark, sf_dir), view.schema).select(F.lit(view.schema.name).alias("view"), "n_rows", "clean_rows")
        out = one if out is None else out.unionByName(one)
    return out


def _clean_counts_sql():
    ok = lambda s: " AND ".join(f"{a.name} BETWEEN 0 AND {a.card - 1}" for a in s.attributes)
    return " UNION ALL ".join(f"SELECT '{v.schema.name}' AS view, count(*)::BIGINT AS n_rows, (count(*) FILTER ({ok(v.schema)}))::BIGINT AS clean_rows FROM ({v.sql})" for v in (ORDERLINE, DOCUMENT, EVENT, CONVERSATION))


def bucketized(spark, sf_dir):
    return _values(prep.bucketize(micro(spark, sf_dir), OL), OL)


def _bucketized_sql():
    return f"WITH {_v()}, b AS (SELECT {', '.join(f'{_b(OL, n)} AS {n}' for n in OL.names)} FROM v) {_values_sql('b', OL)}"


def split_sizes(spark, sf_dir):
    return prep.split(micro(spark, sf_dir)).groupBy("split").agg(F.count("*").alias("n"))


def _split_sizes_sql():
    low, cases = 0.0, []
    for name, share in prep.SHARES:
        low += share
        cases.append(f"WHEN u < {low if low < 1 - 1e-12 else 2.0!r} THEN '{name}'")
    return f"WITH {_v()} SELECT CASE {' '.join(cases)} END AS split, count(*)::BIGINT AS n FROM v GROUP BY 1"


# --- structure


def entropies(spark, sf_dir):
    return info.entropies(split_of(spark, sf_dir, "T"), OL)


def _entropies_sql():
    return f"WITH {_v()}, {_part('T')} {_entropy_sql('t_', OL)}"


def correlations(spark, sf_dir):
    values, _ = info.entropy_sets(split_of(spark, sf_dir, "T"), OL)
    c = info.correlations(values, len(OL))
    return spark.createDataFrame([(OL.names[i], OL.names[j], float(c[i, j])) for i in range(len(OL)) for j in range(len(OL)) if i != j], "child string, parent string, su double")


_CORR = "corr AS (SELECT a.i, a.j, CASE WHEN x.h + b.h <= 0 THEN 0 ELSE greatest(0, least(1, 2 - 2 * a.h / (x.h + b.h))) END AS su FROM e a JOIN e x ON a.role = 'xb' AND x.role = 'x' AND x.i = a.i JOIN e b ON b.role = 'b' AND b.i = a.j)"


def _correlations_sql():
    name = lambda c: f"list_extract({list(OL.names)!r}, {c} + 1)"
    return f"WITH {_v()}, {_part('T').replace(' AS ', ' AS MATERIALIZED ', 1)}, e AS MATERIALIZED ({_entropy_sql('t_', OL)}), {_CORR} SELECT {name('i')} AS child, {name('j')} AS parent, su FROM corr"


NOISE = {"eps_entropy": 0.5, "eps_size": 0.1, "salt": "noise"}


def noisy_entropies(spark, sf_dir):
    values, n = info.entropy_sets(split_of(spark, sf_dir, "T"), OL)
    return spark.createDataFrame([(*k, float(h)) for k, h in info.with_noise(values, n, **NOISE).items()], "role string, i int, j int, h double")


def _noisy_entropies_sql():
    noisy_n = f"greatest(2.0, (SELECT count(*) FROM t_) + {laplace_sql(str(1 / NOISE['eps_size']), repr(NOISE['salt'] + '|size'))})"
    scale = f"(SELECT (2 + 1 / ln(2) + 2 * log2(m)) / m / {NOISE['eps_entropy']} FROM (SELECT {noisy_n} AS m))"
    key = f"'{NOISE['salt']}|' || role || '|' || i || '|' || j"
    return f"WITH {_v()}, {_part('T')}, e AS ({_entropy_sql('t_', OL)}), s AS (SELECT {scale} AS scale) SELECT role, i, j, h + {laplace_sql('scale', key)} AS h FROM e, s"


def merit_scores(spark, sf_dir):
    values, _ = info.entropy_sets(micro(spark, sf_dir), OL)
    c = info.correlations(values, len(OL))
    rows = [(OL.names[i], ",".join(OL.names[p] for p in ps), float(info.merit(i, ps, c)), structure.config_cost(ps, OL)) for i, ps in enumerate(FIXED.parents) if ps]
    return spark.createDataFrame(rows, "child string, parents string, merit double, cost long")


def _merit_sql():
    rows = []
    for i, ps in enumerate(FIXED.parents):
        if ps:
            got = " + ".join(f"(SELECT su FROM corr WHERE i = {i} AND j = {p})" for p in ps)
            red = " + ".join([str(len(ps)), *(f"(SELECT su FROM corr WHERE i = {p} AND j = {q})" for p in ps for q in ps if p != q)])
            rows.append(f"SELECT '{OL.names[i]}' AS child, '{','.join(OL.names[p] for p in ps)}' AS parents, ({got}) / sqrt({red}) AS merit, {structure.config_cost(ps, OL)}::BIGINT AS cost")
    return f"WITH {_v()}, e AS MATERIALIZED ({_entropy_sql('v', OL)}), {_CORR} " + " UNION ALL ".join(rows)


def learned_edges(spark, sf_dir):
    """Edges without noise and at epsilon 1 and 0.1, with how many of the first stay."""
    values, n = info.entropy_sets(split_of(spark, sf_dir, "T"), OL)
    rows, first = [], None
    for eps in (None, 1.0, 0.1):
        v = values if eps is None else info.with_noise(values, n, calibrate(eps, len(OL), 2.0**-30)[0], 0.01, f"edges-{eps}")
        g = structure.learn_structure(info.correlations(v, len(OL)), OL, min_gain=0.02)
        first = first or g
        kept = structure.agreement(first, g)["kept"]
        rows += [(str(eps), OL.names[c], OL.names[p], kept) for c, p in g.edges]
    return spark.createDataFrame(rows, "eps string, child string, parent string, kept long")


def wide_structure(spark, sf_dir, planted: int = 8):
    """Edges among the sign bits of the embeddings, of which the last eight are made to follow the first (one row in eight by the hash
    of its key excepted), above the correlation that independent columns of as many rows show; planted tells which edges were made."""
    schema, df = wide_view(spark, sf_dir, 64)
    first = 64 - planted
    follows = F.pmod(F.xxhash64("rk"), F.lit(8)) > 0
    df = df.withColumns({f"s{first + k}": F.when(follows, F.col(f"s{k}")).otherwise(F.col(f"s{first + k}")) for k in range(planted)})
    values, n = info.entropy_sets(df, schema)
    c = info.correlations(values, len(schema))
    # ten times what independence gives on average: the largest of 4032 pairs stays below
    floor = 10 * max(info.spurious_floor(values, schema, n, 0, j) for j in range(1, 64))
    g = structure.learn_structure(np.where(c > floor, c, 0.0), schema, maxcost=16, min_gain=0.05)
    made = {(k, first + k) for k in range(planted)} | {(first + k, k) for k in range(planted)}
    return spark.createDataFrame([(schema.names[x], schema.names[y], (x, y) in made) for x, y in g.edges], "child string, parent string, planted boolean")


# --- parameters


def cpt_counts(spark, sf_dir):
    return params.counts(split_of(spark, sf_dir, "P"), OL, FIXED)


def _cpt_counts_sql():
    one = " UNION ALL ".join(f"SELECT {i}::INTEGER AS attr, {_config(OL, FIXED, i)} AS config, {n}::INTEGER AS value, count(*)::BIGINT AS n FROM p_ GROUP BY ALL" for i, n in enumerate(OL.names))
    return f"WITH {_v()}, {_part('P')} {one}"


def cpt_probs(spark, sf_dir):
    t = params.learn_parameters(split_of(spark, sf_dir, "P"), OL, FIXED)
    return t.select("attr", "config", F.posexplode("probs").alias("value", "p"))


def _cpt_probs_sql():
    return f"WITH {_v()}, {_part('P')} SELECT attr::INTEGER AS attr, config, value, p FROM ({_probs_sql(_cells_sql('p_', OL, FIXED))})"


def noisy_cpt(spark, sf_dir):
    return params.cells(params.counts(split_of(spark, sf_dir, "P"), OL, FIXED), params.all_configs(spark, OL, FIXED), 0.5, "cells")


def _noisy_cpt_sql():
    key = "'cells|' || attr || '|' || config || '|' || value"
    return f"WITH {_v()}, {_part('P')} SELECT attr::INTEGER AS attr, config, value, greatest(0.0, n + {laplace_sql('2.0', key)}) AS n FROM ({_cells_sql('p_', OL, FIXED)})"


# --- synthesis and tests


def synth_candidates(spark, sf_dir):
    return _values(synth.synthesize(fixed_model(spark, sf_dir), _seeds(spark, sf_dir), 7, SALT), OL)


def _synth_head(omega: int, graph: Graph = FIXED, salt: str = SALT) -> tuple[str, str]:
    text, last = _synth_sql("s_", "cpt", OL, graph, omega, salt)
    return f"WITH {_v()}, {_part('P')}, {_part('S')}, cpt AS MATERIALIZED ({_lists_sql(_cells_sql('p_', OL, graph))}), {text}", last


def _synth_candidates_sql():
    head, last = _synth_head(7)
    return f"{head} {_values_sql(last, OL)}"


def marginal_sample(spark, sf_dir):
    return _values(synth.synthesize(synth.marginal_model(split_of(spark, sf_dir, "P"), OL), _seeds(spark, sf_dir), len(OL), "marginal"), OL)


def _marginal_sample_sql():
    head, last = _synth_head(len(OL), params.without_parents(OL), "marginal")
    return f"{head} {_values_sql(last, OL)}"


KS, GRID = (10, 25, 50, 100, 200), (5, 6, 7, 8, 9, 10)


def pass_rate_grid(spark, sf_dir, grid=GRID):
    """Share of candidates that pass the deterministic test, for every k and omega, with all rows as seeds."""
    m = len(OL)
    index = deniability.prefix_counts(micro(spark, sf_dir), list(ORDER), [m - w for w in grid])
    rates = index.groupBy("depth").agg((F.sum(F.col("n") * F.col("n")) / F.sum("n")).alias("mean_plausible"), *[(F.sum(F.when(F.col("n") >= k, F.col("n")).otherwise(0)) / F.sum("n")).alias(f"k{k}") for k in KS])
    long = rates.select((F.lit(m) - F.col("depth")).cast("int").alias("omega"), "mean_plausible", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"k{k}").alias("pass_rate")) for k in KS])).alias("x"))
    return long.select("omega", "x.k", "mean_plausible", "x.pass_rate")


def pass_rate_whole_grid(spark, sf_dir):
    """As pass_rate_grid, with omega up to the number of attributes, where every row is plausible; it has no SQL of its own."""
    return pass_rate_grid(spark, sf_dir, range(GRID[0], len(OL) + 1))


def pass_rate_random(spark, sf_dir):
    """Share of candidates that pass the deterministic test at gamma 2 when each draws its omega from a set, for every k."""
    model, seeds, out = fixed_model(spark, sf_dir), _seeds(spark, sf_dir), None
    for omegas in RANDOM:
        counted = deniability.plausible_counts(model, synth.synthesize_random(model, seeds, omegas, SALT), seeds, omegas)
        one = counted.agg(*[F.avg((F.col("plausible") >= k).cast("double")).alias(f"k{k}") for k in KS]).select(F.lit(f"{omegas[0]}-{omegas[-1]}").alias("omegas"), F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"k{k}").alias("pass_rate")) for k in KS])).alias("x")).select("omegas", "x.*")
        out = one if out is None else out.unionByName(one)
    return out


def pass_rate_capped(spark, sf_dir, max_check: int = 100_000):
    """As pass_rate_random, with scans that stop after max_check seeds and the rows they look at; the scans' outcomes are drawn from their law."""
    model, seeds, out = fixed_model(spark, sf_dir), _seeds(spark, sf_dir), None
    for omegas in RANDOM:
        judged = release.judged(model, seeds, DeniabilityParams(max(KS), 2.0, max_check=max_check), omegas, SALT, seeds, "deterministic")
        one = judged.agg(F.avg("checked").alias("checked"), *[F.avg((F.col("plausible") >= k).cast("double")).alias(f"k{k}") for k in KS])
        one = one.select(F.lit(f"{omegas[0]}-{omegas[-1]}").alias("omegas"), "checked", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"k{k}").alias("pass_rate")) for k in KS])).alias("x")).select("omegas", "checked", "x.*")
        out = one if out is None else out.unionByName(one)
    return out


def _pass_rate_random_sql():
    m, parts = len(OL), []
    for omegas in RANDOM:
        pick = f"list_extract({list(omegas)}, floor({uniform_sql(f"'{SALT}|' || rk || '|omega'")} * {len(omegas)})::BIGINT + 1)"
        counts = ", ".join(f"count(*) OVER (PARTITION BY {', '.join(ORDER[: m - w])})::BIGINT AS c{w}" if w < m else f"count(*) OVER ()::BIGINT AS c{w}" for w in omegas)
        plausible = "CASE w " + " ".join(f"WHEN {w} THEN c{w}" for w in omegas) + " END"
        parts += [f"SELECT '{omegas[0]}-{omegas[-1]}' AS omegas, {k}::INTEGER AS k, avg(({plausible} >= {k})::INTEGER)::DOUBLE AS pass_rate FROM (SELECT {pick} AS w, {counts} FROM s_)" for k in KS]
    return f"WITH {_v()}, {_part('S').replace(' AS ', ' AS MATERIALIZED ', 1)} " + " UNION ALL ".join(parts)


def _pass_rate_sql():
    m, parts = len(OL), []
    for w in GRID:
        counted = f"SELECT count(*) OVER (PARTITION BY {', '.join(ORDER[: m - w])}) AS c FROM v"
        parts += [f"SELECT {w}::INTEGER AS omega, {k}::INTEGER AS k, avg(c) AS mean_plausible, avg((c >= {k})::INTEGER) AS pass_rate FROM ({counted})" for k in KS]
    return f"WITH {_v()} " + " UNION ALL ".join(parts)


def plausible_counts(spark, sf_dir):
    model, seeds, omegas = fixed_model(spark, sf_dir), _seeds(spark, sf_dir), (7, 8, 9)
    drawn = seeds.withColumn("omega", F.explode(F.array(*map(F.lit, omegas)))).withColumn("cand_id", F.concat_ws("#", "rk", "omega"))
    return deniability.plausible_counts(model, synth.synthesize_by(model, drawn, omegas, SALT), seeds, omegas).groupBy("omega", "plausible").agg(F.count("*").alias("candidates"))


def _plausible_sql():
    m = len(OL)
    one = " UNION ALL ".join(f"SELECT {w}::INTEGER AS omega, plausible, count(*)::BIGINT AS candidates FROM (SELECT count(*) OVER (PARTITION BY {', '.join(ORDER[: m - w])})::BIGINT AS plausible FROM s_) GROUP BY plausible" for w in (7, 8, 9))
    return f"WITH {_v()}, {_part('S')} {one}"


def deterministic_release(spark, sf_dir):
    model, seeds = fixed_model(spark, sf_dir), _seeds(spark, sf_dir)
    out = release.judged(model, seeds, DeniabilityParams(k=50, gamma=2.0), 7, SALT, seeds, "deterministic").where("passed")
    return _values(out.select(*OL.names), OL)


def _deterministic_sql():
    head, last = _synth_head(7)
    kept = ", ".join(ORDER[:4])
    return f"{head}, ok AS (SELECT {kept} FROM s_ GROUP BY {kept} HAVING count(*) >= 50), passed AS (SELECT y.* FROM {last} y JOIN ok USING ({kept})) {_values_sql('passed', OL)}"


def randomized_verdicts(spark, sf_dir):
    """By plausible seeds: candidates, how many passed the noisy threshold, and the closed form of that chance."""
    model, seeds = fixed_model(spark, sf_dir), _seeds(spark, sf_dir)
    out = release.judged(model, seeds, DeniabilityParams(k=50, gamma=2.0, eps0=1.0), 7, SALT, seeds)
    return out.groupBy("plausible").agg(F.count("*").alias("candidates"), F.count_if("passed").alias("released")).withColumn("chance", pass_probability(F.col("plausible"), 50, 1.0))


def _randomized_sql():
    kept = ", ".join(ORDER[:4])
    t = f"50 + {laplace_sql('1.0', f"'{SALT}|' || rk || '|threshold'")}"
    return f"""WITH {_v()}, {_part('S')}, c AS (SELECT rk, count(*) OVER (PARTITION BY {kept})::BIGINT AS plausible FROM s_)
SELECT plausible, count(*)::BIGINT AS candidates, (count(*) FILTER (plausible >= {t}))::BIGINT AS released,
  CASE WHEN plausible >= 50 THEN 1 - 0.5 * exp(-(plausible - 50)) ELSE 0.5 * exp(plausible - 50) END AS chance FROM c GROUP BY plausible"""


def release_sample(spark, sf_dir):
    """The mechanism end to end on a learned model: omega 9, k 50, gamma 4, both scan limits."""
    model = learned_model(spark, sf_dir)
    return release.release(model, split_of(spark, sf_dir, "S"), DeniabilityParams(50, 4.0, 1.0, 100, 50_000), 5000, 9, "sample")


def mixture_release(spark, sf_dir):
    """Pass counts when omega is drawn from a set and the test knows the set alone."""
    model, seeds = fixed_model(spark, sf_dir), _seeds(spark, sf_dir)
    out = release.judged(model, seeds, DeniabilityParams(50, 2.0), RANDOM[1], "mixture", seeds, "deterministic", "mixture")
    return out.groupBy("omega").agg(F.count("*").alias("candidates"), F.count_if("passed").alias("released"))


def pooled_release(spark, sf_dir):
    return release.pooled_release(fixed_model(spark, sf_dir), split_of(spark, sf_dir, "S"), DeniabilityParams(50, 4.0), 2000, (7, 8, 9), 3000, "pool")


CV, CK, CG = CONVERSATION.schema, 5, 2.0


def definition_check(spark, sf_dir):
    """Every possible record of a tiny domain against every seed, by depth of agreement: the definition and the test."""
    df = micro(spark, sf_dir, CONVERSATION)
    names, cards = CV.names, [a.card for a in CV.attributes]
    grid = spark.range(1).select(F.explode(F.sequence(F.lit(0), F.lit(cards[0] - 1))).alias(names[0]))
    for n, c in zip(names[1:], cards[1:], strict=True):
        grid = grid.withColumn(n, F.explode(F.sequence(F.lit(0), F.lit(c - 1))))
    total = df.count()
    y = grid
    for n, c in zip(names, cards, strict=True):
        y = y.join(F.broadcast(df.groupBy(n).agg(((F.count("*") + 1) / F.lit(float(total + c))).alias(f"_p{n}"))), n, "left").withColumn(f"_p{n}", F.coalesce(f"_p{n}", F.lit(1.0 / (total + c))))
    p = [F.col(f"_p{n}") for n in names]
    q = {1: p[2], 2: p[1] * p[2], 3: p[0] * p[1] * p[2]}  # omega -> chance of what is drawn anew
    for d in (1, 2):
        y = y.join(F.broadcast(df.groupBy(*names[:d]).agg(F.count("*").alias(f"_n{d}"))), names[:d], "left").withColumn(f"_n{d}", F.coalesce(f"_n{d}", F.lit(0)))
    # seeds that agree to exactly 0, 1, or 2 and more attributes
    tiers = [(0, F.lit(total) - F.col("_n1"), q[3] / 3), (1, F.col("_n1") - F.col("_n2"), (q[3] + q[2]) / 3), (2, F.col("_n2"), (q[3] + q[2] + q[1]) / 3)]
    rows = y.withColumn("cand_id", F.concat_ws(",", *names)).select("cand_id", F.explode(F.array(*[F.struct(F.lit(d).alias("depth"), n.cast("long").alias("n"), (-F.ln(lik)).alias("neglogp")) for d, n, lik in tiers])).alias("x")).select("cand_id", "x.*").where("n > 0")
    told = deniability.is_deniable(rows, CK, CG).withColumn("bucket", gamma_bucket(-F.col("neglogp"), CG))
    same = told.groupBy("cand_id", "bucket").agg(F.sum("n").alias("k_prime"))
    return told.join(same, ["cand_id", "bucket"]).select("cand_id", "depth", "n", F.col("bucket"), "k_prime", (F.col("k_prime") >= CK).alias("passes"), "deniable")


def _definition_sql():
    names, cards = CV.names, [a.card for a in CV.attributes]
    grid = ", ".join(f"(SELECT range::INTEGER AS {n} FROM range({c}))" for n, c in zip(names, cards, strict=True))
    p = [f"((SELECT count(*) FROM v WHERE v.{n} = g.{n}) + 1) / (SELECT count(*) + {c} FROM v)::DOUBLE" for n, c in zip(names, cards, strict=True)]
    a, b = names[:2]
    w = math.log(CG) + 1e-9
    return f"""WITH {_v(CONVERSATION)}, y AS (
  SELECT g.*, {p[0]} AS pa, {p[1]} AS pb, {p[2]} AS pc, (SELECT count(*) FROM v) AS n0, (SELECT count(*) FROM v WHERE v.{a} = g.{a}) AS n1, (SELECT count(*) FROM v WHERE v.{a} = g.{a} AND v.{b} = g.{b}) AS n2 FROM (SELECT * FROM {grid}) g),
r AS (SELECT {" || ',' || ".join(names)} AS cand_id, 0 AS depth, n0 - n1 AS n, -ln(pa * pb * pc / 3) AS x FROM y
  UNION ALL SELECT {" || ',' || ".join(names)}, 1, n1 - n2, -ln((pa * pb * pc + pb * pc) / 3) FROM y UNION ALL SELECT {" || ',' || ".join(names)}, 2, n2, -ln((pa * pb * pc + pb * pc + pc) / 3) FROM y),
k AS (SELECT *, floor(x / ln({CG}))::BIGINT AS bucket FROM r WHERE n > 0),
h AS (SELECT *, sum(n) OVER (PARTITION BY cand_id ORDER BY x RANGE BETWEEN CURRENT ROW AND {w!r} FOLLOWING) AS ahead, sum(n) OVER (PARTITION BY cand_id, bucket) AS k_prime FROM k)
SELECT cand_id, depth::INTEGER AS depth, n::BIGINT AS n, bucket, k_prime::BIGINT AS k_prime, k_prime >= {CK} AS passes,
  max(ahead) OVER (PARTITION BY cand_id ORDER BY x RANGE BETWEEN {w!r} PRECEDING AND CURRENT ROW) >= {CK} AS deniable FROM h"""


def release_budget_table(spark, sf_dir):
    """What one record costs that is released from the seeds S, by trade-off t; the seeds, those that at least k seeds could stand for at
    omega 7 (whose candidates pass), and the cost of releasing a candidate of each of these."""
    k, gamma, eps0 = 50, 4.0, 1.0
    order, seeds = list(ORDER[: len(OL) - 7]), split_of(spark, sf_dir, "S")
    found = seeds.groupBy(*order).agg(F.count("*").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("seeds"), F.coalesce(F.sum(F.when(F.col("n") >= k, F.col("n"))), F.lit(0)).alias("deniable"))
    cost = F.udf(lambda t, n: (*_pair(release_epsilon(k, gamma, eps0, t)), *_pair(compose(*_pair(release_epsilon(k, gamma, eps0, t)), n))), "eps double, delta double, all_eps double, all_delta double")
    return spark.range(1, k).crossJoin(F.broadcast(found)).select(F.col("id").alias("t"), "seeds", "deniable", cost("id", "deniable").alias("c")).select("t", "c.eps", "c.delta", "seeds", "deniable", "c.all_eps", "c.all_delta")


def _pair(b) -> tuple[float, float]:
    return float(b.eps), float(b.delta)


def _release_budget_sql():
    return f"""WITH {_v()}, {_part('S')}, g AS (SELECT count(*) AS n FROM s_ GROUP BY {', '.join(ORDER[:4])}),
c AS (SELECT coalesce(sum(n), 0)::BIGINT AS seeds, coalesce(sum(n) FILTER (n >= 50), 0)::BIGINT AS deniable FROM g),
b AS (SELECT range AS t, 1 + ln(1 + 4.0 / range) AS eps, exp(-(50.0 - range)) AS delta FROM range(1, 50))
SELECT t, eps, delta, seeds, deniable, deniable * eps AS all_eps, deniable * delta AS all_delta FROM b CROSS JOIN c"""


def sensitivity_table(spark, sf_dir):
    """Bound on the change of an entropy, by the records of each split of each view that it may be taken over."""
    bound, out = F.udf(lambda n: float(entropy_sensitivity(n)), "double"), None
    for view in (ORDERLINE, DOCUMENT, EVENT, CONVERSATION):
        name = F.element_at(F.array(*[F.lit(n) for n, _ in prep.SHARES]), F.col("_s0") + 1)
        one = dealt(spark, sf_dir, view).groupBy("_s0").agg(F.count("*").alias("n")).where("n >= 2").select(F.lit(view.schema.name).alias("view"), name.alias("split"), "n")
        out = one if out is None else out.unionByName(one)
    return out.withColumn("sensitivity", bound("n"))


def _sensitivity_sql():
    low, cases = 0.0, []
    for name, share in prep.SHARES:
        low += share
        cases.append(f"WHEN u < {low if low < 1 - 1e-12 else 2.0!r} THEN '{name}'")
    each = [f"SELECT view, split, n, (2 + 1 / ln(2) + 2 * log2(n)) / n AS sensitivity FROM (WITH {_v(view)} SELECT '{view.schema.name}' AS view, CASE {' '.join(cases)} END AS split, count(*)::BIGINT AS n FROM v GROUP BY 2) WHERE n >= 2" for view in (ORDERLINE, DOCUMENT, EVENT, CONVERSATION)]
    return " UNION ALL ".join(each)


# --- utility


def tv_single(spark, sf_dir):
    return distance.tv_distance(split_of(spark, sf_dir, "S"), split_of(spark, sf_dir, "other"), OL)


def tv_pairs(spark, sf_dir):
    return distance.tv_distance(split_of(spark, sf_dir, "S"), split_of(spark, sf_dir, "other"), OL, True)


def _tv_sql(pairs: bool) -> str:
    parts = []
    for i, j in combinations(range(len(OL)), 2) if pairs else [(i, i) for i in range(len(OL))]:
        x, y = OL.names[i], OL.names[j]
        label, key = (f"{x},{y}", f"{x} * 1000 + {y}") if pairs else (x, x)
        one = lambda t, key=key: f"(SELECT {key} AS k, count(*) / (SELECT count(*) FROM {t})::DOUBLE AS p FROM {t} GROUP BY 1)"
        parts.append(f"SELECT '{label}' AS attrs, 0.5 * sum(abs(coalesce(a.p, 0) - coalesce(b.p, 0))) AS distance FROM {one('s_')} a FULL JOIN {one('other_')} b ON a.k = b.k")
    return f"WITH {_v()}, {_part('S')}, {_part('other')} " + " UNION ALL ".join(parts)


def tv_boxplot(spark, sf_dir):
    return distance.boxplot(tv_pairs(spark, sf_dir))


def _tv_boxplot_sql():
    q = ", ".join(f"quantile_cont(distance, {x}) AS {n}" for x, n in ((0.0, "low"), (0.25, "q1"), (0.5, "median"), (0.75, "q3"), (1.0, "high")))
    return f"SELECT {q} FROM ({_tv_sql(True)})"


#: What the experiments compare: omegas (by how many attributes fewer than all) of each set of synthetics.
CASES = {"omega all": (0,), "omega -1": (1,), "omega -2": (2,), "omega -2 to all": (2, 1, 0), "omega -6 to all": (6, 5, 4, 3, 2, 1, 0)}


def case_names(m: int) -> dict[str, tuple[int, ...]]:
    """omega m, m - 1, m - 2, m-2..m and m-6..m, with their omegas."""
    return {(f"omega {m - less[0]}" if len(less) == 1 else f"omega {m - less[0]}-{m}"): tuple(m - x for x in less) for less in CASES.values()}


def kinds_salt(run: int, what: str = "kinds") -> str:
    return f"{what}-{run}" if run else what


def dealt(spark, sf_dir, view: View = ORDERLINE, runs=(0,)) -> DataFrame:
    """The rows of a view and, for each run, the number of their split in it (_s<run>): to be held, as many scans follow."""
    return micro(spark, sf_dir, view).select("rk", *view.schema.names, *[prep.dealt(salt=run_salt(r)).alias(f"_s{r}") for r in runs])


def of_split(data: DataFrame, which: str, run: int = 0) -> DataFrame:
    return data.where(F.col(f"_s{run}") == prep.number_of(which))


def learned_cases(data: DataFrame, view: View = ORDERLINE, runs=(0,), eps: float = 1.0) -> dict[int, list[Case]]:
    """By run, the sets of made data that are compared: eps-private marginals, and synthetics of an eps-private model by omega (all attributes,
    one and two less, and two random choices). Each run learns from its own deal of the rows with noise of its own; one scan of all
    runs' rows T, one of their rows P."""
    schema = view.schema
    m, k, delta = len(schema), 50, 2.0**-30
    e_entropy, e_count = calibrate(eps, m, delta)

    def rows_of(which):
        mine = [F.when(F.col(f"_s{r}") == prep.number_of(which), F.lit(g)) for g, r in enumerate(runs)]
        return data.select(*schema.names, F.explode(F.array(*mine)).alias("_g")).where("_g IS NOT NULL")

    graphs, alone = [], params.without_parents(schema)
    for r, (values, n) in zip(runs, info.entropy_sets_of(rows_of("T"), schema, len(runs)), strict=True):
        noisy = info.with_noise(values, n, e_entropy, 0.01, f"{kinds_salt(r)}-structure")
        graphs.append(structure.learn_structure(info.correlations(noisy, m), schema, min_gain=0.02))
    counts = params.counts_by_group(rows_of("P"), schema, [[g, alone] for g in graphs])
    sizes = data.agg(*[F.count_if(F.col(f"_s{r}") == prep.number_of("S")) for r in runs]).first()
    out = {}
    for r, graph, counted, seeds in zip(runs, graphs, counts, sizes, strict=True):
        # every attribute's counts are noised, so the marginals pay as the model's parameters do
        out[r] = [Case("marginals", alone, params.learn_tables(counted, schema, alone, eps=e_count, salt=kinds_salt(r, "kinds-marginals")), (m,))]
        if seeds >= k:  # the mechanism releases nothing from fewer than k seeds
            tables = params.learn_tables(counted, schema, graph, estimator="sampled", eps=e_count, salt=f"{kinds_salt(r)}-parameters")
            out[r] += [Case(name, graph, tables, omegas, k) for name, omegas in case_names(m).items()]
    return out


def case_seeds(data: DataFrame, schema: Schema, cases: list[Case], run: int = 0, some=lambda df: df) -> DataFrame:
    """Some rows S of a run, each a seed of every case, with the counts of their prefixes among all rows S."""
    graph = cases[-1].graph
    depths = {len(schema) - w for c in cases for w in c.omegas}
    return with_counts(some(of_split(data, "S", run)).select("rk", *schema.names), of_split(data, "S", run), [schema.names[i] for i in graph.order], depths)


def kinds(data: DataFrame, schema: Schema, cases: list[Case], run: int = 0, some=lambda df: df) -> DataFrame:
    """kind, rk and the attributes of the candidates of learned_cases() that pass; some: a choice of seeds, before anything is drawn."""
    return candidates(case_seeds(data, schema, cases, run, some), schema, cases, kinds_salt(run))


def sampled(df: DataFrame, total: int, share: float, records: int, salt: str) -> DataFrame:
    """About records rows of a share of total rows, by a keyed number of their own; all where there are fewer."""
    keep = records / max(1.0, share * total)
    return df if keep >= 1 else df.where(uniform(f"{salt}-sample", "rk") < keep)


@contextmanager
def held(*frames: DataFrame):
    """Frames that are read many times, computed once; plans that begin like theirs read them. Joins whose one side is small in every partition,
    as measured when it has been shuffled, are hashed in place of sorted."""
    conf, name = frames[0].sparkSession.conf, "spark.sql.adaptive.maxShuffledHashJoinLocalMapThreshold"
    before = conf.get(name)
    conf.set(name, "64MB")
    for df in frames:
        df.persist()
    try:
        yield
    finally:
        conf.set(name, before)
        for df in frames:
            df.unpersist()


def run_salt(run: int) -> str:
    """The salt of the split of one of several independent runs; run 0 has the split of all other queries."""
    return f"{prep.SALT}-{run}" if run else prep.SALT


def tv_synthetic(spark, sf_dir):
    """Box plots of the distances to S, single attributes and pairs, for every kind of data."""
    sets, data = distance.sets_of(OL, False) + distance.sets_of(OL, True), dealt(spark, sf_dir)
    with held(data):
        cases = learned_cases(data)[0]
        real = of_split(data, "S").withColumn("kind", F.lit("_real")).unionByName(of_split(data, "other").withColumn("kind", F.lit("reals")))
        # candidates are counted where they are drawn, and never written
        found = distance.counted(real, OL, sets, "kind").unionByName(histograms(case_seeds(data, OL, cases), OL, cases, sets, kinds_salt(0)))
        rows = [(kind, pairs, *box) for kind, own in distance.boxes(found, sets, "_real").items() for pairs, box in own.items()]
    return spark.createDataFrame(rows, "kind string, pairs boolean, low double, q1 double, median double, q3 double, high double")


def attribute_baselines(spark, sf_dir):
    return predict.baselines(split_of(spark, sf_dir, "P"), split_of(spark, sf_dir, "test"), OL)


def _baselines_sql():
    parts = [f"SELECT '{a.name}' AS attr, avg(({a.name} = (SELECT {a.name} FROM p_ GROUP BY {a.name} ORDER BY count(*) DESC, {a.name} LIMIT 1))::INTEGER)::DOUBLE AS marginal_accuracy, {1.0 / a.card!r}::DOUBLE AS random_accuracy FROM test_" for a in OL.attributes]
    return f"WITH {_v()}, {_part('P')}, {_part('test')} " + " UNION ALL ".join(parts)


def model_error(spark, sf_dir, models: int = 20):
    """Errors of the model without noise and at epsilon 1 and 0.1, and of the marginals; improvement over the last. Those of an
    epsilon are means over that many models, each learned with noise of its own; all are learned and tried in one scan each."""
    cases = {f"error-{eps}-{t}": eps for eps in (None, 1.0, 0.1) for t in range(1 if eps is None else models)}
    graphs = learned_graphs(split_of(spark, sf_dir, "T"), OL, cases)
    tables = learned_tables(split_of(spark, sf_dir, "P"), OL, graphs, cases)
    test = split_of(spark, sf_dir, "test")
    base = {r["attr"]: 1 - r["marginal_accuracy"] for r in predict.baselines(split_of(spark, sf_dir, "P"), test, OL).collect()}
    total: dict[tuple, float] = {}
    for r in predict.model_errors(OL, {k: (graphs[k], tables[k]) for k in cases}, test).collect():
        at = (cases[r["model"]], r["attr"])
        total[at] = total.get(at, 0.0) + r["error"] / (1 if cases[r["model"]] is None else models)
    rows = [("marginals", a, float(e), 0.0) for a, e in base.items()]
    rows += [(f"eps {eps}", a, float(e), float((base[a] - e) / base[a]) if base[a] > 0 else 0.0) for (eps, a), e in total.items()]
    return spark.createDataFrame(rows, "model string, attr string, error double, improvement double")


RECORDS = 100_000


def forest_accuracy(spark, sf_dir, records: int = RECORDS):
    """Accuracy of a random forest for each attribute, trained on about `records` rows, beside the model's."""
    total = micro(spark, sf_dir).count()
    train = sampled(split_of(spark, sf_dir, "P"), total, 0.1875, records, "forest")
    test = split_of(spark, sf_dir, "test")
    rows = sampled(test, total, 0.07, records, "forest").withColumn("_role", F.lit("test")).unionByName(train.withColumn("_role", F.lit("train")))
    each = rows.withColumn("attr", F.explode(F.array(*map(F.lit, OL.names))))

    def tried(pdf):
        a = pdf["attr"].iloc[0]
        x, y = pdf[pdf["_role"] == "train"], pdf[pdf["_role"] == "test"]
        hit = float((bounded.trained("rf", x, OL, a)(y) == y[a]).mean()) if len(x) and len(y) else 0.0
        return type(pdf)({"attr": [a], "forest": [hit]})

    own = predict.model_error(learned_model(spark, sf_dir), test).select("attr", (1 - F.col("error")).alias("model"))
    return each.groupBy("attr").applyInPandas(tried, "attr string, forest double").join(F.broadcast(own), "attr")


def _learner_of(schema: Schema, target: str):
    """One classifier trained on one set of a run, on its rows and the test rows: what it tells of the test rows, in the order of their keys."""

    def tried(pdf):
        pdf = pdf.sort_values(["rk", *schema.names])
        test, own = pdf[pdf["kind"] == "_test"], pdf[pdf["kind"] != "_test"]
        got = []
        if len(test) and len(own):
            run, c, of = pdf[["run", "classifier", "of"]].iloc[0]
            guess = bounded.trained(c, own, schema, target)(test)
            got = [(run, c, of, guess.astype(np.int32).tobytes(), test[target].to_numpy(np.int32).tobytes())]
        return type(pdf)(got, columns=["run", "classifier", "of", "guess", "truth"])

    return tried


def _compared(pdf):
    """Accuracy, and agreement with the yardstick, of the classifiers of one run and kind."""
    codes = lambda b: np.frombuffer(b, np.int32)
    yard, got = pdf[pdf["of"] == "_yard"], []
    if len(yard):
        other = codes(yard["guess"].iloc[0])
        for r in pdf[pdf["of"] != "_yard"].itertuples():
            guess = codes(r.guess)
            got.append((r.of, r.classifier, float((guess == codes(r.truth)).mean()), float((guess == other).mean())))
    return type(pdf)(got, columns=["kind", "classifier", "accuracy", "agreement"])


def classifier_table(spark, sf_dir, runs: int = 5, records: int = RECORDS):
    """Accuracy on reals, and agreement with the classifier trained on reals, by target, classifier and training data; means
    over runs whose training and test rows are drawn anew, about `records` of each. `runs` counts those that had rows to train on (few labelled
    documents may leave nothing to release); without any, the measures are null. All runs are dealt, counted and sampled in one scan each, and
    all classifiers are trained side by side: a task for each run, training set and classifier."""
    rows, every = [], tuple(range(runs))
    for view, target in ((ORDERLINE, "netc"), (DOCUMENT, "quality")):
        schema, all_rows, data = view.schema, dealt(spark, sf_dir, view, every), None
        with held(all_rows):
            total, cases = all_rows.count(), learned_cases(all_rows, view, every)
            # the sampled rows of S, P and test of every run; synthetics have the seeds that are the run's reals
            share, col = dict(prep.SHARES), lambda r: F.col(f"_s{r}")
            keep = lambda r: F.element_at(F.array(*[F.lit(records / max(1.0, share[n] * total) if n in ("S", "P", "test") else 0.0) for n, _ in prep.SHARES]), col(r) + 1)  # noqa: E731, B023
            drawn = lambda r: F.when(keep(r) > 0, keep(r) > uniform(f"table-{r}-sample", "rk"))  # noqa: E731, B023
            mine = [F.when(drawn(r), F.struct(F.lit(r).alias("run"), col(r).alias("part"))) for r in every]
            picked = all_rows.select("rk", *schema.names, F.explode(F.array(*mine)).alias("_p")).where("_p IS NOT NULL").select("rk", *schema.names, "_p.*")
            with held(picked):
                roles = {"S": "reals", "P": "_yard", "test": "_test"}  # the yardstick is trained on another real sample
                role = F.element_at(F.array(*[F.lit(roles.get(n, "")) for n, _ in prep.SHARES]), F.col("part") + 1)
                data = picked.select(role.alias("kind"), "rk", *schema.names, "run")
                for r in every:
                    own = picked.where((F.col("run") == r) & (F.col("part") == prep.number_of("S")))
                    data = data.unionByName(kinds(all_rows, schema, cases[r], r, lambda _, own=own: own).withColumn("run", F.lit(r)))
                sets = ("_yard", "reals", "marginals", *case_names(len(schema)))
                # each set meets the test rows of its run
                of = F.explode(F.when(F.col("kind") == "_test", F.array(*map(F.lit, sets))).otherwise(F.array("kind")))
                each = data.withColumn("of", of).withColumn("classifier", F.explode(F.array(*map(F.lit, bounded.MAKERS))))
                # small groups of long work, which are not to be coalesced by their bytes
                each = each.repartition(runs * len(sets) * len(bounded.MAKERS), "run", "classifier", "of")
                told = each.groupBy("run", "classifier", "of").applyInPandas(_learner_of(schema, target), "run int, classifier string, of string, guess binary, truth binary")
                found = told.groupBy("run", "classifier").applyInPandas(_compared, "kind string, classifier string, accuracy double, agreement double")
                mean = {(r["kind"], r["classifier"]): (r["a"], r["g"], r["n"]) for r in found.groupBy("kind", "classifier").agg(F.avg("accuracy").alias("a"), F.avg("agreement").alias("g"), F.count("*").alias("n")).collect()}
        rows += [(target, k, c, *mean.get((k, c), (None, None, 0))) for k in ("reals", "marginals", *case_names(len(schema))) for c in bounded.MAKERS]
    return spark.createDataFrame(rows, "target string, training string, classifier string, accuracy double, agreement double, runs long")


LAMBDAS = (1e-3, 1e-4, 1e-5, 1e-6)


def private_classifier_table(spark, sf_dir, records: int = RECORDS, salt: str = "private classifiers"):
    """Linear classifiers on reals without and with privacy, and without it on marginals and every kind of synthetics, trained on about `records` rows
    each; lambda is, for each loss, the value at which the classifier of reals without privacy is best."""
    all_rows = dealt(spark, sf_dir)
    with held(all_rows):
        total, target = all_rows.count(), "netc"
        part = lambda which, share: sampled(of_split(all_rows, which), total, share, records, "linear")
        made = kinds(all_rows, OL, learned_cases(all_rows)[0], some=lambda df: sampled(df, total, 0.49, records, "linear"))
        data = made.unionByName(part("S", 0.49).select(F.lit("reals").alias("kind"), "rk", *OL.names))
        every = F.explode(F.array(*map(F.lit, ("reals", "marginals", *case_names(len(OL))))))
        test = part("test", 0.07).select(every.alias("kind"), "rk", *OL.names)
        data = data.withColumn("_test", F.lit(False)).unionByName(test.withColumn("_test", F.lit(True))).persist()

        def sides(pdf):
            x, y = learners.encode(pdf, OL, target), np.where(pdf[target].to_numpy() == 1, 1.0, -1.0)
            held = pdf["_test"].to_numpy(bool)
            return x[~held], y[~held], x[held], y[held]

        hit = lambda w, x, y: float((np.where(x @ w > 0, 1.0, -1.0) == y).mean()) if len(y) else 0.0

        def grid(pdf):
            x, y, tx, ty = sides(pdf)
            loss, lam = pdf["loss"].iloc[0], float(pdf["lam"].iloc[0])
            return type(pdf)({"loss": [loss], "lam": [lam], "accuracy": [hit(learners.minimise_arrays(x, y, loss, lam), tx, ty)]})

        # a task for each loss and lambda
        tried = data.where("kind = 'reals'").withColumn("loss", F.explode(F.array(F.lit("lr"), F.lit("svm")))).withColumn("lam", F.explode(F.array(*map(F.lit, LAMBDAS))))
        best: dict[str, tuple] = {}
        for r in tried.groupBy("loss", "lam").applyInPandas(grid, "loss string, lam double, accuracy double").collect():
            best[r["loss"]] = max(best.get(r["loss"], (-1.0, 0.0)), (r["accuracy"], r["lam"]))

        def fitted(pdf):
            x, y, tx, ty = sides(pdf)
            kind, got = pdf["kind"].iloc[0], []
            for loss in ("lr", "svm") if len(x) else ():
                fit = lambda lam, push, loss=loss: learners.minimise_arrays(x, y, loss, lam, push)
                for how in (None, "output", "objective") if kind == "reals" else (None,):
                    w = learners.private_weights(fit, len(x), x.shape[1], loss, best[loss][1], how, 1.0, salt, OL.name, target)
                    got.append((kind, loss, how or "none", best[loss][1], hit(w, tx, ty)))
            return type(pdf)(got, columns=["training", "loss", "privacy", "lam", "accuracy"])

        rows = data.groupBy("kind").applyInPandas(fitted, "training string, loss string, privacy string, lam double, accuracy double").collect()
        data.unpersist()
        return spark.createDataFrame(rows, "training string, loss string, privacy string, lam double, accuracy double")


def distinguishing_game(spark, sf_dir, records: int = 75_000):
    """How well a tree and a forest tell reals from each kind of data: as many of both sides (about `records` at most), two thirds to train and the
    rest to test; 1/2 says they cannot be told apart."""
    data = dealt(spark, sf_dir)
    with held(data):
        total, names = data.count(), ("reals", "marginals", *case_names(len(OL)))
        label = learners.with_label(OL)
        real = sampled(of_split(data, "T"), total, 0.1875, records, "game").withColumn("kind", F.explode(F.array(*map(F.lit, names))))
        made = kinds(data, OL, learned_cases(data)[0], some=lambda df: sampled(df, total, 0.49, records, "game"))
        others = of_split(data, "other").select(F.lit("reals").alias("kind"), "rk", *OL.names).unionByName(made)
        mixed = real.withColumn("_real", F.lit(1)).select("kind", "rk", *label.names).unionByName(others.withColumn("_real", F.lit(0)).select("kind", "rk", *label.names)).withColumn("_u", uniform("game", "kind", "_real", "rk"))

        def played(pdf):
            return learners.play(pdf, label)

        form = "kind string, classifier string, accuracy double, records long"
        return spark.createDataFrame(mixed.groupBy("kind").applyInPandas(played, form).collect(), form)


def event_drift(spark, sf_dir):
    return daily_drift(read_table(spark, sf_dir, "events"))


EVENT_DRIFT_SQL = """
WITH d AS (SELECT date_trunc('day', ts)::DATE AS day, event_type, count(*) AS n FROM events GROUP BY ALL),
r AS (SELECT event_type, count(*) / (SELECT count(*) FROM events)::DOUBLE AS q FROM events GROUP BY 1),
t AS (SELECT day, sum(n) AS total FROM d GROUP BY 1)
SELECT strftime(t.day, '%Y-%m-%d') AS day, sum(total)::BIGINT // count(*) AS n, 0.5 * sum(abs(coalesce(d.n, 0) / total - q)) AS distance
FROM t CROSS JOIN r LEFT JOIN d ON d.day = t.day AND d.event_type = r.event_type GROUP BY t.day
"""

QUERIES = {
    f.__name__: f
    for f in (
        attribute_profile, clean_counts, bucketized, split_sizes, entropies, correlations, noisy_entropies, merit_scores, learned_edges, wide_structure, cpt_counts, cpt_probs, noisy_cpt,
        synth_candidates, marginal_sample, pass_rate_grid, pass_rate_whole_grid, pass_rate_random, pass_rate_capped, plausible_counts, deterministic_release, randomized_verdicts, release_sample, mixture_release, pooled_release, definition_check,
        release_budget_table, sensitivity_table, tv_single, tv_pairs, tv_boxplot, tv_synthetic, attribute_baselines, model_error, forest_accuracy, classifier_table, private_classifier_table,
        distinguishing_game, event_drift,
    )
} | {"dataset_profile": lambda spark, sf_dir: prep.profile(ORDERLINE.build(spark, sf_dir), OL)}
SQL = {
    "attribute_profile": _attribute_profile_sql(), "dataset_profile": f"WITH {_v()} {_profile_sql(ORDERLINE)}", "clean_counts": _clean_counts_sql(), "bucketized": _bucketized_sql(), "split_sizes": _split_sizes_sql(),
    "entropies": _entropies_sql(), "correlations": _correlations_sql(), "noisy_entropies": _noisy_entropies_sql(), "merit_scores": _merit_sql(), "cpt_counts": _cpt_counts_sql(), "cpt_probs": _cpt_probs_sql(),
    "noisy_cpt": _noisy_cpt_sql(), "synth_candidates": _synth_candidates_sql(), "marginal_sample": _marginal_sample_sql(), "pass_rate_grid": _pass_rate_sql(), "pass_rate_random": _pass_rate_random_sql(), "plausible_counts": _plausible_sql(),
    "deterministic_release": _deterministic_sql(), "randomized_verdicts": _randomized_sql(), "definition_check": _definition_sql(), "release_budget_table": _release_budget_sql(), "sensitivity_table": _sensitivity_sql(),
    "tv_single": _tv_sql(False), "tv_pairs": _tv_sql(True), "tv_boxplot": _tv_boxplot_sql(), "attribute_baselines": _baselines_sql(), "event_drift": EVENT_DRIFT_SQL,
}
