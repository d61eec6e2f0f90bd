import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from synthguard.functions import scalar
from synthguard.functions.noise import laplace, laplace_value, uniform, uniform_value
from synthguard.operators import deniability, distance, info, params, prep, release, structure, synth
from synthguard.plans import budget
from synthguard.plans.schema import DeniabilityParams, Graph, Schema, categorical, topological
from synthguard.workloads import FIXED, OL

TOY = Schema("toy", (categorical("a", range(2)), categorical("b", range(3)), categorical("c", range(2)), categorical("d", range(3))))
TOY_GRAPH = Graph(((), (0,), (1,), (2,)), (0, 1, 2, 3))


def toy_rows(n=200, seed=3):
    rng = np.random.default_rng(seed)
    a = rng.integers(0, 2, n)
    b = (a + (rng.random(n) < 0.3) + (rng.random(n) < 0.1)) % 3
    c = (b > 0).astype(int) ^ (rng.random(n) < 0.2)
    d = (c + rng.integers(0, 2, n)) % 3
    return [(str(i), *map(int, r)) for i, r in enumerate(zip(a, b, c, d, strict=True))]


@pytest.fixture(scope="module")
def toy(spark):
    df = spark.createDataFrame(toy_rows(), "rk string, a int, b int, c int, d int").cache()
    model = synth.Model(TOY, TOY_GRAPH, params.learn_parameters(df, TOY, TOY_GRAPH).cache())
    return df, model


def test_keyed_draws_agree_with_python(spark):
    r = spark.range(1).select(uniform("s", F.lit("a")).alias("u"), laplace(2.0, "s", F.lit("a")).alias("l")).first()
    assert r["u"] == uniform_value("s", "a") == 0.18710061089238017
    assert r["l"] == pytest.approx(laplace_value(2.0, "s", "a"))


def test_gamma_bucket_edges(spark):
    for gamma in (1.5, 2.0, 4.0):
        rows = [(i, -i * math.log(gamma)) for i in range(30)]
        df = spark.createDataFrame(rows, "i int, logp double").withColumn("b", scalar.gamma_bucket(F.col("logp"), gamma))
        assert all(r["b"] == r["i"] for r in df.collect())
    null = spark.createDataFrame([(None,), (float("-inf"),)], "logp double").withColumn("b", scalar.gamma_bucket(F.col("logp"), 2.0))
    assert all(r["b"] is None for r in null.collect())


def test_budget_worked_values():
    t = budget.best_t(50, 4.0, 1.0, 2.0**-30)
    assert t == 29
    b = budget.release_epsilon(50, 4.0, 1.0, t)
    assert b.eps == pytest.approx(1.1292, abs=1e-4) and b.delta == pytest.approx(7.58e-10, rel=1e-2)
    assert budget.entropy_sensitivity(280_000) == pytest.approx(1.4155e-4, rel=1e-3)
    assert budget.amplify(budget.Budget(1.0, 0.0), 280_000 / 1_494_974).eps == pytest.approx(0.279, abs=1e-3)
    e_h, e_p = budget.calibrate(1.0, 11, 2.0**-30)
    assert e_h == pytest.approx(0.01306, abs=1e-5) and e_p == pytest.approx(0.04566, abs=1e-5)
    assert budget.min_k(10, 2, 1.0, 1000) == math.ceil(10 + 2 * math.log(1000))
    with pytest.raises(ValueError):
        DeniabilityParams(k=50, max_plausible=10)


def test_randomized_threshold_ratio():
    p = lambda n: 1 - 0.5 * math.exp(-(n - 10)) if n >= 10 else 0.5 * math.exp(n - 10)
    assert all(p(n + 1) <= math.e * p(n) + 1e-12 for n in range(40))
    assert all(p(t) <= math.exp(-(10 - t)) for t in range(1, 10))


def _likelihood(probs, y, d, omega):
    """Brute force: chance that the re-sampler makes y of d."""
    m, out = 4, 1.0
    for r in range(m):
        if r < m - omega:
            if y[r] != d[r]:
                return 0.0
        else:
            parent = y[r - 1] if r else 0
            out *= probs[r][parent][y[r]]
    return out


def _tables(model):
    got = {}
    for r in model.table.collect():
        got.setdefault(r["attr"], {})[r["config"]] = r["probs"]
    return got


def test_prefix_counts_equal_all_pairs(spark, toy):
    df, model = toy
    probs, rows = _tables(model), [tuple(r)[1:] for r in df.collect()]
    seeds = df.withColumn("cand_id", F.col("rk"))
    for omega in (1, 2, 3, 4):
        got = deniability.plausible_counts(model, synth.synthesize(model, seeds, omega, "x"), df).collect()
        by_id = {r["rk"]: tuple(r)[1:5] for r in df.collect()}
        for r in got[:40]:
            y, own = (r["a"], r["b"], r["c"], r["d"]), by_id[r["cand_id"]]
            q = _likelihood(probs, y, own, omega)
            assert q > 0 and math.exp(r["logq"]) == pytest.approx(q)
            bucket = math.floor(-math.log(q) / math.log(2))
            same = sum(1 for d in rows if (p := _likelihood(probs, y, d, omega)) > 0 and math.floor(-math.log(p) / math.log(2)) == bucket)
            assert same == r["plausible"]


@pytest.mark.parametrize("gamma", [1.5, 4.0])
def test_mixture_equals_all_pairs(spark, toy, gamma):
    df, model = toy
    probs, rows, omegas = _tables(model), [tuple(r)[1:] for r in df.collect()], (2, 3, 4)
    out = release.judged(model, df, DeniabilityParams(5, gamma), omegas, "m", df.withColumn("cand_id", F.col("rk")), "deterministic", "mixture").collect()
    by_id = {r["rk"]: tuple(r)[1:5] for r in df.collect()}
    for r in out[:40]:
        y = (r["a"], r["b"], r["c"], r["d"])
        lik = lambda d, y=y: sum(_likelihood(probs, y, d, w) for w in omegas) / 3
        b = lambda p: math.floor(-math.log(p) / math.log(gamma) + 1e-9)
        own = b(lik(by_id[r["cand_id"]]))
        assert r["plausible"] == sum(1 for d in rows if lik(d) > 0 and b(lik(d)) == own)


def test_likelihoods_sum_to_one(toy):
    probs = _tables(toy[1])
    for omega in (1, 2, 3, 4):
        total = sum(_likelihood(probs, y, (1, 2, 0, 1), omega) for y in itertools.product(range(2), range(3), range(2), range(3)))
        assert total == pytest.approx(1.0)


def test_release_shows_attributes_only_and_is_stable(spark, toy):
    df, model = toy
    p = DeniabilityParams(5, 2.0, 1.0)
    one = release.judged(model, df, p, 3, "r", df.withColumn("cand_id", F.col("rk"))).where("passed").select(*TOY.names)
    two = release.judged(model, df.repartition(7), p, 3, "r", df.repartition(3).withColumn("cand_id", F.col("rk"))).where("passed").select(*TOY.names)
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, two.collect()))
    assert release.release(model, df, p, 50, 3, "r").columns == TOY.names
    with pytest.raises(ValueError):
        release.release(model, df.limit(3), p, 5, 3, "r")
    with pytest.raises(ValueError):
        synth.synthesize(model, df, 0, "r", "rk")


def test_capped_law_matches_scan(spark):
    n, k = 400, 60
    cands = spark.range(300).select(F.col("id").cast("string").alias("cand_id"), F.lit(k).cast("long").alias("plausible"))
    law = deniability.capped(cands, n, 20, 100, "law").agg(F.avg("plausible"), F.avg("checked")).first()
    pairs = spark.range(300).select(F.col("id").cast("string").alias("cand_id")).crossJoin(spark.range(n).select(F.col("id").cast("string").alias("rk"), (F.col("id") < k).alias("plausible")))
    scan = deniability.capped_scan(pairs, 20, 100, "scan").agg(F.avg("plausible"), F.avg("checked")).first()
    assert law[0] == pytest.approx(scan[0], abs=0.8) and law[1] == pytest.approx(scan[1], abs=2.5)


def test_generic_test_and_definition(spark, toy):
    df, _ = toy
    cands = df.limit(10).select(F.col("rk").alias("cand_id"), F.struct("a", "b").alias("y"), F.struct("a", "b").alias("seed"))
    logp = F.when(F.col("y.a") == F.col("d.a"), F.lit(math.log(0.5))).otherwise(F.lit(None).cast("double"))
    got = deniability.generic_counts(cands, df.select(F.struct("a", "b").alias("d")), logp, 2.0)
    own = {r["cand_id"]: r["y"]["a"] for r in cands.collect()}
    want = {k: df.where(F.col("a") == a).count() for k, a in own.items()}
    assert {r["cand_id"]: r["plausible"] for r in got.collect()} == want
    seeds = df.select("rk", F.struct("a", "b").alias("d"))
    assert {r["cand_id"]: r["plausible"] for r in deniability.generic_counts(cands, seeds, logp, 2.0, block=3).collect()} == want
    some = {r["cand_id"]: r["plausible"] for r in deniability.generic_counts(cands, seeds, logp, 2.0, block=3, max_check=40).collect()}
    assert all(0 < some[k] <= min(40, want[k]) for k in want)
    # records on both sides of a bucket's edge: the definition holds, the test does not
    rows = spark.createDataFrame([("y", 0.9 * math.log(2), 3), ("y", 1.1 * math.log(2), 3)], "cand_id string, neglogp double, n long")
    told = deniability.is_deniable(rows, 6, 2.0).withColumn("b", scalar.gamma_bucket(-F.col("neglogp"), 2.0)).collect()
    assert all(r["deniable"] for r in told) and len({r["b"] for r in told}) == 2


def _bits(counts):
    n = sum(counts)
    return math.log2(n) - sum(c * math.log2(c) for c in counts if c) / n


def test_entropy_sensitivity_bound_holds():
    rng = np.random.default_rng(1)
    for _ in range(300):
        c = rng.integers(0, 6, 4)
        if c.sum() >= 2:
            for i in range(4):
                d = c.copy()
                d[i] += 1
                assert abs(_bits(d.tolist()) - _bits(c.tolist())) <= budget.entropy_sensitivity(int(c.sum()))


def test_structure_greedy_exhaustive_and_independence(spark, toy):
    values, n = info.entropy_sets(toy[0], TOY)
    assert n == 200
    c = info.correlations(values, 4)
    g = structure.learn_structure(c, TOY, min_gain=0.02)
    best, top = structure.exhaustive_structure(c, TOY)
    assert sum(info.merit(i, ps, c) for i, ps in enumerate(g.parents)) <= top + 1e-9
    assert all(structure.config_cost(ps, TOY) <= 1000 for ps in (*g.parents, *best.parents))
    # a copy of a parent earns nothing
    c2 = np.array([[1, 1, 1], [1, 1, 1], [1, 1, 1.0]])
    assert info.merit(0, (1, 2), c2) == pytest.approx(1.0)
    rows = [(str(i), i % 2, (i // 2) % 3, (i // 6) % 2, (i // 12) % 3) for i in range(720)]
    free = structure.learn(spark.createDataFrame(rows, "rk string, a int, b int, c int, d int"), TOY, min_gain=0.01)
    assert not free.edges
    with pytest.raises(ValueError):
        topological([(1,), (0,)])


def test_parameters(spark, toy):
    df, _ = toy
    graph = TOY_GRAPH
    every = params.all_configs(spark, TOY, graph)
    assert every.count() == 1 + 2 + 3 + 2
    noisy = params.cells(params.counts(df, TOY, graph), every, 0.5, "n")
    assert noisy.count() == 2 + 6 + 6 + 6 and noisy.where("n < 0").count() == 0
    whole = {(r["attr"], r["config"]): r["probs"] for r in params.learn_parameters(df, TOY, graph, estimator="sampled", eps=0.5, salt="z").collect()}
    some = params.lazy_parameters(df, TOY, graph, every.where("attr = 2"), estimator="sampled", eps=0.5, salt="z").collect()
    assert len(some) == 3 and all(whole[r["attr"], r["config"]] == r["probs"] for r in some)
    assert all(sum(p) == pytest.approx(1) for p in whole.values())
    assert params.dirichlet_log_density([0.5, 0.5], [1, 1]) == pytest.approx(0.0)


def test_arrays_equal_the_joined_tables(spark, toy, monkeypatch):
    df, model = toy
    for how in ({}, {"estimator": "mode"}, {"estimator": "sampled", "eps": 0.5}):
        rows = params.learn_parameters(df, TOY, TOY_GRAPH, salt="z", **how).collect()
        held = params.learn_tables(params.counts_by_set(df, TOY, [TOY_GRAPH]), TOY, TOY_GRAPH, salt="z", **how)
        assert all(held.probs[r["attr"]][r["config"]] == pytest.approx(r["probs"]) and held.cum[r["attr"]][r["config"]] == pytest.approx(r["cum"]) for r in rows)
        assert sum(len(p) for p in held.probs) == len(rows)
    seeds = df.select(F.col("rk").alias("cand_id"), *TOY.names)
    both = []
    for cells in (synth.BROADCAST_CELLS, 3):  # with 3 all but one attribute are joined by a shuffle
        monkeypatch.setattr(synth, "BROADCAST_CELLS", cells)
        drawn = [synth.synthesize(model, seeds, 3, "d"), synth.synthesize_random(model, seeds, (1, 4), "d")]
        both.append([sorted((*tuple(r)[:6], round(r["logq"], 9)) for r in x.collect()) for x in drawn])
        both[-1].append(sorted(round(r["logp"], 9) for r in model.log_prob(df).collect()))
        both[-1].append(sorted((round(r["q_1"], 9), round(r["q_4"], 9)) for r in synth.log_q(model, df, (1, 4)).collect()))
    assert both[0] == both[1]


def test_continuous_targets(spark):
    rng = np.random.default_rng(8)
    rows = [(str(i), i % 2, float(x), float((i % 2) * 3 + 2 * x + e)) for i, (x, e) in enumerate(rng.normal(size=(4000, 2)))]
    df = spark.createDataFrame(rows, "rk string, g int, x double, t double").coalesce(2)
    drawn = params.draw_continuous(df, params.gaussian_params(df, "t", ["g"]), ["g"], "c", "y")
    got = {r["g"]: r for r in drawn.groupBy("g").agg(F.avg("y").alias("m"), F.stddev("y").alias("s"), F.avg("t").alias("tm"), F.stddev("t").alias("ts")).collect()}
    assert all(r["m"] == pytest.approx(r["tm"], abs=0.2) and r["s"] == pytest.approx(r["ts"], rel=0.08) for r in got.values())
    lines = params.linear_params(df, "t", "x", ["g"])
    fitted = params.draw_continuous(df, lines, ["g"], "c", "y", regressor="x", spread=1.0).agg(F.stddev(F.col("y") - F.col("t")).alias("s"), F.avg(F.col("y") - F.col("t")).alias("m")).first()
    assert fitted["m"] == pytest.approx(0, abs=0.1) and fitted["s"] == pytest.approx(2**0.5, rel=0.06)


def test_seeds_hang_on_the_rows_alone(spark, toy):
    df, _ = toy
    draw = lambda x: sorted(map(tuple, prep.sample_seeds(x, 300, "s").collect()))
    assert draw(df) == draw(df.repartition(7)) and len(draw(df)) == 300
    seen, sizes = prep.ranked(df, 200, in_cell=20)
    rows = sorted((r["_c"], r["_r"]) for r in seen.collect())
    assert rows == [(c, r) for c, n in enumerate(sizes) for r in range(n)] and len(sizes) == 10
    with pytest.raises(ValueError):
        prep.sample_seeds(df, 200 * 600, "s", "poisson")


def test_ranking_by_gain_and_seed_partitions(spark, toy):
    df, _ = toy
    values, _ = info.entropy_sets(df, TOY)
    ranks = structure.rank_by_gain(values, 4, 2)
    assert [j for j, _ in ranks][0] in (1, 3) and [g for _, g in ranks] == sorted((g for _, g in ranks), reverse=True)
    pairs = spark.createDataFrame([(-0.1,), (-0.2,), (-0.8,), (None,)], "logp double")
    assert {r["bucket"]: r["n"] for r in deniability.seed_partitions(pairs, 2.0).collect()} == {0: 2, 1: 1}


def test_deniability_theorem_on_toys():
    """Enumerates the release law of tiny data sets, with and without one record, against the theorem."""
    rng, eps0, gamma = np.random.default_rng(7), 1.0, 2.0
    for _ in range(60):
        k = int(rng.integers(2, 4))
        data = [tuple(rng.integers(0, 2, 2)) for _ in range(int(rng.integers(k, 6)))]
        more = [*data, tuple(rng.integers(0, 2, 2))]
        p1 = rng.uniform(0.2, 0.8, 2)

        def law(rows, y):
            lik = [(p1[y[0]] if y[1] else 1 - p1[y[0]]) if d[0] == y[0] else 0.0 for d in rows]
            out = 0.0
            for x in lik:
                if x > 0:
                    b = math.floor(-math.log(x) / math.log(gamma))
                    n = sum(1 for z in lik if z > 0 and math.floor(-math.log(z) / math.log(gamma)) == b)
                    pp = 1 - 0.5 * math.exp(-eps0 * (n - k)) if n >= k else 0.5 * math.exp(eps0 * (n - k))
                    out += x * pp / len(rows)
            return out

        for t in range(1, k):
            b = budget.release_epsilon(k, gamma, eps0, t)
            excess = sum(max(0.0, law(more, y) - math.exp(b.eps) * law(data, y)) for y in itertools.product(range(2), repeat=2))
            assert excess <= b.delta + 1e-12


def test_distance_profile_and_seeds(spark, toy):
    df, _ = toy
    assert all(r["distance"] == pytest.approx(0) for r in distance.tv_distance(df, df, TOY, True).collect())
    low = distance.boxplot(distance.tv_distance(df.where("a = 0"), df.where("a = 1"), TOY)).first()
    assert low["high"] == pytest.approx(1.0)
    p = prep.profile(df.unionByName(df.limit(1).withColumn("a", F.lit(9))), TOY).first()
    assert (p["n_rows"], p["clean_rows"], p["possible_records"]) == (201, 200, "36")
    assert prep.sample_seeds(df, 77, "s").count() == 77
    assert 120 < prep.sample_seeds(df, 200, "s", "poisson").count() < 280
    parts = [prep.part(df, n).select("rk") for n, _ in prep.SHARES]
    assert sum(x.count() for x in parts) == 200 and parts[0].join(parts[1], "rk").count() == 0


def test_fixed_graph_is_consistent():
    assert OL.possible_records() == 5_630_625_000
    assert [OL.names[i] for i in FIXED.order][:2] == ["reg", "nat"]


def test_sql_functions(spark):
    scalar.register(spark)
    r = spark.sql("SELECT gamma_bucket(-2 * ln(2D), 2) AS b, pass_probability(12, 10, 1) AS p, keyed_uniform('s|a') AS u").first()
    assert r["b"] == 2 and r["p"] == pytest.approx(1 - 0.5 * math.exp(-2)) and r["u"] == uniform_value("s", "a")


def test_files_and_stream(spark, toy, tmp_path):
    from synthguard.sources import files
    from synthguard.streaming.release import Ledger, start, stream_release

    df, model = toy
    files.write_release(df, TOY, str(tmp_path / "csv"), "csv")
    back = files.read_csv(spark, str(tmp_path / "csv"), TOY)
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, df.select(*TOY.names).collect()))
    files.store_model(str(tmp_path / "model"), spark, TOY, TOY_GRAPH, model.table)
    schema, graph, table = files.load_model(str(tmp_path / "model"), spark)
    assert schema == TOY and graph == TOY_GRAPH and table.count() == model.table.count()
    df.withColumn("cand_id", F.col("rk")).select("cand_id", *TOY.names).write.parquet(str(tmp_path / "in"))
    index = df.groupBy("a").agg(F.count("*").alias("n"))
    seeds = spark.readStream.schema("cand_id string, a int, b int, c int, d int").parquet(str(tmp_path / "in"))
    ledger = Ledger(spark, str(tmp_path / "ledger"), 500)
    start(stream_release(seeds, index, model, DeniabilityParams(20, 2.0), 3, "st"), str(tmp_path / "out"), str(tmp_path / "cp"), ledger, "toy").awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out")).drop("batch")
    assert got.columns == TOY.names and got.count() == ledger.spent("toy") > 0
    with pytest.raises(RuntimeError):
        ledger.charge("toy", 9, 10_000)
