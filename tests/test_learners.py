import numpy as np
import pytest
from pyspark.sql import functions as F

from synthguard import workloads
from synthguard.operators import bounded, learners, predict
from synthguard.plans.schema import Schema, categorical, numeric

TINY = Schema("tiny", (categorical("a", range(3)), numeric("x", 9, 1), categorical("t", range(2))))


def tiny_rows(spark, n=400, seed=2):
    rng = np.random.default_rng(seed)
    a, x = rng.integers(0, 3, n), rng.integers(0, 9, n)
    t = (a + x / 4 + rng.normal(size=n) > 2).astype(int)
    return spark.createDataFrame([(f"{seed}-{i}", *map(int, r)) for i, r in enumerate(zip(a, x, t, strict=True))], "rk string, a int, x int, t int").coalesce(2).cache()


@pytest.mark.parametrize("loss", ["lr", "svm"])
def test_linear_weights_are_the_minimum(spark, loss):
    df, lam = tiny_rows(spark), 1e-6
    rows = df.toPandas()
    x, y = learners.encode(rows, TINY, "t"), np.where(rows["t"] == 1, 1.0, -1.0)
    slope = learners._loss(loss)[0]
    push = np.linspace(-1, 1, x.shape[1])
    for linear in (np.zeros(x.shape[1]), push):
        w = learners.minimise(df, TINY, "t", loss, lam, linear)
        gradient = x.T @ (slope(y * (x @ w)) * y) / len(x) + lam * w + linear / len(x)
        assert np.linalg.norm(gradient) <= 1e-5


def _reals(n, seed=1):
    """Rows of the order line schema in which netc follows pband and disc, and nat follows reg."""
    rng = np.random.default_rng(seed)
    x = {a.name: rng.integers(0, a.card, n) for a in workloads.OL.attributes}
    x["reg"] = x["nat"] // 5
    x["pband"] = np.minimum(20, x["qty"] // 3 + rng.integers(0, 5, n))
    x["netc"] = (x["pband"] - x["disc"] // 4 + (rng.random(n) < 0.05) * 8 > 9).astype(int)
    return [(f"{i}", *(int(x[k][i]) for k in workloads.OL.names)) for i in range(n)]


@pytest.fixture(scope="module")
def tables(spark):
    """The workloads on made rows instead of the given tables."""
    df = spark.createDataFrame(_reals(30_000), "rk string, " + ", ".join(f"{n} int" for n in workloads.OL.names)).coalesce(4).cache()
    rng = np.random.default_rng(5)
    rows = []
    for i in range(3000):
        r = [int(rng.integers(0, a.card)) for a in workloads.DOCUMENT.schema.attributes]
        r[6] = int(r[1] > 9) ^ int(rng.random() < 0.05)
        rows.append((f"{i}", *r))
    other = spark.createDataFrame(rows, "rk string, " + ", ".join(f"{n} int" for n in workloads.DOCUMENT.schema.names)).coalesce(4).cache()
    with pytest.MonkeyPatch.context() as m:
        m.setattr(workloads, "micro", lambda spark, sf_dir, view=workloads.ORDERLINE: df if view is workloads.ORDERLINE else other)
        yield df


SYNTHETICS = ["omega 11", "omega 10", "omega 9", "omega 9-11", "omega 5-11"]


def test_private_classifier_table_is_whole(spark, tables):
    got = {(r["training"], r["loss"], r["privacy"]): (r["accuracy"], r["lam"]) for r in workloads.private_classifier_table(spark, "").collect()}
    cases = [("reals", "none"), ("reals", "output"), ("reals", "objective"), *[(k, "none") for k in ("marginals", *SYNTHETICS)]]
    assert set(got) == {(k, loss, how) for k, how in cases for loss in ("lr", "svm")} and {lam for _, lam in got.values()} <= set(workloads.LAMBDAS)
    for loss in ("lr", "svm"):
        of = {k: a for (k, lo, how), (a, _) in got.items() if lo == loss and how == "none"}
        # synthetics teach more than marginals, and about as much as private learning from reals does
        assert min(of[k] for k in SYNTHETICS) > of["marginals"] + 0.1 and of["reals"] >= max(of[k] for k in SYNTHETICS) - 0.02
        assert max(of[k] for k in SYNTHETICS) > got["reals", loss, "output"][0]


def test_game_and_distances_have_the_order_that_is_reported(spark, tables):
    game = {(r["kind"], r["classifier"]): r["accuracy"] for r in workloads.distinguishing_game(spark, "").collect()}
    for c in ("tree", "rf"):
        assert abs(game["reals", c] - 0.5) < 0.08 and all(game["marginals", c] > game[k, c] + 0.02 for k in SYNTHETICS)
    box = {(r["kind"], r["pairs"]): r["median"] for r in workloads.tv_synthetic(spark, "").collect()}
    assert {k for k, _ in box} == {"reals", "marginals", *SYNTHETICS}


def test_classifier_table_has_the_order_that_is_reported(spark, tables):
    got = {(r["target"], r["training"], r["classifier"]): r for r in workloads.classifier_table(spark, "", runs=1).collect()}
    assert set(got) == {(t, k, c) for t, v in (("netc", workloads.ORDERLINE), ("quality", workloads.DOCUMENT)) for k in ("reals", "marginals", *workloads.case_names(len(v.schema))) for c in ("tree", "rf", "adaboost")}
    assert all(r["runs"] == 1 for r in got.values())
    for c in ("tree", "rf", "adaboost"):
        reals, marginals = got["netc", "reals", c], got["netc", "marginals", c]
        for k in SYNTHETICS:
            assert reals["accuracy"] > got["netc", k, c]["accuracy"] > marginals["accuracy"] and got["netc", k, c]["agreement"] > marginals["agreement"]


def test_model_error_is_the_mean_of_private_models(spark, tables):
    got = {(r["model"], r["attr"]): (r["error"], r["improvement"]) for r in workloads.model_error(spark, "", models=3).collect()}
    assert {m for m, _ in got} == {"marginals", "eps None", "eps 1.0", "eps 0.1"} and len(got) == 44
    test = workloads.split_of(spark, "", "test")
    one = [{r["attr"]: r["error"] for r in predict.model_error(workloads.learned_model(spark, "", 1.0, f"error-1.0-{t}"), test).collect()} for t in range(3)]
    assert got["eps 1.0", "netc"][0] == pytest.approx(sum(x["netc"] for x in one) / 3)
    for a in ("netc", "reg"):
        assert got["eps None", a][1] >= got["eps 1.0", a][1] - 1e-9 and got["eps None", a][1] > 0.2
    # the arrays' guesses are those of the joined tables
    model = workloads.learned_model(spark, "")
    for a in ("netc", "reg", "qty"):
        joined = predict.predict_attribute(model, test, a).agg(F.avg((F.col("truth") != F.col("guess")).cast("double"))).first()[0]
        assert joined == pytest.approx(got["eps None", a][0], abs=1e-9)


def test_trees_are_the_best_splits():
    rng = np.random.default_rng(7)
    x, cards = rng.integers(0, 5, (400, 3)), [5, 5, 5]
    y = ((x[:, 0] > 2) ^ (x[:, 2] > 1)).astype(int)
    assert (bounded.tree(x, y, cards, 2, None)(x) == y).all() and (bounded.forest(x, y, cards, 2, bounded.generator("f"))(x) == y).mean() > 0.95
    stump = bounded.grow(x, (x[:, 1] > 3).astype(int), np.ones(400), cards, 2, 1)
    assert stump.feature[0] == 1 and stump.cut[0] == 3 and len(stump.feature) == 3
    noisy = y ^ (rng.random(400) < 0.1)
    assert (bounded.adaboost(x, noisy, cards, 2, None, 20, 2)(x) == y).mean() > (bounded.adaboost(x, noisy, cards, 2, None, 1, 1)(x) == y).mean()


def test_private_noise_hangs_on_the_salt():
    one, two = learners._noise(9, 2.0, "a", "lr"), learners._noise(9, 2.0, "b", "lr")
    assert (one == learners._noise(9, 2.0, "a", "lr")).all() and (one != two).all()
    norms = [np.linalg.norm(learners._noise(9, 2.0, k)) for k in range(2000)]
    assert np.mean(norms) == pytest.approx(4.5, rel=0.05) and np.var(norms) == pytest.approx(9 / 4, rel=0.15)
    with pytest.raises(ValueError):
        learners.linear_weights(FakeFrame(), TINY, "t", privacy="output")


class FakeFrame:
    def count(self):
        return 10


@pytest.mark.parametrize("sizes", [(90, 600), (600, 90), (90, 90)])
def test_game_is_even_on_both_sides_of_the_cut(spark, monkeypatch, sizes):
    seen = {}
    count = lambda df: {r["_real"]: r["n"] for r in df.groupBy("_real").agg(F.count("*").alias("n")).collect()}
    monkeypatch.setattr(learners, "fit", lambda kind, df, *_: seen.update(train=count(df)))
    monkeypatch.setattr(learners, "accuracy", lambda model, df, target: seen.update(test=count(df)))
    learners.game(tiny_rows(spark, sizes[0], 3), tiny_rows(spark, sizes[1], 4), TINY, "tree", "g")
    assert seen == {"train": {0: 60, 1: 60}, "test": {0: 30, 1: 30}}


def test_kinds_are_private(spark, tables, monkeypatch):
    """The tables that kinds() draws from are those of the private model and private marginals, and differ from the un-noised."""
    made = []
    real = workloads.synth.synthesize_by
    monkeypatch.setattr(workloads.synth, "synthesize_by", lambda model, *a, **k: (made.append(model), real(model, *a, **k))[1])
    data = workloads.kinds(spark, "")
    assert {r["kind"] for r in data.select("kind").distinct().collect()} == {"reals", "marginals", *SYNTHETICS}
    marginals, model = made
    want, plain = workloads.learned_model(spark, "", 1.0, "kinds"), workloads.learned_model(spark, "")
    same = lambda a, b: a.graph == b.graph and all((x == y).all() for x, y in zip(a.arrays.probs, b.arrays.probs, strict=True))
    assert same(model, want) and not same(model, plain)
    un_noised = workloads.synth.marginal_model(workloads.split_of(spark, "", "P"), workloads.OL)
    assert all((x != y).any() for x, y in zip(marginals.arrays.probs, un_noised.arrays.probs, strict=True))


def test_pass_rates_of_every_omega(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(str(i), *(int(rng.integers(0, min(2, a.card))) for a in workloads.OL.attributes)) for i in range(120)]
    df = spark.createDataFrame(rows, "rk string, " + ", ".join(f"{n} int" for n in workloads.OL.names))
    monkeypatch.setattr(workloads, "micro", lambda *_: df)
    got = {(r["omega"], r["k"]): (r["mean_plausible"], r["pass_rate"]) for r in workloads.QUERIES["pass_rate_whole_grid"](spark, "").collect()}
    assert set(got) == {(w, k) for w in range(5, 12) for k in workloads.KS}
    assert all(got[11, k] == (120.0, float(k <= 120)) for k in workloads.KS)
    narrow = {(r["omega"], r["k"]): (r["mean_plausible"], r["pass_rate"]) for r in workloads.pass_rate_grid(spark, "").collect()}
    assert narrow == {c: x for c, x in got.items() if c[0] < 11}


@pytest.mark.parametrize("eps", [1.0, None])
def test_run_of_a_configuration(spark, tmp_path, eps):
    import json

    from synthguard.sources import files

    files.write_release(tiny_rows(spark), TINY, str(tmp_path / "in"), "csv")
    (tmp_path / "meta.json").write_text(TINY.to_json())
    # 0 candidates fail: all attributes are drawn anew, so every seed is plausible
    x = {"k": 10, "gamma": 2.0, "eps": eps, "omega": 3, "n": 70, "test": "deterministic", "salt": "s", "input": str(tmp_path / "in"), "metadata": str(tmp_path / "meta.json"), "output": str(tmp_path / "out")}
    (tmp_path / "run.json").write_text(json.dumps(x))
    assert files.run_config(spark, str(tmp_path / "run.json")) == 70
    back = files.read_csv(spark, x["output"], TINY)
    assert back.count() == 70 and back.dropna().count() == 70
