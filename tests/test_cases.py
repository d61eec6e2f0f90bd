import numpy as np
import pytest
from pyspark.sql import functions as F

from synthguard import workloads
from synthguard.operators import cases, deniability, distance, info, params, prep, synth
from synthguard.plans.schema import Graph, Schema, categorical, numeric

S3 = Schema("three", (categorical("a", range(3)), numeric("x", 9, 3), categorical("t", range(2))))
GRAPH = Graph(((), (0,), (1,)), (0, 1, 2))


@pytest.fixture(scope="module")
def rows(spark):
    rng = np.random.default_rng(4)
    a, x, t = rng.integers(0, 3, 3000), rng.integers(0, 9, 3000) ** 2 // 8, rng.integers(0, 2, 3000)
    return spark.createDataFrame([(str(i), *map(int, r)) for i, r in enumerate(zip(a, x, t, strict=True))], "rk string, a int, x int, t int").repartition(3).cache()


def test_rows_are_dealt_as_parts_are(spark, rows):
    told = rows.withColumn("s", prep.dealt(salt="other salt"))
    for n, (which, _) in enumerate(prep.SHARES):
        assert {r["rk"] for r in told.where(F.col("s") == n).collect()} == {r["rk"] for r in prep.part(rows, which, salt="other salt").collect()}


def test_groups_are_counted_as_by_themselves(spark, rows):
    marked = rows.withColumn("_g", (F.col("rk").cast("int") % 3 > 0).cast("int"))
    graphs = [[GRAPH], [Graph(((), (), (0,)), (0, 1, 2)), params.without_parents(S3)]]
    many, counts = info.entropy_sets_of(marked, S3, 3), params.counts_by_group(marked, S3, graphs)
    for g in (0, 1):
        own = marked.where(F.col("_g") == g)
        values, n = info.entropy_sets(own, S3)
        assert many[g][1] == n and many[g][0] == pytest.approx(values)
        alone = params.counts_by_set(own, S3, graphs[g])
        assert counts[g].keys() == alone.keys() and all((counts[g][k] == alone[k]).all() for k in alone)
    assert many[2][1] == 0 and set(many[2][0].values()) == {0.0}


def _cases(rows):
    model = synth.from_tables(rows.sparkSession, S3, GRAPH, params.learn_tables(params.counts_by_set(rows, S3, [GRAPH]), S3, GRAPH))
    alone = params.without_parents(S3)
    base = params.learn_tables(params.counts_by_set(rows, S3, [alone]), S3, alone)
    return model, [cases.Case("base", alone, base, (3,)), cases.Case("one", GRAPH, model.arrays, (1,), 110), cases.Case("some", GRAPH, model.arrays, (1, 2, 3), 110, 2.0)]


def test_candidates_are_tested_and_drawn_by_their_law(spark, rows):
    model, sets_ = _cases(rows)
    seeds = cases.with_counts(rows.where("rk < '5'"), rows, ["a", "x", "t"], {0, 1, 2}).cache()
    counted = deniability.plausible_counts(model, rows.where("rk < '5'").withColumn("omega", F.lit(1)), rows, [1])
    near = {r["rk"]: r["plausible"] for r in counted.collect()}
    assert {r["rk"]: r["_n"][2] for r in seeds.collect()} == near and len(near) == rows.where("rk < '5'").count()
    made = cases.candidates(seeds, S3, sets_, "salt").toPandas()
    own = rows.toPandas().set_index("rk")
    one = made[made["kind"] == "one"].set_index("rk")
    # kept attributes are the seed's, and few candidates of fewer seeds than k pass
    assert (own.loc[one.index, ["a", "x"]].to_numpy() == one[["a", "x"]].to_numpy()).all()
    assert all(near[k] > 95 for k in one.index) and all(k in one.index for k, n in near.items() if n > 140)
    base = made[made["kind"] == "base"]
    assert len(base) == len(near)
    for n in S3.names:
        share = lambda df, n=n: df[n].value_counts(normalize=True).reindex(range(9), fill_value=0)
        assert (share(base) - share(own)).abs().max() < 0.05
    assert set(made["kind"]) == {"base", "one", "some"}


def test_candidates_are_counted_where_they_are_drawn(spark, rows):
    _, sets_ = _cases(rows)
    seeds = cases.with_counts(rows, rows, ["a", "x", "t"], {0, 1, 2})
    sets = distance.sets_of(S3, False) + distance.sets_of(S3, True)
    count = lambda df: {(r["_kind"], r["s"], r["at"]): r["n"] for r in df.collect()}
    assert count(cases.histograms(seeds, S3, sets_, sets, "salt")) == count(distance.counted(cases.candidates(seeds, S3, sets_, "salt"), S3, sets, "kind"))


def test_boxes_are_those_of_the_joined_distances(spark, rows):
    kinds = rows.withColumn("kind", F.concat(F.lit("k"), (F.col("rk").cast("int") % 2).cast("string")))
    sets = distance.sets_of(S3, False) + distance.sets_of(S3, True)
    both = distance.counted(rows.withColumn("kind", F.lit("_real")).unionByName(kinds), S3, sets, "kind")
    got = distance.boxes(both, sets, "_real")
    for pairs in (False, True):
        for r in distance.boxplot(distance.tv_distance(rows, kinds, S3, pairs, "kind"), ["kind"]).collect():
            assert got[r["kind"]][pairs] == pytest.approx(list(r[1:]))


def test_numbers_are_placed_by_their_sums():
    rng = np.random.default_rng(1)
    p = rng.random((40, 50)) ** 8
    cum = np.cumsum(p / p.sum(1, keepdims=True), 1)
    c, u = rng.integers(0, 40, 20_000), rng.random(20_000)
    u[:40], c[:40] = np.minimum(cum[:, 7], 1 - 1e-12), np.arange(40)
    assert (cases.placed(cum, cases.guides(cum), c, u) == np.minimum((cum[c] <= u[:, None]).sum(1), 49)).all()


def test_each_experiment_deals_its_rows_once(spark, rows, monkeypatch):
    """All runs share one scan of a view; each of them read it anew before."""
    asked = []
    rng = np.random.default_rng(3)
    made = {v.schema.name: spark.createDataFrame([(str(i), *(int(rng.integers(0, a.card)) for a in v.schema.attributes)) for i in range(1500)], "rk string, " + ", ".join(f"{n} int" for n in v.schema.names)).cache() for v in (workloads.ORDERLINE, workloads.DOCUMENT)}
    monkeypatch.setattr(workloads, "micro", lambda spark, sf_dir, view=workloads.ORDERLINE: asked.append(view.schema.name) or made[view.schema.name])
    assert workloads.classifier_table(spark, "", runs=2).count() == 42 and sorted(asked) == ["document_micro", "orderline_micro"]
    asked.clear()
    assert workloads.tv_synthetic(spark, "").count() >= 4 and asked == ["orderline_micro"]
