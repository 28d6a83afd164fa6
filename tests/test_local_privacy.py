from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from ldpspark.erm import descent, losses, projection
from ldpspark.functions import constants as C
from ldpspark.functions.rng import uniform
from ldpspark.operators import audit, budget, relops
from ldpspark.operators import categorical as cat
from ldpspark.operators import estimate as est
from ldpspark.operators import measure as mea
from ldpspark.operators import mixed as mix
from ldpspark.operators import numeric as num
from ldpspark.plans import experiments as ex
from ldpspark.plans import replay
from ldpspark.sources.stored import stored
from ldpspark.plans.schema import validate_tuple
from ldpspark.plans.views import CAT3, LI18, LI23, NUM4, users

SF = "/root/testdata/sf0.001"
SF2 = "/root/testdata/sf0.01"
NAMES = [a.name for a in NUM4.numerics]


# --- closed forms

@pytest.mark.parametrize("d", range(1, 13))
def test_halfspace_sizes_by_counting(d):
    assert C.halfspace_size(d) == sum(bin(x).count("1") * 2 > d for x in range(2**d))
    assert abs(C.halfspace_bias(d, 1.0, "repaired") - 1) < 1e-9


def test_printed_toss_is_wrong_for_even_dimensions_only():
    for d in range(1, 9):
        bias, eps = C.halfspace_bias(d, 1.0, "printed"), C.effective_epsilon(d, 1.0, "printed")
        if d % 2:
            assert abs(bias - 1) < 1e-9 and abs(eps - 1) < 1e-9
        else:
            assert bias > 1.4 and eps > 1.5
    assert abs(C.effective_epsilon(2, 0.7, "printed") - 0.7 - math.log(3)) < 1e-12
    assert abs(C.effective_epsilon(6, 0.7, "repaired") - 0.7) < 1e-12
    assert abs(C.halfspace_bias(2, 0.5, "printed") - 3.5587) < 1e-4
    assert abs(C.halfspace_scale(501, 1.0) / C.halfspace_scale(499, 1.0) - math.sqrt(501 / 499)) < 1e-3


def test_exact_audit(spark):
    cases = [("one_coordinate", d, e) for d in (1, 2, 4) for e in (0.3, 2.0)] + [("halfspace_repaired", d, 1.0) for d in range(1, 6)] + [("coin_flip", 1, 0.8), ("orthogonal", 5, 0.8)]
    for r in audit.exact_epsilon(spark, cases).collect():
        assert abs(r["effective"] - r["eps"]) < 1e-9
    violating = audit.exact_epsilon(spark, [("halfspace_printed", 2, 1.0)]).first()["effective"]
    assert abs(violating - 1 - math.log(3)) < 1e-9


def test_report_expectation_by_enumeration():
    t = (0.3, -0.8, 0.1, 1.0)
    out = audit.halfspace_outputs(t, 1.2, "repaired")
    b = C.halfspace_scale(4, 1.2)
    assert all(abs(b * sum(y[j] * p for y, p in out.items()) - t[j]) < 1e-9 for j in range(4))
    one = audit.one_coordinate_outputs(t, 1.2)
    c = C.report_scale(1.2)
    assert all(abs(c * 4 * sum(s * p for (k, s), p in one.items() if k == j) - t[j]) < 1e-9 for j in range(4))


def test_batch_sizes_of_the_study():
    assert [C.batch_size(85, e, 0) for e in ex.EPS_GRID] == [302101, 75526, 18882, 4721, 1181]
    assert LI23.one_hot_dimension == 85 and LI18.one_hot_dimension == 95 and sum(c.k for c in LI23.categoricals) == 97
    with pytest.raises(ValueError):
        descent.steps_for(1000, 85, 0.05)


# --- randomness

def test_salts_are_independent_and_even(spark):
    df = spark.range(20_000).select(F.col("id").cast("string").alias("k"))
    for mode in ("md5", "xx"):
        u = df.select(*[uniform("k", s, mode=mode).alias(s) for s in ("attr", "toss", "row", "batch")]).toPandas().to_numpy()
        assert abs(np.corrcoef(u.T) - np.eye(4)).max() < 4 / math.sqrt(len(u))
        assert abs(u.mean(0) - 0.5).max() < 0.01 and u.min() >= 0 and u.max() < 1
    again = df.repartition(7).select("k", uniform("k", "toss").alias("u")).orderBy("k").collect()
    assert again == df.select("k", uniform("k", "toss").alias("u")).orderBy("k").collect()


# --- estimates

def test_user_keys_are_unique_and_codes_inside(spark):
    for spec in (NUM4, LI23, LI18):
        found = validate_tuple(users(spark, SF, spec), spec)
        assert found["rows"] == 6000 and found["repeated_keys"] == found["with_nulls"] == found["outside_domain"] == 0


def test_means_are_within_their_radius(spark):
    v = users(spark, SF2, NUM4).persist()
    exact = {r["attr"]: r["exact"] for r in est.exact_mean(v, NAMES).collect()}
    for build in (
        lambda s: est.mean_sparse(num.one_coordinate_report(v, NAMES, 1.0, seed=s), NAMES, 1.0),
        lambda s: est.mean_sparse(num.one_coordinate_report(v, NAMES, 1.0, seed=s, attr_choice="public_hash"), NAMES, 1.0),
        lambda s: est.mean_halfspace(num.halfspace_report(v, NAMES, 1.0, seed=s), NAMES, 1.0),
    ):
        for r in build(1).collect():
            assert abs(r["estimate"] - exact[r["attr"]]) < C.mean_radius(60_000, 4, 1.0, 1e-4)
    v.unpersist()


def test_printed_halfspace_report_is_biased_as_computed(spark):
    same = spark.range(20_000).select(F.col("id").cast("string").alias("ukey"), *[F.lit(0.5).alias(f"a{i}") for i in range(4)])
    names = [f"a{i}" for i in range(4)]
    for variant in ("printed", "repaired"):
        got = np.mean([r["estimate"] for r in est.mean_halfspace(num.halfspace_report(same, names, 1.0, variant), names, 1.0).collect()])
        assert abs(got / 0.5 - C.halfspace_bias(4, 1.0, variant)) < 0.15


def test_frequencies_decode_alike_and_are_unbiased(spark):
    v = users(spark, SF2, CAT3)
    sent = cat.orthogonal_report(v, "line_no", 7, 1.0)
    slow = {r["code"]: r["estimate"] for r in est.decode_orthogonal(sent, 7, 1.0).collect()}
    fast = {r["code"]: r["estimate"] for r in est.decode_fast(sent, 7, 1.0).collect()}
    exact = {r["code"]: r["exact"] for r in est.exact_histogram(v, [("line_no", 7)]).collect()}
    assert slow == fast
    assert max(abs(slow[c] - exact[c]) for c in exact) < C.frequency_radius(60_000, 1, 7, 1.0, 1e-4)


def test_postprocessing_and_marginals(spark):
    e = spark.createDataFrame([("a", 0, -0.1), ("a", 1, 0.5), ("a", 2, 1.4)], "attr string, code int, estimate double")
    assert [round(r["estimate"], 6) for r in est.project_simplex(e, ["attr"], "norm").orderBy("code").collect()] == [0.0, round(1 / 3, 6), round(2 / 3, 6)]
    cells = spark.createDataFrame([(i, float(i)) for i in range(6)], "code int, estimate double")
    got = {(r["attr"], r["code"]): r["estimate"] for r in mix.marginalise(cells, [("x", 2), ("y", 3)]).collect()}
    assert got == {("x", 0): 3.0, ("x", 1): 12.0, ("y", 0): 3.0, ("y", 1): 5.0, ("y", 2): 7.0}


def test_sampling_beats_splitting_by_about_the_root_of_d(spark):
    rows = {(r["method"], r["eps"]): r["mean_linf"] for r in ex.frequency_errors(spark, SF2, LI23, [2.0], 3).collect()}
    assert 3 < rows[("hybrid", 2.0)] / rows[("mixed", 2.0)] < 8


def test_mean_errors_match_the_model_of_the_figures(spark):
    rows = {r["method"]: r["mean_linf"] for r in ex.mean_errors(spark, SF2, LI23, [1.0], 100).collect()}
    model = 1.655 * C.report_scale(1.0) * math.sqrt(6 / 60_000)
    assert 0.75 < rows["mixed"] / model < 1.25 and rows["mixed"] < rows["hybrid"] < 2 * rows["mixed"]


def test_error_grows_linearly_or_by_root(spark):
    rows = {(r["method"], r["d"]): r["rms"] for r in ex.dimension_sweep(spark, SF2, [1, 4, 16], 1.0, 40).collect()}
    slope = lambda m: math.log(rows[(m, 16)] / rows[(m, 1)]) / math.log(16)
    assert abs(slope("laplace") - 1) < 0.12 and abs(slope("one_coordinate") - 0.5) < 0.12 and abs(slope("half_space") - 0.5) < 0.15


def test_plan_of_the_report_is_narrow_and_native(spark):
    out = est.mean_sparse(num.one_coordinate_report(users(spark, SF, NUM4), NAMES, 1.0, mode="xx"), NAMES, 1.0)
    plan = out._jdf.queryExecution().executedPlan().toString()
    schema = plan[plan.index("ReadSchema") :].split("\n")[0]
    assert "Python" not in plan and "l_shipdate" not in schema and "l_quantity" in schema
    assert plan.count("hashpartitioning") == 1


# --- learning

def test_gradients_match_differences(spark):
    rng = np.random.default_rng(0)
    rows = [([float(v) for v in rng.uniform(-1, 1, 3)], float(rng.choice([-1, 1]))) for _ in range(50)]
    df = spark.createDataFrame(rows, "x array<double>, y double")
    w = [0.4, -0.3, 0.2]
    for kind in losses.KINDS:
        g = np.array([r["g"] for r in df.select(losses.gradient(kind, F.col("x"), F.col("y"), losses.weights(w), 0.1).alias("g")).collect()]).mean(0)
        for j in range(3):
            up, down = list(w), list(w)
            up[j] += 1e-6
            down[j] -= 1e-6
            diff = (losses.objective(df, up, kind, 0.1).first()["objective"] - losses.objective(df, down, kind, 0.1).first()["objective"]) / 2e-6
            assert abs(diff - g[j]) < 1e-5


def test_exact_descent_nears_least_squares():
    rng = np.random.default_rng(3)
    x = rng.uniform(-1, 1, (20_000, 5))
    beta = np.array([0.3, -0.2, 0.1, 0.0, 0.25])
    y = x @ beta
    w = descent.fold_users(x, y, "linear", 0.0, 0.3)
    assert abs(w - beta).max() < 0.02
    with pytest.raises(ArithmeticError):
        descent.fold_users(np.ones((2000, 85)), np.ones(2000), "linear", 0.0, 5.0)


@pytest.mark.parametrize("mechanism", [None, "halfspace", "laplace", "one_coordinate"])
def test_sequential_descent_sees_all_users_over_batches(spark, mechanism):
    rng = np.random.default_rng(8)
    rows = [(f"u{i}", [float(v) for v in rng.uniform(-1, 1, 3)], float(rng.choice([-1, 1]))) for i in range(2500)]
    users = descent.prepared(spark.createDataFrame(rows, "ukey string, x array<double>, y double"), 2)
    all_users = sorted(users.collect(), key=lambda r: (r["ub"], r["ukey"]))
    models = [descent.Model(f"{e}/{f}", 3, e, 1, f) for f in (0, 1) for e in (1.0, 2.0)]
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 100)
    try:
        got = {r["model"]: r for r in descent.sgd(users, models, "logistic", 1e-3, 0.5, mechanism).collect()}
        few = {r["model"]: r for r in descent.sgd(users, models, "logistic", 1e-3, 0.5, mechanism, max_users=64).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for m in models:
        own = [r for r in all_users if r["fold"] != m.fold]
        for found, n in ((got[m.name], len(own)), (few[m.name], 64)):
            x, y = np.array([r["x"] for r in own[:n]]), np.array([r["y"] for r in own[:n]])
            assert found["users"] == n
            assert np.allclose(found["weights"], descent.fold_users(x, y, "logistic", 1e-3, 0.5, mechanism, m.eps), atol=1e-12)


@pytest.mark.parametrize("mechanism", [None, "halfspace", "laplace", "one_coordinate"])
@pytest.mark.parametrize("kind", losses.KINDS)
def test_steps_on_plain_numbers_equal_those_on_arrays(monkeypatch, kind, mechanism):
    rng = np.random.default_rng(5)
    x, y = rng.uniform(-1, 1, (5000, 3)), rng.choice([-1.0, 1.0], 5000)
    found = []
    for limit in (descent.PLAIN, 0):
        monkeypatch.setattr(descent, "PLAIN", limit)
        walk = descent.Walk(kind, 1e-3, 0.3, mechanism, [0.5, 2.0])
        for a in (0, 1300, 1301):
            walk.run(x[a : {0: 1300, 1300: 1301, 1301: 5000}[a]], y[a : {0: 1300, 1300: 1301, 1301: 5000}[a]])
        found.append(walk.w)
    assert np.allclose(*found, atol=1e-10)


@pytest.mark.parametrize("mechanism", [None, "halfspace"])
@pytest.mark.parametrize("kind", losses.KINDS)
def test_steps_in_few_calls_equal_those_one_by_one(kind, mechanism):
    rng = np.random.default_rng(6)
    x, y = rng.uniform(-1, 1, (3000, 12)), rng.choice([-1.0, 1.0], 3000)
    fast, slow = (descent.Walk(kind, 1e-3, 0.1, mechanism, [0.5, 2.0] if mechanism else [1.0], tol=tol) for tol in (0.0, 1e-300))
    assert hasattr(fast, "_run_wide")
    calls = []
    fast._noise = lambda *a: calls.append(a)
    for a, b in ((0, 1300), (1300, 3000)):
        fast.run(x[a:b], y[a:b])
    slow.run(x, y)
    assert not calls and np.allclose(fast.w, slow.w, atol=1e-9)


def test_a_stream_gets_packed_users_in_order(spark):
    base = users(spark, SF, NUM4).select("ukey", F.array("quantity", "discount", "tax").alias("x"), F.col("price").alias("y"))
    ready = descent.prepared(base, 4)
    rows = descent._streams(ready, 2, True).where("part = 1")
    assert rows.rdd.getNumPartitions() == 2 and rows.count() < 100
    got = [(*x, y, ub) for b in rows.toArrow().to_batches() for _, _, xs, ys, ubs, _, _ in descent._unpacked(b, True) for x, y, ub in zip(xs.tolist(), ys.tolist(), ubs.tolist())]
    assert got == [(*r["x"], r["y"], r["ub"]) for r in sorted(ready.collect(), key=lambda r: r["ub"])]


def test_streams_of_stored_users_shuffle_nothing(spark):
    base = users(spark, SF, NUM4).select("ukey", F.array("quantity", "discount", "tax").alias("x"), F.col("price").alias("y"))
    ready = descent.prepared(base, 4)
    rows = descent._streams(stored(descent.packed(ready), "packed"), 3, True)
    assert "Exchange" not in rows._jdf.queryExecution().executedPlan().toString()
    assert rows.rdd.glom().map(lambda part: [r["part"] for r in part]).map(lambda p: (len(set(p)), len(p) > 0)).collect() == [(1, True)] * 3
    want = [(*r["x"], r["y"], r["ub"], r["uj"], r["ut"], r["fold"]) for r in sorted(ready.collect(), key=lambda r: r["ub"])]
    for i in range(3):
        own = rows.where(F.col("part") == i).toArrow().to_batches()
        assert [(*a, *b) for batch in own for _, f, x, y, ub, uj, ut in descent._unpacked(batch, True) for a, b in zip(x.tolist(), zip(y, ub, uj, ut, f))] == want


def test_users_are_packed_before_they_are_shuffled(spark, monkeypatch):
    base = users(spark, SF2, NUM4).select("ukey", F.array("quantity", "discount", "tax").alias("x"), F.col("price").alias("y"))
    ready = descent.prepared(base, 4, mode="xx")
    rows = descent.packed(ready)
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") >= 2 and plan.rindex("MapInArrow") > plan.index("Exchange")
    size = rows.agg(F.sum(F.length("draws")) / F.sum("rows")).first()[0]
    assert size < 21
    monkeypatch.setattr(descent, "RANGE", 100_000)  # many ranges and parts give the same order
    order = lambda df: [tuple(v) for b in df.orderBy("range", "nth").withColumn("part", F.lit(0)).toArrow().to_batches() for _, *cells in descent._unpacked(b, True) for v in zip(*(c.tolist() for c in (cells[0], cells[2], *cells[3:])))]
    many = descent.packed(ready)
    assert many.select("range").distinct().count() > rows.select("range").distinct().count()
    assert order(many) == order(rows)


def test_equal_places_have_one_order(spark):
    rows = [(f"u{i}", [float(i % 3), float(i % 5)], float(i % 2)) for i in range(500)] * 2
    found = []
    for parts in (1, 7):
        ready = descent.prepared(spark.createDataFrame(rows, "ukey string, x array<double>, y double").repartition(parts), 3).withColumn("ub", F.floor(F.col("ub") * 20) / 20)
        one = descent._streams(ready, 1, True).toArrow().to_batches()
        found.append([(*x, *v) for b in one for _, f, xs, *rest in descent._unpacked(b, True) for x, v in zip(xs.tolist(), zip(f.tolist(), *(c.tolist() for c in rest)))])
    assert len(found[0]) == 1000 and found[0] == found[1]


@pytest.mark.parametrize("name", ["sgd_exact_linear", "sgd_exact_svm", "sgd_halfspace_linear", "sgd_laplace", "sgd_one_coordinate"])
def test_registered_descent_takes_the_whole_table(spark, name):
    from ldpspark import queries

    assert {r["users"] for r in queries.QUERIES[name](spark, SF2).collect()} == {spark.read.parquet(f"{SF2}/lineitem.parquet").count()}


@pytest.mark.parametrize("kind", ["linear", "logistic", "svm"])
def test_first_steps_of_exact_descent_equal_recursive_sql(spark, kind):
    import duckdb

    from ldpspark import queries
    from ldpspark.oracle import sql

    duck = duckdb.connect()
    for t in ("lineitem", "orders", "customer"):
        duck.execute(f"create view {t} as select * from '{SF2}/{t}.parquet'")
    want = duck.execute(sql.sequential(queries._ERM[kind], queries._XS, kind, 64, queries.LAM, 1 / 6)).fetchall()
    users = descent.prepared(queries.erm(spark, SF2, kind))
    got = descent.sgd(users, [descent.Model("exact", 3, queries.EPS, 1)], kind, queries.LAM, 1 / 6, max_users=64).collect()[0]
    assert got["users"] == 64
    assert np.allclose(got["weights"], [w for _, w in sorted(want)], atol=2e-9)


def test_participations_train_on_all_their_reports(spark, monkeypatch):
    from ldpspark import queries

    steps = []

    def trained(data, models, kind, lam):
        steps.append(models[0].steps)
        models[0].weights = [0.0] * models[0].dim
        return models

    monkeypatch.setattr(queries, "train", trained)
    rows = queries.QUERIES["w16_participation"](spark, SF2).collect()
    n = spark.read.parquet(f"{SF2}/lineitem.parquet").count()
    assert steps == [n * r["participations"] // r["g"] for r in rows]


def test_cross_validation_trains_on_all_users_of_the_folds(spark, monkeypatch):
    from ldpspark.erm import crossval

    seen = []

    def kept(*args):
        out = descent.sgd(*args)
        seen.extend(r["users"] for r in out.collect())
        return out

    monkeypatch.setattr(crossval, "sgd", kept)
    rows = [(f"u{i}", [0.1, -0.2], 1.0 if i % 3 else -1.0) for i in range(25_000)]
    data = spark.createDataFrame(rows, "ukey string, x array<double>, y double")
    crossval.cross_validated(data, "svm", 25_000, 2, [1.0], folds=10, methods=("sgd_halfspace", "sgd_exact")).collect()
    assert sum(seen) == 2 * 9 * 25_000


def test_small_batches_are_trained_without_slices(spark, monkeypatch):
    from ldpspark.erm import crossval

    monkeypatch.setattr(crossval, "sliced", lambda *a: pytest.fail("users are laid out in slices that no step reads"))
    data = spark.createDataFrame([(f"u{i}", [i % 7 / 7, -0.2], 1.0 if i % 3 else -1.0) for i in range(3000)], "ukey string, x array<double>, y double")
    rows = crossval.cross_validated(data, "linear", 3000, 2, [1.0], folds=4, r=1).collect()
    assert {r["method"] for r in rows} == {"sgd_halfspace", "mgd", "mgd_projected", "sgd_exact"} and {r["users"] for r in rows} == {3000} and {r["folds"] for r in rows} == {4}


def test_order_of_methods_in_linear_regression(spark):
    from ldpspark.erm.crossval import cross_validated

    data = ex.learning_view(spark, SF2, LI23, "linear")
    got = {r["method"]: r["error"] for r in cross_validated(data, "linear", 60_000, 85, [2.44], folds=3, floor_share=24, max_users=1500).collect()}
    assert got["sgd_halfspace"] > 50 * got["mgd"] > 50 * got["mgd_projected"] and got["mgd_projected"] > got["sgd_exact"]


def test_a_step_reads_its_own_slices_and_sums_the_same(spark):
    base = users(spark, SF, NUM4).select("ukey", F.array("quantity", "discount", "tax").alias("x"), F.col("price").alias("y"))
    ready = descent.prepared(base, 4)
    laid = descent.sliced(ready)
    models = [descent.Model("a", 3, 1.0, 3, weights=[0.1, 0.2, 0.3]), descent.Model("b", 3, 2.0, 50, 1), descent.Model("c", 3, 2.0, 7, 2)]
    for t in (0, 1, 2, 6, 49):
        a = descent.gradient_sums(ready, models, t, "linear", 1e-4)
        b = descent.gradient_sums(laid, models, t, "linear", 1e-4)
        assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect())) != []
    assert "PartitionFilters: [isnotnull(slice" in b._jdf.queryExecution().toString() or "PartitionFilters: [slice" in b._jdf.queryExecution().toString()
    assert descent._slices(models, 49) == [descent.SLICES - 1]


@pytest.mark.parametrize("kind", losses.KINDS)
def test_streamed_training_takes_the_steps_of_the_jobs(spark, kind):
    data = users(spark, SF, NUM4).select("ukey", F.array("quantity", "discount", "tax").alias("x"), F.signum(F.col("price")).alias("y"))
    ready = descent.sliced(descent.prepared(data, 3))
    make = lambda: [descent.Model(f"{e}/{f}", 3, e, s, f) for f in range(3) for e, s in ((1.0, 4), (3.0, 9))]
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 700)
    try:
        by_stream = descent.streamed(ready, make(), kind)
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for a, b in zip(by_stream, descent.minibatch(ready, make(), kind)):
        assert np.allclose(a.weights, b.weights, atol=1e-12) and len(a.history) == len(b.history) == a.steps


def test_replayed_runs_are_those_of_the_mechanisms(spark):
    """Means and spreads of the sums over many runs: unbiased, and with the variance of one report per user."""
    data = stored(users(spark, SF, LI23).where("line_no < 2"), "some")
    n, grid, runs = data.count(), [1.0, 4.0], 200
    exact = {("codes", i): 0.0 for i in range(len(LI23.domain()))}
    places = {(x[1], x[3]): i for i, x in enumerate(LI23.domain())}
    for r in est.exact_histogram(data, [(c.name, c.k) for c in LI23.categoricals]).collect():
        exact["codes", places[r["attr"], r["code"]]] = r["exact"]
    numbers = [a.name for a in LI23.numerics]
    for r in est.exact_mean(data, numbers).collect():
        exact["numbers", numbers.index(r["attr"])] = r["exact"]
    scale = {
        replay.MIXED_NUMBERS: lambda e: C.report_scale(e) * 23, replay.MIXED_CODES: lambda e: C.report_scale(e) * 23, replay.SPLIT_NUMBERS: lambda e: C.halfspace_scale(6, e * 6 / 23),
        replay.SPLIT_CODES: lambda e: C.report_scale(e / 23), replay.ALONE_MIXED: lambda e: C.report_scale(e) * 6, replay.ALONE_SPLIT: lambda e: C.halfspace_scale(6, e),
    }
    found = replay.replayed(data, LI23, grid, runs, n, 0.05, tuple(scale)).groupBy("kind", "e", "at").agg(F.avg("total").alias("m"), F.stddev("total").alias("sd"), F.count(F.lit(1)).alias("runs")).collect()
    assert {r["runs"] for r in found} == {runs}
    wide = []
    for r in found:
        b = scale[r["kind"]](grid[r["e"]]) / n
        codes = r["kind"] in (replay.MIXED_CODES, replay.SPLIT_CODES)
        off = b * r["m"] - exact["codes" if codes else "numbers", r["at"]]
        # the runs share their random matrices, whose columns are at inner products of about 1 / sqrt(rows)
        rows = min(C.projection_rows(c.k, n, grid[r["e"]] / 23, 0.05) for c in LI23.categoricals)
        if abs(off) > 4 * b * r["sd"] / math.sqrt(runs) + (4 / math.sqrt(rows) if r["kind"] == replay.SPLIT_CODES else 0):
            wide.append((r["kind"], r["e"], r["at"], off, b * r["sd"]))
    assert not wide


def test_replayed_sums_do_not_depend_on_tables_or_held_users(spark, monkeypatch):
    data = stored(users(spark, SF, LI23), "some")
    kinds = tuple(range(6))
    read = lambda: sorted(map(tuple, replay.replayed(data, LI23, [0.5, 9.0], 3, 6000, 0.05, kinds).collect()))
    want = read()
    for name, value in (("TABLE", 0), ("TABLE", 3000), ("HELD", 400), ("ROWS", 100)):
        with monkeypatch.context() as m:
            m.setattr(replay, name, value)
            assert read() == want


def test_half_space_signs_equal_those_by_sorting():
    rng = np.random.default_rng(2)
    v, u, p = rng.uniform(-1, 1, (6, 500)), rng.random((14, 500)), np.array([0.5, 0.8])
    cdfs = tuple(np.array(x) for x in C.halfspace_cdf(6))
    rank = u[6:12].T.argsort(1).argsort(1)
    alike = [np.searchsorted(c, u[12], "right") for c in cdfs]
    vertex = np.where(u[:6] < (1 + v) / 2, 1, -1).T
    want = [np.where(rank < np.where(u[13] < x, *alike)[:, None], vertex, -vertex).sum(0) for x in p]
    assert (replay._halfspace(v, u, cdfs, p) == want).all()


def test_projection_keeps_the_cube():
    p = np.array(projection.matrix(20, 85))
    x = np.random.default_rng(1).uniform(-1, 1, (500, 85))
    assert abs(x @ p.T).max() <= 1 and set(np.unique(abs(p))) == {1 / 85}


# --- around it

def test_asof_join_with_and_without_buckets(spark):
    left = spark.createDataFrame([(1, t, t) for t in (0, 5, 9, 25, 99)] + [(2, 3, 3)], "u int, t int, id int")
    right = spark.createDataFrame([(1, 5, "a"), (1, 20, "b"), (3, 1, "z")], "u int, t int, v string")
    for bucket in (None, F.floor(F.col("t") / 10)):
        got = {(r["u"], r["id"]): r["v"] for r in relops.asof_join(left, right, "t", ["u"], ["v"], bucket).collect()}
        assert got == {(1, 0): None, (1, 5): "a", (1, 9): "a", (1, 25): "b", (1, 99): "b", (2, 3): None}


def test_budget_and_survey_numbers(spark):
    assert budget.split(1.0, [1, 3]) == [0.25, 0.75]
    assert abs(C.fair_coin_epsilon(0.5) - math.log(3)) < 1e-12
    assert num.bits_per_user("half_space", 6) == 6 and num.bits_per_user("one_coordinate", 6) == 1
    df = spark.createDataFrame([(0, 0.1), (1, 0.3)], "run int, linf double")
    assert mea.coverage(df, 0.2, []).first()["covered"] == 0.5


def test_participation_stores_no_slices_for_batches_that_train_on_a_stream(spark, monkeypatch):
    from ldpspark import queries

    cuts = []
    monkeypatch.setattr(queries, "sliced", lambda users, *a, kept=queries.sliced: cuts.append(1) or kept(users, *a))
    assert queries.QUERIES["w16_participation"](spark, SF2.replace("0.01", "0.001")).count() == 3
    assert not cuts


@pytest.mark.parametrize("kind", losses.KINDS)
def test_wide_descent_is_compiled_and_takes_the_steps_of_a_walk(spark, monkeypatch, kind):
    rng = np.random.default_rng(4)
    rows = [(f"u{i}", [float(v) for v in rng.uniform(-1, 1, 12)], float(rng.choice([-1, 1]))) for i in range(1500)]
    ready = descent.prepared(spark.createDataFrame(rows, "ukey string, x array<double>, y double"), 3)
    ordered = sorted(ready.collect(), key=lambda r: r["ub"])
    models = [descent.Model(f"0.0/{f}", 12, 0.0, 1, f) for f in range(3)]
    want = {}
    for n in (None, 64):
        for f in range(3):
            own = [r for r in ordered if r["fold"] != f][:n]
            want[n, f] = len(own), descent.fold_users(np.array([r["x"] for r in own]), np.array([r["y"] for r in own]), kind, 1e-3, 0.05)
    monkeypatch.setattr(descent, "_unpacked", lambda *a: pytest.fail("a wide model steps through calls of array functions"))
    stream = stored(descent.packed(ready), "packed")
    for n in (None, 64):
        found = descent.sgd(stream, models, kind, 1e-3, 0.05, max_users=n)
        assert "MapInArrow" not in found._jdf.queryExecution().executedPlan().toString()
        for r in found.collect():
            users, w = want[n, int(r["model"][-1])]
            assert r["users"] == users and np.allclose(r["weights"], w, atol=1e-12)


def test_compiled_half_space_reports_are_unbiased_and_fill_the_half_space(spark):
    """One step from 0 of many folds on one user: the move is the step size times a report of the clamped gradient."""
    x, d, runs = [1.0, -1.0, 0.5, -0.5, 0.0, 0.25, 1.0, -1.0, 0.75, -0.25], 10, 3000
    one = descent.prepared(spark.createDataFrame([("u", x, 1.0)], "ukey string, x array<double>, y double"))
    stream = stored(descent.packed(one), "packed")
    rows = descent.walked(descent._streams(stream, 1, False), [(0, f, f"{e}/{f}", e) for f in range(runs) for e in (0.5, 3.0)], d, "svm", 0.0, 1.0, True, 42, None).collect()
    assert len(rows) == 2 * runs
    for e in (0.5, 3.0):
        size = C.halfspace_scale(d, e)
        moves = np.array([r["weights"] for r in rows if r["model"].startswith(f"{e}/")])
        assert np.allclose(abs(moves), size)
        assert (abs(moves.mean(0) - np.array(x)) < 4.5 * size / math.sqrt(runs)).all()
        # the places of certain sign say how often the report agrees
        sure = [0, 1, 6, 7]
        assert abs((moves[:, sure] * np.array(x)[sure] > 0).mean() - (1 + 1 / size) / 2) < 4.5 / math.sqrt(4 * runs)


def test_packed_users_are_tested_and_projected_where_they_are(spark):
    for kind in ("linear", "svm"):
        ready = stored(descent.prepared(ex.learning_view(spark, SF, LI23, kind), 4), "ready")
        rows = stored(descent.packed(ready), "packed")
        assert descent.fold_sizes(rows) == {r["fold"]: r["count"] for r in ready.groupBy("fold").count().collect()}
        p = projection.matrix(20, 85)
        for users_, table, dim in ((ready, rows, 85), (projection.projected(ready, p), descent.projected_rows(rows, p), 20)):
            models = [(f"{m}/{f}", f, [float(v) for v in np.random.default_rng(10 * m + f).normal(size=dim)]) for m in (1, 2) for f in range(4)]
            weights = spark.createDataFrame([(a, b, c) for a, b, c in models], "model string, mfold int, w array<double>")
            at = users_.join(F.broadcast(weights), F.col("fold") == F.col("mfold"))
            want = {r["model"]: (r["users"], r["error"]) for r in losses.evaluate(at, F.col("w"), kind, "model").collect()}
            got = {r["model"]: (r["users"], r["error"]) for r in descent.tested_rows(table, models, kind).collect()}
            assert got.keys() == want.keys()
            assert all(got[k][0] == want[k][0] and abs(got[k][1] - want[k][1]) < 1e-9 * max(1, want[k][1]) for k in want)


def test_batches_of_the_studies_need_no_jobs(spark, monkeypatch):
    from ldpspark import queries
    from ldpspark.erm import crossval

    monkeypatch.setattr(descent, "gradient_sums", lambda *a: pytest.fail("a step is a job"))
    monkeypatch.setattr(crossval, "sliced", lambda *a: pytest.fail("users are laid out in slices that no step reads"))
    rows = queries.QUERIES["w10_svm_narrow"](spark, SF2).collect()
    assert {r["users"] for r in rows} == {60_000} and len(rows) == 21


def test_a_cross_validation_reads_few_packed_rows_at_once(spark, monkeypatch):
    from ldpspark.erm import crossval

    before, seen = spark.conf.get(crossval.READER), []
    monkeypatch.setattr(crossval, "sgd", lambda rows, *a: seen.append(int(spark.conf.get(crossval.READER))) or descent.sgd(rows, *a))
    data = spark.createDataFrame([(f"u{i}", [i % 7 / 7, -0.2], 1.0 if i % 3 else -1.0) for i in range(300)], "ukey string, x array<double>, y double")
    crossval.cross_validated(data, "linear", 300, 2, [1.0], folds=2, r=1).collect()
    assert len(seen) == 2 and max(seen) <= 64 and spark.conf.get(crossval.READER) == before
