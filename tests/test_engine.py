"""Gradients, schemes, clock, optimisers and training."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenkeel.functions import metrics
from evenkeel.functions.losses import L2, Logistic, Squared
from evenkeel.operators import clock, codes, gradient, live, messages, optim, placement, schemes, train
from evenkeel.operators.clock import Costs
from evenkeel.operators.stragglers import Delays, Stragglers, late_table
from evenkeel.plans import planner
from evenkeel.sources import datasets

X = datasets.SCALED


@pytest.fixture(scope="module")
def samples(spark, small):
    return datasets.lineitem_planted(spark, small).persist()


@pytest.mark.parametrize("loss", [Logistic(), Squared()], ids=["logistic", "squared"])
def test_kernels_agree_with_numpy(spark, samples, loss):
    beta = np.array([0.3, -0.2, 0.5, 0.1, -0.4])
    d = placement.assign_blocks(samples, F.col("key"), 6).withColumn("x", F.array(*X))
    table = d.select("y", "block", *X).toPandas()
    x = table[X].to_numpy()
    want = loss.slope_np(x @ beta, table["y"].to_numpy()) @ x
    xs = d.select("block", "y", F.monotonically_increasing_id().alias("row_id"), F.array(*[F.struct(F.lit(j).alias("idx"), F.col(c).alias("val")) for j, c in enumerate(X)]).alias("xs"))
    for kernel in ("wide", "array", "arrow"):
        assert np.allclose(gradient.full_gradient(d, loss, beta, kernel, X), want, rtol=1e-9)
    assert np.allclose(gradient.full_gradient(xs, loss, beta, "sparse"), want, rtol=1e-9)
    joined = gradient.to_vector(gradient.partial_sparse(xs, loss, beta, limit=0).groupBy("idx").agg(F.sum("g").alias("g")), 5, 0)
    assert np.allclose(joined, want, rtol=1e-9)


def test_plan_is_one_codegen_aggregate(spark, small):
    d = placement.assign_blocks(datasets.lineitem_integer(spark, small), F.col("key"), 6)
    plan = gradient.partial_wide(d, Logistic(), [0.0] * 4, datasets.INTEGER)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and plan.count("Exchange") == 1
    assert "ReadSchema: struct<l_orderkey:bigint,l_linenumber:int,l_quantity:double," in plan and "l_shipdate" not in plan


def test_worker_scan_is_pruned(spark, small, tmp_path):
    code = codes.ring_code(6, 2)
    d = placement.assign_blocks(datasets.lineitem_integer(spark, small), F.col("key"), 6)
    placement.write_blocks(d, str(tmp_path / "b"), 6)
    exact = gradient.full_gradient(d, Logistic(), np.zeros(4), "wide", datasets.INTEGER)
    sent = np.array([messages.worker_message(spark, str(tmp_path / "b"), code, w, Logistic(), np.zeros(4), datasets.INTEGER) for w in range(6)])
    from evenkeel.operators.decode import Decoder

    for alive in codes.patterns(6, 2):
        assert np.allclose(Decoder(code).row(alive) @ sent, exact, rtol=1e-7)
    plan = spark.read.parquet(str(tmp_path / "b")).where("block in (0, 1, 2)")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [block" in plan


def test_live_round_does_not_wait(spark, small, tmp_path):
    code = codes.ring_code(4, 1)
    d = placement.assign_blocks(datasets.lineitem_integer(spark, small), F.col("key"), 4)
    placement.write_blocks(d, str(tmp_path / "b"), 4)
    exact = gradient.full_gradient(d, Logistic(), np.zeros(4), "wide", datasets.INTEGER)
    done = live.run_round(spark, str(tmp_path / "b"), code, Logistic(), np.zeros(4), datasets.INTEGER, [0, 60.0, 0, 0])
    assert 1 not in done.used and done.ms < 50_000 and np.allclose(done.gradient, exact, rtol=1e-7)
    assert np.allclose(live.run_round_single_job(spark, str(tmp_path / "b"), Logistic(), np.zeros(4), datasets.INTEGER).gradient, exact)


NAMES = ["uncoded", "block", "ring", "full_copy", "feedback_replica"]


@pytest.mark.parametrize("name", NAMES)
def test_exact_schemes_are_exact(name):
    g, rows = np.random.default_rng(1).standard_normal((12, 7)), np.full(12, 100.0)
    scheme = schemes.build(name, 12, 2)
    for t in range(8):
        done = scheme.round(g, rows, Stragglers("additive", s=2, delay_ms=50.0).of_round(t, 12))
        assert np.allclose(done.gradient, g.sum(axis=0), atol=1e-8) and done.share == pytest.approx(1)


def test_dead_workers():
    g, rows, dead = np.ones((12, 2)), np.ones(12), Stragglers("dead", fixed=(3, 7)).of_round(0, 12)
    for name in ("block", "ring", "full_copy"):
        assert np.allclose(schemes.build(name, 12, 2).round(g, rows, dead).gradient, 12)
    with pytest.raises(schemes.RoundFailed):
        schemes.build("uncoded", 12, 0).round(g, rows, dead)
    with pytest.raises(schemes.RoundFailed):
        schemes.build("two_stage_ring", 12, 2, 2.0).round(g, g, rows, rows, dead)


def _times(name, s, delay, alpha=1.5, rounds=12, kind="additive", factor=1.0):
    g, rows, out = np.ones((12, 5)), np.full(12, 46_200.0), []
    scheme = schemes.build(name, 12, s, alpha)
    for t in range(rounds):
        d = Stragglers(kind, s=s, delay_ms=delay, factor=factor).of_round(t, 12)
        if name.startswith("two_stage"):
            done = scheme.round(g, g, rows * scheme.code.plain_share, rows * scheme.code.coded_share, d)
        else:
            done = scheme.round(g, rows, d)
        out.append(done.round_ms)
    return np.mean(out)


def test_run_time_against_delay():
    """Uncoded rounds grow with the delay, coded rounds do not, and win once it is long."""
    for s in (1, 2):
        for name in ("block", "ring"):
            assert _times(name, s, 5000) == pytest.approx(_times(name, s, 200))
            assert _times(name, s, 5000) < _times("uncoded", s, 5000)
            assert _times(name, s, 0) > _times("uncoded", s, 0)
        assert _times("uncoded", s, 5000) > _times("uncoded", s, 500) + 4000
        assert _times("drop_s", s, 5000) <= _times("ring", s, 5000)


def test_two_stage_up_to_alpha():
    at = [_times("two_stage_block", 2, 0, 2.0, kind="slowdown", factor=f) for f in (1.0, 1.5, 2.0, 4.0)]
    assert at[0] == pytest.approx(at[1]) == pytest.approx(at[2], rel=0.01) and at[3] > 1.5 * at[0]
    assert at[0] < _times("block", 2, 0)


def test_drop_s_without_stragglers_is_uncoded():
    g, rows, none = np.random.default_rng(2).standard_normal((12, 3)), np.ones(12), Stragglers().of_round(0, 12)
    a, b = schemes.DropS(12, 0).round(g, rows, none), schemes.Uncoded(12).round(g, rows, none)
    assert np.allclose(a.gradient, b.gradient) and a.round_ms == b.round_ms
    c = schemes.DropS(12, 3).round(g, rows, none)
    assert len(c.used) == 9 and c.share == pytest.approx(0.75)
    assert np.allclose(schemes.DropS(12, 3, rescale=True).round(g, rows, none).gradient, c.gradient * 12 / 9)


def test_first_decodable_stops_early():
    g, rows = np.ones((6, 2)), np.ones(6)
    delays = Delays(np.array([0, 1, 50, 50, 50, 50.0]), np.ones(6), np.zeros(6, bool))
    early = schemes.Coded(codes.block_code(6, 2), "first_decodable").round(g, rows, delays)
    late = schemes.Coded(codes.block_code(6, 2)).round(g, rows, delays)
    assert early.round_ms < late.round_ms and np.allclose(early.gradient, 6)


def test_serial_master():
    assert clock.drained(np.array([3.0, 1.0, 1.5]), 1.0).tolist() == [4.0, 2.0, 3.0]


def test_stragglers_alike_in_spark_and_python(spark):
    rows = late_table(spark, 6, 12, 2).collect()
    s = Stragglers("additive", s=2)
    assert all(r.late == (r.worker in s.late(r.round, 12)) for r in rows)


def test_training_path_does_not_depend_on_the_code(samples):
    fit = lambda name, alpha=1.5: train.fit(samples.where("not holdout"), "key", schemes.build(name, 12, 2, alpha), Logistic(), optim.NAG(5, 2.0), 4, Stragglers("additive", s=2, delay_ms=90.0), columns=X, keep_betas=True)
    plain = fit("uncoded")
    for name in ("block", "ring", "two_stage_ring"):
        assert np.allclose(fit(name).betas, plain.betas, atol=1e-8)
    with pytest.raises(ValueError):
        fit("drop_s")


def test_mini_batches(samples):
    done = train.fit(samples, "key", schemes.build("ring", 6, 1), Logistic(), optim.GD(5, 1.0), 4, columns=X, batches=2)
    assert len(done.trace) == 4 and max(r["gradient_error"] for r in done.trace) < 1e-7


@pytest.mark.parametrize("make", [lambda: optim.GD(3, 0.5), lambda: optim.NAG(3, 0.3), lambda: optim.LBFGS(3), lambda: optim.DecayGD(3, 20, 30), lambda: optim.Prox(3, 0.5, 0.0), lambda: optim.AcceleratedProx(3, 0.3, 0.0), lambda: optim.FrankWolfe(3, 10.0)])
def test_optimisers_reach_the_minimum(make):
    a, b = np.diag([1.0, 0.5, 1.5]), np.array([1.0, -2.0, 0.5])
    o = make()
    for _ in range(400):
        o.step(a @ o.point() - b)
    assert np.abs(o.beta - np.linalg.solve(a, b)).max() < (0.3 if isinstance(o, optim.FrankWolfe) else 1e-2)


def test_penalties():
    o = optim.GD(1, 0.5, L2(1.0))
    for _ in range(100):
        o.step(o.point() - 1)
    assert o.beta[0] == pytest.approx(0.5)
    p = optim.Prox(2, 0.5, 0.4)
    for _ in range(100):
        p.step(p.point() - np.array([1.0, 0.3]))
    assert p.beta == pytest.approx([0.6, 0.0])


def test_auc(spark):
    rng = np.random.default_rng(5)
    score, y = rng.integers(0, 8, 200) / 8, (rng.random(200) > 0.6).astype(float)
    pos, neg = score[y == 1], score[y == 0]
    want = ((pos[:, None] > neg).sum() + (pos[:, None] == neg).sum() / 2) / (len(pos) * len(neg))
    assert metrics.auc_np(score, y) == pytest.approx(want)
    frame = spark.createDataFrame([(float(a), float(b)) for a, b in zip(score, y, strict=True)], "score double, y double")
    assert metrics.auc(frame).first()["auc"] == pytest.approx(want)
    assert metrics.auc_np(np.ones(10), np.arange(10) % 2) == 0.5


def test_packing_by_cost():
    packed = placement.pack_by_cost({i: float(c) for i, c in enumerate([50, 1, 1, 30, 20, 10, 9, 9])}, 3)
    totals = np.zeros(3)
    for i, c in enumerate([50, 1, 1, 30, 20, 10, 9, 9]):
        totals[packed[i]] += c
    assert totals.max() <= 50 and totals.min() >= 38


def test_advice():
    assert planner.advise(12, 2, 10**6, 10, 0.001, 0.0001, 8.0).scheme.startswith("two_stage")
    assert planner.advise(12, 2, 10**6, 10, 0.001, 0.0001, 1.0).scheme != "block"
    assert planner.advise(12, 2, 10**6, 10, 0.001, 0.0001, 8.0, may_fail=True).scheme == "block"


def test_mixture_recovers_the_model(spark):
    d = datasets.mixture_logistic(spark, 4000, 6)
    done = train.fit(d, "key", schemes.build("block", 6, 1), Logistic(), optim.NAG(6, 1.5), 30, kernel="arrow")
    assert np.corrcoef(done.beta, -2 * datasets.true_beta(6))[0, 1] > 0.97
    again = datasets.mixture_logistic(spark, 4000, 6, partitions=3)
    assert d.exceptAll(again).count() == 0
    assert Costs().row_ms > 0


def test_measures(spark):
    assert metrics.load("two_stage", 3, 1, 2.0)["load"] == pytest.approx(4 / 9)
    assert metrics.bytes_on_wire(3, 10, 2) == 272
    t = spark.createDataFrame([(0, 1.0), (0, 3.0), (1, 10.0), (1, 10.0), (2, 2.0), (2, 2.0)], "worker int, delay_ms double")
    ratio = {r.worker: r.ratio for r in metrics.communication(t).collect()}
    assert ratio == {0: 1.0, 1: 5.0, 2: 1.0}


def test_errors_of_weighted_sums_equal_numpy(spark):
    """Block gradients stay on executors; a block without some coordinate has 0 there."""
    from evenkeel.plans import run_queries

    rng = np.random.default_rng(4)
    g, weights = rng.standard_normal((5, 300)) * (rng.random((5, 300)) < 0.6), rng.standard_normal((7, 5))
    long = spark.createDataFrame([(int(b), int(i), float(g[b, i])) for b, i in zip(*np.nonzero(g), strict=True)], "block int, idx int, g double")
    want = np.linalg.norm((weights - 1) @ g, axis=1) / np.linalg.norm(g.sum(axis=0))
    assert np.allclose(run_queries._errors(long, weights), want, rtol=1e-12)


def test_counted_samples_equal_single_ones(spark, small):
    """Two steps on one-hot categories: a row a combination and number by block, or a row a sample."""
    scheme, late = schemes.build("ring", 10, 1), Stragglers("additive", s=1, delay_ms=100.0)
    single = train.fit(datasets.star_one_hot(spark, small, 500), "key", scheme, Logistic(), optim.GD(500, 2.0), 2, late, kernel="sparse")
    counted, places = datasets.star_counted(spark, small, 10, 500)
    many = train.fit(counted, "", scheme, Logistic(), optim.GD(500, 2.0), 2, late, kernel="counted", places=places)
    assert np.allclose(single.beta, many.beta, rtol=1e-9, atol=1e-12)
    assert [t["round_ms"] for t in single.trace] == [t["round_ms"] for t in many.trace]


def test_mixture_samples_equal_the_table(spark):
    table = datasets.mixture_logistic(spark, 500, 7).orderBy("key").toPandas()
    x, y = datasets.mixture_samples(table["key"].to_numpy(), 7, datasets.mixture_heads(spark))
    assert np.allclose(x, np.stack(table["x"].to_numpy()), rtol=1e-12, atol=1e-12) and (y == table["y"]).all()


def test_training_of_all_schemes_equals_each_alone(spark, small, monkeypatch):
    """In one scan a round, without a table of samples."""
    from evenkeel.plans import run_queries as q

    monkeypatch.setattr(q, "P", 6)
    d = q._size(spark, small)
    samples, late = datasets.mixture_logistic(spark, d, 6), Stragglers("additive", s=1, delay_ms=2 * (d / q.N * q.COSTS.row_ms + 6 * q.COSTS.float_ms + q.COSTS.latency_ms))
    monkeypatch.setattr(q.datasets, "mixture_logistic", None)
    got = q.artificial_training(spark, small, 3).toPandas()
    for name, alpha in (("drop_s", 0.0), ("ring", 0.0), ("two_stage_ring", 2.0)):
        make = optim.DecayGD(6, 2.0, 10.0) if name == "drop_s" else optim.NAG(6, 0.2)
        want = train.fit(samples, "key", schemes.build(name, q.N, 1, alpha or 1.5), Logistic(), make, 3, late, q.COSTS, kernel="arrow").trace
        own = got[got["scheme"] == name]
        for c in ("round", "round_ms", "cum_ms", "share", "gradient_error"):
            assert np.allclose(own[c], [r[c] for r in want], rtol=1e-8, atol=1e-12), (name, c)
