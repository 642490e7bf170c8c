"""Invariants of the engine on Spark."""

import datetime as dt
import math

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from learned_upkeep.functions import columns as fn
from learned_upkeep.nn.darn import MaskedAutoregressive
from learned_upkeep.nn.mdn import MixtureDensity
from learned_upkeep.nn.training import Settings, fit_by_partitions, full_gradient, gradient, matrix, score
from learned_upkeep.nn.vae import TabularVae
from learned_upkeep.operators import answers, counts, detect, drift, drift_tests, joins, metrics, networks, regression, update, workload
from learned_upkeep.plans import experiments, queries, sqlapi, upkeep
from learned_upkeep.sources import catalog
from learned_upkeep.sources.catalog import D1, INDEP, Fixture
from learned_upkeep.sources.registry import Registry
from learned_upkeep.streaming import monitor


@pytest.fixture(scope="module")
def d1(spark, sf):
    return D1.build(spark, sf).persist()


@pytest.fixture(scope="module")
def ood(d1):
    return drift.permuted_batch(d1, D1.columns).persist()


def bag(df, *columns):
    return sorted(map(tuple, df.select(*columns).collect()))


def test_samples_are_nested_and_do_not_depend_on_partitions(d1):
    small, large = fn.hash_sample(d1, 0.1, 1), fn.hash_sample(d1, 0.3, 1)
    assert small.exceptAll(large).isEmpty() and bag(small, "rk") == bag(fn.hash_sample(d1.repartition(7), 0.1, 1), "rk")


def test_sorting_keeps_every_marginal(d1):
    full = drift.permuted_batch(d1, D1.columns, 1.0)
    for c in D1.columns:
        assert bag(full, c) == bag(d1, c)
    pair = drift.permuted_pair(catalog.D2.build(d1.sparkSession, "/root/testdata/sf0.001"), "qty_band", "log_unit", 1.0).orderBy("log_unit").toPandas()
    assert pair["qty_band"].is_monotonic_increasing


def test_global_rank_counts_up(d1):
    got = drift.global_rank(d1, ["unit_band", "rk"], parts=5).orderBy("rank").toPandas()
    assert got["rank"].tolist() == list(range(len(got))) and got["unit_band"].is_monotonic_increasing


def test_normal_cdf(spark):
    z = [(-4 + 0.25 * i,) for i in range(33)]
    for r in spark.createDataFrame(z, "z double").select("z", fn.normal_cdf(F.col("z")).alias("p")).collect():
        assert r["p"] == pytest.approx(0.5 * math.erfc(-r["z"] / math.sqrt(2)), abs=1e-7)


def test_count_model_is_a_distribution(d1):
    assert counts.fit(d1, D1).masses().agg(F.sum("prob")).first()[0] == pytest.approx(1)


def model_rows(m):
    return {tuple(r)[:-1]: r["prob"] for r in m.masses().collect()}


def test_distillation_identities(d1, ood):
    old, new = counts.cells(d1, D1.columns), counts.cells(ood, D1.columns)
    n_old, n_new = d1.count(), ood.count()
    exact = counts.fit_cells(old, D1, 1e-12, n_old)
    grown = counts.fit_cells(old.unionByName(new).groupBy(*D1.columns).agg(F.sum("n").alias("n")), D1, 1e-12, n_old + n_new)
    kd = counts.distil(exact, old, new, 1.0, update.new_weight(n_new, n_old, "mass"), n_old + n_new)
    want, got = model_rows(grown), model_rows(kd)
    assert max(abs(want[k] - got[k]) for k in want) < 1e-9  # the whole old data as transfer set, weights by mass: retraining
    alone = model_rows(counts.distil(exact, old, new, 0.5, 1.0, n_new))
    batch_only = model_rows(counts.fit_cells(new, D1, 1e-12, n_new))
    assert max(abs(alone[k] - batch_only[k]) for k in alone if batch_only[k] > 1e-6) < 1e-6
    same = model_rows(counts.distil(exact, old, new, 1.0, 0.0, n_old))
    base = model_rows(exact)
    assert max(abs(same[k] - base[k]) for k in base) < 1e-9  # no batch, teacher only: nothing moves


def test_weights_of_the_batch_term():
    assert update.new_weight(20, 100, "described") == 0.2 and update.new_weight(20, 100, "printed") == 0.8
    assert update.new_weight(20, 100, "mass") == pytest.approx(1 / 6) and update.new_weight(300, 100) == 1 and update.new_weight(1, 2, 0.3) == 0.3


def test_bootstraps_agree_with_the_normal_limit(d1):
    scored = counts.fit(d1, D1).score(d1)
    std = detect.normal_std(scored, 600).first()["std"]
    means = detect.bootstrap_binned(scored, 2000, 600)
    assert means.std() == pytest.approx(std, rel=0.1) and means.mean() == pytest.approx(scored.agg(F.avg("loss")).first()[0], abs=0.05)
    sample = scored.where(fn.row_hash("rk", 5) < fn.cut(0.1))
    poisson = detect.bootstrap_poisson(sample, 200).agg(F.stddev("mean_loss")).first()[0]
    assert poisson == pytest.approx(detect.normal_std(sample, sample.count()).first()["std"], rel=0.25)


def test_detection_fires_on_drift_only(d1, ood, spark, sf):
    m = counts.fit(d1, D1)
    base = detect.offline(m.score(d1), 500)
    assert not detect.test_batch(m.score(drift.ind_batch(d1)), base).is_ood
    v = detect.test_batch(m.score(ood), base)
    assert v.is_ood and v.shift > 5 * v.threshold and v.p_normal < 1e-6 and v.p_empirical < 0.01
    reverse = drift.permuted_batch(d1, D1.columns, descending=("qty_band",))
    assert detect.test_batch(m.score(reverse), base).is_ood
    free = INDEP.build(spark, sf)
    mi = counts.fit(free, INDEP)
    control = detect.test_batch(mi.score(drift.permuted_batch(free, INDEP.columns)), detect.offline(mi.score(free), 500))
    assert abs(control.shift) < 3 * control.threshold  # independent columns: sorting can't show in the mean loss


def test_detection_edge_cases(spark, d1):
    base = detect.Baseline(1.0, 0.0, 100, 0.0, 100, (1.0,) * 10)
    one = lambda *v: spark.createDataFrame([(x,) for x in v], "loss double")
    assert not detect.test_batch(one(1.0, 1.0), base).is_ood and detect.test_batch(one(2.0, 2.0), base).is_ood
    for bad in (one(), one(1.0), one(1.0, float("nan"))):
        with pytest.raises(ValueError):
            detect.test_batch(bad, base)
    assert detect.threshold(detect.Baseline(0, 0.1, 400, 2.0, 400), 100, "size_matched") == pytest.approx(0.4)
    assert detect.factor(0.05) == pytest.approx(1.96, abs=0.01) and detect.factor(None) == 2
    with pytest.raises(ValueError):
        detect.bootstrap_binned(one(), 10)
    assert not detect.fires(-3, 1, "upper") and detect.fires(-3, 1, "lower") and detect.fires(-3, 1)


def test_batches_of_pools(spark, sf):
    rows = [(1, float(i)) for i in range(40)] + [(2, 100.0 + i) for i in range(60)]
    drawn = detect.pool_batches(spark.createDataFrame(rows, "level int, loss double"), 300, (1, 30, 80)).toPandas()
    assert len(drawn) == 3 * 300 * 3 and set(drawn["level"]) == {0, 1, 2}
    whole = drawn[(drawn["level"] == 1) & (drawn["size"] == 80)]
    assert (whole["n"] == 40).all() and np.allclose(whole["l"], 19.5)  # without replacement: the whole slice
    assert drawn[(drawn["level"] == 0) & (drawn["size"] == 30)]["l"].mean() == pytest.approx(np.mean([r[1] for r in rows]), abs=3)
    rates = {(r["size"], r["level"]): r for r in queries.queries()["batch_size_sweep_pools"](spark, sf).collect()}
    assert {k for _, k in rates} == set(range(6)) and max(k for k, _ in rates) == 2000
    assert all(r["n"] == (2000 if level == 0 else 1000) for (_, level), r in rates.items())
    # misses fall with the batch's size
    assert rates[(1, 0)]["fnr"] > rates[(200, 0)]["fnr"]


def test_discrepancy_of_all_rows(spark, d1):
    a, b = d1.orderBy("rk").limit(700), d1.orderBy(F.desc("rk")).limit(900)
    x, y = (t.select(*D1.columns).toPandas().to_numpy(float) for t in (a, b))
    k = lambda p, q: np.exp(-0.1 * ((p[:, None] - q[None]) ** 2).sum(axis=2)).mean()
    assert drift_tests.mmd_cells(a, b, D1.columns).first()[0] == pytest.approx(k(x, x) + k(y, y) - 2 * k(x, y), abs=2e-6)
    moved = b.withColumn("flag", F.when(F.row_number().over(Window.orderBy("rk")) > 200, F.lit(0)).otherwise(F.col("flag")))
    assert drift_tests.mmd_cells(a, moved, D1.columns).first() != drift_tests.mmd_cells(a, b, D1.columns).first()  # drift beyond the first 200 rows shows
    assert drift_tests.mmd_cells(a, a, D1.columns).first()[0] == 0


def test_bootstrap_of_all_rows(spark, sf, d1):
    m = counts.fit(d1, D1)
    scored = m.score(d1)
    got = detect.bootstrap_cells(m.score(counts.cells(d1, D1.columns))).toPandas()["mean_loss"]
    loss, rng = scored.select("loss").toPandas()["loss"].to_numpy(), np.random.default_rng(2)
    brute = np.array([loss[rng.integers(0, len(loss), len(loss))].mean() for _ in range(1000)])
    assert len(got) == 1000 and got.mean() == pytest.approx(loss.mean(), abs=4 * brute.std() / 1000**0.5) and got.std() == pytest.approx(brute.std(), rel=0.12)
    assert queries.queries()["bootstrap_all_rows"](spark, sf).agg(F.stddev("mean_loss")).first()[0] == pytest.approx(brute.std(), rel=0.12)


def test_detection_trains_on_all_rows(spark, sf, d1, monkeypatch):
    def refused(*args, **kwargs):
        raise AssertionError("a sample was taken")

    monkeypatch.setattr(networks, "fit", refused)
    m = networks.train_all(MaskedAutoregressive(D1.sizes, 16), d1.repartition(2), list(D1.columns), Settings(epochs=3, rate=5e-3))
    assert m.rows == d1.count() and m.steps == 3 * d1.count()
    verdicts = {r["batch"]: r["is_ood"] for r in experiments.detection(spark, sf, D1, "darn").collect()}
    assert verdicts == {"ind": False, "ood": True}


def test_truth_adds_up_and_boxes_match_sql(d1, ood):
    q = workload.ce_queries(d1, D1, 30).persist()
    both = workload.truth(q, d1.unionByName(ood), D1)
    assert bag(workload.truth_added(workload.truth(q, d1, D1), workload.truth(q, ood, D1)), "qid", "truth") == bag(both, "qid", "truth")
    for r in q.limit(5).collect():
        where = " AND ".join(f"{c} BETWEEN {r[f'{c}_lo']} AND {r[f'{c}_hi']}" for c in D1.columns)
        assert both.where(f"qid = {r['qid']}").first()["truth"] == d1.unionByName(ood).where(where).count()


def test_policy_order(d1, ood):
    q = workload.ce_queries(d1, D1, 100)
    after = workload.truth_added(workload.truth(q, d1, D1), workload.truth(q, ood, D1))
    p95 = {}
    for name, m in update.policies(D1, d1, ood, which=("retrain", "kd_described", "kd_mass", "fine_tune", "stale")).items():
        est = workload.over_cells(q, m.masses(), D1.columns, "prob", "p").select("qid", (F.col("p") * m.rows).alias("estimate"))
        p95[name] = metrics.summary(metrics.q_errors(est, after), by=()).first()["p95"]
    assert p95["retrain"] <= p95["kd_mass"] * 1.05 and p95["kd_described"] < p95["stale"] < p95["fine_tune"]


def test_metrics_by_hand(spark):
    e = spark.createDataFrame([(0, 10.0, 5), (1, 0.0, 0), (2, 0.0, 4), (3, 8.0, 8)], "qid int, estimate double, truth long")
    q = {r["qid"]: r["q_error"] for r in metrics.q_errors(e.drop("truth"), e.select("qid", "truth")).collect()}
    assert q == {0: 2.0, 1: 1.0, 2: 4.0, 3: 1.0}
    r = {x["qid"]: x["rel_error"] for x in metrics.relative_errors(e.drop("truth"), e.select("qid", F.col("truth").cast("double"))).collect()}
    assert r[0] == 100 and r[1] is None and r[3] == 0
    before = e.select("qid", F.when(F.col("qid") < 2, F.col("truth")).otherwise(F.col("truth") - 1).alias("truth"))
    errors = metrics.q_errors(e.drop("truth"), e.select("qid", "truth")).withColumn("policy", F.lit("x"))
    t = metrics.transfer(errors, before, e.select("qid", "truth")).first()
    assert (t["at"], t["fwt"], t["bwt"], t["n_changed"]) == (2.0, 2.5, 1.5, 2)
    assert metrics.changed_share(before, e.select("qid", "truth")).first()["pct_changed"] == 50


def test_joins(spark):
    a = spark.createDataFrame([(i, i % 3) for i in range(9)], "id int, k int")
    b = spark.createDataFrame([(i, f"b{i}") for i in range(3)] + [(1, "again"), (7, "dangling")], "k int, v string")
    whole = a.join(b, "k")
    grown = joins.grow(a.where("id < 5").join(b.where("v <> 'again'"), "k"), joins.delta_two(a.where("id < 5"), a.where("id >= 5"), b.where("v <> 'again'"), b.where("v = 'again'"), ["k"]))
    assert bag(grown, "k", "id", "v") == bag(whole, "k", "id", "v") and joins.bag_difference(whole.select("k", "id", "v"), grown.select("k", "id", "v")).isEmpty()
    for s in joins.STRATEGIES:
        assert bag(joins.equi(a, b, ["k"], strategy=s), "id", "v") == bag(whole, "id", "v")
    iv = spark.createDataFrame([(0.0, 2.5, "x"), (2.0, 9.0, "y")], "lo double, hi double, name string")
    assert bag(joins.in_range(a.select(F.col("id").cast("double").alias("x")), iv, "x", "lo", "hi", 1.0), "x", "name") == sorted([(float(i), n) for i in range(9) for n in (["x"] if i <= 2 else []) + (["y"] if i >= 2 else [])])
    assert joins.lookup(a, b.where("v like 'b%'"), ["k"]).count() == 9


def test_mixture_answers(spark):
    table = spark.createDataFrame([(0, [0.5, 0.5], [-0.5, 0.5], [0.1, 0.2])], "c int, omega array<double>, mu array<double>, sigma array<double>")
    freq = spark.createDataFrame([(0, 1000)], "c int, n long")
    q = spark.createDataFrame([(0, 0, -100.0, 300.0), (1, 0, 0.0, 100.0), (2, 0, 40.0, 30.0)], "qid int, c int, lo double, hi double")
    r = {x["qid"]: x for x in answers.aqp(q, table, freq, "c", 0.0, 200.0).collect()}
    assert r[0]["count"] == pytest.approx(1000, rel=1e-6) and r[0]["avg"] == pytest.approx(100, rel=1e-4) and r[0]["sum"] == pytest.approx(r[0]["count"] * r[0]["avg"])
    assert 0 <= r[1]["avg"] <= 100 and r[1]["count"] == pytest.approx(503, rel=0.01) and r[2]["count"] == 0


def test_trainers_agree(d1):
    c = MaskedAutoregressive(D1.sizes, 16)
    p = c.initial(np.random.default_rng(0))
    cols = list(D1.columns)
    data = matrix(d1, cols)
    value, grads, n = full_gradient(d1.repartition(3), c, p, cols)
    v2, g2 = gradient(lambda leaves: c.loss(leaves, data), p)
    assert n == len(data) and value == pytest.approx(v2, abs=1e-9) and all(np.allclose(grads[k], g2[k], atol=1e-9) for k in p)
    after = fit_by_partitions(d1.repartition(2), c, cols, p, 2, Settings(epochs=1, rate=5e-3))
    assert c.row_loss(after, data).mean() < v2
    assert score(d1.select("rk", *cols), c, p, cols).agg(F.avg("loss")).first()[0] == pytest.approx(v2)
    with pytest.raises(ValueError):
        matrix(d1, cols, 10)


def test_progressive_sampling_matches_enumeration(d1):
    c = MaskedAutoregressive(D1.sizes, 16)
    m = networks.train(c, matrix(d1, list(D1.columns)), 6000, Settings(epochs=5, rate=5e-3))
    q = workload.ce_queries(d1, D1, 20).persist()
    exact = workload.over_cells(q, answers.cell_masses(counts.grid(d1.sparkSession, D1.columns, D1.sizes), c, m.params, D1.columns), D1.columns, "prob", "p").orderBy("qid").toPandas()
    drawn = answers.estimate_counts(q, c, m.params, D1.columns, 1, 2000).orderBy("qid").toPandas()
    assert np.allclose(exact["p"], drawn["estimate"], rtol=0.1, atol=2e-4)


def test_generated_rows(spark):
    c = TabularVae((3, 4), 2, 8)
    p = c.initial(np.random.default_rng(0))
    g = answers.generate(spark, 25, c, p, ("a", "b"), block=10)
    assert g.count() == 25 and bag(g, "a", "b") == bag(answers.generate(spark, 25, c, p, ("a", "b"), block=10), "a", "b")
    assert g.agg(F.max("a"), F.max("b")).first()[0] < 3


def test_controller_registry_and_replay(spark, d1, ood, tmp_path):
    policy = upkeep.Policy(settings=Settings(epochs=4, rate=5e-3), min_batch_rows=100)
    state = upkeep.start(MaskedAutoregressive(D1.sizes, 16), d1, D1.columns, policy)
    registry = Registry(spark, str(tmp_path / "registry"))
    quiet, v = upkeep.step(state, drift.ind_batch(d1), policy, registry, 1)
    assert not v.is_ood and quiet.model.params is state.model.params and quiet.baseline is state.baseline and quiet.model.rows == d1.count() + v.n_new
    none, v = upkeep.step(quiet, ood.limit(20), policy, registry, 2)
    assert v is None and none is quiet
    loud, v = upkeep.step(quiet, ood, policy, registry, 3)
    assert v.is_ood and loud.model.version == 1 and loud.model.parent == 0
    assert registry.processed("darn", 3) and not registry.publish("darn", 9, 0, 3, 1, loud.model.params)
    version, rows, params, _ = registry.latest("darn")
    assert version == 1 and rows == loud.model.rows and all(np.array_equal(params[k], loud.model.params[k]) for k in params)
    assert registry.baseline("darn", 1) == loud.baseline and registry.verdicts("darn").count() == 2
    assert detect.test_batch(score(ood.select("rk", *D1.columns), loud.model.component, loud.model.params, list(D1.columns)), state.baseline).shift < v.shift


def test_stream_of_insertions(spark, d1, ood, tmp_path):
    folder = tmp_path / "in"
    for k, b in enumerate((drift.ind_batch(d1), ood)):
        b.select("rk", *D1.columns).coalesce(1).write.mode("append").parquet(str(folder))
    policy = upkeep.Policy(settings=Settings(epochs=2, rate=5e-3), min_batch_rows=100)
    sink = monitor.Upkeep(upkeep.start(MaskedAutoregressive(D1.sizes, 16), d1, D1.columns, policy), Registry(spark, str(tmp_path / "r")), policy)
    stream = monitor.file_stream(spark, str(folder), "rk string, qty_band int, unit_band int, flag int")
    sink.run(stream, str(tmp_path / "cp")).awaitTermination()
    assert sink.state.model.rows == d1.count() + drift.ind_batch(d1).count() + ood.count() and sink.registry.verdicts("darn").count() == 2
    again = sink.state.model.rows
    sink(ood, 1)  # a replayed batch changes nothing
    assert sink.state.model.rows == again


def test_stream_operators(spark, sf, tmp_path):
    catalog.events(spark, sf).write.parquet(str(tmp_path / "e"))
    ev = monitor.file_stream(spark, str(tmp_path / "e"), "event_id long, ts timestamp, user_id long, event_type string, value double, k int")
    scored = monitor.deduplicated(ev).withColumn("loss", F.col("value"))
    frames = {
        "curve": monitor.drift_curve(scored, late=None), "keyed": monitor.keyed_monitor(ev.withColumn("loss", F.col("value")), "event_type", 50.0, 50.0),
        "joined": monitor.joined_insertions(ev.where("event_type = 'click'"), ev.where("event_type = 'purchase'")),
    }
    for name, df in frames.items():
        q = df.writeStream.format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination()
    assert spark.table("curve").count() > 20 and spark.table("keyed").count() == 5
    assert spark.table("joined").where("purchase_ts < click_ts").isEmpty()


def test_sql_surface(spark, sf, d1):
    assert "d1" in sqlapi.register_fixtures(spark, sf)
    m = counts.fit(d1, D1)
    sqlapi.register_model(spark, "m", m)
    assert sqlapi.estimate_count(spark, "m", "qty_band = 3 AND unit_band >= 2") == pytest.approx(d1.where("qty_band = 3 AND unit_band >= 2").count(), rel=0.05)
    sqlapi.register_functions(spark)
    m.score(d1).createOrReplaceTempView("scored")
    r = spark.sql("SELECT sum(n) AS n FROM drift_report(TABLE(scored), 4.6D, 0.1D)").first()
    assert r["n"] == d1.count()
    box = sqlapi.boxes_from_sql(spark, ["qty_band = 3 and unit_band >= 2", "flag <= 1"], D1.columns, D1.sizes).orderBy("qid").collect()
    assert tuple(box[0])[1:] == (3, 3, 2, 7, 0, 2) and tuple(box[1])[1:] == (0, 9, 0, 7, 0, 1)
    with pytest.raises(ValueError):
        sqlapi.boxes_from_sql(spark, ["flag = 1 or flag = 2"], D1.columns, D1.sizes)


def test_sources_and_sinks(spark, d1, tmp_path):
    for fmt in ("parquet", "orc", "json", "csv"):
        catalog.save(d1.limit(10), str(tmp_path / fmt), fmt)
        assert catalog.load(spark, str(tmp_path / fmt), fmt, d1.schema.simpleString()[7:-1].replace(":", " ")).count() == 10


def test_toy_mixture(spark):
    toy = workload.toy_mixture(spark, 1, 300)
    got = toy.groupBy("x").agg(F.count("*").alias("n"), F.avg("y").alias("m")).toPandas()
    assert (got["n"] == 300).all() and (got["m"].abs() < 0.15).all()
    c = MixtureDensity(10, 10, 32)
    assert c.row_loss(c.initial(np.random.default_rng(0)), matrix(toy, ["x", "y"])).shape == (3000,)


def test_new_categories_and_missing_values_fire(spark, d1):
    """Rows with values that no domain holds stay in the test and shift its mean loss."""
    m = counts.fit(d1, D1)
    base = detect.offline(m.score(d1))
    batch = d1.limit(1000)
    strange = batch.withColumn("flag", F.when(F.col("qty_band") == 0, F.lit(3)).when(F.col("qty_band") == 1, F.lit(None).cast("int")).otherwise(F.col("flag")))
    scored = m.score(strange).persist()
    assert scored.count() == 1000 and scored.where("loss > 27").count() == strange.where("qty_band < 2").count() > 0
    assert detect.test_batch(scored, base).is_ood
    c = MaskedAutoregressive(D1.sizes, 16)
    p = c.initial(np.random.default_rng(0))
    net = score(strange, c, p, list(D1.columns)).select("rk", F.col("loss").alias("net")).join(score(batch, c, p, list(D1.columns)), "rk")
    odd = net.where("net > loss + 20").count()
    assert net.count() == 1000 and odd == strange.where("qty_band < 2").count()
    assert detect.test_batch(score(strange, c, p, list(D1.columns)), detect.offline(score(d1, c, p, list(D1.columns)))).is_ood


def test_drift_of_a_conditional_is_told_from_that_of_its_column(spark):
    rng = np.random.default_rng(4)
    x = rng.integers(0, 4, 6000)
    y = (x + (rng.random(6000) < 0.1)) % 4
    make = lambda a, b: spark.createDataFrame([(int(i), int(j)) for i, j in zip(a, b, strict=True)], "x int, y int")
    f = Fixture("xy", ("x", "y"), (4, 4), None)
    old = make(x, y)
    m = counts.fit(old, f)
    shifted = rng.choice(4, 2000, p=[0.7, 0.1, 0.1, 0.1])
    virtual = make(shifted, (shifted + (rng.random(2000) < 0.1)) % 4)
    real = make(x[:2000], rng.integers(0, 4, 2000))
    fired = lambda new: {r["column"]: r["is_ood"] for r in detect.by_column(m.score_columns(old), m.score_columns(new), f.columns).collect()}
    assert fired(real) == {"x": False, "y": True} and not fired(virtual)["y"]


def test_policies_on_all_rows(spark, d1, ood):
    """Updates over partitions: the distilled model keeps the old rows better than fine-tuning, and learns the batch."""
    cols, s = list(D1.columns), Settings(epochs=6, rate=5e-3, batch=256)
    c = MaskedAutoregressive(D1.sizes, 32, temperature=1.0, reduction="sum")
    base = networks.train_all(c, d1, cols, s)
    n = ood.count()
    models = networks.policies_all(base, d1, ood, fn.hash_sample(d1, 0.1, "transfer1"), cols, n, s)
    loss = lambda df, m: score(df.select(*cols), c, m.params, cols).agg(F.avg("loss")).first()[0]
    old, new = ({k: loss(df, m) for k, m in models.items()} for df in (d1, ood))
    assert new["kd"] < new["stale"] and new["retrain"] < new["stale"] and new["fine_tune"] < new["stale"]
    assert old["kd"] < old["fine_tune"] and all(m.rows == d1.count() + n for k, m in models.items() if k != "stale")


def test_joins_in_time_meet_brute_force(spark):
    at = lambda m: dt.datetime(2024, 3, 1) + dt.timedelta(minutes=m)
    rng = np.random.default_rng(3)
    rows = [(i, ("hot", "hot", "b", None)[rng.integers(4)], at(int(m))) for i, m in enumerate(rng.integers(0, 9_000, 300))] + [(900, "hot", None), (901, "alone", at(5)), (902, "hot", at(60))]
    kept = [(str(k), at(int(m)), int(v)) for k, m, v in zip(rng.choice(["hot", "b", "unasked"], 40), rng.integers(0, 9_000, 40), range(40), strict=True)] + [("hot", at(60), 77), ("hot", at(60), 78), ("b", at(2), None), ("hot", None, 99), (None, at(30), 5)]
    df = spark.createDataFrame(rows, "id int, k string, ts timestamp_ntz")
    got = {r["id"]: r["v"] for r in joins.as_of(df, spark.createDataFrame(kept, "k string, ts timestamp_ntz, v int"), ["k"], "ts", "v").collect()}
    want = {i: max(((t, v) for q, t, v in kept if q == k and ts and t and v is not None and t <= ts), default=(None, None))[1] for i, k, ts in rows}
    assert got == want
    later = spark.createDataFrame(kept, "k string, u timestamp_ntz, v int")
    for seconds in (0, 3600):
        pairs = sorted((r["id"], r["v"]) for r in joins.interval(df, later, ["k"], "ts", "u", seconds).where("v is not null").collect())
        assert pairs == sorted((i, v) for i, k, ts in rows for q, t, v in kept if k and q == k and ts and t and v is not None and ts <= t <= ts + dt.timedelta(seconds=seconds))


def test_aggregate_truths_meet_brute_force(spark):
    rng = np.random.default_rng(4)
    rows = [(int(c), float(v)) for c, v in zip(rng.integers(0, 3, 400), rng.integers(-6, 6, 400) / 2, strict=True)] + [(1, None), (7, 1.0)]
    asked = [(i, int(c), float(a), float(b)) for i, (c, a, b) in enumerate(zip(rng.integers(0, 5, 60), rng.integers(-7, 7, 60) / 2, rng.integers(-7, 7, 60) / 2, strict=True))] + [(90, 1, -0.0, 0.0), (91, 1, 0.0, 9.0)]
    q = spark.createDataFrame(asked, "qid int, c int, lo double, hi double")
    df = spark.createDataFrame(rows, "c int, y double")
    got = {r["qid"]: (r["count"], r["sum"]) for r in workload.aqp_truth(q, df, "c", "y").collect()}
    inside = {i: [v for k, v in rows if k == c and v is not None and a <= v <= b] for i, c, a, b in asked}
    assert got == {i: (len(x), sum(x)) for i, x in inside.items()}
    assert workload.aqp_truth(q.limit(0), df, "c", "y").count() == 0


def test_squared_errors_of_cell_means(spark):
    old = spark.createDataFrame([(0, 1.0), (0, 3.0), (1, 5.0), (None, 7.0), (None, 9.0), (1, None)], "c int, y double")
    m = regression.fit(old, ("c",), "y")
    got = [(r["c"], r["y"], r["loss"]) for r in m.score(spark.createDataFrame([(0, 2.0), (1, 6.0), (None, 8.0), (4, 5.0), (0, None)], "c int, y double")).collect()]
    assert sorted(got, key=str) == sorted([(0, 2.0, 0.0), (1, 6.0, 1.0), (None, 8.0, 0.0), (4, 5.0, 0.0), (0, None, None)], key=str)
    none = regression.fit(old.limit(0), ("c",), "y")
    assert none.overall == 0.0 and none.score(old).count() == 6


def test_delta_of_three_growing_tables_is_the_difference(spark):
    rng = np.random.default_rng(8)
    table = lambda n, schema: [spark.createDataFrame([tuple(map(int, r)) for r in rng.integers(0, 5, (k, 2))], schema) for k in (n, n // 2)]
    a, b, c = table(14, "x int, y int"), table(10, "y int, z int"), table(8, "z int, w int")
    joined = lambda s, t, u: s.join(t, ["y"]).join(u, ["z"]).select("x", "y", "z", "w")
    whole, before = joined(*(joins.grow(*t) for t in (a, b, c))), joined(a[0], b[0], c[0])
    new = joins.delta_many([tuple(a), tuple(b), tuple(c)], [["y"], ["z"]]).select("x", "y", "z", "w")
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(new) == rows(joins.bag_difference(whole, before)) and rows(before.unionByName(new)) == rows(whole)


@pytest.mark.parametrize("name", ["logit_mse_rows", "mixture_pdf", "mixture_range_mass", "soft_ce_rows"])
def test_measures_of_logits_and_mixtures_read_a_given_table(spark, sf, name):
    assert any(f.endswith("lineitem.parquet") for f in queries.queries()[name](spark, sf).inputFiles())


def test_measures_of_logits_at_their_edges(spark):
    """Equal and shifted logits, one-hot-like ones, a single one and very large ones."""
    pairs = [([1.0, 2.0, 3.0], [1.0, 2.0, 3.0]), ([1.0, 2.0, 3.0], [2.0, 3.0, 4.0]), ([10.0, 0.0, 0.0], [0.0, 10.0, 0.0]), ([0.5], [0.1]), ([500.0, 400.0], [400.0, 500.0])]
    df = spark.createDataFrame([(i, t, s, 2.0) for i, (t, s) in enumerate(pairs)], "id int, t array<double>, s array<double>, temperature double")
    ce, gap = fn.soft_cross_entropy(F.col("t"), F.col("s"), F.col("temperature")), fn.squared_logit_gap(F.col("t"), F.col("s"))
    for r in df.select("t", "s", ce.alias("ce"), gap.alias("gap")).collect():
        t, s = np.array(r["t"]), np.array(r["s"])
        p, log_q = np.exp((t - t.max()) / 2), (s - s.max()) / 2
        assert r["gap"] == ((t - s) ** 2).sum() and r["ce"] == pytest.approx(-(p / p.sum()) @ (log_q - np.log(np.exp(log_q).sum())), abs=1e-9)
