"""Gradients, identities and behaviour of the network components."""

import itertools

import numpy as np
import pytest

from learned_upkeep.nn import losses, training
from learned_upkeep.nn.darn import MaskedAutoregressive
from learned_upkeep.nn.mdn import MixtureDensity
from learned_upkeep.nn.tensor import Tensor
from learned_upkeep.nn.vae import TabularVae
from learned_upkeep.operators import detect, networks, spn
from learned_upkeep.plans import experiments
from learned_upkeep.sources import catalog

SIZES = (4, 3, 5)
RNG = np.random.default_rng(0)
CODES = np.column_stack([RNG.integers(0, k, 24) for k in SIZES]).astype(float)
PAIRS = np.column_stack([RNG.integers(0, 3, 24), RNG.uniform(-1, 1, 24)])
COMPONENTS = [(MixtureDensity(3, 4, 16), PAIRS), (MaskedAutoregressive(SIZES, 16), CODES), (MaskedAutoregressive(SIZES, 16, reduction="sum"), CODES), (TabularVae(SIZES, 3, 16), CODES)]


@pytest.mark.parametrize("component,data", COMPONENTS)
@pytest.mark.parametrize("what", ["loss", "imitation"])
def test_gradients_agree_with_differences(component, data, what):
    rng = np.random.default_rng(1)
    params, teacher, noise = component.initial(rng), component.initial(np.random.default_rng(9)), component.noise(rng, len(data))
    value = lambda p: component.loss(p, data, noise) if what == "loss" else component.imitation(p, teacher, data, noise)
    _, grads = training.gradient(value, params)
    for k in params:
        for _ in range(3):
            at = tuple(rng.integers(0, s) for s in params[k].shape)
            side = []
            for d in (1e-6, -1e-6):
                moved = {n: v.copy() for n, v in params.items()}
                moved[k][at] += d
                side.append(training.gradient(value, moved)[0])
            assert grads[k][at] == pytest.approx((side[0] - side[1]) / 2e-6, abs=1e-5, rel=1e-4)


@pytest.mark.parametrize("component,data", COMPONENTS)
def test_a_student_that_equals_its_teacher_does_not_move_under_imitation(component, data):
    params = component.initial(np.random.default_rng(2))
    noise = component.noise(np.random.default_rng(3), len(data))
    _, grads = training.gradient(lambda p: component.imitation(p, params, data, noise), params)
    assert max(np.abs(g).max() for g in grads.values()) < 1e-9


def test_soft_cross_entropy_is_least_at_the_teacher():
    z = np.array([[1.0, 2.0, -1.0]])
    p = losses.softmax(z, 2.0)
    entropy = -(p * np.log(p)).sum()
    assert float(losses.soft_cross_entropy(z, Tensor(z + 7), 2.0).value) == pytest.approx(entropy)
    assert float(losses.soft_cross_entropy(z, Tensor(z[:, ::-1]), 2.0).value) > entropy
    assert np.allclose(losses.softmax(z, 1e6), 1 / 3, atol=1e-5)


def test_autoregressive_masses_sum_to_one_and_look_back_only():
    c = MaskedAutoregressive(SIZES, 16)
    params = c.initial(np.random.default_rng(4))
    cells = np.array(list(itertools.product(*map(range, SIZES))), float)
    mass = c.cell_mass(params, cells)
    assert mass.sum() == pytest.approx(1)
    x = c.encode(cells)
    y = x.copy()
    y[:, c.starts[1] :] = np.random.default_rng(5).random((len(x), x.shape[1] - c.starts[1]))
    assert np.allclose(c.conditional(params, x, 1), c.conditional(params, y, 1))
    inside = (cells[:, 0] >= 1) & (cells[:, 2] <= 2)
    assert c.box_mass(params, np.array([1, 0, 0]), np.array([3, 2, 2]), 4000, np.random.default_rng(6)) == pytest.approx(mass[inside].sum(), rel=0.03)
    assert c.box_mass(params, np.array([2, 0, 0]), np.array([1, 2, 4]), 10, np.random.default_rng(6)) == 0


def correlated(n, seed, flip=False):
    rng = np.random.default_rng(seed)
    a = rng.integers(0, 6, n)
    b = (a + rng.integers(0, 2, n)) % 6
    return np.column_stack([a, (5 - b) if flip else b]).astype(float)


def test_distillation_keeps_old_knowledge_where_fine_tuning_forgets():
    settings = training.Settings(epochs=25, rate=5e-3, batch=256)
    old, new, both = correlated(4000, 1), correlated(800, 2, True), None
    base = networks.train(MaskedAutoregressive((6, 6), 32), old, len(old), settings)
    made = networks.policies(base, old, new, old[:400], len(new), settings)
    loss = {k: (m.component.row_loss(m.params, old).mean(), m.component.row_loss(m.params, new).mean()) for k, m in made.items()}
    both = {k: (5 * o + n) / 6 for k, (o, n) in loss.items()}
    assert loss["fine_tune"][0] > loss["kd"][0] + 1 and loss["stale"][1] > loss["kd"][1] + 0.5
    assert both["retrain"] < both["kd"] < min(both["fine_tune"], both["stale"])
    assert made["kd"].steps < made["retrain"].steps and made["kd"].parent == base.version


def test_plain_distillation_into_a_smaller_student_and_generations():
    settings = training.Settings(epochs=30, rate=5e-3, batch=256)
    old = correlated(2000, 1)
    base = networks.train(MaskedAutoregressive((6, 6), 32), old, len(old), settings)
    small = networks.plain_distillation(base, MaskedAutoregressive((6, 6), 8), old, 0.9, settings)
    assert small.params["w1"].size < base.params["w1"].size
    assert small.component.row_loss(small.params, old).mean() < base.component.row_loss(base.params, old).mean() + 0.4
    again = networks.generations(base, old[:500], 2, settings=training.Settings(epochs=3))
    assert again.version == 2 and again.component.row_loss(again.params, old).mean() == pytest.approx(base.component.row_loss(base.params, old).mean(), abs=0.1)
    held = networks.anchored(base, correlated(500, 3, True), old, 500, settings=training.Settings(epochs=3))
    free = networks.fine_tune(base, correlated(500, 3, True), 500, training.Settings(epochs=3, rate=1e-3), 1e-3)
    assert held.component.row_loss(held.params, old).mean() <= free.component.row_loss(free.params, old).mean() + 0.05
    lam, tried = networks.tune_lambda(base, correlated(400, 4, True), old[:400], old[:400], 400, settings=training.Settings(epochs=1))
    assert lam in tried and len(tried) == 4


def test_mixture_learns_peaks():
    rng = np.random.default_rng(0)
    x = rng.integers(0, 3, 6000)
    y = rng.choice([-0.6, 0.0, 0.6], 6000) + rng.normal(0, 0.05, 6000)
    c = MixtureDensity(3, 6, 32)
    m = networks.train(c, np.column_stack([x, y]), 6000, training.Settings(epochs=20, rate=5e-3))
    peaks, valleys = c.density(m.params, 1, np.array([-0.6, 0.0, 0.6])), c.density(m.params, 1, np.array([-0.3, 0.3]))
    assert peaks.min() > 4 * valleys.max()
    assert all(abs(sum(w) - 1) < 1e-9 and min(s) > 0 for _, w, _, s in c.table(m.params))


def test_generator_keeps_dependence():
    c = TabularVae((6, 6), 4, 32)
    data = correlated(4000, 1)
    m = networks.train(c, data, 4000, training.Settings(epochs=30, rate=5e-3, batch=256))
    rows = c.sample(m.params, 4000, np.random.default_rng(0))
    assert ((rows[:, 1] - rows[:, 0]) % 6 <= 1).mean() > 0.7
    frozen = TabularVae((6, 6), 4, 32, decoder_only=True)
    after = networks.distil(networks.Model(frozen, m.params, 4000), correlated(200, 2), data[:200], 200, settings=training.Settings(epochs=1))
    assert np.array_equal(after.params["ew1"], m.params["ew1"]) and not np.array_equal(after.params["dw1"], m.params["dw1"])


def test_sum_product_network_counts():
    cells, n = np.unique(correlated(5000, 1).astype(int), axis=0, return_counts=True)
    net = spn.SumProduct((6, 6)).fit(cells, n)
    whole = (np.zeros((1, 2), int), np.full((1, 2), 5))
    assert net.estimate(*whole)[0] == pytest.approx(5000)
    more, k = np.unique(correlated(1000, 2).astype(int), axis=0, return_counts=True)
    assert net.insert(more, k).estimate(*whole)[0] == pytest.approx(6000)
    one = net.estimate(np.array([[2, 2]]), np.array([[2, 3]]))[0]
    assert one == pytest.approx(((cells == [2, 2]).all(1) * n).sum() + ((cells == [2, 3]).all(1) * n).sum(), rel=0.8)


def test_sum_product_network_scales_each_column_by_its_own_domain():
    """Below a product node the columns aren't the first ones: a wide and a narrow domain side by side."""
    rng = np.random.default_rng(3)
    alone, wide = rng.integers(0, 3, 20_000), rng.integers(0, 40, 20_000)
    narrow = np.where(wide < 20, 0, 1) ^ (rng.random(20_000) < 0.02)
    cells, n = np.unique(np.column_stack([alone, wide, narrow]), axis=0, return_counts=True)
    net = spn.SumProduct((3, 40, 2)).fit(cells, n)
    for lo, hi in (((0, 0, 0), (2, 19, 0)), ((0, 0, 1), (2, 19, 1)), ((1, 20, 1), (1, 39, 1)), ((0, 5, 0), (2, 30, 0))):
        inside = ((cells >= lo) & (cells <= hi)).all(1)
        assert net.estimate(np.array([lo]), np.array([hi]))[0] == pytest.approx(n[inside].sum(), rel=0.15, abs=60)


def test_noise_of_rows_is_normal_and_theirs():
    c = TabularVae((50, 60), 4, 8)
    rows = np.stack(np.meshgrid(np.arange(50), np.arange(60)), -1).reshape(-1, 2).astype(float)
    e = c.noise_of(rows)
    assert e.shape == (3000, 4) and np.array_equal(e[7:9], c.noise_of(rows[7:9]))
    assert abs(e.mean()) < 0.03 and abs(e.std() - 1) < 0.03 and abs(np.corrcoef(e.T) - np.eye(4)).max() < 0.07 and np.abs(e).max() > 3


def test_counted_objective_is_that_of_the_rows():
    """Weighted cells give the loss, the imitation and the gradient of all rows."""
    data, old = correlated(700, 1), correlated(400, 2)
    cells = np.unique(np.concatenate([data, old]), axis=0)
    of = lambda rows: np.array([(rows == c).all(1).sum() for c in cells], float)
    for c in (MaskedAutoregressive((6, 6), 16, temperature=1.0, reduction="sum"), MaskedAutoregressive((6, 6), 16)):
        teacher, params = c.initial(np.random.default_rng(1)), c.initial(np.random.default_rng(2))
        rows = training.Update(data, old, teacher, 0.25, 0.6).objective(c, np.arange(700), np.arange(400), np.random.default_rng(0))
        counted = c.counted(cells, 0.6 * of(data) / 700 + 0.3 * of(old) / 400, 0.1 * of(old) / 400, teacher)
        (a, ga), (b, gb) = training.gradient(rows, params), training.gradient(counted, params)
        assert a == pytest.approx(b) and all(np.allclose(ga[k], gb[k]) for k in ga)


def test_training_from_counts():
    cells, n = np.unique(correlated(6000, 1), axis=0, return_counts=True)
    n, c = n.astype(float), MaskedAutoregressive((6, 6), 32, temperature=1.0, reduction="sum")
    m = networks.train_counted(c, cells, 1000 * n, training.Settings(epochs=8, rate=3e-3))
    best = -np.average(np.log(n / n.sum()), weights=n)
    assert m.rows == 6_000_000 and np.average(c.row_loss(m.params, cells), weights=n) - best < 0.01
    none = networks.policies_counted(m, cells, n, 0 * n, 0 * n, training.Settings(epochs=1), which=("fine_tune",))["fine_tune"]
    assert all(np.array_equal(none.params[k], m.params[k]) for k in m.params)
    loss = c.row_loss(m.params, cells)
    base = detect.offline_counted(loss, n)
    assert not detect.test_counted(loss, n, base, "size_matched").is_ood and detect.test_counted(loss, n[::-1] * (loss > loss.mean()), base, "size_matched").is_ood


@pytest.fixture
def no_rows_in_python(monkeypatch):
    """Experiments on small domains count rows in Spark: none is trained on or scored one by one."""

    def refused(*args, **kwargs):
        raise AssertionError("rows went through Python")

    monkeypatch.setattr(networks, "fit_by_partitions", refused)
    monkeypatch.setattr(experiments, "score", refused)


def _incremental(spark, sf, kind):
    got = experiments.incremental(spark, sf, kind=kind).toPandas()
    assert len(got) == 20 and got.notna().all().all()
    return got.set_index(["policy", "step"])


def test_insertions_without_drift_are_counted(spark, sf, no_rows_in_python):
    got = _incremental(spark, sf, "ind")
    assert got.loc["kd"]["median"].max() < 1.3 and abs(got.loc[("stale", 5), "median"] - 1.2) < 0.15


def test_drifted_insertions_are_counted(spark, sf, no_rows_in_python):
    got = _incremental(spark, sf, "ood")
    assert got.loc["kd"]["loglik"].min() > got.loc["stale"]["loglik"].max()
    assert (got.loc["fine_tune"]["p95"] > got.loc["kd"]["p95"]).all()


def _joined(spark, sf, f):
    got = experiments.joined_partitions(spark, sf, f=f).toPandas()
    assert len(got) == 20 and got.notna().all().all() and (got.groupby("part")["is_ood"].nunique() == 1).all()
    return got.set_index(["policy", "part"])


def test_joins_of_orders_over_time_are_counted(spark, sf, no_rows_in_python):
    got = _joined(spark, sf, catalog.D3)
    assert got.loc[("retrain", 4), "p95"] < got.loc[("stale", 4), "p95"]


def test_joins_of_lines_over_time_are_counted(spark, sf, no_rows_in_python):
    got = _joined(spark, sf, catalog.J2)
    assert got.loc[("kd", 4), "p95"] < got.loc[("stale", 4), "p95"]


def test_counted_mixture_objective_is_that_of_the_rows():
    rng = np.random.default_rng(3)
    cells = np.column_stack([rng.integers(0, 3, 40), rng.uniform(-1, 1, 40)])
    data, old = cells[rng.integers(0, 40, 500)], cells[rng.integers(0, 40, 300)]
    of = lambda rows: np.array([(rows == c).all(1).sum() for c in cells], float)
    c = MixtureDensity(3, 4, 16)
    teacher, params = c.initial(np.random.default_rng(1)), c.initial(np.random.default_rng(2))
    rows = training.Update(data, old, teacher, 0.25, 0.6).objective(c, np.arange(500), np.arange(300), rng)
    counted = c.counted(cells, 0.6 * of(data) / 500 + 0.3 * of(old) / 300, 0.1 * of(old) / 300, teacher)
    (a, ga), (b, gb) = training.gradient(rows, params), training.gradient(counted, params)
    assert a == pytest.approx(b) and all(np.allclose(ga[k], gb[k]) for k in ga)


def test_peaks_come_from_the_parts_given(spark, sf, tmp_path):
    """Other parts, other densities: the rows are those of the table."""
    parts = spark.read.parquet(f"{sf}/part.parquet")
    parts.where("p_partkey % 2 = 0").write.parquet(str(tmp_path / "part.parquet"))
    few = training.Settings(epochs=2, rate=5e-3)
    whole, half = (experiments.toy(spark, d, 3, few, few).toPandas() for d in (sf, str(tmp_path)))
    assert len(whole) == 21 and whole["density"].notna().all() and not np.allclose(whole["density"], half["density"])
