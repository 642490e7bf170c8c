"""The experiments, re-expressed on the given tables.  Each returns a DataFrame of measures.

Sizes are parameters: the registered queries take modest ones, the published settings are arguments away.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import HASH_SPACE, cut, hash_sample, q_error, row_hash
from ..nn.darn import MaskedAutoregressive
from ..nn.mdn import MixtureDensity
from ..nn.training import Settings, losses, score
from ..nn.vae import TabularVae
from ..operators import answers, counts, detect, drift, metrics, networks, spn, workload
from ..operators.update import merge_frequencies
from ..sources import catalog
from ..sources.catalog import D1, D2, D3, D5, D6, Fixture

#: The settings of the registered queries.
QUICK = Settings(epochs=8, rate=3e-3, batch=512)
#: A generator's reconstruction needs larger steps to part from that of independent columns.
FAST = Settings(epochs=8, rate=1e-2, batch=512)
N_QUERIES = 200


def _frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def _settled(few: DataFrame, *persisted: DataFrame) -> DataFrame:
    """A result of a few rows, computed now, so that what it came from can be released."""
    out = few.sparkSession.createDataFrame(few.collect(), few.schema)
    for df in persisted:
        df.unpersist()
    return out


def autoregressive(f: Fixture) -> MaskedAutoregressive:
    """Imitation is summed over columns at temperature 1, so that lambda weighs it against a likelihood of the same scale."""
    return MaskedAutoregressive(f.sizes, temperature=1.0, reduction="sum")


def component_for(f: Fixture, kind: str):
    return {"darn": lambda: autoregressive(f), "vae": lambda: TabularVae(f.sizes), "mdn": lambda: MixtureDensity(f.sizes[0])}[kind]()


def _numbers(df: DataFrame, f: Fixture, limits: tuple[float, float] | None = None) -> tuple[DataFrame, tuple[float, float]]:
    """Scales the target to [-1, 1] by the range of the first data."""
    lo, hi = limits or df.agg(F.min(f.target), F.max(f.target)).first()
    return df.withColumn("y", F.lit(2.0) * (F.col(f.target) - F.lit(lo)) / F.lit(hi - lo) - F.lit(1.0)), (lo, hi)


def _tables(f: Fixture, kind: str, spark, sf_dir) -> tuple[DataFrame, DataFrame, DataFrame, list[str]]:
    """(old, ind, ood, columns) encoded for a component."""
    old = f.build(spark, sf_dir)
    if kind != "mdn":
        return old, drift.ind_batch(old), drift.permuted_batch(old, f.columns), list(f.columns)
    back = (f.target,) if f.name == "d4" else ()
    ood = drift.permuted_pair(old, f.columns[0], f.target, descending=back)
    old_y, limits = _numbers(old, f)
    return old_y, _numbers(drift.ind_batch(old), f, limits)[0], _numbers(ood, f, limits)[0], [f.columns[0], "y"]


def detection(spark: SparkSession, sf_dir: str, f: Fixture, kind: str, settings: Settings | None = None) -> DataFrame:
    """Mean losses on old, IND and OOD rows, the bootstrap, both verdicts, and offline and online seconds."""
    old, ind, ood, cols = _tables(f, kind, spark, sf_dir)
    model = networks.train_all(component_for(f, kind), old, cols, settings or (FAST if kind == "vae" else QUICK))
    began = time.perf_counter()
    base = detect.offline(score(old.select("rk", *cols), model.component, model.params, cols))
    offline = time.perf_counter() - began
    rows = []
    for name, batch in (("ind", ind), ("ood", ood)):
        began = time.perf_counter()
        v = detect.test_batch(score(batch.select("rk", *cols), model.component, model.params, cols), base, "size_matched")
        rows.append((f.name, kind, name, base.mean, base.mean + v.shift, v.shift, v.threshold, v.p_normal, v.is_ood, offline, time.perf_counter() - began))
    return _frame(spark, rows, "fixture string, component string, batch string, old_mean double, new_mean double, shift double, threshold double, p double, is_ood boolean, offline_s double, online_s double")


def ce_one_shot(spark: SparkSession, sf_dir: str, f: Fixture = D1, n_queries: int = N_QUERIES, settings: Settings = QUICK, paths: int = 200) -> DataFrame:
    """q-error of the autoregressive component under each policy after one drifted batch, split by changed answers, with training cost."""
    old, _, ood, cols = _tables(f, "darn", spark, sf_dir)
    n_old, n_new = old.count(), ood.count()
    q = workload.ce_queries(old, f, n_queries).persist()
    before = workload.truth(q, old, f).where("truth > 0").persist()
    q = workload.without_empty(q, before).persist()
    after = workload.truth_added(before, workload.truth(q, ood, f)).persist()
    ood = ood.persist()
    transfer = hash_sample(old, 0.1, "transfer1")
    base = networks.train_all(autoregressive(f), old, cols, settings)
    timed = {}
    models = {"base": base}
    for p in ("stale", "retrain", "fine_tune", "kd", "pooled"):
        began = time.perf_counter()
        models |= networks.policies_all(base, old, ood, transfer, cols, n_new, settings, which=(p,))
        timed[p] = time.perf_counter() - began
    out = []
    for name, m in models.items():
        truth = before if name == "base" else after
        est = answers.estimate_counts(q, m.component, m.params, f.columns, m.rows, paths)
        e = metrics.q_errors(est, truth).join(before.select("qid", F.col("truth").alias("b")), "qid").join(after.select("qid", F.col("truth").alias("a")), "qid")
        e = e.withColumn("grp", F.when(F.col("a") != F.col("b"), "changed").otherwise("unchanged"))
        out.append(e.select(F.lit(name).alias("policy"), "grp", "q_error", F.lit(float(timed.get(name, 0.0))).alias("seconds"), F.lit(m.steps).alias("row_epochs")))
    errors = out[0]
    for o in out[1:]:
        errors = errors.unionByName(o)
    found = errors.groupBy("policy").agg(
        F.expr("percentile(q_error, 0.5)").alias("median"), F.expr("percentile(q_error, 0.95)").alias("p95"), F.expr("percentile(q_error, 0.99)").alias("p99"), F.max("q_error").alias("max"),
        F.avg(F.when(F.col("grp") == "changed", F.col("q_error"))).alias("fwt"), F.avg(F.when(F.col("grp") == "unchanged", F.col("q_error"))).alias("bwt"),
        F.first("seconds").alias("seconds"), F.first("row_epochs").alias("row_epochs"),
    )
    return _settled(found, ood, q, before, after)


def aqp_one_shot(spark: SparkSession, sf_dir: str, f: Fixture = D2, n_queries: int = N_QUERIES, settings: Settings = QUICK) -> DataFrame:
    """COUNT q-error and SUM and AVG relative error of the mixture component under each policy."""
    raw = f.build(spark, sf_dir)
    back = (f.target,) if f.name == "d4" else ()
    batch = drift.permuted_pair(raw, f.columns[0], f.target, descending=back)
    old, limits = _numbers(raw, f)
    new, _ = _numbers(batch, f, limits)
    cols = [f.columns[0], "y"]
    n_new = new.count()
    q = workload.aqp_queries(raw, f.columns[0], f.target, n_queries).persist()
    ask = lambda df: workload.aqp_truth(q, df, f.columns[0], f.target)
    before, after = ask(raw).persist(), ask(raw.unionByName(batch)).persist()
    some = before.where("count > 0").select("qid")
    new = new.persist()
    transfer = hash_sample(old, 0.1, "transfer1")
    base = networks.train_all(component_for(f, "mdn"), old, cols, settings)
    # of the published grid, the weight that leaves most to the likelihood suits a mixture, whose imitation terms are small
    models = {"base": base} | networks.policies_all(base, old, new, transfer, cols, n_new, settings, 1 / 4, which=("stale", "retrain", "fine_tune", "kd"))
    freq_old, freq_new = counts.cells(raw, (f.columns[0],)), merge_frequencies(raw, batch, f.columns[0])
    out = None
    for name, m in models.items():
        table = answers.mixture_table(spark, m.component, m.params, f.columns[0])
        freq = freq_old if name in ("base", "stale") else freq_new
        est = answers.aqp(q.join(some, "qid", "left_semi"), table, freq, f.columns[0], *limits)
        t = (before if name == "base" else after).select("qid", F.col("count").alias("t_count"), F.col("sum").alias("t_sum"), F.col("avg").alias("t_avg"))
        e = est.join(t, "qid").where("t_count > 0")
        pct = lambda a, b: 100 * F.avg(F.try_divide(F.abs(F.col(a) - F.col(b)), F.abs(F.col(b))))
        r = e.agg(F.expr("percentile(greatest(greatest(count, 1D), t_count) / least(greatest(count, 1D), t_count), array(0.5D, 0.95D))").alias("q"), pct("sum", "t_sum").alias("sum_pct"), pct("avg", "t_avg").alias("avg_pct"))
        r = r.select(F.lit(name).alias("policy"), F.col("q")[0].alias("count_median"), F.col("q")[1].alias("count_p95"), "sum_pct", "avg_pct")
        out = r if out is None else out.unionByName(r)
    return _settled(out, new, q, before, after)


def generation(spark: SparkSession, sf_dir: str, f: Fixture = D6, target: str = "lang", settings: Settings = Settings(epochs=15, rate=3e-3), n: int | None = None) -> DataFrame:
    """Micro-F1 of a forest trained on real and on synthetic rows, judged on a 30 % hold-out, under each policy."""
    everything = f.build(spark, sf_dir)
    held = row_hash("rk", "holdout") < F.lit(cut(0.3))
    old = everything.where(~held)
    batch_all = drift.permuted_batch(everything, f.columns)
    batch_held = row_hash("rk", "holdout") < F.lit(cut(0.3))
    batch, cols = batch_all.where(~batch_held), list(f.columns)
    features = tuple(c for c in cols if c != target)
    n_old, n_new = old.count(), batch.count()
    base = networks.train_all(TabularVae(f.sizes), old, cols, settings)
    models = {"base": base} | networks.policies_all(base, old, batch, hash_sample(old, 0.05, "transfer1"), cols, n_new, settings, which=("stale", "retrain", "fine_tune", "kd"))
    rows = []
    for name, m in models.items():
        real = old if name == "base" else old.unionByName(batch)
        test = everything.where(held) if name == "base" else everything.where(held).unionByName(batch_all.where(batch_held))
        fake = answers.generate(spark, n or n_old, m.component, m.params, f.columns)
        rows.append((f.name, name, answers.judge(real, test, features, target), answers.judge(fake, test, features, target)))
    return _frame(spark, rows, "fixture string, policy string, real_f1 double, synthetic_f1 double")


def _counted(df: DataFrame, columns: tuple[str, ...], samples: dict[str, Column]) -> tuple[np.ndarray, dict[str, np.ndarray]]:
    """(cells, counts of each sample's rows in them): one pass over rows of any number, a row of the driver for each cell that occurs."""
    table = df.groupBy(*columns).agg(*[F.count_if(c).alias(name) for name, c in samples.items()]).orderBy(*columns).toPandas()
    return table[list(columns)].to_numpy("float64"), {name: table[name].to_numpy("float64") for name in samples}


def _boxes(q: DataFrame, f: Fixture, cells: np.ndarray, old: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(query numbers, lower and upper codes, cells inside) of the queries that old rows answer with more than 0."""
    table = q.orderBy("qid").toPandas()
    lo, hi = (table[[f"{c}_{e}" for c in f.columns]].to_numpy(int) for e in ("lo", "hi"))
    met = np.stack([((cells >= a) & (cells <= b)).all(1) for a, b in zip(lo, hi, strict=True)]) if len(lo) else np.zeros((0, len(cells)), bool)
    some = met @ old > 0
    return table["qid"].to_numpy(int)[some], lo[some], hi[some], met[some]


def _error_quantiles(estimate: np.ndarray, truth: np.ndarray) -> tuple[float, float]:
    """Median and 95th percentile of the q-error."""
    e, t = np.maximum(estimate, 1.0), np.maximum(truth, 1.0)
    return tuple(float(x) for x in np.quantile(np.maximum(e, t) / np.minimum(e, t), (0.5, 0.95)))


def incremental(spark: SparkSession, sf_dir: str, f: Fixture = D1, steps: int = 5, kind: str = "ood", settings: Settings = QUICK, n_queries: int = N_QUERIES, which: tuple[str, ...] = ("stale", "retrain", "fine_tune", "kd")) -> DataFrame:
    """Five insertions: p95 q-error and plain average log-likelihood of old and new rows at each step.

    All rows are counted by cell once, those of each batch and of each step's transfer set; training,
    truths and likelihoods are exact on the counts.
    """
    old, ind, ood, cols = _tables(f, "darn", spark, sf_dir)
    batches = drift.split_batches(ood if kind == "ood" else ind, steps)
    q = workload.ce_queries(old, f, n_queries)
    rows_all = old.select("rk", *cols).withColumn("batch_id", F.lit(-1)).unionByName(batches.select("rk", *cols, "batch_id"))
    at = F.col("batch_id")
    samples = {f"n{k}": at == k for k in range(-1, steps)} | {f"t{s}": (at < s) & (row_hash("rk", f"transfer{s}") < F.lit(cut(0.1))) for s in range(steps)}
    cells, n = _counted(rows_all, f.columns, samples)
    grid = counts.grid(spark, f.columns, f.sizes).toPandas().to_numpy("float64")
    _, lo, hi, met = _boxes(q, f, cells, n["n-1"])
    on_grid = np.stack([((grid >= a) & (grid <= b)).all(1) for a, b in zip(lo, hi, strict=True)])
    base = networks.train_counted(autoregressive(f), cells, n["n-1"], settings)
    seen = np.cumsum([n[f"n{k}"] for k in range(-1, steps)], axis=0)

    def chain(name: str, first: int, last: int) -> list[tuple[int, str, networks.Model]]:
        m, out = base, []
        for s in range(first, last):
            m = networks.policies_counted(m, cells, seen[s], n[f"n{s}"], n[f"t{s}"], settings, which=(name,))[name]
            out.append((s, name, m))
        return out

    # a retrained model doesn't depend on the one before, so its steps are jobs of their own
    spans = [(name, *span) for name in which for span in ([(s, s + 1) for s in range(steps)] if name == "retrain" else [(0, steps)])]
    spans.sort(key=lambda span: span[1] - span[2])  # the longest first
    made = networks.at_once(spark, [lambda span=span: chain(*span) for span in spans])
    rows = []
    for s, name, m in sorted((x for part in made for x in part), key=lambda x: (x[0], which.index(x[1]))):
        rows_known = m.rows if name == "stale" else int(seen[s + 1].sum())
        e = _error_quantiles(rows_known * (on_grid @ m.component.cell_mass(m.params, grid)), met @ seen[s + 1])
        loss = losses(m.component, m.params, cells)
        ll = -(np.average(loss, weights=n["n-1"]) + np.average(loss, weights=n[f"n{s}"])) / 2
        rows.append((s + 1, name, *e, float(ll)))
    return _frame(spark, rows, "step int, policy string, median double, p95 double, loglik double")


def _order_parts(spark: SparkSession, sf_dir: str, drifted: bool) -> DataFrame:
    """Orders with customers and nations in five parts by time; with ``drifted`` the customers of later parts come from two regions only."""
    parts = drift.time_partitions(catalog.orders_with_nation(spark, sf_dir), "o_orderdate")
    return catalog.code_orders(parts.where((F.col("batch_id") == 0) | (F.col("n_regionkey") < 2)) if drifted else parts, "batch_id")


def _line_parts(spark: SparkSession, sf_dir: str, drifted: bool) -> DataFrame:
    """Lines with parts and suppliers in five parts by time; with ``drifted`` later parts sell small quantities only."""
    parts = drift.time_partitions(catalog.J2.build(spark, sf_dir), "l_shipdate")
    return (parts.where((F.col("batch_id") == 0) | (F.col("qty_band") < 3)) if drifted else parts).select("rk", *catalog.J2.columns, "batch_id")


def joined_partitions(spark: SparkSession, sf_dir: str, drifted: bool = False, f: Fixture = D3, settings: Settings = QUICK, n_queries: int = 100) -> DataFrame:
    """A three-table join, its fact table in five parts by time: a verdict and q-errors for each later part.

    The verdict is that of the distilled model, whose baseline is renewed after each update.  All rows
    of the join are counted by cell once, those of each part and sample; training, losses and truths
    are exact on the counts.
    """
    parts = (_order_parts if f is D3 else _line_parts)(spark, sf_dir, drifted).persist()
    q = workload.ce_queries(parts.where("batch_id = 0"), f, n_queries)
    sizes = dict(parts.groupBy("batch_id").count().collect())
    upto = np.cumsum([sizes.get(k, 0) for k in range(5)])
    at = F.col("batch_id")
    picked = lambda what, share: row_hash("rk", what) < F.lit(cut(share))
    samples = {f"n{k}": at == k for k in range(5)} | {f"t{k}": (at < k) & picked(f"transfer{k}", 0.1) for k in range(1, 5)}
    # a light training on 1 % of the join, 100 rows at least
    samples |= {f"l{k}": (at <= k) & picked(f"light{k}", min(1.0, max(0.01, 100 / int(upto[k])))) for k in range(1, 5)}
    cells, n = _counted(parts, f.columns, samples)
    qid, lo, hi, met = _boxes(q, f, cells, n["n0"])
    parts.unpersist()
    seen = np.cumsum([n[f"n{k}"] for k in range(5)], axis=0)
    base = networks.train_counted(autoregressive(f), cells, n["n0"], settings)

    def estimates(m: networks.Model) -> np.ndarray:
        return m.rows * np.array([m.component.box_mass(m.params, a, b, 100, np.random.default_rng((1, int(i)))) for i, a, b in zip(qid, lo, hi, strict=True)])

    def chain(name: str, first: int, last: int) -> list[tuple[int, str, networks.Model, np.ndarray]]:
        m, out = base, []
        for k in range(first, last):
            if name == "fast_retrain":
                m = replace(networks.train_counted(m.component, cells, n[f"l{k}"], settings), rows=int(upto[k]))
            else:
                m = networks.policies_counted(m, cells, seen[k - 1], n[f"n{k}"], n[f"t{k}"], settings, which=(name,))[name]
            if name == "retrain":
                m = replace(m, rows=int(upto[k]))
            out.append((k, name, m, estimates(m)))
        return out

    names = ("stale", "retrain", "fine_tune", "kd", "fast_retrain")
    # models trained afresh don't depend on the one before, so their parts are jobs of their own
    spans = [(name, *span) for name in names for span in ([(k, k + 1) for k in range(1, 5)] if name.endswith("retrain") else [(1, 5)])]
    spans.sort(key=lambda span: span[1] - span[2])  # the longest first
    made = {(k, name): (m, est) for part in networks.at_once(spark, [lambda span=span: chain(*span) for span in spans]) for k, name, m, est in part}
    rows, kept = [], base
    for k in range(1, 5):
        loss = losses(kept.component, kept.params, cells)
        v = detect.test_counted(loss, n[f"n{k}"], detect.offline_counted(loss, seen[k - 1]), "size_matched")
        kept = made[k, "kd"][0]
        rows += [(k, name, v.is_ood, v.shift, *_error_quantiles(made[k, name][1], met @ seen[k]), made[k, name][0].steps) for name in names]
    return _frame(spark, rows, "part int, policy string, is_ood boolean, shift double, median double, p95 double, row_epochs long")


def speedup(spark: SparkSession, sf_dir: str, f: Fixture = D1, sizes: tuple[float, ...] = (0.2, 0.05), kind: str = "darn", settings: Settings = QUICK) -> DataFrame:
    """Retraining over updating, in seconds and in rows times epochs, by update size."""
    rows = []
    old, _, ood, cols = _tables(f, kind, spark, sf_dir)
    old, ood = old.select("rk", *cols).persist(), ood.select("rk", *cols).persist()
    n = old.count()
    base = networks.train_all(component_for(f, kind), old, cols, settings)
    transfer = hash_sample(old, 0.05 if kind == "vae" else 0.1, "transfer1")
    for share in sizes:  # the batch has a fifth of the old rows
        some = hash_sample(ood, min(1.0, share / 0.2), "part")
        n_new, out = some.count(), {}
        for p in ("retrain", "kd"):
            began = time.perf_counter()
            m = networks.policies_all(base, old, some, transfer, cols, n_new, settings, which=(p,))[p]
            out[p] = (time.perf_counter() - began, m.steps)
        rows.append((f.name, kind, share, n + n_new, out["retrain"][0], out["kd"][0], out["retrain"][0] / out["kd"][0], out["retrain"][1] / out["kd"][1]))
    old.unpersist()
    ood.unpersist()
    return _frame(spark, rows, "fixture string, component string, share double, n_rows long, retrain_s double, kd_s double, speedup double, row_epoch_ratio double")


def losses_by_policy(spark: SparkSession, sf_dir: str, f: Fixture = D6, kind: str = "vae", settings: Settings = QUICK) -> DataFrame:
    """Mean loss on old rows and on the drifted batch under each policy."""
    old, _, ood, cols = _tables(f, kind, spark, sf_dir)
    ood = ood.persist()
    base = networks.train_all(component_for(f, kind), old, cols, settings)
    models = networks.policies_all(base, old, ood, hash_sample(old, 0.05 if kind == "vae" else 0.1, "transfer1"), cols, ood.count(), settings)
    mean = lambda df, m: float(score(df.select(*cols), m.component, m.params, cols).agg(F.avg("loss")).first()[0])
    rows = [(f.name, kind, name, mean(old, m), mean(ood, m), m.steps, metrics.model_bytes(m.params)) for name, m in models.items()]
    ood.unpersist()
    return _frame(spark, rows, "fixture string, component string, policy string, old_loss double, new_loss double, row_epochs long, bytes long")


def spn_comparison(spark: SparkSession, sf_dir: str, f: Fixture = D1, n_queries: int = N_QUERIES) -> DataFrame:
    """The sum-product network before, after insertion, and refitted."""
    old, _, ood, _ = _tables(f, "darn", spark, sf_dir)
    q = workload.ce_queries(old, f, n_queries).persist()
    before = workload.truth(q, old, f).where("truth > 0").persist()
    after = workload.truth_added(before, workload.truth(workload.without_empty(q, before), ood, f)).persist()
    if f.joint_domain > counts.MAX_CELLS:
        raise ValueError(f"{f.joint_domain} cells; take fewer or coarser columns")
    tables = [counts.cells(d, f.columns).toPandas() for d in (old, ood)]  # at most the joint domain
    (a, na), (b, nb) = [(t[list(f.columns)].to_numpy(int), t["n"].to_numpy(float)) for t in tables]
    boxes = q.orderBy("qid").toPandas()
    lo, hi = (boxes[[f"{c}_{e}" for c in f.columns]].to_numpy(int) for e in ("lo", "hi"))
    nets = {"base": spn.SumProduct(f.sizes).fit(a, na), "insert": spn.SumProduct(f.sizes).fit(a, na).insert(b, nb), "retrain": spn.SumProduct(f.sizes).fit(np.concatenate([a, b]), np.concatenate([na, nb]))}
    rows = [(name, int(k), float(e)) for name, net in nets.items() for k, e in zip(boxes["qid"], net.estimate(lo, hi), strict=True)]
    est = _frame(spark, rows, "policy string, qid int, estimate double")
    e = est.join(before.select("qid", F.col("truth").alias("b")), "qid").join(after.select("qid", F.col("truth").alias("a")), "qid")
    e = e.withColumn("q_error", q_error(F.col("estimate"), F.when(F.col("policy") == "base", F.col("b")).otherwise(F.col("a"))))
    return metrics.summary(e)


def toy(spark: SparkSession, sf_dir: str, updates: int = 50, settings: Settings = Settings(epochs=30, rate=5e-3), update_settings: Settings = Settings(epochs=2, rate=1e-3)) -> DataFrame:  # noqa: B008
    """Ten categories with five peaks, then many batches with two other peaks: the density near all seven at the end.

    The rows are parts: the band of the key is the category, and the place of the price within the
    band's range is scaled to [-1, 1].  Old rows lie within 0.1 of five peaks and new ones within 0.1
    of two others; a hash deals new rows to batches and all rows to ten slices, of which each update
    takes one as its transfer set.  Rows are counted by value, and training is exact on the counts.
    """
    old_means, new_means, f = (-0.8, -0.4, 0.0, 0.4, 0.8), (-0.6, 0.6), catalog.D4
    x, price = f.columns[0], F.col(f.target)
    y = F.round((price - F.lit(900.0) - F.lit(10.0) * F.col(x)) / F.lit(5.0) - F.lit(1.0), 6)
    near = lambda means: F.exists(F.array(*[F.lit(m) for m in means]), lambda m: F.abs(F.col("y") - m) < F.lit(0.1))
    rows = f.build(spark, sf_dir).select("rk", x, y.alias("y"))
    parts = drift.split_batches(rows, updates).withColumn("batch_id", F.when(near(old_means), -1).when(near(new_means), F.col("batch_id")))
    tenth = F.floor(row_hash("rk", "transfer") * F.lit(10) / F.lit(HASH_SPACE)).cast("int")
    table = parts.where("batch_id is not null").groupBy(x, "y", "batch_id", tenth.alias("slice")).count().toPandas()  # by value, not by row
    values = table.groupby([x, "y"]).ngroup().to_numpy()
    cells = table[[x, "y"]].groupby(values).first().to_numpy("float64")
    batch, part, n = table["batch_id"].to_numpy(), table["slice"].to_numpy(), table["count"].to_numpy("float64")
    of = lambda rows: np.bincount(values, np.where(rows, n, 0.0), minlength=len(cells))
    base = networks.train_counted(MixtureDensity(10, 10, 32), cells, of(batch < 0), settings)

    def chain(name: str) -> networks.Model:
        m = base
        for u in range(updates):
            m = networks.policies_counted(m, cells, of(batch < u), of(batch == u), of((batch < u) & (part == u % 10)), update_settings, which=(name,))[name]
        return m

    kd, ft = networks.at_once(spark, [lambda name=name: chain(name) for name in ("kd", "fine_tune")])
    found = [(name, m, bool(m in new_means), float(model.component.density(model.params, 3, np.array([m]))[0])) for name, model in (("base", base), ("kd", kd), ("fine_tune", ft)) for m in (*old_means, *new_means)]
    return _frame(spark, found, "policy string, mean double, is_new boolean, density double")


def registered() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "detect_darn_d1": lambda s, d: detection(s, d, D1, "darn"), "detect_darn_d3": lambda s, d: detection(s, d, D3, "darn"), "detect_mdn_d2": lambda s, d: detection(s, d, D2, "mdn"),
        "detect_mdn_d4": lambda s, d: detection(s, d, catalog.D4, "mdn"), "detect_vae_d6": lambda s, d: detection(s, d, D6, "vae"), "detect_vae_d5": lambda s, d: detection(s, d, D5, "vae"),
        "darn_update": ce_one_shot, "mdn_update": aqp_one_shot, "vae_judge_f1": generation, "incremental_ood": incremental, "incremental_ind": lambda s, d: incremental(s, d, kind="ind"),
        "joins_by_time": joined_partitions, "joins_by_time_drifted": lambda s, d: joined_partitions(s, d, True),
        "joins_by_time_lines": lambda s, d: joined_partitions(s, d, f=catalog.J2), "joins_by_time_lines_drifted": lambda s, d: joined_partitions(s, d, True, catalog.J2), "joins_aqp": lambda s, d: aqp_one_shot(s, d, catalog.J1),
        "update_speedup": speedup, "update_speedup_mdn": lambda s, d: speedup(s, d, D2, kind="mdn"), "update_speedup_vae": lambda s, d: speedup(s, d, D6, kind="vae"),
        "vae_update": losses_by_policy, "detect_darn_v1": lambda s, d: detection(s, d, catalog.V1, "darn"), "spn_insert": spn_comparison, "spn_insert_d5": lambda s, d: spn_comparison(s, d, D5),
        "toy_mixture_50": toy,
    }
