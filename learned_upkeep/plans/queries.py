"""Registered queries: each method, baseline, measure and workload on the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import columns as fn
from ..operators import counts, detect, drift, drift_tests, joins, metrics, regression, update, workload
from ..sources import catalog
from ..sources.catalog import D1, D2, D3, INDEP, Fixture
from ..streaming import monitor

Query = Callable[[SparkSession, str], DataFrame]
N_QUERIES = 200
SWEEP = (1, 2, 5, 10, 20, 50, 100, 200)


def _base(f: Fixture, spark: SparkSession, sf: str) -> tuple[DataFrame, counts.ChainCounts]:
    df = f.build(spark, sf)
    return df, counts.fit_cells(counts.cells(df, f.columns), f, counts.SMOOTHING, 0)


def _batch(f: Fixture, df: DataFrame, kind: str) -> DataFrame:
    return {"old": lambda: df, "ind": lambda: drift.ind_batch(df), "ood": lambda: drift.permuted_batch(df, f.columns)}[kind]()


def _rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)


def batch_query(f: Fixture, kind: str) -> Query:
    return lambda spark, sf: _batch(f, f.build(spark, sf), kind)


def permuted_batch_d2(spark, sf):
    return _rounded(drift.permuted_pair(D2.build(spark, sf), "qty_band", "log_unit"))


def incremental_split_5(spark, sf):
    b = drift.split_batches(_batch(D1, D1.build(spark, sf), "ood"))
    return b.groupBy("batch_id").agg(F.count("*").alias("n"), F.sum("qty_band").alias("s1"), F.sum("unit_band").alias("s2"))


def time_partitions_orders_5(spark, sf):
    parts = drift.time_partitions(catalog.table(spark, sf, "orders"), "o_orderdate")
    return parts.groupBy("batch_id").agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("s"))


def ood_pool_levels(spark, sf):
    p = drift.ood_pool(D1.build(spark, sf), D1.columns)
    return p.groupBy("level").agg(F.count("*").alias("n"), F.sum("qty_band").alias("s1"), F.sum("unit_band").alias("s2"), F.sum("flag").alias("s3"), F.sum(F.col("qty_band") * F.col("unit_band")).alias("s12"))


def support_check(spark, sf):
    df = D1.build(spark, sf)
    known = counts.cells(df, D1.columns).drop("n")
    return _batch(D1, df, "ood").join(F.broadcast(known), list(D1.columns), "left_anti").agg(F.count("*").alias("foreign_rows"))


def joint_domain(spark, sf):
    k = [F.count_distinct(c) for c in D1.columns]
    a = D1.build(spark, sf).agg(F.count("*").alias("n_rows"), *[x.alias(f"k{i + 1}") for i, x in enumerate(k)])
    return a.select(F.lit("d1").alias("fixture"), "*", (F.col("k1") * F.col("k2") * F.col("k3")).alias("joint"))


def dictionary_encode(spark, sf):
    from pyspark.sql import Window as W

    seen = catalog.table(spark, sf, "orders").groupBy(F.col("o_orderpriority").alias("value")).agg(F.count("*").alias("n"))
    return seen.select("value", (F.dense_rank().over(W.orderBy("value")) - 1).alias("code"), "n")


def scaled_range(spark, sf):
    o = catalog.table(spark, sf, "orders").select("o_orderkey", "o_totalprice")
    lo, hi = o.agg(F.min("o_totalprice"), F.max("o_totalprice")).first()
    return o.select("o_orderkey", F.round(fn.scale(F.col("o_totalprice"), lo, hi), 6).alias("scaled"))


def count_model_fit(spark, sf):
    return _rounded(_base(D1, spark, sf)[1].frame)


def nll_query(kind: str) -> Query:
    def run(spark, sf):
        df, m = _base(D1, spark, sf)
        return _rounded(m.score(_batch(D1, df, kind)).select("rk", "loss"))

    return run


def loss_table_query(f: Fixture) -> Query:
    def run(spark, sf):
        df, m = _base(f, spark, sf)
        return metrics.loss_table({n: m.score(_batch(f, df, k)) for n, k in (("s_old", "old"), ("ind", "ind"), ("ood", "ood"))})

    return run


def bootstrap_poisson(spark, sf):
    df, m = _base(D1, spark, sf)
    return _rounded(detect.bootstrap_poisson(m.score(df), 50))


def bootstrap_all_rows(spark, sf):
    df, m = _base(D1, spark, sf)
    return _rounded(detect.bootstrap_cells(m.score(counts.cells(df, D1.columns))))


def bootstrap_normal_std(spark, sf):
    df, m = _base(D1, spark, sf)
    return _rounded(detect.normal_std(m.score(df), 600))


def threshold_modes(spark, sf):
    df, m = _base(D1, spark, sf)
    n, sigma, mean = m.score(df).agg(F.count("*"), F.stddev_pop("loss"), F.avg("loss")).first()
    base = detect.Baseline(mean, sigma / 600**0.5, 600, sigma, n)
    rows = [(mode, round(detect.threshold(base, 1200, mode), 6)) for mode in ("fixed", "size_matched", "pooled")]
    return spark.createDataFrame(rows, "mode string, threshold double")


def two_sample_query(f: Fixture, kind: str) -> Query:
    def run(spark, sf):
        df, m = _base(f, spark, sf)
        t = detect.two_sample(m.score(df), m.score(_batch(f, df, kind)), 600)
        return t.select(F.round("old_mean", 6).alias("old_mean"), F.round("new_mean", 6).alias("new_mean"), "old_n", "new_n", F.round("shift", 6).alias("shift"), F.round("threshold", 6).alias("threshold"), F.round("z", 4).alias("z"), F.round("p", 6).alias("p"), "is_ood")

    return run


def _drawn(spark, sf, batches: int, size: int) -> tuple[DataFrame, float, float]:
    df, m = _base(D1, spark, sf)
    mean, std = m.score(df).agg(F.avg("loss"), F.stddev_pop("loss")).first()
    parts = [detect.detector_batches(m.score(_batch(D1, df, kind)), batches, size, seed).withColumn("truth", F.lit(kind == "ood")) for kind, seed in (("ind", 1), ("ood", 2))]
    return _union(parts), mean, std


def fpr_fnr_batches(spark, sf):
    drawn, mean, std = _drawn(spark, sf, 40, 200)
    b = drawn.groupBy("truth", "batch_no").agg(F.avg("loss").alias("l"), F.count("*").alias("n"))
    return metrics.detector_rates(b.withColumn("fired", F.abs(F.col("l") - F.lit(mean)) > 2.0 * std / F.sqrt("n")))


def batch_size_sweep(spark, sf):
    """Nested batches: a size is a prefix of one draw, so one draw serves all sizes."""
    drawn, mean, std = _drawn(spark, sf, 20, 200)
    each = drawn.withColumn("size", F.explode(F.array(*[F.lit(k) for k in SWEEP]))).where("pos <= size")
    b = each.groupBy("size", "truth", "batch_no").agg(F.avg("loss").alias("l"))
    return metrics.detector_rates(b.withColumn("fired", F.abs(F.col("l") - F.lit(mean)) > 2.0 * std / F.sqrt("size")), ("size",))


POOL_BATCHES = 1000
POOL_SIZES = (1, 2, 5, 10, 20, 50, 100, 200, 500, 1000, 2000)


def _pool_rates(spark, sf, sizes: tuple[int, ...]) -> DataFrame:
    """Rates by size and level: IND batches from half of the rows; OOD ones from five slices of 10 % with one to five sorted columns (level 0: from all five)."""
    df, m = _base(D3, spark, sf)
    mean, std = m.score(df).agg(F.avg("loss"), F.stddev_pop("loss")).first()
    pools = {False: fn.hash_sample(df, 0.5, "ind_pool").withColumn("level", F.lit(0)), True: drift.ood_pool(df, D3.columns)}
    b = _union([detect.pool_batches(m.score(p), POOL_BATCHES, sizes, 1 + truth).withColumn("truth", F.lit(truth)) for truth, p in pools.items()])
    return metrics.detector_rates(b.withColumn("fired", F.abs(F.col("l") - F.lit(mean)) > 2.0 * std / F.sqrt("n")), ("size", "level"))


def fpr_fnr_pools(spark, sf):
    return _pool_rates(spark, sf, (2000,))


def batch_size_sweep_pools(spark, sf):
    return _pool_rates(spark, sf, POOL_SIZES)


POLICIES = ("stale", "stale_refreshed", "retrain", "fine_tune", "fine_tune_small", "pooled", "kd_described", "kd_printed", "kd_mass", "no_teacher")


def policy_counts_query(name: str) -> Query:
    def run(spark, sf):
        df = D1.build(spark, sf)
        return _rounded(update.policies(D1, df, _batch(D1, df, "ood"), which=(name,))[name].masses(), 9)

    return run


def kd_lambda_grid(spark, sf):
    df = D1.build(spark, sf)
    return _rounded(update.lambda_grid(D1, df, _batch(D1, df, "ood")))


def _workload(f: Fixture, spark, sf, n: int = N_QUERIES) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(rows, OOD batch, queries, truth before)."""
    df = f.build(spark, sf)
    raw = workload.ce_queries(df, f, n).persist()
    before = workload.truth(raw, df, f).where("truth > 0").persist()
    return df, _batch(f, df, "ood"), workload.without_empty(raw, before), before


def _errors(f: Fixture, spark, sf) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(policy, qid, estimate, truth, q_error), truth before and after."""
    df, batch, q, before = _workload(f, spark, sf)
    after = workload.truth_added(before, workload.truth(q, batch, f)).persist()
    models = update.policies(f, df, batch, which=POLICIES)
    est = []
    for name, m in models.items():
        p = workload.over_cells(q, m.masses(), f.columns, "prob", "p")
        est.append(p.select(F.lit(name).alias("policy"), "qid", (F.lit(float(m.rows)) * F.col("p")).alias("estimate")))
    return metrics.q_errors(_union(est), after), before, after


def ce_truth(spark, sf):
    return _workload(D1, spark, sf)[3]


def truth_incremental(spark, sf):
    df, batch, q, before = _workload(D1, spark, sf)
    return workload.truth_added(before, workload.truth(q, batch, D1))


def qerror_query(f: Fixture) -> Query:
    return lambda spark, sf: metrics.summary(_errors(f, spark, sf)[0])


def fwt_bwt_at(spark, sf):
    return metrics.transfer(*_errors(D1, spark, sf))


def changed_share(spark, sf):
    df, batch, q, before = _workload(D1, spark, sf)
    return metrics.changed_share(before, workload.truth_added(before, workload.truth(q, batch, D1)))


def loglik_old_new(spark, sf):
    df = D1.build(spark, sf)
    batch = _batch(D1, df, "ood")
    models = update.policies(D1, df, batch, which=("stale", "fine_tune", "kd_described", "retrain"))
    return _union([metrics.loglik_old_new(m.score(df), m.score(batch)).select(F.lit(n).alias("policy"), "loglik") for n, m in models.items()])


def topk_qerror(spark, sf):
    e = _errors(D1, spark, sf)[0].select("policy", "qid", F.round("q_error", 4).alias("q_error"), "truth")
    return e.orderBy(F.desc("q_error"), "policy", "qid").limit(20)


def rollup_metrics(spark, sf):
    e, before, after = _errors(D1, spark, sf)
    b = before.select("qid", F.col("truth").alias("b"))
    e = e.join(b, "qid").withColumn("changed", F.col("truth") != F.col("b"))
    return e.rollup("policy", "changed").agg(F.round(F.avg("q_error"), 4).alias("mean"), F.count("*").alias("n"))


def _aqp(spark, sf) -> tuple[DataFrame, DataFrame, DataFrame]:
    df = D2.build(spark, sf)
    q = workload.aqp_queries(df, "qty_band", "log_unit", 100).persist()
    return df, q, workload.aqp_truth(q, df, "qty_band", "log_unit")


def aqp_truth(spark, sf):
    return _aqp(spark, sf)[2].select("qid", "count", F.round("sum", 4).alias("sum"), F.round("avg", 4).alias("avg"))


def _sampled(df, q):
    s = workload.aqp_truth(q, fn.hash_sample(df, 0.1, "sample1"), "qty_band", "log_unit")
    return s.select("qid", (F.col("count") * F.lit(10.0)).alias("estimate"), (F.col("sum") * 10).alias("sum_estimate"))


def sample_answer_aqp(spark, sf):
    df, q, _ = _aqp(spark, sf)
    return _sampled(df, q).select("qid", "estimate", F.round("sum_estimate", 4).alias("sum_estimate"))


def rel_error_summary(spark, sf):
    df, q, t = _aqp(spark, sf)
    e = metrics.relative_errors(_sampled(df, q).select("qid", F.col("sum_estimate").alias("estimate")), t.select("qid", F.col("sum").alias("truth")))
    return metrics.summary(e, "rel_error", ())


def frequency_table_merge(spark, sf):
    df = D1.build(spark, sf)
    return update.merge_frequencies(df, _batch(D1, df, "ood"), "qty_band")


def cardinality_merge(spark, sf):
    df = D1.build(spark, sf)
    both = df.select(F.lit(0).alias("s")).unionByName(_batch(D1, df, "ood").select(F.lit(1).alias("s")))
    return both.agg(F.count_if(F.col("s") == 0).alias("n_old"), F.count_if(F.col("s") == 1).alias("n_new"), F.count("*").alias("n_all"))


def _triple(spark, sf):
    o, c, n = (catalog.table(spark, sf, t) for t in ("orders", "customer", "nation"))
    return o, (c, F.col("o_custkey") == F.col("c_custkey")), (F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))


def _arrived():
    return fn.row_hash(F.col("o_orderkey").cast("string"), "arrive") < fn.cut(0.2)


def join_delta_orders(spark, sf):
    o, *dims = _triple(spark, sf)
    return joins.delta(o.where(_arrived()), *dims).groupBy("n_name").agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("s"))


def join_delta_many_orders(spark, sf):
    """New rows of orders, customer and nation by market segment when a fifth of the orders, of the customers and of the nations arrive together."""
    o, c, n = (catalog.table(spark, sf, t) for t in ("orders", "customer", "nation"))
    o = o.select("o_orderkey", F.col("o_custkey").alias("c_custkey"))
    c = c.select("c_custkey", "c_mktsegment", F.col("c_nationkey").alias("n_nationkey"))
    n = n.select("n_nationkey", "n_name")
    arrived = lambda key: fn.row_hash(F.col(key).cast("string"), "arrive") < fn.cut(0.2)
    tables = [(t.where(~arrived(k)), t.where(arrived(k))) for t, k in ((o, "o_orderkey"), (c, "c_custkey"), (n, "n_nationkey"))]
    new = joins.delta_many(tables, [["c_custkey"], ["n_nationkey"]])
    return new.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("s"), F.count_distinct("n_name").alias("nations"))


def squared_error_query(kind: str) -> Query:
    """The test on the squared error of a regression of the unit price on the quantity band."""

    def run(spark, sf):
        df = D2.build(spark, sf)
        batch = drift.ind_batch(df) if kind == "ind" else drift.permuted_pair(df, "qty_band", "log_unit")
        m = regression.fit(df, D2.columns, D2.target)
        both = detect.mean_shift(m.score(df), m.score(batch)).crossJoin(detect.normal_std(m.score(df), 600).select("std"))  # one row each
        return both.select(*[F.round(c, 6).alias(c) for c in ("old_mean", "new_mean", "shift")], "old_n", "new_n", F.round(2 * F.col("std"), 6).alias("threshold"), (F.abs("shift") > 2 * F.col("std")).alias("is_ood"))

    return run


def join_delta_equals_recompute(spark, sf):
    """Rows that the grown join lacks or has too many of, against the join computed anew, when both tables grow."""
    o, c = (catalog.table(spark, sf, t) for t in ("orders", "customer"))
    o, c = o.select("o_orderkey", F.col("o_custkey").alias("k")), c.select(F.col("c_custkey").alias("k"), "c_name")
    new_o = fn.row_hash(F.col("o_orderkey").cast("string"), "arrive") < fn.cut(0.2)
    new_c = fn.row_hash(F.col("k").cast("string"), "arrive") < fn.cut(0.2)
    grown = joins.grow(o.where(~new_o).join(c.where(~new_c), "k"), joins.delta_two(o.where(~new_o), o.where(new_o), c.where(~new_c), c.where(new_c), ["k"]))
    whole = o.join(c, "k")
    tagged = whole.select("k", "o_orderkey", "c_name", F.lit(1).alias("d")).unionByName(grown.select("k", "o_orderkey", "c_name", F.lit(-1).alias("d")))
    per_row = tagged.groupBy("k", "o_orderkey", "c_name").agg(F.sum("d").alias("d"))
    return per_row.agg(F.coalesce(F.sum(F.greatest("d", F.lit(0))), F.lit(0)).alias("missing"), F.coalesce(F.sum(F.greatest(-F.col("d"), F.lit(0))), F.lit(0)).alias("surplus"))


def join_sample_1pct(spark, sf):
    o, *dims = _triple(spark, sf)
    s = joins.join_sample(o.withColumn("rk", F.col("o_orderkey").cast("string")), 0.01, 1, *dims)
    return s.groupBy("n_name").agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("s"))


def join_three_way_d3(spark, sf):
    return D3.build(spark, sf).groupBy("nation", "region").agg(F.count("*").alias("n"))


def join_lineitem_part_supplier(spark, sf):
    return catalog.J2.build(spark, sf).groupBy("size_band", "s_nation").agg(F.count("*").alias("n"))


def ks_columns(spark, sf):
    df = D1.build(spark, sf)
    return drift_tests.ks(df, _batch(D1, df, "ood"), D1.columns)


def mmd_all_rows(spark, sf):
    df = D1.build(spark, sf)
    return drift_tests.mmd_cells(df, _batch(D1, df, "ood"), D1.columns)


def dependence_matrix(spark, sf):
    return drift_tests.dependence(D1.build(spark, sf), D1.columns)


TEMPERATURES = (0.5, 1.0, 2.0, 10.0)


def _logits(spark, sf):
    """(qty_band, unit_band, t, s): logits of the flag given both bands, from smoothed counts of the old rows (t) and of those with the drifted batch (s)."""
    df = D1.build(spark, sf)
    both = df.select(*D1.columns, F.lit(True).alias("old")).unionByName(_batch(D1, df, "ood").select(*D1.columns, F.lit(False).alias("old")))
    logit = lambda k, which: F.log(F.count_if((F.col("flag") == k) & which) + F.lit(counts.SMOOTHING))
    flags = range(D1.sizes[2])
    return both.groupBy("qty_band", "unit_band").agg(F.array(*[logit(k, F.col("old")) for k in flags]).alias("t"), F.array(*[logit(k, F.lit(True)) for k in flags]).alias("s"))


def soft_ce_rows(spark, sf):
    each = _logits(spark, sf).withColumn("temperature", F.explode(F.array(*[F.lit(t) for t in TEMPERATURES])))
    return each.select("qty_band", "unit_band", "temperature", (F.round(fn.soft_cross_entropy(F.col("t"), F.col("s"), F.col("temperature")), 6) + 0.0).alias("soft_ce"))


def logit_mse_rows(spark, sf):
    return _logits(spark, sf).select("qty_band", "unit_band", F.round(fn.squared_logit_gap(F.col("t"), F.col("s")), 6).alias("logit_mse"))


def _mixtures(spark, sf):
    """(id, w, m, s, y): for each quantity band a mixture over return flags of the scaled logarithm of the unit price, at 21 points."""
    li = catalog.table(spark, sf, "lineitem").select(
        F.floor((F.col("l_quantity") - 1) / 5).cast("int").alias("id"), catalog.coded(F.col("l_returnflag"), catalog.FLAGS).alias("c"),
        ((F.log(F.try_divide("l_extendedprice", "l_quantity")) - F.lit(7.0)) / F.lit(5.0)).alias("y"),
    )
    parts = li.where("id is not null and y is not null").groupBy("id", "c").agg(F.count("*").alias("n"), F.avg("y").alias("m"), (F.stddev_pop("y") + F.lit(1e-3)).alias("s"))
    k = parts.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("c", "n", "m", "s"))).alias("k"), F.sum("n").alias("n"))  # a part for each flag
    m = k.select("id", F.transform("k", lambda x: x["n"] / F.col("n")).alias("w"), F.col("k")["m"].alias("m"), F.col("k")["s"].alias("s"))
    return m.withColumn("y", F.explode(F.transform(F.sequence(F.lit(0), F.lit(20)), lambda i: (i - 10) / F.lit(10.0))))


def mixture_pdf(spark, sf):
    return _mixtures(spark, sf).select("id", "y", F.round(fn.mixture_pdf(F.col("y"), F.col("w"), F.col("m"), F.col("s")), 6).alias("pdf"))


def mixture_range_mass(spark, sf):
    mass = fn.mixture_mass(F.lit(-1.0), F.col("y"), F.col("w"), F.col("m"), F.col("s"))
    return _mixtures(spark, sf).select("id", F.col("y").alias("hi"), (F.round(mass, 6) + 0.0).alias("mass"))


def cube_marginals(spark, sf):
    return counts.marginals(D1.build(spark, sf), D1.columns).drop("gid")


def json_props_counts(spark, sf):
    return catalog.events(spark, sf).groupBy("event_type", "k").agg(F.count("*").alias("n"))


def asof_model_version(spark, sf):
    ev = catalog.events(spark, sf)
    weeks = spark.range(6).select(F.col("id").alias("version"))
    types = ev.select("event_type").distinct()
    start = F.to_timestamp(F.lit("2024-01-01"))
    v = types.crossJoin(F.broadcast(weeks)).select("event_type", (start + F.make_interval(days=(F.col("version") * 7).cast("int"))).alias("ts"), "version")
    return joins.as_of(ev, v, ["event_type"], "ts", "version").groupBy("event_type", "version").agg(F.count("*").alias("n"))


def interval_drift_rows(spark, sf):
    ev = catalog.events(spark, sf)
    a = ev.where("event_type = 'click'").select("user_id", F.col("ts").alias("click_ts"))
    b = ev.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("purchase_ts"))
    return joins.interval(a, b, ["user_id"], "click_ts", "purchase_ts", 3600).groupBy("user_id").agg(F.count("*").alias("n"))


def sliding_value_sums(spark, sf):
    ev = catalog.events(spark, sf)
    w = ev.groupBy(F.window("ts", "24 hours", "6 hours")).agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"), F.count("*").alias("n"))
    return w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "cents", "n")


def session_event_counts(spark, sf):
    ev = catalog.events(spark, sf)
    s = ev.groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("events"))
    return s.groupBy("events").agg(F.count("*").alias("sessions"))


def drift_by_column(spark, sf):
    """The shift of each column's loss given those before it: a column that fires is drift of its conditional, not of what it depends on."""
    df, m = _base(D3, spark, sf)
    return _rounded(detect.by_column(m.score_columns(df), m.score_columns(_batch(D3, df, "ood")), D3.columns))


def streaming_replay(spark, sf):
    """Events as a stream: mean loss by day under the shares of event types in the first week."""
    ev = catalog.events(spark, sf)
    first = ev.where(F.col("ts") < F.lit("2024-01-08"))
    n = first.count()
    shares = first.groupBy("event_type").agg((-F.log(F.count("*") / F.lit(float(n)))).alias("loss"))  # a row for each type
    raw = catalog.table(spark, sf, "events")
    stream = monitor.file_stream(spark, f"{sf}/events.parquet*", raw.schema)  # a pattern takes a single file, too
    scored = stream.withColumn("ts", F.col("ts").cast("timestamp")).join(F.broadcast(shares), "event_type", "left").withColumn("loss", F.coalesce("loss", F.lit(counts.UNSEEN_LOSS)))
    return _rounded(monitor.replayed(monitor.drift_curve(scored, late=None)).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "mean_loss", "n"))


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {
        "ind_batch_lineitem": batch_query(D1, "ind"), "ind_batch_orders": batch_query(D3, "ind"),
        "permuted_batch_d1": batch_query(D1, "ood"), "permuted_batch_d3": batch_query(D3, "ood"),
        "loss_table_d1": loss_table_query(D1), "loss_table_d3": loss_table_query(D3), "loss_table_indep": loss_table_query(INDEP),
        "two_sample_ind": two_sample_query(D1, "ind"), "two_sample_ood": two_sample_query(D1, "ood"), "two_sample_control": two_sample_query(INDEP, "ood"),
        "qerror_summary_by_policy": qerror_query(D1), "qerror_summary_d3": qerror_query(D3),
    }
    out |= {f"squared_error_{k}": squared_error_query(k) for k in ("ind", "ood")}
    out |= {f"count_model_nll_{k}": nll_query(k) for k in ("old", "ind", "ood")}
    out |= {f"{p}_counts": policy_counts_query(p) for p in POLICIES}
    plain = [
        permuted_batch_d2, incremental_split_5, time_partitions_orders_5, ood_pool_levels, support_check, joint_domain, dictionary_encode, scaled_range, count_model_fit,
        bootstrap_poisson, bootstrap_all_rows, bootstrap_normal_std, threshold_modes, fpr_fnr_batches, batch_size_sweep, fpr_fnr_pools, batch_size_sweep_pools, kd_lambda_grid, ce_truth, truth_incremental, fwt_bwt_at, changed_share,
        loglik_old_new, topk_qerror, rollup_metrics, aqp_truth, sample_answer_aqp, rel_error_summary, frequency_table_merge, cardinality_merge, join_delta_orders,
        join_delta_equals_recompute, join_delta_many_orders, join_sample_1pct, join_three_way_d3, join_lineitem_part_supplier, ks_columns, mmd_all_rows, dependence_matrix, soft_ce_rows, logit_mse_rows,
        mixture_pdf, mixture_range_mass, cube_marginals, json_props_counts, asof_model_version, interval_drift_rows, sliding_value_sums, session_event_counts, drift_by_column, streaming_replay,
    ]
    return out | {f.__name__: f for f in plain}
