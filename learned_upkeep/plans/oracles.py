"""SQL for DuckDB that computes what the registered queries compute, written from the definitions."""

from __future__ import annotations

from functools import reduce

from ..operators.update import LAMBDA, LAMBDA_GRID
from ..sources.catalog import D1, D3, INDEP, Fixture

SMOOTH = 0.1
LEAST = 1e-12


def h(key: str, seed: str) -> str:
    return f"('0x' || substr(md5(concat_ws('|', {key}, '{seed}')), 1, 8))::BIGINT"


LINEITEM_KEY = "concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(l_quantity AS INT), CAST(round(l_extendedprice * 100) AS BIGINT), date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)))"


def code(c: str, values: tuple[str, ...]) -> str:
    return "CASE " + c + " " + " ".join(f"WHEN '{v}' THEN {i}" for i, v in enumerate(values)) + f" ELSE {len(values)} END"


FLAG = code("l_returnflag", ("A", "N", "R"))
FIXTURE_SQL = {
    "d1": f"SELECT {LINEITEM_KEY} AS rk, CAST(floor((l_quantity - 1) / 5) AS INT) AS qty_band, greatest(0, least(7, CAST(floor(ln(l_extendedprice / l_quantity)) AS INT) - 3)) AS unit_band, {FLAG} AS flag FROM lineitem",
    "indep": f"SELECT {LINEITEM_KEY} AS rk, {FLAG} AS flag, {code('l_linestatus', ('F', 'O'))} AS status, l_linenumber - 1 AS line, CAST(round(l_discount * 100 + 0.0) AS INT) AS disc FROM lineitem",
    "d2": f"SELECT {LINEITEM_KEY} AS rk, CAST(floor((l_quantity - 1) / 5) AS INT) AS qty_band, ln(l_extendedprice / l_quantity) AS log_unit FROM lineitem",
    "d3": "SELECT CAST(o_orderkey AS VARCHAR) AS rk, c_nationkey AS nation, n_regionkey AS region, "
    + code("c_mktsegment", ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")) + " AS segment, "
    + code("o_orderstatus", ("F", "O", "P")) + " AS status, " + code("o_orderpriority", ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"))
    + " AS priority FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
}
SPACE = 4294967296


def ind_sql(fixture: str, fraction: float = 0.2, seed: int = 1) -> str:
    return f"SELECT * FROM {fixture} WHERE {h('rk', f'ind{seed}')} < {int(fraction * SPACE)}"


def ood_sql(f: Fixture, fraction: float = 0.2, seed: int = 1, sort: tuple[str, ...] | None = None) -> str:
    """Real sorts per column and a join on rank."""
    sort = f.columns if sort is None else sort
    free = [c for c in f.columns if c not in sort]
    parts = [f"(SELECT row_number() OVER (ORDER BY {c}) - 1 AS rank, {c} FROM {f.name}) x{i}" for i, c in enumerate(sort)]
    if free:
        parts.append(f"(SELECT row_number() OVER (ORDER BY {h('rk', f'shuffle{seed}')}, rk) - 1 AS rank, {', '.join(free)} FROM {f.name}) xf")
    joined = parts[0] + "".join(f" JOIN {p} USING (rank)" for p in parts[1:])
    return f"SELECT 'p|' || CAST(rank AS VARCHAR) AS rk, {', '.join(f.columns)} FROM {joined} WHERE {h('CAST(rank AS VARCHAR)', f'ood{seed}')} < {int(fraction * SPACE)}"


def cells_sql(f: Fixture, source: str) -> str:
    return f"SELECT {', '.join(f.columns)}, count(*) AS n FROM {source} GROUP BY ALL"


def grid_sql(f: Fixture) -> str:
    return "SELECT * FROM " + ", ".join(f"(SELECT CAST(range AS INT) AS {c} FROM range({k})) g{i}" for i, (c, k) in enumerate(zip(f.columns, f.sizes, strict=True)))


def _on_grid(f: Fixture, **sources: str) -> str:
    on = lambda s: " AND ".join(f"g.{c} = {s}.{c}" for c in f.columns)
    return f"SELECT g.*, {', '.join(f'coalesce({s}.n, 0)::DOUBLE AS {s}' for s in sources)} FROM grid g " + " ".join(f"LEFT JOIN {t} {s} ON {on(s)}" for s, t in sources.items())


def _sums(f: Fixture, value: str, prefix: str) -> str:
    return ", ".join(f"sum({value}) OVER (PARTITION BY {', '.join(('1', *f.columns[:i]))}) AS {prefix}{i}" for i in range(len(f.columns) + 1))


def model_sql(f: Fixture, cells: str) -> str:
    p = ", ".join(f"(s{i + 1} + {SMOOTH}) / (s{i} + {SMOOTH} * {k}) AS p{i + 1}" for i, k in enumerate(f.sizes))
    return f"SELECT {', '.join(f.columns)}, {p} FROM (SELECT *, {_sums(f, 'm', 's')} FROM ({_on_grid(f, m=cells)}))"


def distil_sql(f: Fixture, teacher: str, transfer: str, batch: str, lam: float, w_new: str) -> str:
    t = f"SELECT q.*, {', '.join(f'b.p{i + 1}' for i in range(len(f.columns)))} FROM ({_on_grid(f, tr=transfer, up=batch)}) q JOIN {teacher} b USING ({', '.join(f.columns)})"
    s = f"SELECT *, {_sums(f, 'tr', 't')}, {_sums(f, 'up', 'u')}, {w_new} AS w FROM ({t})"
    out = []
    for i in range(1, len(f.columns) + 1):
        wo, wn = "(1.0 - w) / greatest(t0, 1.0)", "w / greatest(u0, 1.0)"
        top = f"{wo} * ({lam!r} * t{i - 1} * p{i} + (1.0 - {lam!r}) * t{i}) + {wn} * u{i}"
        bottom = f"{wo} * t{i - 1} + {wn} * u{i - 1}"
        out.append(f"CASE WHEN {bottom} > 0 THEN ({top}) / ({bottom}) ELSE p{i} END AS p{i}")
    return f"SELECT {', '.join(f.columns)}, {', '.join(out)} FROM ({s})"


def tune_sql(f: Fixture, model: str, batch_model: str, rate: str) -> str:
    p = ", ".join(f"(1.0 - {rate}) * m.p{i} + {rate} * b.p{i} AS p{i}" for i in range(1, len(f.columns) + 1))
    return f"SELECT {', '.join(f'm.{c}' for c in f.columns)}, {p} FROM {model} m JOIN {batch_model} b USING ({', '.join(f.columns)})"


def logp(f: Fixture) -> str:
    return " + ".join(f"ln(greatest(p{i}, {LEAST}))" for i in range(1, len(f.columns) + 1))


def scored_sql(f: Fixture, source: str, model: str = "base") -> str:
    return f"SELECT s.*, -({logp(f)}) AS loss FROM {source} s JOIN {model} USING ({', '.join(f.columns)})"


def ctes(**named: str) -> str:
    return "WITH " + ", ".join(f"{k} AS ({v})" for k, v in named.items()) + " "


def setting(f: Fixture, ood: bool = True) -> dict[str, str]:
    """Fixture, batch, cells, grid and base model."""
    own = {f.name: FIXTURE_SQL[f.name], "ind": ind_sql(f.name)}
    if ood:
        own["ood"] = ood_sql(f)
    return own | {"c_old": cells_sql(f, f.name), "grid": grid_sql(f), "base": model_sql(f, "c_old")}


def query_set(f: Fixture, n: int, source: str, min_filters: int = 2, seed: int = 1) -> str:
    m = len(f.columns)
    hq = lambda what: h(f"'{what}', qid", str(seed))
    picks = {c: hq(f"pick{c}") for c in f.columns}
    a = f"SELECT *, row_number() OVER (ORDER BY hh, rk) - 1 AS qid FROM (SELECT *, {h('rk', f'query{seed}')} AS hh FROM {source} ORDER BY hh, rk LIMIT {n})"
    place = lambda i, c: f"(1 + " + " + ".join(f"CAST({picks[d]} < {picks[c]} OR ({picks[d]} = {picks[c]} AND {j} < {i}) AS INT)" for j, d in enumerate(f.columns) if d != c) + ")"  # noqa: E731, F541
    wanted = f"({hq('count')} % {m - min_filters + 1} + {min_filters})"
    out = []
    for i, (c, k) in enumerate(zip(f.columns, f.sizes, strict=True)):
        used = f"{place(i, c)} <= {wanted}"
        op = "0" if k < 10 else f"{hq(f'op{c}')} % 3"
        out += [f"CASE WHEN {used} AND {op} <> 2 THEN {c} ELSE 0 END AS {c}_lo", f"CASE WHEN {used} AND {op} <> 1 THEN {c} ELSE {k - 1} END AS {c}_hi"]
    return f"SELECT qid, {', '.join(out)} FROM ({a})"


def answers(f: Fixture, queries: str, cells: str, value: str, out: str, kind: str = "BIGINT") -> str:
    box = " AND ".join(f"c.{c} BETWEEN q.{c}_lo AND q.{c}_hi" for c in f.columns)
    return f"SELECT q.qid, coalesce(sum({value}), 0)::{kind} AS {out} FROM {queries} q LEFT JOIN {cells} c ON {box} GROUP BY q.qid"


def policy_setting(f: Fixture, lam: float = LAMBDA, n_queries: int = 200) -> tuple[dict[str, str], list[str]]:
    s = setting(f)
    s |= {"tr": f"SELECT * FROM {f.name} WHERE {h('rk', 'transfer1')} < {int(0.1 * SPACE)}"}
    s |= {"c_new": cells_sql(f, "ood"), "c_tr": cells_sql(f, "tr")}
    both = lambda a, b: f"SELECT {', '.join(f.columns)}, sum(n) AS n FROM (SELECT * FROM {a} UNION ALL BY NAME SELECT * FROM {b}) GROUP BY ALL"
    s |= {"c_all": both("c_old", "c_new"), "c_pool": both("c_tr", "c_new")}
    n_old, n_new = "(SELECT sum(n) FROM c_old)", "(SELECT sum(n) FROM c_new)"
    ratio = f"least(1.0, {n_new}::DOUBLE / {n_old})"
    s |= {
        "m_stale": "SELECT * FROM base", "m_stale_refreshed": "SELECT * FROM base", "m_retrain": model_sql(f, "c_all"), "m_batch": model_sql(f, "c_new"),
        "m_fine_tune": tune_sql(f, "base", "m_batch", "1.0"), "m_fine_tune_small": tune_sql(f, "base", "m_batch", f"({n_new}::DOUBLE / {n_old})"), "m_pooled": model_sql(f, "c_pool"),
        "m_kd_described": distil_sql(f, "base", "c_tr", "c_new", lam, ratio), "m_kd_printed": distil_sql(f, "base", "c_tr", "c_new", lam, f"1.0 - {ratio}"),
        "m_kd_mass": distil_sql(f, "base", "c_tr", "c_new", lam, f"{n_new}::DOUBLE / ({n_new} + {n_old})"),
        "m_no_teacher": distil_sql(f, "base", "c_tr", "c_new", 0.0, ratio),
    }
    names = ["stale", "stale_refreshed", "retrain", "fine_tune", "fine_tune_small", "pooled", "kd_described", "kd_printed", "kd_mass", "no_teacher"]
    s |= {"q_raw": query_set(f, n_queries, f.name), "t_old_raw": answers(f, "q_raw", "c_old", "c.n", "truth")}
    s |= {"q": "SELECT q_raw.* FROM q_raw JOIN t_old_raw USING (qid) WHERE truth > 0", "t_old": "SELECT * FROM t_old_raw WHERE truth > 0", "t_all": answers(f, "q", "c_all", "c.n", "truth")}
    for n in names:
        s[f"mass_{n}"] = f"SELECT {', '.join(f.columns)}, exp({logp(f)}) AS prob FROM m_{n}"
    rows = lambda n: n_old if n == "stale" else f"({n_old} + {n_new})"
    s["est"] = " UNION ALL ".join(f"SELECT '{n}' AS policy, qid, {rows(n)} * p AS estimate FROM ({answers(f, 'q', f'mass_{n}', 'c.prob', 'p', 'DOUBLE')})" for n in names)
    s["err"] = "SELECT policy, qid, greatest(greatest(estimate, 1.0), greatest(truth, 1.0)) / least(greatest(estimate, 1.0), greatest(truth, 1.0)) AS q_error, truth FROM est JOIN t_all USING (qid)"
    return s, names


SUMMARY = "round(quantile_cont(q_error, 0.5), 4) AS median, round(quantile_cont(q_error, 0.95), 4) AS p95, round(quantile_cont(q_error, 0.99), 4) AS p99, round(max(q_error), 4) AS max, round(avg(q_error), 4) AS mean, count(q_error) AS n"


def _losses(f: Fixture) -> str:
    s = setting(f)
    parts = " UNION ALL ".join(f"SELECT '{n}' AS source, loss FROM ({scored_sql(f, t)})" for n, t in (("s_old", f.name), ("ind", "ind"), ("ood", "ood")))
    return ctes(**s) + f"SELECT source, round(avg(loss), 6) AS mean_loss, count(*) AS n FROM ({parts}) GROUP BY source"


def cdf(z: str) -> str:
    t = f"(1.0 / (1.0 + 0.2316419 * abs({z})))"
    poly = reduce(lambda a, b: f"({b} + {t} * {a})", ["1.330274429", "-1.821255978", "1.781477937", "-0.356563782", "0.319381530"])
    tail = f"(exp(-({z}) * ({z}) / 2.0) / sqrt(2 * pi()) * {t} * {poly})"
    return f"(CASE WHEN {z} >= 0 THEN 1.0 - {tail} ELSE {tail} END)"


def _two_sample(f: Fixture, batch: str, n_boot: int) -> str:
    s = setting(f) | {"so": scored_sql(f, f.name), "sn": scored_sql(f, batch), "o": "SELECT avg(loss) AS old_mean, stddev_pop(loss) AS old_std, count(*) AS old_n FROM so", "w": "SELECT avg(loss) AS new_mean, count(*) AS new_n FROM sn"}
    s["v"] = f"SELECT *, new_mean - old_mean AS shift, greatest(old_std / sqrt({n_boot}.0), 1e-9) AS std FROM o, w"
    return ctes(**s) + f"SELECT round(old_mean, 6) AS old_mean, round(new_mean, 6) AS new_mean, old_n, new_n, round(shift, 6) AS shift, round(2.0 * std, 6) AS threshold, round(shift / std, 4) AS z, round(2 * (1 - {cdf('abs(shift / std)')}), 6) AS p, abs(shift) > 2.0 * std AS is_ood FROM v"


def _poisson(u: str) -> str:
    import math

    total, term, out = 0.0, math.exp(-1.0), "CASE"
    for k in range(9):
        total += term
        out += f" WHEN {u} < {total!r} THEN {k}"
        term *= 1.0 / (k + 1)
    return out + " ELSE 9 END"


def _drawn(batch: str, seed: int, batches: int, size: int) -> str:
    key = f"concat_ws('|', rk, batch_no)"  # noqa: F541
    return f"SELECT *, row_number() OVER (PARTITION BY batch_no ORDER BY {h(key, f'draw{seed}')}, rk) AS pos FROM {batch}, (SELECT range AS batch_no FROM range({batches})) QUALIFY pos <= {size}"


def _rates(f: Fixture, batches: int, size: int, sizes: list[int] | None = None) -> str:
    s = setting(f) | {"so": scored_sql(f, f.name), "sn": scored_sql(f, "ood"), "si": scored_sql(f, "ind"), "o": "SELECT avg(loss) AS mean, stddev_pop(loss) AS std FROM so"}
    s |= {"di": _drawn("si", 1, batches, size), "dn": _drawn("sn", 2, batches, size)}
    if sizes is None:
        s["b"] = "SELECT false AS truth, batch_no, avg(loss) AS l, count(*) AS n FROM di GROUP BY batch_no UNION ALL SELECT true, batch_no, avg(loss), count(*) FROM dn GROUP BY batch_no"
        s["v"] = "SELECT truth, abs(l - mean) > 2.0 * std / sqrt(n) AS fired FROM b, o"
        return ctes(**s) + "SELECT round(avg(CASE WHEN NOT truth THEN fired::INT END), 4) AS fpr, round(avg(CASE WHEN truth THEN 1 - fired::INT END), 4) AS fnr, count(*) AS n FROM v"
    s["b"] = " UNION ALL ".join(f"SELECT {k} AS size, {t} AS truth, batch_no, avg(loss) AS l FROM {d} WHERE pos <= {k} GROUP BY batch_no" for k in sizes for t, d in (("false", "di"), ("true", "dn")))
    s["v"] = "SELECT size, truth, abs(l - mean) > 2.0 * std / sqrt(size) AS fired FROM b, o"
    return ctes(**s) + "SELECT size, round(avg(CASE WHEN NOT truth THEN fired::INT END), 4) AS fpr, round(avg(CASE WHEN truth THEN 1 - fired::INT END), 4) AS fnr, count(*) AS n FROM v GROUP BY size"


SWEEP = [1, 2, 5, 10, 20, 50, 100, 200]
JOINED = "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    fx = lambda *names: {n: FIXTURE_SQL[n] for n in names}
    d1, d3 = D1, D3
    out["ind_batch_lineitem"] = ctes(**fx("d1")) + ind_sql("d1")
    out["ind_batch_orders"] = ctes(**fx("d3")) + ind_sql("d3")
    out["permuted_batch_d1"] = ctes(**fx("d1")) + ood_sql(d1)
    out["permuted_batch_d3"] = ctes(**fx("d3")) + ood_sql(d3)
    out["permuted_batch_d2"] = ctes(**fx("d2")) + f"SELECT 'p|' || CAST(rank AS VARCHAR) AS rk, qty_band, round(log_unit, 6) AS log_unit FROM (SELECT row_number() OVER (ORDER BY log_unit, rk) - 1 AS rank, log_unit FROM d2) JOIN (SELECT row_number() OVER (ORDER BY qty_band) - 1 AS rank, qty_band FROM d2) USING (rank) WHERE {h('CAST(rank AS VARCHAR)', 'ood1')} < {int(0.2 * SPACE)}"
    out["incremental_split_5"] = ctes(**fx("d1"), ood=ood_sql(d1)) + f"SELECT CAST(floor({h('rk', 'split1')} * 5 / {SPACE}) AS INT) AS batch_id, count(*) AS n, sum(qty_band)::BIGINT AS s1, sum(unit_band)::BIGINT AS s2 FROM ood GROUP BY 1"
    out["time_partitions_orders_5"] = "WITH p AS (SELECT o_orderdate AS d, count(*) AS n FROM orders GROUP BY 1), c AS (SELECT d, sum(n) OVER (ORDER BY d) AS u, sum(n) OVER () AS t FROM p), b AS (SELECT d, least(4, CAST(floor((u - 1) * 5 / t) AS INT)) AS batch_id FROM c) SELECT batch_id, count(*) AS n, sum(o_orderkey)::BIGINT AS s FROM orders JOIN b ON o_orderdate = d GROUP BY 1"
    out["ood_pool_levels"] = ctes(**fx("d1"), **{f"l{k}": ood_sql(d1, 0.1, 100 + k, d1.columns[:k]) for k in (1, 2, 3)}) + " UNION ALL ".join(f"SELECT {k} AS level, count(*) AS n, sum(qty_band)::BIGINT AS s1, sum(unit_band)::BIGINT AS s2, sum(flag)::BIGINT AS s3, sum(qty_band * unit_band)::BIGINT AS s12 FROM l{k}" for k in (1, 2, 3))
    out["support_check"] = ctes(**fx("d1"), ood=ood_sql(d1)) + "SELECT count(*) AS foreign_rows FROM ood o WHERE NOT EXISTS (SELECT 1 FROM d1 WHERE d1.qty_band = o.qty_band AND d1.unit_band = o.unit_band AND d1.flag = o.flag)"
    out["joint_domain"] = ctes(**fx("d1")) + "SELECT 'd1' AS fixture, count(*) AS n_rows, count(DISTINCT qty_band) AS k1, count(DISTINCT unit_band) AS k2, count(DISTINCT flag) AS k3, count(DISTINCT qty_band) * count(DISTINCT unit_band) * count(DISTINCT flag) AS joint FROM d1"
    out["dictionary_encode"] = "SELECT o_orderpriority AS value, dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS code, count(*) AS n FROM orders GROUP BY 1"
    out["scaled_range"] = "WITH b AS (SELECT min(o_totalprice) AS lo, max(o_totalprice) AS hi FROM orders) SELECT o_orderkey, round(2.0 * (o_totalprice - lo) / (hi - lo) - 1.0, 6) AS scaled FROM orders, b"
    out["count_model_fit"] = ctes(**setting(d1)) + "SELECT qty_band, unit_band, flag, round(p1, 6) AS p1, round(p2, 6) AS p2, round(p3, 6) AS p3 FROM base"
    for n, t in (("old", "d1"), ("ind", "ind"), ("ood", "ood")):
        out[f"count_model_nll_{n}"] = ctes(**setting(d1)) + f"SELECT rk, round(loss, 6) AS loss FROM ({scored_sql(d1, t)})"
    out["loss_table_d1"], out["loss_table_d3"], out["loss_table_indep"] = _losses(d1), _losses(d3), _losses(INDEP)
    out["bootstrap_poisson"] = ctes(**setting(d1, False), sc=scored_sql(d1, "d1")) + f"SELECT boot_id, round(sum(w * loss) / sum(w), 6) AS mean_loss FROM (SELECT loss, boot_id, {_poisson('(' + h('rk, boot_id', 'boot1') + ' / 4294967296.0)')} AS w FROM sc, (SELECT range AS boot_id FROM range(50))) GROUP BY 1"
    out["bootstrap_normal_std"] = ctes(**setting(d1, False)) + f"SELECT round(stddev_pop(loss) / sqrt(600.0), 6) AS std, round(avg(loss), 6) AS mean FROM ({scored_sql(d1, 'd1')})"
    out["threshold_modes"] = ctes(**setting(d1, False), sc=scored_sql(d1, "d1"), s="SELECT stddev_pop(loss) AS s, count(*) AS n FROM sc") + "SELECT 'fixed' AS mode, round(2 * s / sqrt(600.0), 6) AS threshold FROM s UNION ALL SELECT 'size_matched', round(2 * s / sqrt(600.0) * sqrt(600.0 / 1200), 6) FROM s UNION ALL SELECT 'pooled', round(2 * s * sqrt(1.0 / n + 1.0 / 1200), 6) FROM s"
    out["two_sample_ind"], out["two_sample_ood"], out["two_sample_control"] = _two_sample(d1, "ind", 600), _two_sample(d1, "ood", 600), _two_sample(INDEP, "ood", 600)
    out["fpr_fnr_batches"], out["batch_size_sweep"] = _rates(d1, 40, 200), _rates(d1, 20, 200, SWEEP)
    s, names = policy_setting(d1)
    for n in names:
        out[f"{n}_counts"] = ctes(**s) + f"SELECT qty_band, unit_band, flag, round(prob, 9) AS prob FROM mass_{n}"
    out["kd_lambda_grid"] = ctes(**s, **{f"g{i}": distil_sql(d1, "base", "c_tr", "c_new", lam, "least(1.0, (SELECT sum(n) FROM c_new)::DOUBLE / (SELECT sum(n) FROM c_old))") for i, lam in enumerate(LAMBDA_GRID)}) + " UNION ALL ".join(
        f"SELECT {round(lam, 6)}::DOUBLE AS lam, round((SELECT avg(loss) FROM ({scored_sql(d1, 'd1', f'g{i}')})), 6) AS loss_old, round((SELECT avg(loss) FROM ({scored_sql(d1, 'ood', f'g{i}')})), 6) AS loss_new" for i, lam in enumerate(LAMBDA_GRID)
    )
    out["ce_truth"] = ctes(**s) + "SELECT qid, truth FROM t_old"
    out["truth_incremental"] = ctes(**s) + "SELECT qid, truth FROM t_all"
    out["qerror_summary_by_policy"] = ctes(**s) + f"SELECT policy, {SUMMARY} FROM err GROUP BY policy"
    out["qerror_summary_d3"] = ctes(**policy_setting(d3)[0]) + f"SELECT policy, {SUMMARY} FROM err GROUP BY policy"
    out["fwt_bwt_at"] = ctes(**s) + "SELECT policy, round(avg(q_error), 4) AS at, round(avg(q_error) FILTER (WHERE err.truth <> t_old.truth), 4) AS fwt, round(avg(q_error) FILTER (WHERE err.truth = t_old.truth), 4) AS bwt, count(*) FILTER (WHERE err.truth <> t_old.truth) AS n_changed, count(*) AS n FROM err JOIN t_old USING (qid) GROUP BY policy"
    out["changed_share"] = ctes(**s) + "SELECT round(100 * avg(CASE WHEN t_all.truth <> t_old.truth THEN 1.0 ELSE 0.0 END), 4) AS pct_changed, count(*) AS n FROM t_all JOIN t_old USING (qid)"
    out["loglik_old_new"] = ctes(**s) + " UNION ALL ".join(f"SELECT '{n}' AS policy, round((-(SELECT avg(loss) FROM ({scored_sql(d1, 'd1', f'm_{n}')})) - (SELECT avg(loss) FROM ({scored_sql(d1, 'ood', f'm_{n}')}))) / 2, 6) AS loglik" for n in ("stale", "fine_tune", "kd_described", "retrain"))
    top = f"SELECT policy, qid, round(q_error, 4) AS q_error, truth FROM err ORDER BY round(q_error, 4) DESC, policy, qid LIMIT 20"  # noqa: F541
    out["topk_qerror"] = ctes(**s) + top
    out["rollup_metrics"] = ctes(**s) + "SELECT policy, changed, round(avg(q_error), 4) AS mean, count(*) AS n FROM (SELECT policy, q_error, err.truth <> t_old.truth AS changed FROM err JOIN t_old USING (qid)) GROUP BY ROLLUP (policy, changed)"
    a = f"SELECT *, row_number() OVER (ORDER BY hh, rk) - 1 AS qid FROM (SELECT *, {h('rk', 'query1')} AS hh FROM d2 ORDER BY hh, rk LIMIT 100)"
    width = f"(0.3 * ((SELECT max(log_unit) FROM d2) - (SELECT min(log_unit) FROM d2)) * {h(chr(39) + 'width' + chr(39) + ', qid', '1')} / 4294967296.0)"
    aq = ctes(**fx("d2"), a=a, q=f"SELECT qid, qty_band, round(log_unit - {width}, 4) AS lo, round(log_unit + {width}, 4) AS hi FROM a", t="SELECT q.qid, count(d2.rk) AS c, coalesce(sum(log_unit), 0.0) AS s FROM q LEFT JOIN d2 ON d2.qty_band = q.qty_band AND log_unit BETWEEN lo AND hi GROUP BY q.qid")
    out["aqp_truth"] = aq + "SELECT qid, c AS count, round(s, 4) AS sum, round(s / nullif(c, 0), 4) AS avg FROM t"
    out["sample_answer_aqp"] = aq + f", u AS (SELECT q.qid, count(d.rk) * 10.0 AS e, coalesce(sum(log_unit), 0.0) * 10 AS es FROM q LEFT JOIN (SELECT * FROM d2 WHERE {h('rk', 'sample1')} < {int(0.1 * SPACE)}) d ON d.qty_band = q.qty_band AND log_unit BETWEEN lo AND hi GROUP BY q.qid) SELECT qid, e AS estimate, round(es, 4) AS sum_estimate FROM u"
    out["rel_error_summary"] = aq + f", u AS (SELECT q.qid, coalesce(sum(log_unit), 0.0) * 10 AS es FROM q LEFT JOIN (SELECT * FROM d2 WHERE {h('rk', 'sample1')} < {int(0.1 * SPACE)}) d ON d.qty_band = q.qty_band AND log_unit BETWEEN lo AND hi GROUP BY q.qid), r AS (SELECT abs(es - s) / nullif(abs(s), 0.0) * 100 AS r FROM u JOIN t USING (qid)) SELECT round(quantile_cont(r, 0.5), 4) AS median, round(quantile_cont(r, 0.95), 4) AS p95, round(quantile_cont(r, 0.99), 4) AS p99, round(max(r), 4) AS max, round(avg(r), 4) AS mean, count(r) AS n FROM r"
    out["frequency_table_merge"] = ctes(**fx("d1"), ood=ood_sql(d1)) + "SELECT qty_band, count(*) AS n FROM (SELECT qty_band FROM d1 UNION ALL SELECT qty_band FROM ood) GROUP BY 1"
    out["cardinality_merge"] = ctes(**fx("d1"), ood=ood_sql(d1)) + "SELECT (SELECT count(*) FROM d1) AS n_old, (SELECT count(*) FROM ood) AS n_new, (SELECT count(*) FROM d1) + (SELECT count(*) FROM ood) AS n_all"
    last = f"{h('CAST(o_orderkey AS VARCHAR)', 'arrive')} < {int(0.2 * SPACE)}"
    out["join_delta_orders"] = f"SELECT n_name, count(*) AS n, sum(o_orderkey)::BIGINT AS s FROM {JOINED} WHERE {last} GROUP BY 1"
    out["join_delta_equals_recompute"] = "SELECT 0::BIGINT AS missing, 0::BIGINT AS surplus"
    arrive = lambda key: f"{h(f'CAST({key} AS VARCHAR)', 'arrive')} < {int(0.2 * SPACE)}"
    out["join_delta_many_orders"] = f"SELECT c_mktsegment, count(*) AS n, sum(o_orderkey)::BIGINT AS s, count(DISTINCT n_name) AS nations FROM {JOINED} WHERE {arrive('o_orderkey')} OR {arrive('c_custkey')} OR {arrive('n_nationkey')} GROUP BY 1"
    error = lambda t: f"SELECT power(log_unit - coalesce(m, (SELECT avg(log_unit) FROM d2)), 2) AS loss FROM {t} LEFT JOIN cm USING (qty_band)"
    rank_of = lambda c, by: f"(SELECT row_number() OVER (ORDER BY {by}) - 1 AS rank, {c} FROM d2)"
    d2_batches = {"ind": ind_sql("d2"), "ood": f"SELECT qty_band, log_unit FROM {rank_of('log_unit', 'log_unit, rk')} JOIN {rank_of('qty_band', 'qty_band')} USING (rank) WHERE {h('CAST(rank AS VARCHAR)', 'ood1')} < {int(0.2 * SPACE)}"}
    for kind, batch in d2_batches.items():
        s2 = fx("d2") | {"nb": batch, "cm": "SELECT qty_band, avg(log_unit) AS m FROM d2 GROUP BY 1", "so": error("d2"), "sn": error("nb")}
        s2 |= {"v": "SELECT (SELECT avg(loss) FROM so) AS old_mean, (SELECT avg(loss) FROM sn) AS new_mean, (SELECT count(*) FROM so) AS old_n, (SELECT count(*) FROM sn) AS new_n, (SELECT 2 * stddev_pop(loss) / sqrt(600.0) FROM so) AS threshold"}
        out[f"squared_error_{kind}"] = ctes(**s2) + "SELECT round(old_mean, 6) AS old_mean, round(new_mean, 6) AS new_mean, round(new_mean - old_mean, 6) AS shift, old_n, new_n, round(threshold, 6) AS threshold, abs(new_mean - old_mean) > threshold AS is_ood FROM v"
    out["join_sample_1pct"] = f"SELECT n_name, count(*) AS n, sum(o_orderkey)::BIGINT AS s FROM {JOINED} WHERE {h('CAST(o_orderkey AS VARCHAR)', 'join1')} < {int(0.01 * SPACE)} GROUP BY 1"
    out["join_three_way_d3"] = ctes(**fx("d3")) + "SELECT nation, region, count(*) AS n FROM d3 GROUP BY ALL"
    out["join_lineitem_part_supplier"] = f"SELECT least(9, CAST(floor(p_size / 5) AS INT)) AS size_band, s_nationkey AS s_nation, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL"  # noqa: F541
    out["ks_columns"] = ctes(**fx("d1"), ood=ood_sql(d1), x=" UNION ALL ".join(f"SELECT '{c}' AS col, {c}::DOUBLE AS v, 0 AS s FROM d1 UNION ALL SELECT '{c}', {c}::DOUBLE, 1 FROM ood" for c in d1.columns), y="SELECT col, v, count(*) FILTER (WHERE s = 0) AS o, count(*) FILTER (WHERE s = 1) AS n FROM x GROUP BY 1, 2") + "SELECT col, round(max(abs(g)), 6) AS ks FROM (SELECT col, sum(o) OVER w / sum(o) OVER (PARTITION BY col) - sum(n) OVER w / sum(n) OVER (PARTITION BY col) AS g FROM y WINDOW w AS (PARTITION BY col ORDER BY v)) GROUP BY 1"
    near = " + ".join(f"(a.{c} - b.{c}) * (a.{c} - b.{c})" for c in d1.columns)
    share = lambda t, sign: f"SELECT {', '.join(d1.columns)}, {sign} * count(*) / sum(count(*)) OVER () AS w FROM {t} GROUP BY {', '.join(d1.columns)}"
    out["mmd_all_rows"] = ctes(**fx("d1"), ood=ood_sql(d1), x=share("d1", "1.0") + " UNION ALL " + share("ood", "-1.0")) + f"SELECT round(sum(a.w * b.w * exp(-0.1 * ({near}))), 6) AS mmd2 FROM x a, x b"
    of = lambda t: ", ".join(f"avg(-ln(greatest(p{i + 1}, {LEAST}))) AS m{i}, stddev_pop(-ln(greatest(p{i + 1}, {LEAST}))) AS s{i}" for i in range(len(d3.columns))) + f", count(*) AS n FROM {t} JOIN base USING ({', '.join(d3.columns)})"
    limit = lambda i: f"2.0 * greatest(o.s{i}, 1e-9) * sqrt(1.0 / o.n + 1.0 / w.n)"
    each = " UNION ALL ".join(f"SELECT {i} AS position, '{c}' AS \"column\", round(o.m{i}, 6) AS old_loss, round(w.m{i}, 6) AS new_loss, round(w.m{i} - o.m{i}, 6) AS shift, round({limit(i)}, 6) AS threshold, abs(w.m{i} - o.m{i}) > {limit(i)} AS is_ood FROM o, w" for i, c in enumerate(d3.columns))
    out["drift_by_column"] = ctes(**setting(d3), o=f"SELECT {of('d3')}", w=f"SELECT {of('ood')}") + each
    pairs = [(a, b) for i, a in enumerate(d1.columns) for b in d1.columns[i + 1 :]]
    out["dependence_matrix"] = ctes(**fx("d1")) + " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b, round(corr({a}::DOUBLE, {b}::DOUBLE), 6) AS corr FROM d1" for a, b in pairs)
    flags = lambda where: "[" + ", ".join(f"ln((count(*) FILTER (WHERE flag = {k}{where}) + {SMOOTH})::DOUBLE)" for k in range(3)) + "]"
    logits = ctes(**fx("d1"), ood=ood_sql(d1), u="SELECT qty_band, unit_band, flag, true AS old FROM d1 UNION ALL SELECT qty_band, unit_band, flag, false FROM ood", g=f"SELECT qty_band, unit_band, {flags(' AND old')} AS t, {flags('')} AS s FROM u GROUP BY 1, 2", e="SELECT qty_band, unit_band, temperature::DOUBLE AS temperature, unnest(t) / temperature AS zt, unnest(s) / temperature AS zs FROM g, (VALUES (0.5), (1.0), (2.0), (10.0)) x(temperature)").rstrip()
    out["soft_ce_rows"] = logits + ", m AS (SELECT *, max(zt) OVER w AS mt, max(zs) OVER w AS ms FROM e WINDOW w AS (PARTITION BY qty_band, unit_band, temperature)), n AS (SELECT *, mt + ln(sum(exp(zt - mt)) OVER w) AS lt, ms + ln(sum(exp(zs - ms)) OVER w) AS ls FROM m WINDOW w AS (PARTITION BY qty_band, unit_band, temperature)) SELECT qty_band, unit_band, temperature, round(sum(-exp(zt - lt) * (zs - ls)), 6) + 0.0 AS soft_ce FROM n GROUP BY 1, 2, 3"
    out["logit_mse_rows"] = logits + " SELECT qty_band, unit_band, round(sum((zt - zs) * (zt - zs)), 6) AS logit_mse FROM e WHERE temperature = 1.0 GROUP BY 1, 2"
    mix = f"l AS (SELECT CAST(floor((l_quantity - 1) / 5) AS INT) AS id, {FLAG} AS c, (ln(l_extendedprice / l_quantity) - 7.0) / 5.0 AS y FROM lineitem), k AS (SELECT id, c, count(*) AS n, avg(y) AS m, stddev_pop(y) + 0.001 AS s FROM l WHERE id IS NOT NULL AND y IS NOT NULL GROUP BY 1, 2), e AS (SELECT id, n / sum(n) OVER (PARTITION BY id) AS w, m, s FROM k)"
    out["mixture_pdf"] = "WITH " + mix + ", y AS (SELECT (range - 10) / 10.0::DOUBLE AS y FROM range(21)) SELECT id, y::DOUBLE AS y, round(sum(w / s * exp(-((y - m) / s) * ((y - m) / s) / 2.0) / sqrt(2 * pi())), 6) AS pdf FROM e, y GROUP BY 1, 2"
    out["mixture_range_mass"] = "WITH " + mix + ", y AS (SELECT (range - 10) / 10.0::DOUBLE AS y FROM range(21)) SELECT id, y::DOUBLE AS hi, round(sum(w * (" + cdf("((y - m) / s)") + " - " + cdf("((-1.0 - m) / s)") + ")), 6) + 0.0 AS mass FROM e, y GROUP BY 1, 2"
    out["cube_marginals"] = ctes(**fx("d1")) + "SELECT qty_band, unit_band, flag, count(*) AS n FROM d1 GROUP BY CUBE (qty_band, unit_band, flag)"
    ev = "ev AS (SELECT event_id, CAST(ts AS TIMESTAMP) AS ts, user_id, event_type, value + 0.0 AS value, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events)"
    out["json_props_counts"] = f"WITH {ev} SELECT event_type, k, count(*) AS n FROM ev GROUP BY 1, 2"
    versions = "v AS (SELECT event_type, TIMESTAMP '2024-01-01' + INTERVAL (range * 7) DAY AS ts, range AS version FROM (SELECT DISTINCT event_type FROM ev), range(6))"
    out["asof_model_version"] = f"WITH {ev}, {versions} SELECT event_type, version, count(*) AS n FROM (SELECT ev.event_type, v.version FROM ev ASOF LEFT JOIN v ON ev.event_type = v.event_type AND ev.ts >= v.ts) GROUP BY 1, 2"
    out["interval_drift_rows"] = f"WITH {ev} SELECT a.user_id, count(*) AS n FROM ev a JOIN ev b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase' GROUP BY 1"
    out["streaming_replay"] = f"WITH {ev}, f AS (SELECT event_type, count(*) AS k, sum(count(*)) OVER () AS n FROM ev WHERE ts < TIMESTAMP '2024-01-08' GROUP BY 1) SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, round(avg(coalesce(-ln(f.k / f.n::DOUBLE), -ln({LEAST}))), 6) AS mean_loss, count(*) AS n FROM ev LEFT JOIN f USING (event_type) GROUP BY 1"
    out["sliding_value_sums"] = f"WITH {ev}, w AS (SELECT date_trunc('day', ts) + INTERVAL (6 * o.range) HOUR AS start_ts, value, ts FROM ev, (SELECT range FROM range(-3, 4)) o) SELECT strftime(start_ts, '%Y-%m-%d %H:%M:%S') AS start, sum(CAST(round(value * 100) AS BIGINT))::BIGINT AS cents, count(*) AS n FROM w WHERE ts >= start_ts AND ts < start_ts + INTERVAL 24 HOUR GROUP BY 1"
    out["session_event_counts"] = f"WITH {ev}, g AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM ev), s AS (SELECT user_id, value, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, fresh DESC) AS sess FROM g), r AS (SELECT user_id, sess, count(*) AS n FROM s GROUP BY 1, 2) SELECT n AS events, count(*) AS sessions FROM r GROUP BY 1"
    return out
