"""Whole ensembles, trained by `fit` and, with the same keyed noise, in DuckDB SQL: several levels, nodes and trees."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privgrove.functions.noise import laplace_sql, uniform_sql
from privgrove.operators.gradient import UNIT
from privgrove.operators.leaves import scale_of
from privgrove.plans.boost import BoostParams, fit, plans_of, strict_plan
from privgrove.queries import methods as m
from privgrove.queries.base import query


def cuts_at(p: BoostParams, plan, t: int, d: int, at: str) -> str:
    """CTEs up to cuts (node, feature, slot, cut_bin) of a level: of every open node, or of the root for the whole tree."""
    local, weight = p.proposal == "local", "coalesce(n, 0.0)"
    if plan and p.proposal_noise:
        key = f"'{p.noise_key}|sketch|{t}|' || " + ("node || '|' || " if local else "") + "feature || '|' || bin"
        weight = f"greatest(0.0, {weight} + {laplace_sql(uniform_sql(key), str(plan.m / plan.sketch * (plan.h if local else 1)))})"
    return f"""grid{at} AS (SELECT node, feature, bin FROM (SELECT DISTINCT node FROM hist{at}), (SELECT unnest(range({m.SPEC.m})) AS feature), (SELECT unnest(range({p.bins})) AS bin)),
  weights{at} AS MATERIALIZED (SELECT node, feature, bin, CAST({weight} AS DOUBLE) AS weight FROM grid{at} LEFT JOIN hist{at} USING (node, feature, bin)),
  sums{at} AS (SELECT *, sum(weight) OVER (PARTITION BY node, feature) AS total, sum(weight) OVER (PARTITION BY node, feature ORDER BY bin) AS upto FROM weights{at}),
  marks{at} AS (SELECT *, least(floor(round(upto / (total / {p.max_cuts + 1}), 9)), {p.max_cuts}) AS mark FROM sums{at}),
  steps{at} AS (SELECT *, coalesce(lag(mark) OVER (PARTITION BY node, feature ORDER BY bin), 0) AS before FROM marks{at}),
  cuts{at} AS MATERIALIZED (SELECT node, feature, row_number() OVER (PARTITION BY node, feature ORDER BY bin) - 1 AS slot, bin AS cut_bin FROM steps{at} WHERE mark > before AND bin < {p.bins - 1}),"""


def split_at(p: BoostParams, plan, t: int, d: int, at: str) -> str:
    """CTEs of one level: histogram of its open nodes, their splits, and where every row goes."""
    long = " UNION ALL ".join(f"SELECT node, {k} AS feature, b_{k} AS bin, g FROM at{at} WHERE live AND node >= {2**d - 1}" for k in range(m.SPEC.m))
    proposals = cuts_at(p, plan, t, d, at) if d == 0 or p.proposal == "local" else ""
    cuts, on = (f"cuts{at}", "c.node = h.node AND c.feature = h.feature") if p.proposal == "local" else (f"cuts_{t}_0", "c.feature = h.feature")
    if plan and p.split_mode == "exponential":
        u = uniform_sql(f"'{p.noise_key}|split|{t}|' || node || '|' || feature || '|' || slot || '|' || CAST(default_left AS INTEGER)")
        order = f"ln(-ln({u})) - gain * {plan.level / (6 * p.g_star**2)!r}"
    else:
        order = "-round(gain, 6)"
    child = max(p.min_child, p.min_hessian)
    goes = " ".join(f"WHEN feature = {k} THEN CASE WHEN b_{k} < 0 THEN default_left ELSE b_{k} <= cut_bin END" for k in range(m.SPEC.m))
    return f"""hist{at} AS MATERIALIZED (SELECT node, feature, bin, CAST(sum(g) AS BIGINT) AS g, count(*) AS n FROM ({long}) GROUP BY ALL),
  {proposals}
  whole{at} AS (SELECT node, sum(g) AS gt, sum(n) AS nt FROM hist{at} WHERE feature = 0 GROUP BY node),
  missing{at} AS (SELECT node, feature, coalesce(sum(g) FILTER (WHERE bin < 0), 0) AS gm, coalesce(sum(n) FILTER (WHERE bin < 0), 0) AS nm FROM hist{at} GROUP BY ALL),
  left{at} AS (SELECT h.node, h.feature, c.slot, c.cut_bin, sum(h.g) AS g0, sum(h.n) AS n0 FROM hist{at} h JOIN {cuts} c ON {on} WHERE h.bin BETWEEN 0 AND c.cut_bin GROUP BY ALL),
  both{at} AS (SELECT *, unnest([true, false]) AS default_left FROM left{at} JOIN missing{at} USING (node, feature) JOIN whole{at} USING (node)),
  side{at} AS (SELECT node, feature, slot, cut_bin, default_left, (g0 + CASE WHEN default_left THEN gm ELSE 0 END) / {float(UNIT)} AS gl, n0 + CASE WHEN default_left THEN nm ELSE 0 END AS nl, gt / {float(UNIT)} AS gt, nt FROM both{at} WHERE default_left OR nm > 0),
  gains{at} AS (SELECT *, gl * gl / (nl + {p.lam}) + (gt - gl) * (gt - gl) / (nt - nl + {p.lam}) AS gain FROM side{at} WHERE nl >= {child} AND nt - nl >= {child}),
  best{at} AS MATERIALIZED (SELECT node, feature, cut_bin, default_left FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY {order}, feature, default_left DESC, slot) AS k FROM gains{at}) WHERE k = 1),
  at_{t}_{d + 1} AS MATERIALIZED (SELECT row_key, b_0, b_1, b_2, y, margin, g, live, CASE WHEN feature IS NULL THEN node WHEN (CASE {goes} END) THEN 2 * node + 1 ELSE 2 * node + 2 END AS node FROM at{at} LEFT JOIN best{at} USING (node)),"""


def leaf_at(p: BoostParams, plan, t: int) -> str:
    """The released value of each leaf of a tree, from its sums g and n."""
    plain = f"(-g / (n + {p.lam}))"
    if not plan or p.leaf_mode == "exact":
        return f"{plain} * {p.learning_rate}"
    noise = laplace_sql(uniform_sql(f"'{p.noise_key}|leaf|{t}|' || node"), repr(scale_of(p.leaf_mode, plan.leaf(), p.g_star, p.lam, p.min_child, t, p.learning_rate)))
    if p.leaf_mode == "noisy_average":
        return f"-greatest(-{p.g_star}, least({p.g_star}, (g + {noise}) / ({f'greatest(n, {p.min_child})' if p.strict else 'n'} + {p.lam}))) * {p.learning_rate}"
    if p.leaf_mode == "geometric":
        bound = p.g_star * (1 - p.learning_rate) ** t
        plain = f"greatest({-bound!r}, least({bound!r}, {plain}))"
    return f"({plain} + {noise}) * {p.learning_rate}"


def trained_sql(p: BoostParams) -> str:
    """The nodes of the ensemble that `fit` gives for these settings."""
    ctes, shown = [m.BINNED_SQL + ", rows_0 AS (SELECT *, CAST(0.0 AS DOUBLE) AS margin FROM binned),"], []
    for t in range(p.trees):
        plan = strict_plan(p, plans_of(m.SPEC, p)[t]) if p.private else None
        live = [f"abs(margin - y) <= {p.g_star}"] if p.gradient_filter else []
        if p.disjoint:
            shares = [p.learning_rate * (1 - p.learning_rate) ** k for k in range(p.trees)]
            edges = [sum(shares[:k]) / sum(shares) for k in range(1, p.trees)]
            u = uniform_sql(f"'{p.noise_key}|part|' || row_key")
            live.append(f"{' + '.join(['0', *(f'CAST({u} >= {e!r} AS INTEGER)' for e in edges)])} = {t}")
        elif p.subsample < 1:
            live.append(f"{uniform_sql(f"'{p.noise_key}|sample|{t}|' || row_key")} < {p.subsample}")
        ctes.append(f"at_{t}_0 AS MATERIALIZED (SELECT *, CAST(trunc((margin - y) * {UNIT}) AS BIGINT) AS g, {' AND '.join(live) or 'true'} AS live, 0 AS node FROM rows_{t}),")
        ctes += [split_at(p, plan, t, d, f"_{t}_{d}") for d in range(p.max_depth)]
        last = f"at_{t}_{p.max_depth}"
        ctes.append(f"sums_of_{t} AS (SELECT node, sum(g) / {float(UNIT)} AS g, count(*) AS n FROM {last} WHERE live GROUP BY node), leaves_{t} AS MATERIALIZED (SELECT node, {leaf_at(p, plan, t)} AS value FROM sums_of_{t}),")
        ctes.append(f"rows_{t + 1} AS MATERIALIZED (SELECT row_key, b_0, b_1, b_2, y, margin + value AS margin FROM {last} JOIN leaves_{t} USING (node)),")
        shown += [f"SELECT {t} AS tree, node, feature, cut_bin, default_left, 0.0 AS value FROM best_{t}_{d}" for d in range(p.max_depth)]
        shown.append(f"SELECT {t}, node, -1, -1, true, round(value, 8) FROM leaves_{t}")
    union = " UNION ALL ".join(shown)
    return f"WITH {' '.join(ctes)} shown AS ({union}) SELECT CAST(tree AS INTEGER) AS tree, CAST(node AS INTEGER) AS node, CAST(feature AS INTEGER) AS feature, CAST(cut_bin AS INTEGER) AS cut_bin, default_left, CAST(value AS DOUBLE) AS value FROM shown"


def trained(name: str, params: BoostParams) -> None:
    @query(name, trained_sql(params))
    def run(spark, d) -> DataFrame:
        model, _, _ = fit(m.binned(spark, d), m.SPEC, params)
        return model.nodes(spark).select("tree", "node", "feature", "cut_bin", "default_left", F.round("value", 8).alias("value"))


ONE = BoostParams(epsilon_total=4.0, trees=1, max_depth=2, subsample=1.0, bins=m.BINS, max_cuts=m.CUTS, min_child=50, noise_key="k0")
TWO = replace(ONE, trees=2, epsilon_total=8.0)

trained("m30_tree_depth_2", ONE)
trained("m30_tree_depth_4", replace(ONE, max_depth=4, min_child=20))
trained("m30_two_trees", TWO)
trained("m30_private_ensemble", replace(TWO, trees=3, max_depth=3, subsample=0.5, learning_rate=0.5))
trained("m31_uneven_trees", replace(TWO, tree_weights=(3.0, 1.0)))
trained("b01_open_trees", replace(TWO, max_depth=3).open())
trained("b02_exact_cuts_trees", replace(TWO, proposal_noise=False))
trained("m19b_local_trees", replace(TWO, proposal="local"))
trained("m23_worst_case_trees", replace(TWO, leaf_mode="worst_case"))
trained("m25_noisy_average_trees", replace(TWO, leaf_mode="noisy_average"))
trained("b03_precursor_trees", replace(TWO, proposal_noise=False, shares=(0.0, 0.5, 0.5), leaf_mode="geometric", min_child=1, disjoint=True))
trained("m26_hessian_weight_trees", replace(TWO, min_hessian=400.0))
