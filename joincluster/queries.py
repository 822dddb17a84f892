"""The contract's queries of the method, and their SQL over the joined rows."""

from __future__ import annotations

import math
import tempfile
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import oracles as o
from .operators import baseline, bounds, fd, objective
from .operators.categorical import category_centroid, heavy_light_table
from .operators.components import ComponentSet, solve, solve_line
from .operators.grid import grid_summary, grid_weights, grid_zero_fill
from .operators.lloyd import Penalty, grid_lloyd, nearest, seed_pp, seed_top
from .operators.pipeline import cluster_join
from .operators.transport import wasserstein_1d
from .operators.vector import block_grid
from .plans.costmodel import Sizes, cost_model
from .plans.hypergraph import Hypergraph
from .plans.messages import Calibration
from .sources import workloads as wl
from .sources.workloads import tables

Query = Callable[[SparkSession, str], DataFrame]
CAT, CONT = "cat", "cont"
WM = {"priority": CAT, "status": CAT, "segment": CAT, "suppkey": CAT, "nation": CAT, "region": CAT}
WR = {"qty": CONT, "disc_cents": CONT, "size": CONT, "brand": CAT, "type": CAT, "segment": CAT, "nation": CAT, "region": CAT}
WS = {"qty_a": CONT, "flag_a": CAT, "qty_b": CONT, "flag_b": CAT}
WF = {"units": CONT, "promo": CAT, "class": CAT, "nation": CAT, "no_oil": CAT, "weekend": CAT}
WY = {"event_type": CAT, "segment": CAT, "nation": CAT, "region": CAT, "priority": CAT, "status": CAT, "n_orders": CONT}
#: The workloads with all their features; the shorter lists above are what the quadratic SQL of the grids can follow.
WF_ALL, WY_ALL, WT_ALL = WF | {"price": CONT, "tx_n": CONT, "oil": CONT}, WY | {"value": CONT}, {"n_chars": CONT, "lang": CAT, "source": CAT, "quality": CAT, "toxic": CAT}
WC = {"segment": CAT, "priority": CAT, "nation": CAT, "qty": CONT}
GEO, DAYS = ["custkey", "nation", "region"], ["day", "month", "quarter", "year"]

QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def _add(name: str, run: Query, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql is not None:
        SQL[name] = sql


def _query(workload: str, features, spark: SparkSession, sf: str):
    return wl.ALL[workload](spark, sf).only(*features)


def _marginal(workload: str, feature: str) -> Query:
    return lambda spark, sf: Calibration(wl.ALL[workload](spark, sf)).marginal(feature)


def _marginals(workload: str, features) -> Query:
    return lambda spark, sf: Calibration(_query(workload, features, spark, sf)).marginals()


def _solved(q, kappa) -> tuple[Calibration, DataFrame, ComponentSet]:
    cal = Calibration(q)
    m = cal.marginals().persist()
    return cal, m, solve(q, m, kappa)


def _grid(workload: str, features, kappa: int) -> Query:
    def run(spark, sf):
        q = _query(workload, features, spark, sf)
        _, _, comps = _solved(q, kappa)
        return grid_weights(q, comps)

    return run


def _line(workload: str, feature: str, kappa: int, p: int = 2, lam: float = 0.0, method: str = "auto") -> Query:
    def run(spark, sf):
        line = solve_line(Calibration(wl.ALL[workload](spark, sf)).marginal(feature), kappa, method, p, lam)
        return spark.createDataFrame([(i, float(h), round(line.cost, 4)) for i, h in enumerate(line.upper)], "comp int, hi double, cost double")

    return run


# ---- marginals
for _w, _f, _name in (("w_m", "priority", "wm_priority"), ("w_r", "brand", "wr_brand"), ("w_y", "event_type", "wy_event_type"), ("w_c", "segment", "wc_segment"), ("w_f", "oil", "wf_oil"), ("w_t", "lang", "wt_lang")):
    _add(f"marginal_{_name}", _marginal(_w, _f), o.marginal(_w, _f, CONT if _f == "oil" else CAT))
_add("marginals_all_wr", _marginals("w_r", WR), o.marginals("w_r", WR))
_add("marginals_all_wm", _marginals("w_m", WM), o.marginals("w_m", WM))
_add("marginals_all_ws", _marginals("w_s", WS), o.marginals("w_s", WS))
_add("marginals_all_wy", _marginals("w_y", WY_ALL), o.marginals("w_y", WY_ALL))
_add("marginals_all_wf", _marginals("w_f", WF_ALL), o.marginals("w_f", WF_ALL))
_add("marginals_all_wt", _marginals("w_t", WT_ALL), o.marginals("w_t", WT_ALL))


def _flat_marginal(spark, sf):
    q = wl.w_r(spark, sf)
    return baseline.materialise(q).groupBy(F.col("brand").alias("vcat")).agg(F.sum("w").alias("w")).select(F.lit("brand").alias("subspace"), F.lit(None).cast("double").alias("vnum"), "vcat", "w")


_add("marginal_flat_wr_brand", _flat_marginal, o.marginal("w_r", "brand", CAT))


def _grouping_sets(spark, sf):
    (p,) = tables(spark, sf, "part")
    p.createOrReplaceTempView("jc_part")
    return spark.sql("SELECT p_brand, p_type, count(*) AS w FROM jc_part GROUP BY GROUPING SETS ((p_brand), (p_type))")


_add("marginal_grouping_sets", _grouping_sets, "SELECT p_brand, p_type, count(*) AS w FROM part GROUP BY GROUPING SETS ((p_brand), (p_type))")


def _rollup(spark, sf):
    n, r = tables(spark, sf, "nation", "region")
    return n.join(r, F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("w"))


_add("chain_rollup", _rollup, "SELECT r_name, n_name, count(*) AS w FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")


# ---- subspaces
def _heavy(workload, feature, kappa) -> Query:
    return lambda spark, sf: heavy_light_table(Calibration(wl.ALL[workload](spark, sf)).marginal(feature), kappa)


_add("heavy_light_brand_k5", _heavy("w_r", "brand", 5), o.heavy_light("w_r", "brand", 5))
_add("heavy_light_suppkey_k10", _heavy("w_m", "suppkey", 10), o.heavy_light("w_m", "suppkey", 10))


def _heavy_cost(spark, sf):
    q = wl.w_r(spark, sf).only("brand", "type", "nation")
    _, _, comps = _solved(q, 5)
    return spark.createDataFrame([(s.name, float(round(s.cost, 4)), float(round(s.sqnorm, 8))) for s in comps.subspaces], "subspace string, cost double, sqnorm double")


_add("heavy_light_cost", _heavy_cost, " UNION ALL ".join(
    f"SELECT '{f}' AS subspace, round(coalesce(sum(w) - sum(w*w)/sum(w), 0), 4)::DOUBLE AS cost, round(coalesce(sum(w*w)/(sum(w)*sum(w)), 0), 8)::DOUBLE AS sqnorm FROM (SELECT w::DOUBLE AS w, rk FROM ({o.ranks('w_r', f)})) WHERE rk >= 4" for f in ("brand", "type", "nation")))


def _shares(spark, sf):
    m = category_centroid(Calibration(wl.w_m(spark, sf)).marginal("priority"))
    return m.select("subspace", "vcat", F.round("share", 9).alias("share"))


_add("category_centroid_wm", _shares, f"SELECT 'priority' AS subspace, priority AS vcat, round(count(*) / (SELECT count(*) FROM {o.matrix('w_m')}), 9)::DOUBLE AS share FROM {o.matrix('w_m')} GROUP BY priority")
for _n, _w, _f, _k in (("quantity_k5", "w_r", "qty", 5), ("size_k4", "w_r", "size", 4), ("discount_k3", "w_r", "disc_cents", 3)):
    _add(f"line_kmeans_{_n}", _line(_w, _f, _k), o.line(_w, _f, _k))
_add("line_kmeans_quantity_dc", _line("w_r", "qty", 5, method="dc"), o.line("w_r", "qty", 5))
_add("line_kmeans_regularised", _line("w_r", "qty", 4, lam=50000.0), o.line("w_r", "qty", 4, lam=50000.0))
_add("line_kmedian_size_k3", _line("w_r", "size", 3, p=1), o.line("w_r", "size", 3, p=1))
_add("round_distinct_profile", lambda spark, sf: objective.distinct_profile(tables(spark, sf, "lineitem")[0], "l_extendedprice", (2, 1, 0, -2)),
     " UNION ALL ".join(f"SELECT {d} AS decimals, count(DISTINCT round(l_extendedprice, {d}))::BIGINT AS n FROM lineitem" for d in (2, 1, 0, -2)))


def _encode(spark, sf):
    q = wl.w_r(spark, sf).only("qty")
    _, _, comps = _solved(q, 5)
    return tables(spark, sf, "lineitem")[0].groupBy(comps["qty"].encode(F.col("l_quantity")).alias("comp")).agg(F.count("*").alias("n"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"))


_add("encode_quantity", _encode, f"WITH {o.line_ctes('lineitem', 'l_quantity', 5, 'd')} SELECT (SELECT count(*) FROM d_ends WHERE hi < l_quantity)::INT AS comp, count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem GROUP BY 1")


def _components(spark, sf):
    _, _, comps = _solved(wl.w_r(spark, sf), 5)
    return comps.table(spark)


_add("components_wr", _components)

# ---- grids
for _n, _w, _fs, _k in (
    ("wm_k5", "w_m", WM, 5), ("wm_k10", "w_m", WM, 10), ("wr_k5", "w_r", WR, 5), ("wy_k5", "w_y", WY, 5), ("wf_k5", "w_f", WF, 5), ("wf_lite_k5", "w_f_lite", {"units": CONT, "promo": CAT, "class": CAT, "weekend": CAT}, 5),
    ("wc_k5", "w_c", WC, 5), ("ws_k3", "w_s", WS, 3), ("wt_k5", "w_t", {"lang": CAT, "source": CAT, "quality": CAT, "toxic": CAT}, 5),
):
    _add(f"grid_{_n}", _grid(_w, _fs, _k), o.grid(_w, _fs, _k))
for _n, _w, _fs in (("wf", "w_f", WF_ALL), ("wy", "w_y", WY_ALL), ("wt", "w_t", WT_ALL)):
    _add(f"grid_{_n}_all_k5", _grid(_w, _fs, 5))


def _zero_fill(spark, sf):
    left, right, seen = wl.w_i(spark, sf)
    left = left.select("l", F.col("type").alias("c_type"), F.floor((F.col("retailprice") - 900) / 25).cast("int").alias("c_price"))
    right = right.select("r", F.floor((F.col("acctbal") + 1000) / 2200).cast("int").alias("c_bal"))
    value = F.when(F.col("value") <= 0, 0).when(F.col("value") <= 25, 1).otherwise(2)
    return grid_zero_fill(left, right, seen, value, 0).select("c_type", "c_price", "c_bal", "c_value", "w")


_WEEK = "SELECT l_partkey AS pk, l_suppkey AS sk, sum(l_quantity) AS q FROM lineitem WHERE l_shipdate::DATE BETWEEN DATE '1998-05-13' AND DATE '1998-05-20' GROUP BY 1, 2"
_add("grid_zero_fill_wi", _zero_fill, f"""SELECT p_type AS c_type, floor((p_retailprice - 900) / 25)::INT AS c_price, floor((s_acctbal + 1000) / 2200)::INT AS c_bal,
  CASE WHEN coalesce(q, 0) <= 0 THEN 0 WHEN q <= 25 THEN 1 ELSE 2 END AS c_value, count(*) AS w
  FROM part CROSS JOIN supplier LEFT JOIN ({_WEEK}) t ON pk = p_partkey AND sk = s_suppkey GROUP BY ALL""")
_add("weekly_zero_sales", lambda spark, sf: _weekly(spark, sf), f"SELECT p_type AS type, sum(coalesce(q, 0))::DOUBLE AS units, count(q) AS pairs FROM part CROSS JOIN supplier LEFT JOIN ({_WEEK}) t ON pk = p_partkey AND sk = s_suppkey GROUP BY 1")


def _weekly(spark, sf):
    left, _, seen = wl.w_i(spark, sf)
    sums = seen.groupBy("l").agg(F.sum("value").alias("v"), F.count("*").alias("n"))
    return left.join(sums, "l", "left").groupBy("type").agg(F.sum(F.coalesce("v", F.lit(0.0))).alias("units"), F.sum(F.coalesce("n", F.lit(0))).alias("pairs"))


def _stats(spark, sf):
    q = wl.w_m(spark, sf)
    cal = Calibration(q)
    m, rows = cal.marginals().persist(), cal.size
    out = []
    for k in (5, 10, 20, 50):
        cells = grid_weights(q, solve(q, m, k))
        out.append(cells.agg(F.count("*").alias("cells"), F.sum("w").cast("bigint").alias("matrix_rows")).select(F.lit(k).alias("kappa"), "cells", "matrix_rows"))
    assert rows >= 0
    return reduce(DataFrame.unionByName, out)


def _stats_sql() -> str:
    parts = []
    for k in (5, 10, 20, 50):
        ctes, joins, cols = o.encoders("w_m", WM, k)
        parts.append(f"SELECT * FROM (WITH {ctes} SELECT {k} AS kappa, count(*) AS cells, sum(w)::BIGINT AS matrix_rows FROM (SELECT {', '.join('c_' + f for f in WM)}, count(*) AS w FROM (SELECT {cols} FROM {joins}) GROUP BY ALL))")
    return " UNION ALL ".join(parts)


_add("coreset_stats_wm", _stats, _stats_sql())


def _matrix_stats(spark, sf):
    out = []
    for name, fs in (("w_r", WR), ("w_m", WM), ("w_y", WY), ("w_c", WC)):
        q = _query(name, fs, spark, sf)
        out.append(objective.matrix_stats(q, Calibration(q).marginals()).drop("input_rows", "relations"))
    return reduce(DataFrame.unionByName, out)


_add("matrix_stats_all", _matrix_stats, " UNION ALL ".join(
    f"SELECT '{n}' AS workload, {len(fs)} AS attributes, ({' + '.join(f'count(DISTINCT {f})' if k == CAT else '1' for f, k in fs.items())})::BIGINT AS onehot_width, count(*) AS matrix_rows FROM {o.matrix(n)}" for n, fs in (("w_r", WR), ("w_m", WM), ("w_y", WY), ("w_c", WC))))
_add("onehot_width", lambda spark, sf: Calibration(_query("w_m", WM, spark, sf)).marginals().groupBy("subspace").agg(F.count("*").alias("width")),
     " UNION ALL ".join(f"SELECT '{f}' AS subspace, count(DISTINCT {f}) AS width FROM {o.matrix('w_m')}" for f in WM))


def _grid_diff(spark, sf):
    from .operators.grid import grid_weights_flat

    q = wl.w_m(spark, sf)
    _, _, comps = _solved(q, 5)
    a, b = grid_weights(q, comps), grid_weights_flat(q, comps, baseline.counted)
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("different"))


_add("grid_diff_except", _grid_diff, "SELECT 0::BIGINT AS different")


def _top_cells(spark, sf):
    q = wl.w_m(spark, sf)
    _, _, comps = _solved(q, 5)
    cells = grid_weights(q, comps)
    return cells.withColumn("rank", F.row_number().over(W.partitionBy("c_region").orderBy(F.desc("w"), *[c for c in cells.columns if c != "w"]))).where("rank <= 3").select("c_region", "rank", "w")


def _top_cells_sql() -> str:
    g = o.grid("w_m", WM, 5)
    return f"SELECT c_region, rank, w FROM (SELECT c_region, w, row_number() OVER (PARTITION BY c_region ORDER BY w DESC, {', '.join('c_' + f for f in WM)})::INT AS rank FROM ({g})) WHERE rank <= 3"


_add("topk_cells", _top_cells, _top_cells_sql())
_add("grid_summary_centers", lambda spark, sf: (lambda q, t: grid_summary(grid_weights(q, t[2]), t[2], "centers"))(*(lambda q: (q, _solved(q, 5)))(wl.w_f_lite(spark, sf))))

# ---- dependencies
_FDS = (("customer", "c_custkey", "c_nationkey"), ("supplier", "s_suppkey", "s_nationkey"), ("nation", "n_nationkey", "n_regionkey"), ("part", "p_brand", "p_type"), ("part", "p_name", "p_type"), ("documents", "source", "lang"))
_add("fd_check_all", lambda spark, sf: fd.fd_report({r: tables(spark, sf, r)[0] for r, _, _ in _FDS}, list(_FDS)), " UNION ALL ".join(
    f"SELECT '{r}' AS relation, '{a}' AS lhs, '{b}' AS rhs, max(n) <= 1 AS holds, max(n)::BIGINT AS max_images FROM (SELECT {a}, count(DISTINCT {b}) AS n FROM {r} GROUP BY 1)" for r, a, b in _FDS))


def _chain(workload: str, chain: list[str], kappa: int) -> Query:
    def run(spark, sf):
        q = _query(workload, chain, spark, sf)
        _, _, comps = _solved(q, kappa)
        return fd.chain_cells(baseline.materialise(q), comps, chain)

    return run


def _chain_sql(workload: str, chain: list[str], kappa: int) -> str:
    ctes, joins, cols = o.encoders(workload, dict.fromkeys(chain, CAT), kappa)
    keys = ", ".join(f"c_{f}" for f in chain)
    return f"WITH {ctes} SELECT {keys}, (row_number() OVER (ORDER BY {keys}) - 1)::INT AS cell FROM (SELECT DISTINCT {cols} FROM {joins})"


_add("chain_cells_geo_k5", _chain("w_d_geo", GEO, 5), _chain_sql("w_d_geo", GEO, 5))
_add("chain_cells_calendar_k5", _chain("w_d_calendar", DAYS, 5), _chain_sql("w_d_calendar", DAYS, 5))


def _bound_check(spark, sf):
    out = []
    for name, chain in (("w_d_geo", GEO), ("w_d_calendar", DAYS)):
        for k in (5, 10):
            n = _chain(name, chain, k)(spark, sf).count()
            out.append((name, k, n, fd.cell_bound([chain], k), n <= fd.cell_bound([chain], k)))
    return spark.createDataFrame(out, "workload string, kappa int, cells bigint, bound bigint, holds boolean")


_add("cell_bound_check", _bound_check, " UNION ALL ".join(
    f"SELECT '{n}' AS workload, {k} AS kappa, count(*) AS cells, {fd.cell_bound([ch], k)}::BIGINT AS bound, count(*) <= {fd.cell_bound([ch], k)} AS holds FROM ({_chain_sql(n, ch, k)})" for n, ch in (("w_d_geo", GEO), ("w_d_calendar", DAYS)) for k in (5, 10)))
_add("chain_grid_wm", lambda spark, sf: _chain_grid(spark, sf))


def _chain_grid(spark, sf):
    q = wl.w_m(spark, sf)
    _, _, comps = _solved(q, 5)
    n, r = tables(spark, sf, "nation", "region")
    ids = fd.chain_cells(n.join(r, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("nation"), F.col("r_name").alias("region")), comps, ["nation", "region"])
    return grid_weights(q, comps, chains={"geo": ids})


# ---- clustering
def _race_sql(workload: str, features: dict[str, str], k: int, seed: int) -> str:
    """Seeds by weight times squared distance, for categories: a round a CTE, distances from the components' squared norms."""
    ctes, joins, cols = o.encoders(workload, features, k)
    keys = ", ".join(f"c_{f}" for f in features)
    out = [ctes, f"g AS MATERIALIZED (SELECT {keys}, count(*)::DOUBLE AS w FROM (SELECT {cols} FROM {joins}) GROUP BY ALL)"]
    for f in features:
        out.append(f"n_{f} AS MATERIALIZED (SELECT c, sum(w*w)/(sum(w)*sum(w)) AS q FROM (SELECT least(r.rk, {k - 1})::INT AS c, n.w FROM r_{f} r JOIN (SELECT {f} AS v, count(*)::DOUBLE AS w FROM x GROUP BY 1) n ON n.v = r.v) GROUP BY 1)")
    named = f"SELECT g.*, {', '.join(f'n_{f}.q AS q_{f}' for f in features)} FROM g {' '.join(f'JOIN n_{f} ON n_{f}.c = g.c_{f}' for f in features)}"
    out.append(f"gq AS MATERIALIZED ({named})")
    apart = " + ".join(f"CASE WHEN g.c_{f} = s.c_{f} THEN 0 ELSE g.q_{f} + s.q_{f} END" for f in features)
    for r in range(k):
        u = f"(('0x' || substr(md5(concat_ws(':', '{seed}', '{r}', {', '.join(f'g.c_{f}' for f in features)})), 1, 8))::BIGINT + 1) / 4294967296.0"
        chosen = " UNION ALL ".join(f"SELECT * FROM s{i}" for i in range(r))
        far = f"(SELECT min({apart}) FROM ({chosen}) s)" if r else "1.0"
        out.append(f"s{r} AS MATERIALIZED (SELECT * EXCLUDE (d) FROM (SELECT g.*, -ln({u}) AS e, {far} AS d FROM gq g) WHERE d > 1e-12 ORDER BY e / (w * d), {keys} LIMIT 1)")
        out[-1] = out[-1].replace("EXCLUDE (d)", "EXCLUDE (d, e)")
    return f"WITH {', '.join(out)} " + " UNION ALL ".join(f"SELECT {keys} FROM s{r}" for r in range(k))


def _seeds(how: str) -> Query:
    def run(spark, sf):
        q = wl.w_m(spark, sf)
        _, _, comps = _solved(q, 5)
        cells = grid_weights(q, comps).persist()
        seeds = seed_top(cells, comps, 5) if how == "top" else seed_pp(cells, comps, 5)
        return spark.createDataFrame([[int(v) for v in r] for r in seeds], ", ".join(f"c_{s.name} int" for s in comps.subspaces))

    return run


_add("seed_top_wm", _seeds("top"), f"SELECT {', '.join('c_' + f for f in WM)} FROM ({o.grid('w_m', WM, 5)}) ORDER BY w DESC, {', '.join('c_' + f for f in WM)} LIMIT 5")
_add("seed_pp_wm", _seeds("pp"), _race_sql("w_m", WM, 5, 1))


def _lloyd(workload: str, features, k: int, local: bool, what: str) -> Query:
    def run(spark, sf):
        q = _query(workload, features, spark, sf)
        cal, m, comps = _solved(q, k)
        cells = cal.grid(comps.encoders, comps.defaults).persist()
        got = grid_lloyd(cells, comps, seed_top(cells, comps, k), max_iter=3, tol=0, local=local)
        if what == "coef":
            t = got.centroids.table(spark)
            return t.select("cluster", "subspace", "comp", F.round("coef", 6).alias("coef"))
        a = nearest(cells, got.centroids)
        return a.drop("d") if what == "assign" else a.groupBy("cluster").agg(F.sum("w").cast("bigint").alias("weight"), F.count("*").alias("cells"))

    return run


def _lloyd_sql(workload: str, features: dict[str, str], k: int, sweeps: int, what: str) -> str:
    """Lloyd by explicit one-hot coordinates of the cells: a light component is the vector of its categories' shares."""
    ctes, joins, cols = o.encoders(workload, features, k)
    keys = ", ".join(f"c_{f}" for f in features)
    out = [ctes, f"g AS MATERIALIZED (SELECT row_number() OVER (ORDER BY w DESC, {keys}) AS id, * FROM (SELECT {keys}, count(*)::DOUBLE AS w FROM (SELECT {cols} FROM {joins}) GROUP BY ALL))"]
    coord = []
    for f in features:
        out.append(f"s_{f} AS (SELECT least(r.rk, {k - 1})::INT AS comp, r.v AS cat, n.w / sum(n.w) OVER (PARTITION BY least(r.rk, {k - 1})) AS x FROM r_{f} r JOIN (SELECT {f} AS v, count(*)::DOUBLE AS w FROM x GROUP BY 1) n ON n.v = r.v)")
        coord.append(f"SELECT id, '{f}:' || cat AS dim, s.x AS x FROM g JOIN s_{f} s ON s.comp = g.c_{f}")
    out.append(f"p AS MATERIALIZED ({' UNION ALL '.join(coord)})")
    out.append("pn AS MATERIALIZED (SELECT id, sum(x*x) AS n FROM p GROUP BY 1)")
    out.append(f"m0 AS (SELECT id - 1 AS cluster, dim, x FROM p WHERE id <= {k})")
    for i in range(sweeps + 1):
        out.append(f"q{i} AS MATERIALIZED (SELECT cluster, sum(x*x) AS n FROM m{i} GROUP BY 1)")
        out.append(f"i{i} AS MATERIALIZED (SELECT p.id, m.cluster, sum(p.x*m.x) AS s FROM p JOIN m{i} m USING (dim) GROUP BY 1, 2)")
        out.append(f"a{i} AS MATERIALIZED (SELECT id, first(cluster ORDER BY round(d, 9), cluster) AS cluster FROM (SELECT pn.id, q.cluster, pn.n + q.n - 2*coalesce(i.s, 0) AS d FROM pn CROSS JOIN q{i} q LEFT JOIN i{i} i ON i.id = pn.id AND i.cluster = q.cluster) GROUP BY id)")
        if i < sweeps:
            out.append(f"m{i+1} AS MATERIALIZED (SELECT cluster, dim, sum(g.w*p.x) / max(t.w) AS x FROM a{i} JOIN g USING (id) JOIN p USING (id) JOIN (SELECT cluster, sum(w) AS w FROM a{i} JOIN g USING (id) GROUP BY 1) t USING (cluster) GROUP BY cluster, dim UNION ALL SELECT cluster, dim, x FROM m{i} WHERE cluster NOT IN (SELECT cluster FROM a{i}))")
    last = f"a{sweeps}"
    if what == "coef":  # the shares of the last means' components
        own = f"(SELECT * FROM a{sweeps - 1} JOIN g USING (id))"
        shares = " UNION ALL ".join(f"SELECT cluster::INT AS cluster, '{f}' AS subspace, c_{f} AS comp, sum(w) / (SELECT sum(w) FROM {own} t WHERE t.cluster = y.cluster) AS coef FROM {own} y GROUP BY cluster, c_{f}" for f in features)
        return f"WITH {', '.join(out)} SELECT cluster, subspace, comp, round(coef, 6) AS coef FROM ({shares})"
    if what == "assign":
        return f"WITH {', '.join(out)} SELECT {keys}, w::BIGINT AS w, cluster::INT AS cluster FROM g JOIN {last} USING (id)"
    return f"WITH {', '.join(out)} SELECT cluster::INT AS cluster, sum(w)::BIGINT AS weight, count(*) AS cells FROM g JOIN {last} USING (id) GROUP BY 1"


WM4 = {"priority": CAT, "status": CAT, "segment": CAT, "region": CAT}
_add("lloyd_wm_iter3", _lloyd("w_m", WM, 5, True, "coef"), _lloyd_sql("w_m", WM, 5, 3, "coef"))
_add("lloyd_wr_iter3", _lloyd("w_r", WR, 5, False, "coef"))
_add("lloyd_assign_wm", _lloyd("w_m", WM4, 5, True, "assign"), _lloyd_sql("w_m", WM4, 5, 3, "assign"))
_add("lloyd_weighted_sizes", _lloyd("w_m", WM4, 5, False, "sizes"), _lloyd_sql("w_m", WM4, 5, 3, "sizes"))


def _cluster(workload: str, features, k: int, kappa: int | None = None, **more) -> Query:
    def run(spark, sf):
        q = _query(workload, features, spark, sf) if features else wl.ALL[workload](spark, sf)
        got = cluster_join(spark, q, k, kappa, max_iter=10, **more)
        return got.sizes()

    return run


_add("cluster_join_wm_k5", _cluster("w_m", None, 5))
_add("cluster_join_wm_k20_kappa10", _cluster("w_m", None, 20, 10))
_add("cluster_join_wr_zscore", _cluster("w_r", None, 5, scaling="zscore"))
_add("cluster_join_wy_parallel", _cluster("w_y", None, 5, seeding="parallel"))
_add("cluster_join_wf", _cluster("w_f", None, 5))
_add("cluster_join_wc", _cluster("w_c", None, 5))
_add("cluster_join_ws_kmedian", _cluster("w_s", None, 4, 3, p=1))
_add("regularised_l1_wr", _cluster("w_r", ["qty", "size", "brand"], 5, penalty=Penalty("l1", 5000.0)))
_add("regularised_group_wm", _cluster("w_m", None, 5, penalty=Penalty("group", 500.0)))


def _vectors(spark, sf):
    return block_grid(wl.w_v(spark, sf), "embedding", 64, 16, 4, "label")[0]


_add("vector_blocks_wv", _vectors)


# ---- measures
def _objective_wm(spark, sf):
    q = wl.w_m(spark, sf).only(*WM4)
    cal, m, comps = _solved(q, 5)
    cells = cal.grid(comps.encoders, comps.defaults).persist()
    got = grid_lloyd(cells, comps, seed_top(cells, comps, 5), max_iter=0)
    return spark.createDataFrame([(round(objective.objective(baseline.counted(q), q, got.centroids, m), 4),)], "objective double")


def _objective_sql() -> str:
    ctes, joins, cols = o.encoders("w_m", WM4, 5)
    keys = ", ".join(f"c_{f}" for f in WM4)
    shares = ", ".join(f"n_{f} AS (SELECT v, count(*)::DOUBLE AS w FROM (SELECT {f} AS v FROM x) GROUP BY 1), t_{f} AS (SELECT least(rk, 4)::INT AS comp, sum(w) AS t, sum(w*w)/(sum(w)*sum(w)) AS q FROM (SELECT r.rk, n.w FROM r_{f} r JOIN n_{f} n ON n.v = r.v) GROUP BY 1)" for f in WM4)
    dist = " + ".join(f"CASE WHEN e.c_{f} = s.c_{f} AND e.c_{f} < 4 THEN 0 WHEN e.c_{f} = s.c_{f} THEN 1 - 2*e.w_{f}/t_{f}.t + t_{f}.q ELSE 1 + t_{f}.q END" for f in WM4)
    enc = ", ".join(f"least(r_{f}.rk, 4)::INT AS c_{f}, n_{f}.w AS w_{f}" for f in WM4)
    more = " ".join(f"JOIN n_{f} ON n_{f}.v = x.{f}" for f in WM4)
    last = " ".join(f"JOIN t_{f} ON t_{f}.comp = s.c_{f}" for f in WM4)
    distinct = ", ".join([f"c_{f}" for f in WM4] + [f"w_{f}" for f in WM4])
    return f"""WITH {ctes}, {shares}, seeds AS (SELECT {keys}, row_number() OVER () AS k FROM (SELECT {keys}, count(*) AS w FROM (SELECT {cols} FROM {joins}) GROUP BY ALL ORDER BY w DESC, {keys} LIMIT 5)),
e AS (SELECT {distinct}, count(*) AS n FROM (SELECT {enc} FROM {joins} {more}) GROUP BY ALL)
SELECT round(sum(n * d), 4)::DOUBLE AS objective FROM (SELECT {', '.join('e.' + c.strip() for c in distinct.split(','))}, e.n, min({dist}) AS d FROM e CROSS JOIN seeds s {last} GROUP BY ALL)"""


_add("objective_wm", _objective_wm, _objective_sql())


def _identity(spark, sf):
    q = wl.w_r(spark, sf).only("qty", "brand", "segment")
    cal, m, comps = _solved(q, 5)
    return spark.createDataFrame([(round(comps.cost, 3),)], "cost double")


def _identity_sql() -> str:
    fs = {"qty": CONT, "brand": CAT, "segment": CAT}
    ctes, joins, cols = o.encoders("w_r", fs, 5)
    parts = []
    for f, k in fs.items():
        if k == CONT:
            parts.append(f"(SELECT sum(s) FROM (SELECT sum({f}*{f}) - sum({f})*sum({f})/count(*) AS s FROM y GROUP BY c_{f}))")
        else:
            parts.append(f"(SELECT sum(t - q/t) FROM (SELECT c_{f}, sum(n)::DOUBLE AS t, sum(n*n)::DOUBLE AS q FROM (SELECT c_{f}, {f}, count(*)::DOUBLE AS n FROM y GROUP BY 1, 2) GROUP BY 1))")
    return f"WITH {ctes}, y AS (SELECT x.*, {cols} FROM {joins}) SELECT round({' + '.join(parts)}, 3)::DOUBLE AS cost"


_add("quantisation_identity_wr", _identity, _identity_sql())


def _approx(spark, sf):
    q = wl.w_m(spark, sf)
    base, seconds = baseline.standard_kmeans(q, 5, max_iter=10, build=baseline.counted)
    got = cluster_join(spark, q, 5, max_iter=10)
    ours = objective.objective(baseline.counted(q), q, got.centroids, got.marginals)
    own = objective.induced_cost(q, got.comps, got.centroids, got.marginals)
    rel = objective.relative_approx(ours, base)
    return spark.createDataFrame([("w_m", 5, 5, rel, own / ours, bounds.bound_slack(ours, base), objective.relative_speedup(seconds["materialise"], seconds["cluster"], sum(got.seconds.values())))], "workload string, k int, kappa int, relative_approx double, induced_over_exact double, bound_slack double, speedup double")


_add("relative_approx_wm", _approx)


def _induced(spark, sf):
    q = wl.w_m(spark, sf).only(*WM4)
    cal, m, comps = _solved(q, 5)
    cells = cal.grid(comps.encoders, comps.defaults).persist()
    got = grid_lloyd(cells, comps, seed_top(cells, comps, 5), max_iter=2, tol=0)
    a, b = objective.induced_cost(q, comps, got.centroids, m), objective.objective(baseline.counted(q), q, got.centroids, m)
    return spark.createDataFrame([(a, b, a >= b - 1e-6)], "induced double, exact double, above boolean")


_add("induced_cost_wm", _induced)


def _w(power: int) -> Query:
    def run(spark, sf):
        q = wl.w_r(spark, sf)
        cal = Calibration(q)
        pick = lambda n: cal.marginal(n).select(F.col("vnum").alias("x"), "w")
        return wasserstein_1d(pick("qty"), pick("size"), power).select(F.round("wp", 6).alias("wp"))

    return run


def _w_sql(power: int) -> str:
    steps = lambda f: f"SELECT {f}::DOUBLE AS x, round(sum(count(*)) OVER (ORDER BY {f} ROWS UNBOUNDED PRECEDING) / (SELECT count(*) FROM m), 12) AS c FROM m GROUP BY {f}"
    return f"""WITH m AS MATERIALIZED {o.matrix('w_r')}, a AS ({steps('qty')}), b AS ({steps('size')}), c AS (SELECT c FROM a UNION SELECT c FROM b),
    d AS (SELECT c, c - coalesce(lag(c) OVER (ORDER BY c), 0) AS d FROM c)
    SELECT round(pow(sum(d * pow(abs((SELECT min(x) FROM a WHERE a.c >= d.c) - (SELECT min(x) FROM b WHERE b.c >= d.c)), {power})), 1.0/{power}), 6)::DOUBLE AS wp FROM d"""


_add("w1_marginals", _w(1), _w_sql(1))
_add("w2_marginals_quantity", _w(2), _w_sql(2))
_add("zscore_from_marginals", lambda spark, sf: objective.zscores(Calibration(wl.w_r(spark, sf)).marginals()).select("subspace", "n", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd")),
     " UNION ALL ".join(f"SELECT '{f}' AS subspace, count(*) AS n, round(avg({f}), 6) AS mean, round(stddev_pop({f}), 6) AS sd FROM {o.matrix('w_r')}" for f in ("qty", "disc_cents", "size")))


def _bounds_table(spark, sf):
    """Guarantees at the ratios that two solvers reach on each kind of order line: one center, rounded down to a whole number, for quantities (a) and for discounts (b)."""
    (li,) = tables(spark, sf, "lineitem")
    x, y = F.col("l_quantity").cast("double"), F.round(F.col("l_discount") * 100).cast("double")
    sums = [f(v).alias(n + t) for t, v in (("x", x), ("y", y)) for n, f in (("n", F.count), ("s", F.sum), ("q", lambda v: F.sum(v * v)))]
    groups = li.groupBy(F.concat("l_returnflag", "l_linestatus").alias("lines")).agg(*sums, F.count_distinct("l_quantity").alias("k")).collect()

    def ratio(n, s, q):
        best, c = q - s * s / n, math.floor(s / n)
        return (q - 2 * c * s + n * c * c) / best if best > 0 else 1.0

    rows = []
    for r in groups:
        a, b = (ratio(r["n" + t], r["s" + t], r["q" + t]) for t in "xy")
        rows += [(r["lines"], "approx", a, g, bounds.approx_bound(a, g)) for g in (b, bounds.BEST_GAMMA)]
        rows += [(r["lines"], "regularised", a, b, bounds.approx_bound_reg(a, b)), (r["lines"], "lower", float(r["k"]), 2.0, bounds.approx_lower_bound(r["k"], 2, 4))]
    return spark.createDataFrame([(l, k, round(a, 9), round(b, 9), round(v, 9)) for l, k, a, b, v in rows], "lines string, kind string, a double, b double, bound double")


_RATIO = "CASE WHEN q{0} - s{0}*s{0}/n{0} > 0 THEN (q{0} - 2*floor(s{0}/n{0})*s{0} + n{0}*floor(s{0}/n{0})*floor(s{0}/n{0})) / (q{0} - s{0}*s{0}/n{0}) ELSE 1.0::DOUBLE END"
_add("bounds_table", _bounds_table, f"""WITH g AS (SELECT l_returnflag || l_linestatus AS lines, count(x) AS nx, sum(x) AS sx, sum(x*x) AS qx, count(y) AS ny, sum(y) AS sy, sum(y*y) AS qy, count(DISTINCT x)::DOUBLE AS k
    FROM (SELECT *, l_quantity::DOUBLE AS x, round(l_discount*100)::DOUBLE AS y FROM lineitem) GROUP BY 1),
  r AS (SELECT lines, {_RATIO.format('x')} AS a, {_RATIO.format('y')} AS b, k FROM g)
  SELECT lines, kind, round(a, 9) AS a, round(b, 9) AS b, round(bound, 9) AS bound FROM (
  SELECT lines, 'approx' AS kind, a, b, pow(sqrt(a) + sqrt(b) + sqrt(a*b), 2) AS bound FROM (SELECT lines, a, b FROM r UNION ALL SELECT lines, a, {bounds.BEST_GAMMA}::DOUBLE FROM r)
  UNION ALL SELECT lines, 'regularised', a, b, 2*a + 4*b + 4*a*b FROM r
  UNION ALL SELECT lines, 'lower', k, 2.0, sqrt(1 - exp(-4 / 4.0)) * sqrt(12 * pow(k, 0.5) / 4) / (4 * 2) FROM r)""")

#: Joins of given tables by shape: each relation's keys, and its letters in the shape.
_SHAPES = {
    "triangle": (("lineitem", "l_orderkey", "l_partkey"), ("lineitem", "l_partkey", "l_suppkey"), ("lineitem", "l_orderkey", "l_suppkey")),
    "star": (("lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"), ("orders", "o_orderkey"), ("part", "p_partkey"), ("supplier", "s_suppkey")),
    "path": (("orders", "o_custkey", "o_orderkey"), ("lineitem", "l_orderkey", "l_partkey"), ("lineitem", "l_partkey", "l_suppkey")),
}


def _widths(spark, sf):
    """Widths of three shapes, the rows of their longest relation (those whose keys are not null), and the bound on the join's rows that both give."""
    shapes = {"triangle": Hypergraph.of("ab", "bc", "ac"), "star": Hypergraph.of("abcd", "a", "b", "c"), "path": Hypergraph.of("ab", "bc", "cd")}
    every = sorted({r for rs in _SHAPES.values() for r in rs})
    held = {}
    for t in {r[0] for r in every}:
        mine = [r for r in every if r[0] == t]
        full = [F.count_if(reduce(lambda a, b: a & b, [F.col(k).isNotNull() for k in r[1:]])) for r in mine]
        held |= dict(zip(mine, tables(spark, sf, t)[0].agg(*full).first(), strict=True))
    rows = []
    for n, h in shapes.items():
        longest = max(held[r] for r in _SHAPES[n])
        x = cost_model(Sizes(3, 3, longest, 3, 5, 5, 10, 30, 100, 1000), h)
        rows.append((n, float(x["rho_star"]), float(x["fhtw"]), longest, float(round(x["agm"]))))
    return spark.createDataFrame(rows, "shape string, rho_star double, fhtw double, longest bigint, most_rows double")


def _widths_sql() -> str:
    size = lambda t, *ks: f"(SELECT count(*) FROM {t} WHERE {' AND '.join(k + ' IS NOT NULL' for k in ks)})"
    known = {"triangle": (1.5, 1.5), "star": (1.0, 1.0), "path": (2.0, 1.0)}
    parts = [f"SELECT '{n}' AS shape, {rho}::DOUBLE AS rho_star, {w}::DOUBLE AS fhtw, greatest({', '.join(size(*r) for r in _SHAPES[n])}) AS longest" for n, (rho, w) in known.items()]
    return f"SELECT shape, rho_star, fhtw, longest, round(pow(longest, rho_star))::DOUBLE AS most_rows FROM ({' UNION ALL '.join(parts)})"


_add("widths", _widths, _widths_sql())


def _models(spark, sf):
    out = []
    for name in ("w_r", "w_m", "w_c", "w_s"):
        q = wl.ALL[name](spark, sf)
        h = Hypergraph.of_query(q)
        got = cost_model(Sizes(len(q.relations), len(q.features), max(d.count() for d in q.relations.values()), len(q.features), 5, 5, 20, 100, 1000, Calibration(q).size), h)
        out.append((name, got["rho_star"], got["fhtw"], got["gap_exponent"], got["ratio"]))
    return spark.createDataFrame(out, "workload string, rho_star double, fhtw double, gap double, ratio double")


_add("cost_models", _models)

# ---- baselines and operators
for _w in ("w_r", "w_m", "w_y", "w_c", "w_f"):
    _fs = {"w_r": WR, "w_m": WM, "w_y": WY, "w_c": WC, "w_f": {**WF, "oil": CONT, "tx_n": CONT}}[_w]
    _build = baseline.counted if _w == "w_m" else baseline.materialise  # w_m's joined rows far outnumber its different ones
    _add(f"materialise_{_w.replace('_', '')}", (lambda w, fs, build: lambda spark, sf: build(_query(w, fs, spark, sf)).groupBy(*fs).agg(F.sum("w").alias("n")))(_w, list(_fs), _build),
         f"SELECT {', '.join(f + ('::DOUBLE AS ' + f if k == CONT else '') for f, k in _fs.items())}, count(*)::BIGINT AS n FROM {o.matrix(_w)} GROUP BY ALL")


def _mllib(spark, sf):
    cost, seconds = baseline.standard_kmeans(wl.w_m(spark, sf).only(*WM4), 5, max_iter=5, build=baseline.counted)
    return spark.createDataFrame([(cost, seconds["materialise"], seconds["cluster"])], "objective double, materialise_s double, cluster_s double")


_add("mllib_baseline", _mllib)
_add("sample_baseline", lambda spark, sf: baseline.sample_kmeans(wl.w_m(spark, sf).only(*WM4), 5, 0.2))


def _asof(spark, sf):
    """The last order price at or before each shipping day: a union of both sides (a row a day) and a window over the days, no range join."""
    li, od = tables(spark, sf, "lineitem", "orders")
    oil = od.groupBy(F.to_date("o_orderdate").alias("day")).agg(F.floor(F.avg("o_totalprice")).cast("bigint").alias("price"))
    days = li.select(F.to_date("l_shipdate").alias("day")).distinct().withColumn("want", F.lit(1))
    both = oil.withColumn("want", F.lit(0)).unionByName(days.withColumn("price", F.lit(None).cast("bigint")))
    w = W.orderBy("day", "want").rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn("price", F.last("price", ignorenulls=True).over(w)).where("want = 1").select("day", "price")


_add("oil_asof", _asof, """SELECT day, (SELECT price FROM (SELECT o_orderdate::DATE AS d, floor(avg(o_totalprice))::BIGINT AS price FROM orders GROUP BY 1) WHERE d <= day ORDER BY d DESC LIMIT 1) AS price FROM (SELECT DISTINCT l_shipdate::DATE AS day FROM lineitem)""")
_add("transactions_agg", lambda spark, sf: tables(spark, sf, "lineitem")[0].groupBy(F.to_date("l_shipdate").alias("day"), "l_suppkey").agg(F.count("*").alias("n"), F.count_if(F.col("l_discount") >= 0.07).alias("promo")),
     "SELECT l_shipdate::DATE AS day, l_suppkey, count(*) AS n, count(*) FILTER (WHERE l_discount >= 0.07) AS promo FROM lineitem GROUP BY 1, 2")


def _semi(spark, sf):
    od, c, n = tables(spark, sf, "orders", "customer", "nation")
    return od.join(c.join(n.where("n_regionkey = 1"), F.col("c_nationkey") == F.col("n_nationkey"), "left_semi"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").groupBy("o_orderpriority").agg(F.count("*").alias("n"))


_add("semi_reduce", _semi, "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_regionkey = 1) GROUP BY 1")
_add("anti_dangling", lambda spark, sf: (lambda c, od: c.join(od, F.col("c_custkey") == F.col("o_custkey"), "left_anti").agg(F.count("*").alias("n")))(*tables(spark, sf, "customer", "orders")),
     "SELECT count(*) AS n FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")


def _block_objective(spark, sf):
    q = wl.w_f_lite(spark, sf)
    got = cluster_join(spark, q, 5, max_iter=5, seeding="top")
    return got.assignment().groupBy("cluster").agg(F.sum(F.col("w") * F.col("d")).alias("cost"))


_add("grid_objective_wf_lite", _block_objective)


# ---- streams
def _folder(spark, df: DataFrame, parts: int) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir is unset: executors need a folder that all of them can read")
    base = base or tempfile.mkdtemp(prefix="joincluster-")
    path = f"{base}/joincluster-stream-{uuid.uuid4().hex}"
    df.repartitionByRange(parts, "ts").write.parquet(path)
    return path


def _stream(run) -> Query:
    def query(spark, sf):
        from .streaming import stream

        (e,) = tables(spark, sf, "events")
        path = _folder(spark, e, 4)
        return run(spark, sf, stream, stream.event_stream(spark, path), path)

    return query


def _daily(spark, sf, stream, events, path):
    return stream.run_to_table(stream.stream_marginals(events, "event_type"), f"jc_{uuid.uuid4().hex}", "complete", f"{path}-state").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "value", "w")


_add("stream_daily_marginals", _stream(_daily), "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type AS value, count(*) AS w FROM events GROUP BY 1, 2")


def _sliding(spark, sf, stream, events, path):
    got = stream.run_to_table(stream.stream_marginals(events, "event_type", "1 day", "12 hours"), f"jc_{uuid.uuid4().hex}", "complete", f"{path}-state")
    return got.select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "value", "w")


_add("stream_sliding_grid", _stream(_sliding), """SELECT strftime(s, '%Y-%m-%d %H') AS start, event_type AS value, count(*) AS w FROM (
  SELECT event_type, unnest([time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1, 2""")


def _sessions(spark, sf, stream, events, path):
    counts = lambda t: t.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))
    return stream.run_to_files(stream.stream_sessions(stream.event_stream(spark, path, "60 days"), "6 hours"), f"{path}-out", f"{path}-state", counts)


_add("stream_session_counts", _stream(_sessions), """SELECT user_id, sum(new)::BIGINT AS sessions, count(*)::BIGINT AS n FROM (
  SELECT user_id, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events) GROUP BY 1""")


def _stream_cells(spark, sf, stream, events, path):
    q = wl.w_y(spark, sf).only("event_type", "segment")
    _, _, comps = _solved(q, 4)
    (cust,) = tables(spark, sf, "customer")
    got = stream.run_to_table(stream.stream_grid(events, cust.select("c_custkey", "c_mktsegment"), ("user_id", "c_custkey"), comps, {"event_type": "event_type", "segment": "c_mktsegment"}), f"jc_{uuid.uuid4().hex}", "complete", f"{path}-state")
    return got


_add("stream_grid_events", _stream(_stream_cells))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five clusters of the blow-up workload: cluster, weight, cells."""
    return cluster_join(spark, wl.w_m(spark, sf_dir), 5, max_iter=10).sizes()
