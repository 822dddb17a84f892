"""The plans and the method on small tables: bag semantics, left joins, cycles, distances, guarantees."""

import itertools
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from joincluster.functions import sql as jc_sql
from joincluster.operators import baseline, fd, objective
from joincluster.operators.components import ComponentSet, Subspace, solve, solve_line
from joincluster.operators.grid import full_grid, grid_weights, grid_weights_flat
from joincluster.operators.lloyd import Centroids, Penalty, distance_table, grid_lloyd, point_mixtures, seed_parallel, seed_pp, seed_top
from joincluster.operators.pipeline import cluster_join
from joincluster.operators.transport import measures, wasserstein_1d
from joincluster.plans.hypergraph import cycle, decompose, join_tree
from joincluster.plans.messages import Calibration
from joincluster.plans.spec import Edge, Feature, FeatureQuery
from joincluster.sources import workloads as wl

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def toy(spark):
    r = spark.createDataFrame([(1, "x"), (1, "x"), (2, "y"), (3, "z"), (None, "n")], "b int, a string")
    s = spark.createDataFrame([(1, 10), (1, 10), (1, 20), (2, 20), (9, 5)], "b int, c int")
    t = spark.createDataFrame([(10, "p"), (10, "q")], "c int, d string")
    return FeatureQuery("toy", {"r": r, "s": s, "t": t}, [Edge("r", "s", (("b", "b"),)), Edge("s", "t", (("c", "c"),), "left")], [Feature("a", "r", "a"), Feature("c", "s", "c", "cont"), Feature("d", "t", "d")], "r")


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_marginals_match_the_matrix(toy):
    x = baseline.materialise(toy)
    cal = Calibration(toy)
    assert cal.size == x.agg(F.sum("w")).first()[0] == 11
    got = {(r["subspace"], r["vcat"] or r["vnum"]): r["w"] for r in cal.marginals().collect()}
    want = {}
    for f in ("a", "c", "d"):
        for r in x.groupBy(f).agg(F.sum("w").alias("w")).collect():
            want[(f, r[f])] = r["w"]
    assert got == want and got[("d", "∅")] == 3


def test_grid_matches_its_definition(toy):
    comps = solve(toy, Calibration(toy).marginals(), 2)
    assert rows(grid_weights(toy, comps)) == rows(grid_weights_flat(toy, comps))


@pytest.mark.parametrize("name", ["w_m", "w_c", "w_y", "w_f", "w_f_lite", "w_t"])
def test_grids_of_workloads(spark, name):
    q = wl.ALL[name](spark, SF)
    cal = Calibration(q)
    m = cal.marginals().persist()
    comps = solve(q, m, 4)
    cells = grid_weights(q, comps).persist()
    assert cells.exceptAll(grid_weights_flat(q, comps)).isEmpty()
    assert cells.agg(F.sum("w")).first()[0] == cal.size
    for s in comps.subspaces:  # the grid's marginals are the components' masses
        got = {r[0]: r[1] for r in cells.groupBy(f"c_{s.name}").agg(F.sum("w")).collect()}
        assert got == {i: v for i, v in enumerate(s.mass)}
    bound = fd.cell_bound(fd.chains_of(q), 4)
    assert cells.count() <= min(bound, cal.size)


def test_aggregates_stand_below_the_joins(spark):
    q = wl.w_m(spark, SF)
    comps = solve(q, Calibration(q).marginals(), 4)
    plan = grid_weights(q, comps)._jdf.queryExecution().optimizedPlan().toString()
    assert "CartesianProduct" not in plan
    first = plan.index("Join")
    assert plan.index("Aggregate", first) > first  # an aggregate under a join
    physical = grid_weights(q, comps)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in physical and "NestedLoop" not in physical


def test_cycles_become_a_bag(spark):
    q = wl.w_c(spark, SF)
    assert set(cycle(q)) == {"customer", "orders", "lineitem", "supplier"}
    with pytest.raises(ValueError):
        join_tree(q)
    assert set(decompose(q).relations) == {"bag", "nation"}
    assert Calibration(q).size == baseline.materialise(q).count() == 235


def test_partitioning_does_not_matter(spark):
    q = wl.w_m(spark, SF)
    comps = solve(q, Calibration(q).marginals(), 4)
    want = rows(grid_weights(q, comps))
    for n in (1, 7):
        q.relations["orders"] = q.relations["orders"].repartition(n)
        assert rows(grid_weights(q, comps)) == want


def test_empty_relation(spark):
    q = wl.w_m(spark, SF)
    q.relations["orders"] = q.relations["orders"].limit(0)
    cal = Calibration(q)
    assert cal.size == 0 and cal.marginals().count() == 0
    comps = solve(q, cal.marginals(), 3)
    assert all(s.size == 0 for s in comps.subspaces)


def category(name, weights, kappa):
    order = sorted(weights, key=lambda e: (-weights[e], e))
    heavy, rest = order[: kappa - 1], order[kappa - 1 :]
    light = sum(weights[e] for e in rest)
    return Subspace(Feature(name, "r", name), np.array([weights[e] for e in heavy] + ([light] if rest else []), float), 0.0, heavy=heavy, sqnorm=sum(weights[e] ** 2 for e in rest) / light**2 if rest else 0.0), np.array([[float(e == h) for e in order] for h in heavy] + ([[weights[e] / light if e in rest else 0.0 for e in order]] if rest else []))


def test_factored_distances_are_dense_distances():
    rng = np.random.default_rng(3)
    s, points = category("f", {"a": 9, "b": 5, "c": 3, "d": 2, "e": 1}, 3)
    a = rng.dirichlet(np.ones(3), 4)
    want = ((points[:, None, :] - (a @ points)[None]) ** 2).sum(2)
    assert distance_table(s, a) == pytest.approx(want)
    line = Subspace(Feature("x", "r", "x", "cont", scale=2.0), np.array([1.0, 2.0]), 0.0, centers=np.array([1.0, 4.0]), upper=np.array([2.0, 5.0]))
    b = np.array([[0.25, 0.75]])
    assert distance_table(line, b) == pytest.approx(np.array([[4 * (1 - 3.25) ** 2], [4 * (4 - 3.25) ** 2]]))


def test_lloyd_is_dense_lloyd(spark):
    q = wl.w_m(spark, SF).only("priority", "status", "segment", "suppkey")
    m = Calibration(q).marginals().persist()
    comps = solve(q, m, 4)
    cells = grid_weights(q, comps).persist()
    seeds = seed_top(cells, comps, 4)
    a = grid_lloyd(cells, comps, seeds, 5, 0.0, local=True)
    b = grid_lloyd(cells, comps, seeds, 5, 0.0, local=False)
    assert a.objective == pytest.approx(b.objective) and a.history == sorted(a.history, reverse=True)
    blocks = []
    for s in comps.subspaces:
        w = {r["vcat"]: r["w"] for r in m.where(F.col("subspace") == s.name).collect()}
        blocks.append(category(s.name, w, 4)[1])
    got = cells.collect()
    x = np.array([np.concatenate([blk[r[f"c_{s.name}"]] for s, blk in zip(comps.subspaces, blocks, strict=True)]) for r in got])
    start = np.array([np.concatenate([blk[c] for blk, c in zip(blocks, row, strict=True)]) for row in seeds])
    _, cost = baseline.dense_lloyd(x, np.array([float(r["w"]) for r in got]), start, 5, 0.0)
    assert cost == pytest.approx(a.objective, rel=1e-6)


def test_objective_and_identities(spark):
    q = wl.w_m(spark, SF).only("priority", "segment", "suppkey")
    got = cluster_join(spark, q, 4, max_iter=5)
    exact = objective.objective(baseline.materialise(q), q, got.centroids, got.marginals)
    assert objective.induced_cost(q, got.comps, got.centroids, got.marginals) >= exact - 1e-6
    assert exact <= 2 * (got.comps.cost + got.clustering.objective) + 1e-6
    wide = got.centroids.expanded(got.marginals).groupBy("cluster", "subspace").agg(F.sum("value").alias("v")).collect()
    assert all(r["v"] == pytest.approx(1.0) for r in wide)
    assert got.guarantee(1.0) == pytest.approx(9)
    for name, df in measures(got).items():
        keys = ["subspace"] if name == "subspaces" else []
        assert all(r["s"] == pytest.approx(1.0) for r in df.groupBy(*keys).agg(F.sum("mass").alias("s")).collect())


def test_ratio_stays_under_nine(spark):
    """Tiny matrices, exact optimum by all partitions, exact solver for the last step too."""
    rng = np.random.default_rng(5)
    from test_kernels import partitions

    worst = 0.0
    for _ in range(6):
        data = [(int(rng.integers(0, 12)), "abcd"[rng.integers(4)]) for _ in range(7)]
        x = np.array([[v, *(float(c == k) * 3 for k in "abcd")] for v, c in data])

        def cost(pts, w, k):
            best = np.inf
            for parts in partitions(range(len(pts)), k):
                c = sum((w[p][:, None] * (pts[p] - (w[p][:, None] * pts[p]).sum(0) / w[p].sum()) ** 2).sum() for p in map(list, parts))
                if c < best:
                    best, at = c, parts
            return best, at

        k = 2
        opt, _ = cost(x, np.ones(7), k)
        line_ = __import__("joincluster.operators.line", fromlist=["line_kmeans"]).line_kmeans(x[:, 0], np.ones(7), k)
        cats = {c: sum(1 for _, d in data if d == c) for c in "abcd" if any(d == c for _, d in data)}
        _, blk = category("c", cats, k)
        order = sorted(cats, key=lambda e: (-cats[e], e))
        grid = {}
        for v, c in data:
            i, j = int(np.searchsorted(line_.upper, v)), min(order.index(c), len(blk) - 1)
            grid[(i, j)] = grid.get((i, j), 0) + 1
        pts = np.array([[line_.centers[i], *(3 * blk[j])] for i, j in grid])
        w = np.array(list(grid.values()), float)
        _, parts = cost(pts, w, k) if len(pts) > 1 else (0, [[0]])
        centers = np.array([(w[list(p)][:, None] * pts[list(p)]).sum(0) / w[list(p)].sum() for p in parts])
        full = np.array([[v, *(float(c == kk) * 3 for kk in order)] for v, c in data])
        ours = ((full[:, None] - centers[None]) ** 2).sum(2).min(1).sum()
        if opt > 1e-9:
            worst = max(worst, ours / opt)
    assert worst <= 9


def test_variants_run(spark):
    q = wl.w_r(spark, SF).only("qty", "size", "brand", "segment")
    base = cluster_join(spark, q, 3, max_iter=4, scaling="zscore")
    assert {s.name: s.size for s in base.comps.subspaces}["qty"] == 3
    for more in ({"kappa": 2}, {"kappa": {"qty": 2, "size": 3, "brand": 4, "segment": 2}}, {"p": 1}, {"penalty": Penalty("group", 100.0)}, {"penalty": Penalty("l1", 100.0)}, {"seeding": "parallel"}, {"seeding": "top"}, {"method": "lloyd"}, {"weight": "decimal(38,0)"}):
        got = cluster_join(spark, q, 3, max_iter=3, **more)
        assert got.sizes().agg(F.sum("weight")).first()[0] == 6000, more
    strong = cluster_join(spark, q, 3, max_iter=4, penalty=Penalty("l1", 1e9))
    assert np.allclose(strong.centroids.value(0), 0)


def test_seeds(spark):
    q = wl.w_m(spark, SF)
    comps = solve(q, Calibration(q).marginals(), 3)
    cells = grid_weights(q, comps).persist()
    a, b = seed_pp(cells, comps, 5, 3), seed_pp(cells.repartition(7), comps, 5, 3)
    assert (a == b).all() and len(np.unique(a, axis=0)) == 5
    assert (a == seed_pp(cells, comps, 5, 3, local=False)).all()
    assert len(seed_parallel(cells, comps, 5)) == 5
    assert len(seed_pp(cells.limit(2), comps, 5)) <= 2
    assert isinstance(point_mixtures(comps, a), Centroids) and isinstance(comps, ComponentSet)


def test_full_grid_and_unseen(spark):
    q = wl.w_m(spark, SF).only("priority", "status")
    comps = solve(q, Calibration(q).marginals(), 3)
    assert full_grid(spark, comps).count() == 9
    assert spark.createDataFrame([("never seen",)], "f__priority string").select(comps["priority"].encode()).first()[0] == 2


def test_buckets_stand_for_many_values(spark):
    m = spark.range(3000).select((F.col("id") * F.col("id") % 7919).cast("double").alias("vnum"), F.lit(1).cast("bigint").alias("w")).groupBy("vnum").agg(F.sum("w").alias("w"))
    exact, coarse = solve_line(m, 4), solve_line(m, 4, buckets=200)
    assert exact.cost <= coarse.cost + 1e-6 <= exact.cost * 1.05
    assert coarse.mass.sum() == pytest.approx(3000)


def test_wasserstein_1d(spark):
    df = lambda xs: spark.createDataFrame([(float(x), w) for x, w in xs], "x double, w long")
    assert wasserstein_1d(df([(0, 1), (1, 1)]), df([(0, 1), (1, 1)])).first()["wp"] == pytest.approx(0)
    assert wasserstein_1d(df([(0, 3)]), df([(2, 1), (4, 1)]), 1).first()["wp"] == pytest.approx(3)
    assert wasserstein_1d(df([(0, 3)]), df([(2, 1), (4, 1)]), 2).first()["wp"] == pytest.approx(10**0.5)


def test_sql_functions(spark):
    jc_sql.register(spark)
    got = spark.sql("SELECT * FROM split_line(array(0D, 1D, 10D), array(1D, 1D, 1D), 2)").collect()
    assert [(r["center"], r["hi"]) for r in got] == [(0.5, 1.0), (10.0, 10.0)]
    assert spark.sql("SELECT count(*) AS n FROM heavy_light(array('a', 'b', 'c'), array(3D, 2D, 1D), 2)").first()["n"] == 2
    assert spark.sql("SELECT grid_encode(7, array(5D, 10D))").first()[0] == 1
    assert spark.sql("SELECT count(*) FROM explode_blocks(array(1D, 2D, 3D), 2)").first()[0] == 2


def test_spec_is_validated(spark):
    (o,) = wl.tables(spark, SF, "orders")
    with pytest.raises(ValueError):
        FeatureQuery("bad", {"o": o}, [Edge("o", "o", (("nope", "x"),))], [], "o").validate()
    with pytest.raises(ValueError):
        FeatureQuery("bad", {"o": o}, [], [Feature("f", "p", "x")], "o").validate()


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 5
    assert set(e.oracle_sql()) <= set(e.queries())
    assert len(list(itertools.islice(e.queries(), 80))) == 80


def test_solved_in_one_go_or_by_feature(spark, monkeypatch):
    from joincluster.operators import components

    q = wl.w_r(spark, SF).only("qty", "size", "brand", "segment")
    m = Calibration(q).marginals().persist()
    one = solve(q, m, 4)
    monkeypatch.setattr(components, "MARGINALS_LOCAL", 3)
    for a, b in zip(one.subspaces, solve(q, m, 4).subspaces, strict=True):
        assert a.heavy == b.heavy and np.allclose(a.mass, b.mass) and a.cost == pytest.approx(b.cost) and a.sqnorm == pytest.approx(b.sqnorm) and a.exact


def test_steps_of_medians_and_penalties(spark):
    """p = 1: cells of one light component are at no distance; l1: the light share moves by t over its squared norm."""
    from joincluster.operators.components import Subspace
    from joincluster.operators.lloyd import shrunk
    from joincluster.plans.spec import Feature

    s = Subspace(Feature("a", "r", "a", "cat"), np.array([6.0, 4.0]), 1.0, heavy=["x"], sqnorm=0.5)
    assert distance_table(s, np.array([[0.0, 1.0], [1.0, 0.0], [0.0, 0.0]]), 1).tolist() == [[2, 0, 1], [0, 2, 1]]
    got = shrunk(s, np.array([[0.4, 0.6]]), np.array([10.0]), Penalty("l1", 4.0))
    grid = np.linspace(0, 1, 2001)
    best = [grid[np.argmin(10 * n * (grid - v) ** 2 + 4 * grid)] for n, v in ((1.0, 0.4), (0.5, 0.6))]
    assert np.allclose(got[0], best, atol=1e-3)


def test_ties_of_distances_go_to_the_smallest_cluster():
    from joincluster.operators.lloyd import _sweep

    assert 0.1 + 0.2 > 0.3  # equal but for the last bit
    tables = [np.array([[0.1, 0.3, 0.3]]), np.array([[0.2, 0.0, 1e-12]])]
    a, d = _sweep(np.zeros((1, 2), int), np.ones(1), tables)
    assert a.tolist() == [0] and d.tolist() == [0.1 + 0.2]
    a, _ = _sweep(np.zeros((1, 2), int), np.ones(1), [np.array([[1.0, 1 - 1e-8]]), np.zeros((1, 2))])
    assert a.tolist() == [1]  # a difference that counts


@pytest.mark.parametrize("name", ["toy", "w_m", "w_c", "w_f", "w_y"])
def test_the_counted_matrix_is_the_matrix(spark, toy, name):
    q = toy if name == "toy" else wl.ALL[name](spark, SF)
    q = replace(q, relations={k: d.withColumn("__w", F.lit(2)) if k == q.root else d for k, d in q.relations.items()})
    fs = [f.name for f in q.features]
    got = baseline.counted(q)
    want = baseline.materialise(q).groupBy(*fs).agg(F.sum("w").alias("w"))
    assert rows(got.select(*fs, "w")) == rows(want)


def test_the_counted_matrix_never_holds_the_joined_rows(spark):
    """1,000 x 1,000 equal rows: every join under the plan yields one row."""
    r = spark.range(1000).select(F.lit(1).alias("b"), F.lit("x").alias("a"))
    s = spark.range(1000).select(F.lit(1).alias("b"), F.lit("y").alias("c"))
    q = FeatureQuery("big", {"r": r, "s": s}, [Edge("r", "s", (("b", "b"),))], [Feature("a", "r", "a"), Feature("c", "s", "c")], "r")
    x = baseline.counted(q)
    assert rows(x) == [("x", "y", 1_000_000)]
    plan = x._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Aggregate", plan.index("Join")) > 0


def test_kmeans_on_the_bag_reads_every_row(spark):
    """As many clusters as different rows: no cost. Dimensions follow the rows' weights, then names."""
    x = wl.w_m(spark, SF).only("status", "region")
    cost, _ = baseline.standard_kmeans(x, 40, build=baseline.counted)
    assert cost < 1e-6
    _, model = baseline.vectors(x, bag := baseline.counted(x))
    want = [r["status"] for r in bag.groupBy("status").agg(F.sum("w").alias("w")).orderBy(F.desc("w"), "status").collect()]
    assert list(model.stages[0].labels) == want
    centers = baseline.sample_kmeans(x, 3, 0.2).collect()
    assert [r["cluster"] for r in centers] == [0, 1, 2] and all(len(r["center"]) == 3 + len(model.stages[1].labels) for r in centers)


def test_a_drawn_bag_is_a_sample_of_its_rows(spark):
    x = spark.range(50).select(F.col("id").cast("string").alias("a"), (F.col("id") * 1000).alias("w"))
    got = {r["a"]: r["w"] for r in baseline.drawn(x, 0.2).collect()}
    assert got == {r["a"]: r["w"] for r in baseline.drawn(x.repartition(7), 0.2).collect()}
    assert "0" not in got and all(0 < w <= 1000 * int(a) for a, w in got.items())
    total = sum(r["w"] for r in x.collect())
    assert abs(sum(got.values()) - 0.2 * total) < 6 * (0.16 * total) ** 0.5


def test_bounds_and_widths_read_their_tables(spark, tmp_path):
    """Other lines give other rows: 3 lines of quantities 1, 2, 2 have their mean at 5/3 and one whole center at 1."""
    from joincluster import queries
    from joincluster.operators import bounds

    li = wl.tables(spark, SF, "lineitem")[0].limit(3).coalesce(1).select("*", F.monotonically_increasing_id().alias("i"))
    li = li.withColumns({"l_quantity": F.when(F.col("i") == 0, 1.0).otherwise(2.0), "l_discount": F.lit(0.05), "l_returnflag": F.lit("R"), "l_linestatus": F.lit("F")})
    li.withColumn("l_orderkey", F.when(F.col("i") > 0, F.col("l_orderkey"))).drop("i").write.parquet(str(tmp_path / "lineitem.parquet"))
    for t in ("orders", "part", "supplier"):
        wl.tables(spark, SF, t)[0].limit(1).write.parquet(str(tmp_path / f"{t}.parquet"))
    got = {(r["kind"], r["b"]): (r["lines"], r["a"], r["bound"]) for r in queries.QUERIES["bounds_table"](spark, str(tmp_path)).collect()}
    assert got[("approx", 1.0)] == ("RF", 3.0, round(bounds.approx_bound(3, 1), 9)) and got[("lower", 2.0)][1] == 2.0
    got = {r["shape"]: (r["longest"], r["most_rows"]) for r in queries.QUERIES["widths"](spark, str(tmp_path)).collect()}
    assert got == {"triangle": (3, 5.0), "star": (2, 2.0), "path": (3, 9.0)}


@pytest.mark.parametrize("name", ["w_m", "w_c", "w_f"])
def test_induced_cost_is_that_of_the_rows(spark, name):
    """Row by row: each goes to its cell's cluster. Raw values hang from the root where no join is a left one."""
    q = wl.ALL[name](spark, SF)
    q = q.only(*[f.name for f in q.features if f.name in ("priority", "suppkey", "segment", "qty", "units", "class", "no_oil")])
    m = Calibration(q).marginals().persist()
    comps = solve(q, m, 3)
    cells = grid_weights(q, comps).persist()
    c = grid_lloyd(cells, comps, seed_top(cells, comps, 3), max_iter=2).centroids
    x = objective.row_distances(baseline.counted(q), q, c, m).withColumns({f"c_{s.name}": s.encode(F.col(s.name)) for s in comps.subspaces})
    from joincluster.operators.lloyd import nearest

    near = nearest(cells, c).drop("w", "d")
    want = x.join(near, [f"c_{s.name}" for s in comps.subspaces]).agg(F.sum(F.col("w") * F.element_at("ds", F.col("cluster") + 1))).first()[0]
    assert objective.induced_cost(q, comps, c, m) == pytest.approx(want, rel=1e-9)
    if name == "w_m":
        assert objective._rooted(q, "suppkey").root == "supplier"
