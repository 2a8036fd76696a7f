"""Worked examples, invariants and plans of the indexing methods."""

import re

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

from cellspace.functions import shapes as sh
from cellspace.functions.curves import hilbert_numbers, morton_numbers
from cellspace.functions.predicate_text import PredicateError, parse_linear_predicate
from cellspace.functions.spaces import CHARGE5, LINE3, covariance, whiten
from cellspace.operators import basins, cells, grid, kdtree, lod, neighbours, polyquery, regress
from cellspace.sources.layout import rows_scanned, write_clustered

EIGHT = [(1, 1, 1), (2, 2, 6), (3, 3, 3), (4, 4, 8), (5, 6, 2), (6, 7, 7), (7, 8, 4), (8, 9, 9)]


@pytest.fixture(scope="module")
def eight(spark):
    df = spark.createDataFrame([(k, float(a), float(b)) for k, a, b in EIGHT], "key long, x0 double, x1 double")
    return kdtree.build_kdtree(df, ["x0", "x1"], 2)


def test_eight_points(eight):
    rows, t = eight
    by = {}
    for r in rows.collect():
        by.setdefault((r.leaf, r.leaf_id), set()).add(r.key)
    assert by == {(0, 1): {1, 3}, (1, 2): {2, 4}, (2, 4): {5, 7}, (3, 5): {6, 8}}
    assert sorted(n[0] for n in kdtree.node_table(2)) == list(range(1, 8)) and kdtree.node_table(2)[-1][4] == 1
    p7 = sh.Polyhedron((sh.HalfSpace((1.0, 1.0), 7.0),))
    got = polyquery.query_polyhedron(rows, t, sh.Polyhedron((sh.HalfSpace((1.0, 1.0), 9.0),)), ["x0", "x1"])
    assert {r.key for r in got.collect()} == {1, 2, 3, 5}
    c = polyquery.poly_cost(t, p7)
    assert (c["partial"], c["outside"]) in {(0, 3), (1, 3)}
    assert [k for k, _ in neighbours.knn_point(rows, t, (5.0, 5.0), ["x0", "x1"], 4)[0]] == [3, 6, 2, 4]
    assert [k for k, _ in neighbours.knn_point(rows, t, (2.0, 2.0), ["x0", "x1"], 4)[0]] == [1, 3, 2, 5]


def test_ties_and_small_tables(spark):
    df = spark.createDataFrame([(k, 1.0, 2.0) for k in range(10)], "key long, x0 double, x1 double")
    rows, t = kdtree.build_kdtree(df, ["x0", "x1"], 2)
    assert t.counts[4:].max() - t.counts[4:].min() <= 1 and t.counts[1] == 10
    q = spark.createDataFrame([(0, 1.0, 2.0)], "key long, x0 double, x1 double")
    assert [r.key for r in neighbours.knn_join(q, rows, t, ["x0", "x1"], 3).orderBy("rank").collect()] == [0, 1, 2]
    assert neighbours.knn_join(q, rows, t, ["x0", "x1"], 50).count() == 10
    empty, te = kdtree.build_kdtree(df.limit(0), ["x0", "x1"], 1)
    assert empty.count() == 0 and te.counts.sum() == 0


def test_layers():
    assert grid.layer_ends(1024, 3, 80_000)[:3] == [1024, 9216, 74752] and grid.layer_ends(64, 3, 5000)[:3] == [64, 576, 4672]


def test_row_numbers_by_range_sort(spark):
    from cellspace.plans.shared import row_numbers

    df = spark.range(5000).selectExpr("id AS key", "pmod(id * 7919, 1000) AS v")
    got = row_numbers(df, ["v", "key"], "at").toPandas().sort_values(["v", "key"])
    assert got["at"].tolist() == list(range(1, 5001))


@pytest.mark.parametrize("method", ["rank", "sketch", "hybrid"])
def test_builds_keep_rows_and_answers(spark, method):
    df = CHARGE5.frame(spark, SF)
    rows, t = kdtree.build_kdtree(df, CHARGE5.cols, 5, method)
    n = t.counts[t.leaves :]
    assert n.sum() == df.count() and (method == "sketch" or n.max() - n.min() <= (1 if method == "rank" else 200))
    p = sh.Union((sh.Polyhedron((sh.HalfSpace((1.0, -1.0, 0, 0.5, 0), 5.0, True),)), sh.box([10, None, None, None, None], [30, None, 12, None, None])))
    want = {r.key for r in df.where(p.column(CHARGE5.cols)).collect()}
    assert {r.key for r in polyquery.query_polyhedron(rows, t, p, CHARGE5.cols).collect()} == want
    everything, nothing = sh.Polyhedron(()), sh.Polyhedron((sh.HalfSpace((1.0, 0, 0, 0, 0), -1e9),))
    assert polyquery.query_polyhedron(rows, t, everything, CHARGE5.cols).count() == df.count()
    assert polyquery.query_polyhedron(rows, t, nothing, CHARGE5.cols).count() == 0


def test_recursion_gives_the_same_leaves(spark):
    df = LINE3.frame(spark, SF)
    a = {r.key: r.leaf for r in kdtree.build_kdtree(df, LINE3.cols, 2)[0].collect()}
    assert a == {r.key: r.leaf for r in kdtree.recursive_leaves(df, LINE3.cols, 2).collect()}


def test_knn_join_equals_brute_force(spark):
    df = LINE3.frame(spark, SF)
    rows, t = kdtree.build_kdtree(df, LINE3.cols, 5)
    q = df.where("key % 97 = 0")
    a = {(r.query_key, r["rank"]): r.key for r in neighbours.knn_join(q, rows, t, LINE3.cols, 8).collect()}
    assert a == {(r.query_key, r["rank"]): r.key for r in neighbours.knn_brute(q, df, LINE3.cols, 8, 100).collect()}


def test_clustered_layout_prunes(spark):
    rows, t = kdtree.build_kdtree(LINE3.frame(spark, SF), LINE3.cols, 6)
    path = write_clustered(rows, ["leaf"], files=8, row_group_bytes=1 << 12)
    q = spark.read.parquet(path).where("leaf BETWEEN 3 AND 5")
    assert "PushedFilters: [IsNotNull(leaf), GreaterThanOrEqual(leaf,3), LessThanOrEqual(leaf,5)]" in q._jdf.queryExecution().toString()
    assert q.count() <= rows_scanned(q) < rows.count() / 2


def test_plans_have_no_cartesian_and_few_shuffles(spark):
    rows, t = kdtree.build_kdtree(LINE3.frame(spark, SF), LINE3.cols, 5)
    plan = polyquery.query_polyhedron(rows, t, sh.box((0, 0, 0), (50, 5, 20)), LINE3.cols)._jdf.queryExecution().toString()
    assert "Exchange" not in plan.split("Physical Plan")[-1] and "Python" not in plan
    join = neighbours.knn_join(rows, rows, t, LINE3.cols, 3)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in join


def test_whitening(spark):
    w, _ = whiten(CHARGE5.frame(spark, SF), CHARGE5.cols)
    _, cov, _ = covariance(w, [f"w{k}" for k in range(5)])
    assert np.allclose(cov, np.diag([1, 1, 1, 1, 0]), atol=1e-6)  # charge = net + tax: rank four


def test_parser():
    p = parse_linear_predicate("not (a + 2*b > 3 or b = 1) and log10(a) < 2", ["a", "b"])
    rng = np.random.default_rng(0)
    import math

    for a, b in rng.integers(1, 300, (200, 2)).tolist() + [[1, 1], [1, 0]]:
        want = not (a + 2 * b > 3 or b == 1) and math.log10(a) < 2
        got = False
        for part, rest in zip(p.shape.parts, p.residuals, strict=True):
            lin = all((np.dot(f.w, (a, b)) < f.b if f.strict else np.dot(f.w, (a, b)) <= f.b) for f in part.faces)
            got |= lin and (rest is None or math.log10(a) < 2)
        assert got == want
    for bad in ("a <", "c < 1", "a < 1; drop", "(a < 1", "a / 0 < 1", "a"):
        with pytest.raises(PredicateError):
            parse_linear_predicate(bad, ["a", "b"])


def test_polynomials():
    g = np.array([(a, b) for a in range(5) for b in range(5)], float) / 4
    y = 1 + 2 * g[:, 0] - g[:, 1] + 3 * g[:, 0] ** 2
    q = np.array([0.3, 0.6])
    truth = 1 + 2 * q[0] - q[1] + 3 * q[0] ** 2
    assert abs(regress.local_fit(g - q, y, 2)[0] - truth) < 1e-9 and abs(regress.local_fit(g - q, y, 1)[0] - truth) > 1e-3
    assert regress.local_fit(np.zeros((4, 2)), np.array([1.0, 2, 3, 4]), 2) == (2.5, 0)
    with pytest.raises(ValueError):
        regress.knn_regress(None, None, ["x0", "x1"], "y", 2, 6)


def test_basins(spark):
    c = spark.createDataFrame([(1, 5.0), (2, 3.0), (3, 4.0), (4, 1.0)], "cell_tag long, density double")
    e = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (2, 4)], "src long, dst long")
    t = basins.basin_tree(c, e)
    assert {r.cell_tag: r.parent_tag for r in t.collect()} == {1: 1, 2: 1, 3: 3, 4: 3}
    assert {r.cell_tag: r.cluster for r in basins.basin_clusters(t).collect()} == {1: 1, 2: 1, 3: 3, 4: 3}


def test_witness_edges_are_true_borders():
    rng = np.random.default_rng(3)
    seeds, rows = rng.random((25, 2)), rng.random((20_000, 2))
    a, b, _ = cells.two_nearest(rows, seeds)
    seen = {(int(min(i, j)), int(max(i, j))) for i, j in zip(a, b, strict=True)}
    assert seen <= cells.delaunay_2d(seeds) and len(seen) > 40
    area = [cells.polygon_area(p) for p in cells.cell_polygons(seeds, (0, 0), (1, 1))]
    assert abs(sum(area) - 1) < 1e-9
    tree = cells.seed_tree(seeds)
    assert cells.tree_nearest(tree, seeds, rows[:200]).tolist() == a[:200].tolist()


def test_curves():
    q = np.array([(a, b) for a in range(8) for b in range(8)])
    h = hilbert_numbers(q, 3)
    assert sorted(h) == list(range(64)) and sorted(morton_numbers(q, 3)) == list(range(64))
    path = q[np.argsort(h)]
    assert (np.abs(np.diff(path, axis=0)).sum(1) == 1).all()


def test_cache_and_source(spark):
    g = grid.build_layered_grid(LINE3.frame(spark, SF), LINE3.cols, 64)
    s = lod.SceneSource(g)
    wide = lod.initial_view(g)
    s.show(wide).result()
    assert len(s.poll()) >= 64 and s.poll() is None
    small = lod.View(tuple(np.array(g.lo) + 1), tuple(np.array(g.hi) - 1), 10)
    s.show(small).result()
    s.show(wide).result()
    assert s.cache.hits == 2 and s.cache.misses == 1
    s.close()


def test_samples_are_uniform(spark):
    g = grid.build_layered_grid(LINE3.frame(spark, SF), LINE3.cols, 64)
    got = grid.sample_box(g, g.lo, g.hi, 500)
    assert got.count() >= 500 and max(grid.ks_distance(got, g.rows, c) for c in g.cols) < 0.08
    assert grid.sample_box(g, g.lo, g.hi, 100, trim=True).count() == 100
    assert grid.sample_box(g, g.lo, [v - 1e9 for v in g.lo], 5).count() == 0


def test_every_query_has_a_name_of_ours():
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and all(re.fullmatch(r"[A-Za-z0-9_]+", n) for n in q) and len(q) > 120


def test_camera_views_get_their_points(spark):
    from pyspark.sql import functions as F

    from cellspace.workloads.streams import camera_stream

    got = {r.request_id: r.points for r in camera_stream(spark, SF).collect()}
    events = spark.read.parquet(f"{SF}/events.parquet")
    newest = {r.e for r in events.groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("e")).collect()}
    assert newest <= set(got)
    lines = spark.read.parquet(f"{SF}/lineitem.parquet").count()
    assert sum(n >= 20 for n in got.values()) > 0.8 * len(got) and max(got.values()) <= lines


# --- exact builds, joins and fits of many ----------------------------------------------------------------------
def _points(spark, n, d, seed=0, ties=False):
    rng = np.random.default_rng(seed)
    x = rng.standard_normal((n, d))
    x = x.round(1) if ties else x
    cols = [f"x{k}" for k in range(d)]
    return spark.createDataFrame([(int(i), *map(float, r)) for i, r in enumerate(x)], "key long, " + ", ".join(f"{c} double" for c in cols)), x, cols


def _plain_leaves(x, levels):
    node = np.ones(len(x), int)
    for level in range(levels):
        for n in np.unique(node):
            own = np.flatnonzero(node == n)
            order = own[np.lexsort((own, x[own, level % x.shape[1]]))]
            node[order[: -(-len(own) // 2)]], node[order[-(-len(own) // 2) :]] = 2 * n, 2 * n + 1
    return node - (1 << levels)


@pytest.mark.parametrize("ties", [False, True])
def test_exact_build_by_middle_rows(spark, ties):
    df, x, cols = _points(spark, 3000, 3, 1, ties)
    want = _plain_leaves(x, 6)
    for node_rows in (10**6, 400):
        idx, tree = kdtree._build_exact(df, cols, 6, 3000, "key", node_rows)
        got = np.empty(3000, int)
        for r in idx.select("key", "leaf", "leaf_id").collect():
            got[r.key] = r.leaf
            assert r.leaf_id == kdtree.postorder_leaf(r.leaf)
        assert (got == want).all() and tree.counts[1] == 3000


@pytest.mark.parametrize("rule", ["widest", "max_variance"])
def test_chosen_axes_by_middle_rows(spark, rule):
    df, x, cols = _points(spark, 3000, 3, 1, True)
    spread, node, axes = (np.ptp if rule == "widest" else np.var), np.ones(3000, int), {}
    for _ in range(5):
        for n in np.unique(node):
            own = np.flatnonzero(node == n)
            axes[int(n)] = int(np.argmax([spread(x[own, k]) for k in range(3)]))
            order = own[np.lexsort((own, x[own, axes[int(n)]]))]
            node[order[: -(-len(own) // 2)]], node[order[-(-len(own) // 2) :]] = 2 * n, 2 * n + 1
    for write in (True, False):
        idx, tree = kdtree.build_kdtree(df, cols, 5, "rank", rule, write=write)
        assert {r.key: r.leaf for r in idx.collect()} == dict(enumerate((node - 32).tolist()))
        assert {n: int(tree.axes[n]) for n in axes} == axes


def test_comparing_builds_writes_no_rows(spark, monkeypatch):
    """Five builds wrote 19 copies of the table."""
    from cellspace.workloads import QUERIES, base

    rows, written = CHARGE5.frame(spark, SF).count(), []

    def staged(df, tag, was=kdtree.staged):
        out = was(df, tag)
        written.append(out.count())
        return out

    monkeypatch.setattr(base, "_KEPT", {})
    monkeypatch.setattr(kdtree, "NODE_ROWS", 100)
    monkeypatch.setattr(kdtree, "staged", staged)
    got = {(r.method, r.axis_rule): r for r in QUERIES["W_kdtree_methods"](spark, SF).collect()}
    assert sum(written) < rows
    assert len(got) == 5 and all(r.most - r.least <= 1 for (m, _), r in got.items() if m == "rank")


def test_regions_fill_the_root(spark):
    df, x, cols = _points(spark, 900, 3, 2, True)
    idx, tree = kdtree.build_kdtree(df, cols, 5)
    lo, hi = tree.region_lo[tree.leaves :], tree.region_hi[tree.leaves :]
    assert np.isclose((hi - lo).prod(1).sum(), (tree.hi[1] - tree.lo[1]).prod())
    some = tree.counts[tree.leaves :] > 0
    assert (lo[some] <= tree.lo[tree.leaves :][some]).all() and (hi[some] >= tree.hi[tree.leaves :][some]).all()
    pts = np.random.default_rng(3).uniform(tree.lo[1], tree.hi[1], (200, 3))
    leaf = tree.locate(pts)
    assert ((lo[leaf] <= pts) & (pts <= hi[leaf])).all()


@pytest.mark.parametrize("held", [64_000_000, 0])
def test_knn_join_equals_all_pairs(spark, held, monkeypatch):
    from cellspace.operators import neighbours

    monkeypatch.setattr(neighbours, "HELD_BYTES", held)
    df, x, cols = _points(spark, 700, 3, 4, True)
    q, y, _ = _points(spark, 90, 3, 5, True)
    idx, tree = kdtree.build_kdtree(df.withColumn("extra", F.col("key") * 2), cols, 4)
    d2 = ((y[:, None] - x[None]) ** 2).sum(2)
    for k in (1, 7, 60):
        got = {}
        for r in neighbours.knn_join(q, idx, tree, cols, k, carry=["extra", "x0"]).collect():
            assert r.extra == 2 * r.key and r.x0 == x[r.key, 0]
            got.setdefault(r.query_key, []).append((r["rank"], r.key))
        for i in range(90):
            near = neighbours.distances(y[i : i + 1], x)[0]
            assert [key for _, key in sorted(got[i])] == np.lexsort((np.arange(700), near))[:k].tolist()
    few = neighbours.knn_join(q.limit(3), *kdtree.build_kdtree(df.limit(4), cols, 1), cols, 10)
    assert few.groupBy("query_key").count().where("count = 4").count() == 3
    assert np.isfinite(d2).all()


def test_boundary_rule_is_near_but_not_beyond_the_exact(spark):
    from cellspace.operators import neighbours

    df, x, cols = _points(spark, 4096, 5, 6)
    held = neighbours.hold(*kdtree.build_kdtree(df, cols, 6), cols)
    pts = np.random.default_rng(7).standard_normal((60, 5))
    right, wrong, leaves = neighbours.bound_recall(held, pts, 10, "box")
    assert right == 1 and wrong == 0
    right, wrong, _ = neighbours.bound_recall(held, pts, 10, "boundary_points")
    assert 0.9 <= right <= 1


@pytest.mark.parametrize("held", [64_000_000, 0])
def test_rules_ask_for_every_row(spark, held, monkeypatch):
    """Sums of both rules over all rows and more, held or not, as one point after the other gives them."""
    from cellspace.operators import neighbours

    df, x, cols = _points(spark, 1500, 3, 11)
    idx, tree = kdtree.build_kdtree(df, cols, 5)
    index = neighbours.hold(idx, tree, cols)
    monkeypatch.setattr(neighbours, "HELD_BYTES", held)
    got = {r["rule"]: r for r in neighbours.rule_recall(idx, idx, tree, cols, 10).collect()}
    for rule in ("box", "boundary_points"):
        right, wrong, leaves = neighbours.bound_recall(index, x, 10, rule)
        r = got[rule]
        assert (r["queries"], r["truth"], r["wrong"]) == (1500, 15_000, wrong)
        assert abs(r["found"] / r["truth"] - right) < 1e-9 and abs(r["leaves"] / r["queries"] - leaves) < 1e-9


def test_pairs_of_many_coordinates(monkeypatch):
    """The matrix product leaves out no pair, far from the origin too, and all distances aren't made."""
    from cellspace.operators import neighbours

    rng = np.random.default_rng(12)
    x, y = rng.standard_normal((2, 300, 39)) + 1000
    y[:40] = x[:40]
    d2 = neighbours.distances(x, y)
    bound = np.sort(d2, axis=1)[:, 6]
    bound[:20] = 0
    want = np.nonzero(d2 <= bound[:, None])
    monkeypatch.setattr(neighbours, "distances", None)
    i, j, d = neighbours.pairs_within(x, y, bound)
    assert np.array_equal(i, want[0]) and np.array_equal(j, want[1]) and np.array_equal(d, d2[want])


def test_bound_recall_covers_its_tables(spark):
    import __spark_entry__ as e

    got = e.queries()["W_knn_bound_recall"](spark, SF).collect()
    n = {"doc": spark.read.parquet(f"{SF}/documents.parquet").count(), "lin": spark.read.parquet(f"{SF}/lineitem.parquet").count()}
    assert len(got) == 10 and all(r.queries > n.get(r.space[:3], n["lin"]) for r in got)


def test_fits_of_many_equal_single_ones():
    rng = np.random.default_rng(8)
    x = rng.standard_normal((40, 25, 3))
    y = 1 + x[:, :, 0] * 2 - x[:, :, 1] + 3 * x[:, :, 2] ** 2 + rng.standard_normal((40, 25)) * 0.1
    x[5, :, 1] = 0  # no spread in one direction
    x[6] = x[6, :1]
    for degree in (1, 2):
        est, used = regress.local_fits(x, y, degree)
        for i in range(40):
            e, g = regress.local_fit(x[i], y[i], degree)
            assert abs(e - est[i]) < 1e-6 * (1 + abs(e)) and g == used[i]


def test_errors_in_one_pass(spark, monkeypatch):
    """A pass that writes no neighbours gives the errors of neighbours that are joined and written."""
    import __spark_entry__ as e
    from cellspace.operators import neighbours

    want = {r["method"]: r for r in e.queries()["m_regression_baselines"](spark, SF).collect()}
    with monkeypatch.context() as m:
        m.setattr(neighbours, "knn_join", None)  # neighbours as rows are what filled the disk
        got = {(r["method"], r["setting"]): r for r in e.queries()["W_regression_compare"](spark, SF).collect()}
        shift = {(r["method"], r["setting"]): r for r in e.queries()["W_calibration_shift"](spark, SF).collect()}
    assert len(got) == 16 and len(shift) == 6
    for method, setting in (("average", "k=10"), ("template curve", "20")):
        r = got[method, setting]
        assert r["n"] == want[method]["n"] and all(abs(r[c] - want[method][c]) < 1e-3 for c in ("mae", "rmse", "bias"))
    for method, setting, other in (("linear", "0.0", "k=10"), ("template grid", "0.0", "1000")):
        assert all(abs(shift[method, setting][c] - got[method, other][c]) < 1e-6 * (1 + abs(got[method, other][c])) for c in ("n", "mae", "rmse", "bias", "sigma"))


def test_nearest_template(spark):
    df, x, cols = _points(spark, 300, 3, 9)
    lib = spark.createDataFrame([(i, float(i) * 2, *map(float, v)) for i, v in enumerate(np.random.default_rng(10).standard_normal((50, 3)))], "template_id long, param double, t0 double, t1 double, t2 double")
    t = np.array([[r.t0, r.t1, r.t2] for r in lib.orderBy("template_id").collect()])
    got = {r.query_key: (r.template_id, r.estimate) for r in regress.template_fit(df, lib, cols, 50).collect()}
    want = ((x[:, None] - t[None]) ** 2).sum(2).argmin(1)
    assert all(got[i] == (want[i], 2.0 * want[i]) for i in range(300))


def test_delaunay_spheres_are_empty():
    for d in (2, 3):
        x = np.random.default_rng(d).standard_normal((40, d))
        edges, simplices = cells.delaunay_exact(x)
        for s in simplices:
            p = x[s]
            c = np.linalg.solve(2 * (p[1:] - p[0]), (p[1:] ** 2).sum(1) - (p[0] ** 2).sum())
            r = ((p[0] - c) ** 2).sum()
            assert (((x - c) ** 2).sum(1) >= r * (1 - 1e-9)).all()
        if d == 2:
            assert cells.delaunay_2d(x) <= edges


def test_seed_graph_edges_are_true(spark):
    x = np.random.default_rng(11).standard_normal((60, 3))
    seeds = cells.Seeds(np.arange(1, 61), x, np.arange(60))
    edges, _ = cells.delaunay_exact(x)
    got = {(r.src - 1, r.dst - 1) for r in cells.seed_graph(spark, seeds, ["x0", "x1", "x2"]).collect()}
    assert got <= edges and len(got) > 60


def test_fidelity_measures(spark):
    df, x, cols = _points(spark, 4000, 2, 12)
    fair, low = df.where("key % 4 = 0"), df.where("x0 < 0")
    lo, hi = x.min(0), x.max(0)
    assert grid.chi_square(fair, df, cols, lo, hi)[0] < 3 < 20 < grid.chi_square(low, df, cols, lo, hi)[0]
    a, b = np.sort(x[::4, 0]), np.sort(x[:, 0])
    exact = max(np.abs(np.searchsorted(a, v, "right") / len(a) - np.searchsorted(b, v, "right") / len(b)).max() for v in (a, b))
    assert abs(grid.ks_distance(fair, df, "x0") - exact) < 0.01 and grid.ks_distance(low, df, "x0") > 0.4


def test_batch_samples_equal_single_ones(spark):
    df, x, cols = _points(spark, 5000, 3, 13)
    g = grid.build_layered_grid(df, cols, 64)
    boxes = [(1, [-1.0] * 3, [1.0] * 3, 200), (2, [-9.0] * 3, [9.0] * 3, 50), (3, [0.0] * 3, [0.2] * 3, 500), (4, [50.0] * 3, [60.0] * 3, 5), (5, [1.0] * 3, [-1.0] * 3, 5)]
    got = {}
    for r in grid.sample_boxes(g, grid.requests_frame(spark, boxes), 5).collect():
        got.setdefault(r.request_id, set()).add(r.key)
    for i, lo, hi, n in boxes[:4]:
        assert got.get(i, set()) == {r.key for r in grid.sample_box(g, lo, hi, n).collect()}
    assert 5 not in got


def test_covers_of_many_intervals(spark):
    """Balls, cuts and hulls whose leaves are in hundreds of intervals, as on tables of some million rows."""
    df, x, cols = _points(spark, 6000, 3, 14)
    idx, tree = kdtree.build_kdtree(df, cols, 12)
    ball = sh.polyhedralise_ball((0.1, 0.0, 0.2), 1.0, 4)
    assert len(ball.faces) == 386 and sum(map(len, tree.cover(ball)[:2])) > polyquery.MAX_RANGES
    for p in (ball, sh.Polyhedron((sh.HalfSpace((1.0, 1.0, 1.0), 0.5),)), sh.Polyhedron((sh.HalfSpace((1.0, 0, 0), 0.3, True),))):
        want = {int(k) for k in np.flatnonzero(np.all([x @ np.array(f.w) < f.b if f.strict else x @ np.array(f.w) <= f.b for f in p.faces], 0))}
        got = [r.key for r in polyquery.query_polyhedron(idx, tree, p, cols).select("key").collect()]
        assert len(got) == len(want) and set(got) == want


def test_few_rows_leave_a_bucket(spark):
    """All pairs of a bucket are compared, k of a query leave it."""
    df, x, cols = _points(spark, 1500, 2, 15, True)
    out = neighbours.knn_lsh(df, df, cols, 3, 2.0)
    assert "Join" not in out._jdf.queryExecution().toString().split("CoGroup")[0]
    rng = np.random.default_rng(5)
    rays, shifts = rng.standard_normal((4, 2, 2)), rng.uniform(0, 2.0, (4, 2))
    keys = np.floor((np.einsum("thc,nc->nth", rays, x) + shifts) / 2.0)
    got = {}
    for r in out.collect():
        got.setdefault(r.query_key, []).append((r["rank"], r.key))
    for i in range(0, 1500, 7):
        seen = np.flatnonzero((keys == keys[i]).all(2).any(1))
        near = neighbours.distances(x[i : i + 1], x[seen])[0]
        assert [key for _, key in sorted(got[i])] == seen[np.lexsort((seen, near))[:3]].tolist()
