"""Hand-made cases, agreement of all indices, invariants and measures."""

import math
import random

import pytest
from pyspark.sql import functions as F

from density_peaks import advise, assign, baselines, catalog, cost, decide, exact, grid, iterate, metrics, pipeline, points, quality, rank, schemas
from density_peaks.index import chist, descent, nlist, quadtree, rnlist, rtree, tree_query
from density_peaks.schemas import PLANE, Space


def plane(spark, xy):
    return spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(xy)], "id long, x double, y double")


def line(spark, xs):
    return plane(spark, [(x, 0.0) for x in xs])


def rows(dep):
    return {r.id: (r.rho, None if r.delta is None else round(r.delta, 9), r.mu) for r in dep.collect()}


def packed(spark, dists):
    return spark.createDataFrame([(0, list(range(1, len(dists) + 1)), dists)], "id long, nbrs array<long>, dists array<double>")


@pytest.mark.parametrize("d_c,rho,reads", [(0.25, 4, 0), (0.21, 3, 2), (0.32, 4, 0), (0.08, 1, 2), (5.0, 6, 0), (0.16, 2, 0)])
def test_histogram_of_one_object(spark, d_c, rho, reads):
    lists = packed(spark, [0.05, 0.10, 0.20, 0.22, 0.40, 0.90])
    hist = chist.build(lists, 0.16)
    assert chist.dense(hist).first()["cum"] == [2, 4, 5, 5, 5, 6]
    assert chist.rho(hist, lists, d_c, 0.16).first()["rho"] == rho
    assert chist.list_reads(hist, d_c, 0.16).first()["entries"] == reads


def test_histogram_edges_in_floating_point(spark):
    w = 0.1
    dists = sorted([k * w for k in range(1, 40)] + [math.nextafter(k * w, 9) for k in range(1, 40)] + [math.nextafter(k * w, 0) for k in range(1, 40)])
    lists = packed(spark, dists)
    hist = iterate.cut(chist.build(lists, w))
    for d in [0.1, 0.3, 0.7, 3 * w, 6 * w, 0.35, math.nextafter(0.3, 1)]:
        assert chist.rho(hist, lists, d, w).first()["rho"] == sum(x < d for x in dists), d
        assert nlist.rho(lists, d).first()["rho"] == sum(x < d for x in dists)


def test_points_on_a_line(spark):
    dep = exact.run(line(spark, [0, 1, 2, 10]), 1.5)
    assert rows(dep) == {0: (1, 1.0, 1), 1: (2, 9.0, None), 2: (1, 1.0, 1), 3: (0, 8.0, 2)}
    found = {r.id: (r.cluster, r.depth, r.is_center) for r in assign.assign(dep, decide.centers(dep, 2, 5.0)).collect()}
    assert found == {0: (1, 1, False), 1: (1, 0, True), 2: (1, 1, False), 3: (1, 2, False)}


def test_two_equal_points_of_density(spark):
    p = line(spark, [0, 5])
    assert rows(exact.run(p, 1.0)) == {0: (0, 5.0, None), 1: (0, 5.0, None)}
    assert rows(exact.run(p, 1.0, tie="by_id")) == {0: (0, 5.0, None), 1: (0, 5.0, 0)}


def test_equal_distances_take_the_smaller_id(spark):
    p = line(spark, [0, -1, 1, -1.2, 1.2, -1.4, 1.4])
    for kind in ("brute", "list", "rtree", "quadtree"):
        assert rows(pipeline.dependent(pipeline.build(p, kind, capacity=2), 0.5))[0][2] == 1, kind


@pytest.mark.parametrize("kind", ["brute", "list", "ch", "quadtree", "rtree"])
def test_degenerate_sets(spark, kind):
    one = pipeline.dependent(pipeline.build(line(spark, [3]), kind, w=1.0), 1.0)
    assert rows(one) == {0: (0, 0.0, None)}
    same = pipeline.dependent(pipeline.build(line(spark, [2] * 10), kind, w=1.0, capacity=4), 1.0)
    assert rows(same) == {i: (9, 0.0, None) for i in range(10)}


def test_duplicates_above_capacity(spark):
    tree = quadtree.build(line(spark, [1] * 100), 8, max_depth=6)
    assert tree.height == 6 and tree.nodes.where("is_leaf").first()["nc"] == 100


def test_bad_points_are_rejected(spark):
    bad = spark.createDataFrame([(1, 1.0, float("nan")), (2, 1.0, 1.0)], "id long, x double, y double")
    with pytest.raises(schemas.InvalidPoints, match="y"):
        schemas.points(bad, check=True)
    with pytest.raises(schemas.InvalidPoints, match="x"):
        schemas.points(spark.createDataFrame([(1, None, 1.0)], "id long, x double, y double"), check=True)


@pytest.fixture(scope="module")
def cloud(spark):
    rng = random.Random(4)
    xy = [(rng.gauss(cx, 3), rng.gauss(cy, 3)) for cx, cy in ((0, 0), (20, 5), (5, 25)) for _ in range(60)] + [(rng.uniform(-10, 40), rng.uniform(-10, 40)) for _ in range(20)]
    return iterate.cut(plane(spark, xy + xy[:5]))


@pytest.mark.parametrize("tie", ["strict", "by_id"])
@pytest.mark.parametrize("d_c", [0.5, 4.0, 200.0])
def test_indices_agree(cloud, tie, d_c):
    want = rows(exact.run(cloud, d_c, tie=tie))
    for kind, how in (("list", {}), ("ch", {"w": 2.0}), ("quadtree", {"capacity": 4}), ("rtree", {"capacity": 4})):
        assert rows(pipeline.dependent(pipeline.build(cloud, kind, **how), d_c, tie)) == want, kind


@pytest.mark.parametrize("metric", ["manhattan", "chebyshev"])
def test_other_metrics(cloud, metric):
    space = Space(metric=metric)
    tree = rtree.build(cloud, 8, space=space)
    r = iterate.cut(tree_query.rho(tree, 4.0))
    want = rows(exact.run(cloud, 4.0, space))
    assert rows(tree_query.delta(tree, r)) == want
    assert {x.id: x.rho for x in grid.rho(cloud, 4.0, space).collect()} == {i: v[0] for i, v in want.items()}
    assert {x.id: x.rho for x in grid.rho_contained(cloud, 4.0, 3, space).collect()} == {i: v[0] for i, v in want.items()}


def test_cut_lists_and_repair(cloud):
    want = rows(exact.run(cloud, 3.0))
    full = nlist.build(cloud)
    for tau in (3.0, 10.0):
        rn = iterate.cut(rnlist.build(cloud, tau))
        assert {tuple(r) for r in nlist.long_form(rn).collect()} == {tuple(r) for r in nlist.long_form(rnlist.from_nlist(full, tau)).collect()}
        r = iterate.cut(rnlist.rho(rn, 3.0, tau))
        assert r.where("not is_exact").count() == 0
        dep = iterate.cut(rnlist.delta(rn, r, rnlist.diagonal(cloud)))
        assert all(want[x.id][2] is None or want[x.id][1] >= tau for x in dep.where("is_capped").collect())
        assert rows(rnlist.repair(dep, rtree.build(cloud, 8))) == want
    assert rnlist.rho(rn, 50.0, 10.0).where("is_exact").count() == 0


def test_local_descent_and_ablation(cloud):
    tree = rtree.build(cloud, 4)
    r = iterate.cut(tree_query.rho(tree, 4.0))
    want = {i: (v[1], v[2]) for i, v in rows(tree_query.delta(tree, r)).items() if v[2] is not None}
    visits = {}
    for order in ("stack", "heap"):
        got = tree_query.delta_local(tree, r, order=order).collect()
        assert {x.id: (round(x.delta, 9), x.mu) for x in got if x.mu is not None} == want
        visits[order] = sum(x.visited for x in got)
    assert visits["heap"] <= visits["stack"]
    base, loose = {}, {}
    tree_query.delta(tree, r, stats=base)
    assert rows(tree_query.delta(tree, r, density_prune=False, distance_prune=False, stats=loose)) == rows(tree_query.delta(tree, r))
    assert base["distances"] < loose["distances"] and base["node_pairs"] < loose["node_pairs"]


def test_insert_equals_build(cloud):
    late = F.col("id") % 3 == 0
    grown = quadtree.insert(quadtree.build(cloud.where(~late), 4), cloud.where(late))
    assert grown.nodes.where("parent is null").first()["nc"] == cloud.count()
    assert grown.leaf_points.count() == cloud.count()
    want = rows(exact.run(cloud, 4.0))
    r = iterate.cut(tree_query.rho(grown, 4.0))
    assert rows(tree_query.delta(grown, r)) == want


def test_invariants(cloud):
    tree = rtree.build(cloud, 8)
    n = cloud.count()
    assert tree.nodes.where("is_leaf").agg(F.sum("nc")).first()[0] == n
    sweep = nlist.rho_sweep(nlist.build(cloud), [1.0, 2.0, 5.0]).groupBy("id").agg(F.array_sort(F.collect_list(F.struct("d_c", "rho"))).alias("r")).collect()
    assert all(a.rho <= b.rho for x in sweep for a, b in zip(x.r, x.r[1:], strict=False))
    dep = pipeline.dependent(pipeline.build(cloud, "rtree"), 4.0, "by_id")
    rho = {x.id: x.rho for x in dep.collect()}
    assert all(x.mu is None or (rho[x.mu], -x.mu) > (x.rho, -x.id) for x in dep.collect())
    assert dep.where("is_top").count() == 1
    box = tree.nodes.where("is_leaf").crossJoin(cloud.withColumnRenamed("id", "pid"))
    inside = box.join(tree.leaf_points.select(F.col("leaf").alias("node"), F.col("x").alias("a"), F.col("y").alias("b")), "node")
    d = metrics.dist([F.col("x"), F.col("y")], [F.col("a"), F.col("b")], PLANE)
    lo, hi = metrics.d_min([F.col("x"), F.col("y")], tree.lo(), tree.hi(), PLANE), metrics.d_max([F.col("x"), F.col("y")], tree.lo(), tree.hi(), PLANE)
    assert inside.where((lo > d) | (d > hi)).count() == 0


def test_nearest(cloud):
    pairs = exact.pairs(cloud).collect()
    by = {}
    for p in sorted(pairs, key=lambda p: (p.dist, p.nbr)):
        by.setdefault(p.id, []).append(p.nbr)
    got = {}
    for r in tree_query.nearest(rtree.build(cloud, 4), 3).orderBy("id", "pos").collect():
        got.setdefault(r.id, []).append(r.nbr)
    assert got == {i: v[:3] for i, v in by.items()}


def test_pair_scores(spark):
    g = spark.createDataFrame([(i, i // 3) for i in range(6)], "id long, cluster long")
    c = spark.createDataFrame([(i, 0 if i < 4 else 1) for i in range(6)], "id long, cluster long")
    s = quality.pair_scores(g, c).first()
    assert (int(s.tp), int(s.fp), int(s.fn)) == (4, 3, 2) and abs(s.f1 - 2 * 4 / 13) < 1e-12
    alone = spark.createDataFrame([(i, i) for i in range(6)], "id long, cluster long")
    assert quality.pair_scores(g, alone).first().precision is None
    assert quality.pair_scores(g, g).first().f1 == 1.0


def test_baselines(spark):
    p = line(spark, [0, 1, 2, 3, 10, 11, 12, 30, 13.5])
    found = {r.id: (r.cluster, r.is_core) for r in baselines.dbscan(p, 1.2, 3).collect()}
    assert found[1] == (1, True) and found[0] == (1, False) and found[7] == (None, False) and found[5] == (5, True) and found[8] == (None, False)
    assert {r.id: r.cluster for r in baselines.linkage_cut(p, 1.6).collect()} == {0: 0, 1: 0, 2: 0, 3: 0, 4: 4, 5: 4, 6: 4, 8: 4, 7: 7}
    assert baselines.kmeans(p, 3).select("cluster").distinct().count() == 3


@pytest.mark.parametrize("shuffled", [False, True])
def test_long_chain_of_links(spark, monkeypatch, shuffled):
    import random

    names = list(range(1001))
    if shuffled:
        random.Random(7).shuffle(names)
    cuts, plain = [], iterate.cut
    monkeypatch.setattr(iterate, "cut", lambda df: cuts.append(1) or plain(df))
    links = spark.createDataFrame([(names[i], names[i + 1]) for i in range(1000)], "a long, b long")
    got = iterate.components(links, spark.range(1003))
    assert {r.id: r.label for r in got.collect()} == {i: 0 if i <= 1000 else i for i in range(1003)}
    assert len(cuts) < 20


def test_components_of_random_links(spark):
    import random

    rng = random.Random(3)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)]
    up = list(range(300))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in pairs:
        up[max(root(a), root(b))] = min(root(a), root(b))
    got = iterate.components(spark.createDataFrame(pairs, "a long, b long"), spark.range(300))
    assert {r.id: r.label for r in got.collect()} == {i: root(i) for i in range(300)}


@pytest.mark.parametrize("kind", ["quadtree", "rtree"])
@pytest.mark.parametrize("tie", ["strict", "by_id"])
def test_large_node_tables_take_the_frontier(cloud, monkeypatch, kind, tie):
    make = {"quadtree": lambda: quadtree.build(cloud, 8), "rtree": lambda: rtree.build(cloud, 8)}[kind]
    one = make()
    rho = tree_query.rho(one, 4.0).collect()
    want = tree_query.delta(one, tree_query.rho(one, 4.0), tie).collect()
    near = tree_query.nearest(one, 3).collect()
    monkeypatch.setattr(descent, "MOST_NODES", 0)
    monkeypatch.setattr(quadtree, "MOST_KEYS", 0)
    two = make()
    assert two.arrays() is None and one.n_nodes == two.n_nodes and one.height == two.height
    assert {tuple(r[c] for c in sorted(r.asDict())) for r in one.nodes.collect()} == {tuple(r[c] for c in sorted(r.asDict())) for r in two.nodes.collect()}
    assert set(tree_query.rho(two, 4.0).collect()) == set(rho)
    assert set(tree_query.delta(two, tree_query.rho(two, 4.0), tie).collect()) == set(want)
    assert set(tree_query.nearest(two, 3).collect()) == set(near)


def test_packed_histograms_equal_searches(cloud):
    lists = nlist.build(cloud)
    for w, d_c in ((1.5, 4.0), (2.0, 4.0), (4.0, 1.0), (4.0, 5000.0), (0.1, 0.3), (0.7, 2.1)):
        assert rows_rho(chist.rho_packed(chist.packed(lists, w), d_c, w)) == rows_rho(nlist.rho(lists, d_c)) == rows_rho(chist.rho(chist.build(lists, w), lists, d_c, w))
    assert chist.suggest_w(lists) > 0


def test_long_lists_and_hot_cells(cloud, monkeypatch):
    lists, long = rnlist.build(cloud, 8.0), rnlist.long(cloud, 8.0)
    rho = nlist.rho(lists, 4.0)
    assert rows_rho(nlist.rho_long(long, cloud, 4.0)) == rows_rho(rho)
    cap = rnlist.diagonal(cloud)
    assert set(nlist.delta_long(long, rho, "by_id", cap).collect()) == set(rnlist.delta(lists, rho, cap, "by_id").collect())
    assert set(grid.eps_join(cloud, cloud, 8.0, hot=2).collect()) == set(grid.eps_join(cloud, cloud, 8.0).collect())
    monkeypatch.setattr(nlist, "MOST_PACKED", 3)
    with pytest.raises(ValueError):
        rnlist.build(cloud, 8.0)


@pytest.mark.parametrize("kind", ["quadtree", "rtree"])
def test_no_points(spark, kind):
    none = spark.createDataFrame([], "id long, x double, y double, rho string, leaf int")
    tree = quadtree.build(none) if kind == "quadtree" else rtree.build(none)
    rho = tree_query.rho(tree, 1.0)
    assert rho.count() == 0 and tree_query.delta(tree, rho).count() == 0 and tree_query.nearest(tree, 2).count() == 0


def test_columns_whose_names_clash(spark, cloud):
    more = cloud.select("*", *[F.lit("extra").alias(c) for c in ("rho", "nbr", "dist", "leaf", "node", "key", "slice", "r", "salt", "delta", "mu", "label")])
    for kind in ("brute", "list", "quadtree", "rtree"):
        assert set(pipeline.cluster(more, 4.0, kind, k=3, tie="by_id").collect()) == set(pipeline.cluster(cloud, 4.0, kind, k=3, tie="by_id").collect())


def test_rank_and_catalog(spark, cloud, tmp_path):
    got = rank.global_rank(cloud, [F.col("x"), F.col("id")]).collect()
    order = sorted(got, key=lambda r: (r.x, r.id))
    assert [r["rank"] for r in order] == list(range(len(order)))
    tree = rtree.build(cloud, 8)
    catalog.save_tree(tree, str(tmp_path / "t"))
    again = catalog.load_tree(spark, str(tmp_path / "t"))
    assert rows_rho(tree_query.rho(again, 4.0)) == rows_rho(tree_query.rho(tree, 4.0))
    lists = nlist.build(cloud)
    catalog.save_list(lists, str(tmp_path / "l"), tau=None)
    assert rows_rho(nlist.rho(catalog.load_list(spark, str(tmp_path / "l")), 4.0)) == rows_rho(nlist.rho(lists, 4.0))
    assert catalog.meta(spark, str(tmp_path / "l"))["kind"] == "list"
    assert cost.stored_bytes(spark, str(tmp_path / "l")) > 0


def rows_rho(df):
    return {r.id: r.rho for r in df.collect()}


def test_advice():
    assert advise.choose(5_000, 50, 16e9).index == "ch"
    assert advise.choose(400_000, 1_000, 16e9, exact=False).index == "rn_ch"
    assert advise.choose(400_000, 1_000, 16e9).index == "rtree"
    assert advise.choose(10**12, 100, 1e12, exact=False).index == "rtree"


def test_flagship(spark):
    import __spark_entry__ as e

    got = e.entry(spark)
    assert got.columns == ["id", "cluster", "depth", "is_center"] and got.count() == points.view(spark, "/root/testdata/sf0.001", "P_blob15").count()
    assert set(e.oracle_sql()) <= set(e.queries())
