"""Tables that repeat their rows under other keys: queries whose work grows with the square of equal points, or that refuse many points."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from density_peaks import exact, grid, iterate, pipeline, points, rank, spots, sqltext
from density_peaks.index import descent, nlist, quadtree, rtree, tree_query


@pytest.fixture(scope="module")
def copies(tmp_path_factory):
    at, con = str(tmp_path_factory.mktemp("copies")), duckdb.connect()
    for name, key, step, times in (("part", "p_partkey", 1000, 4), ("events", "event_id", 100_000, 2), ("lineitem", "l_orderkey", 100_000, 2), ("documents", "doc_id", 100_000, 2)):
        con.execute(f"COPY (SELECT {key} + {step} * j AS {key}, * EXCLUDE ({key}) FROM '/root/testdata/sf0.001/{name}.parquet', range({times}) r(j)) TO '{at}/{name}.parquet' (FORMAT parquet)")
    return at


def same_as_sql(spark, at, name):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for f in os.listdir(at):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS FROM '{at}/{f}'")
    df = entry.queries()[name](spark, at)
    flat = lambda rows: sorted((tuple(round(float(v), 6) if isinstance(v, float) else v for v in r) for r in rows), key=repr)
    assert flat(map(tuple, df.collect())) == flat(con.sql(entry.oracle_sql()[name]).select(*[f'"{c}"' for c in df.columns]).fetchall())


def never(*_, **__):
    raise AssertionError("pairs of points became rows of a table")


def once(monkeypatch, module, name):
    """Checks that the function sees no two points of the same place."""
    own = getattr(module, name)

    def seen(pts, *more, **how):
        axes = [c for c in ("x", "y", "z") if c in pts.columns]
        assert pts.groupBy(*axes).count().where("count > 1").isEmpty()
        return own(pts, *more, **how)

    monkeypatch.setattr(module, name, seen)


#: query: what must not happen on the way
PRUNED = {
    "delta_quadtree": lambda m: m.setattr(tree_query, "_search_arrays", never),
    "rho_range_search_part": lambda m: once(m, rtree, "build"),
    "cutoff_clusters": lambda m: m.setattr(nlist, "MOST_POINTS", 0),
    "rtree_three_axes": lambda m: m.setattr(tree_query, "_range", never),
    "pair_scores_tau_docs": lambda m: m.setattr(nlist, "MOST_POINTS", 0),
    "stream_reindex": lambda m: once(m, rtree, "build"),
    "pair_scores_truth_docs": lambda m: m.setattr(nlist, "MOST_POINTS", 0),
    "rho_quadtree_events": lambda m: m.setattr(tree_query, "_range", never),
    "isolated_objects": lambda m: m.setattr(grid, "eps_join", never),
    "dbscan_labels": lambda m: once(m, grid, "eps_join"),
    "delta_no_distance_prune": lambda m: once(m, rtree, "build"),
    "delta_peak_scan": lambda m: once(m, grid, "eps_join"),
    "delta_rtree_stack": lambda m: once(m, rtree, "build"),
    "rho_chebyshev": lambda m: once(m, grid, "eps_join"),
    "rho_grid_part": lambda m: once(m, grid, "eps_join"),
    "rho_grid_salted": lambda m: once(m, grid, "eps_join"),
    "rho_rtree_lineitem": lambda m: once(m, rtree, "build"),
    "assign_clusters": lambda m: m.setattr(nlist, "MOST_POINTS", 0),
    "bisect_udf": lambda m: m.setattr(nlist, "MOST_POINTS", 0),
    "centers_common": lambda m: m.setattr(nlist, "MOST_POINTS", 0),
    "centers_threshold": lambda m: m.setattr(nlist, "MOST_POINTS", 0),
}


@pytest.mark.parametrize("name", PRUNED)
def test_copies_of_rows(spark, copies, monkeypatch, name):
    PRUNED[name](monkeypatch)
    same_as_sql(spark, copies, name)


@pytest.mark.parametrize("tie", ["strict", "by_id"])
@pytest.mark.parametrize("kind", ["quadtree", "rtree"])
def test_spots_answer_for_their_points(spark, monkeypatch, kind, tie):
    xy = [(i % 7 * 1.5, i % 5 * 1.1) for i in range(90)] + [(float(i), i * i / 9.0) for i in range(30)]
    p = iterate.cut(spark.createDataFrame([(3 * i + 1, x, y) for i, (x, y) in enumerate(xy)], "id long, x double, y double"))
    want = set(exact.run(p, 2.0, tie=tie).collect())
    index = pipeline.build(p, kind, capacity=4)
    assert index.parts["tree"].leaf_points.count() == len(set(xy))
    assert set(pipeline.dependent(index, 2.0, tie).collect()) == want
    monkeypatch.setattr(descent, "MOST_SENT", 0)
    assert set(pipeline.dependent(index, 2.0, tie).collect()) == want
    monkeypatch.setattr(descent, "MOST_SENT", 1000)
    monkeypatch.setattr(descent, "BLOCK", 3)
    assert set(pipeline.dependent(index, 2.0, tie).collect()) == want


def test_points_without_a_place_are_not_merged(spark):
    odd = [(1, None, 0.0), (2, None, 0.0), (3, float("nan"), 0.0), (4, float("nan"), 0.0), (5, 1.0, 0.0), (6, 1.0, -0.0)]
    p = spark.createDataFrame(odd, "id long, x double, y double")
    assert {(r.id, r.weight) for r in spots.merge(p).spots.collect()} == {(1, 1), (2, 1), (3, 1), (4, 1), (5, 2)}
    assert {(r.id, r.rho) for r in grid.rho(p, 1.0).collect()} == {(1, 0), (2, 0), (3, 0), (4, 0), (5, 1), (6, 1)}


def test_percentiles_by_the_tree(spark, copies, monkeypatch):
    want = exact.rho(points.view(spark, copies, "P_blob15"), 20.0).agg(F.percentile_approx("rho", [0.25, 0.5, 0.75, 0.99]), F.approx_count_distinct("rho")).first()
    monkeypatch.setattr(grid, "eps_join", never)
    assert tuple(entry.queries()["density_percentiles"](spark, copies).first()) == tuple(want)


def test_sql_of_density_joins_places_once(spark, copies):
    points.view(spark, copies, "P_part").createOrReplaceTempView("all_points")
    places = spark.table("all_points").select("x", "y").distinct().count()
    assert places < spark.table("all_points").count() and "GROUP BY x, y" in sqltext.spark_rho("all_points", 4.0)
    same_as_sql(spark, copies, "sql_rho")


def test_local_descent_of_many_nodes(spark):
    p = spark.range(300).select("id", (F.col("id") % 17 * 1.0).alias("x"), (F.col("id") % 23 * 1.0).alias("y"))
    tree = rtree.build(p, 4)
    tree.n_nodes = 50_003  # the count of 1.2 million points
    rho = iterate.cut(tree_query.rho(tree, 3.0))
    want = {(r.id, r.delta, r.mu) for r in tree_query.delta(tree, rho).collect() if r.mu is not None}
    for order in ("stack", "heap"):
        assert {(r.id, r.delta, r.mu) for r in tree_query.delta_local(tree, rho, order=order).collect() if r.mu is not None} == want


def test_visits_of_places_count_for_all_their_points(spark, copies):
    got = {r.order: r for r in entry.queries()["visit_orders"](spark, copies).collect()}
    assert 0 < got["heap"].visited <= got["stack"].visited and got["heap"].distances > 0


def plan_nodes(df):
    """Runs df; each node of the plan as it ran: its name, and the rows of a stage."""
    df.collect()
    seen, todo = [], [df._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        kind = node.getClass().getSimpleName()
        seen.append((kind, node.getRuntimeStatistics().rowCount().get() if kind == "ShuffleQueryStageExec" else 0))
        inner = node.executedPlan() if kind == "AdaptiveSparkPlanExec" else node.plan() if kind.endswith("QueryStageExec") else None
        todo += [inner] if inner else [node.children().apply(i) for i in range(node.children().size())]
    return seen


@pytest.mark.parametrize("name", ["rho_chebyshev", "rho_grid_part", "rho_grid_salted"])
def test_points_are_never_broadcast(spark, copies, name):
    kinds = [k for k, _ in plan_nodes(entry.queries()[name](spark, copies))]
    assert "SortMergeJoinExec" in kinds
    assert kinds.count("BroadcastHashJoinExec") == (2 if name == "rho_grid_salted" else 0)  # its counted table of hot cells, to both sides


def dense(spark):
    """400 places, each nearer than 1 to all others, in one cell or two."""
    return iterate.cut(spark.range(400).select("id", (0.1 + F.col("id") % 20 / 50).alias("x"), (0.1 + F.floor(F.col("id") / 20) / 50).alias("y")))


def test_pairs_of_density_are_not_shuffled(spark):
    own = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as where tables are too large for it
    try:
        found = grid.rho(dense(spark), 1.0)
        assert {r.rho for r in found.collect()} == {399}
        assert max(n for _, n in plan_nodes(found)) <= 9 * 400
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", own)


def test_hot_cells_are_copied_by_the_root_of_their_keys(spark):
    p = dense(spark)
    found = grid.rho(p, 1.0, hot=3)
    assert {r.rho for r in found.collect()} == {399}
    assert max(n for _, n in plan_nodes(found)) <= 2 * 9 * 400
    pairs = grid.eps_join(p, p, 1.0, hot=3).groupBy("id", "nbr").count()
    assert pairs.count() == 400 * 399 and pairs.where("count > 1").isEmpty()


def test_lineitem_is_numbered_without_a_checkpoint(spark, copies, monkeypatch):
    monkeypatch.setattr(rank, "cut", never)  # of whole rows, uncompressed
    p = points.view(spark, copies, "P_lineitem")
    want = duckdb.sql(points.sql("P_lineitem").replace("FROM lineitem", f"FROM '{copies}/lineitem.parquet'")).fetchall()
    assert sorted(map(tuple, p.collect())) == sorted(want)
    assert all("parked-" in f for f in p.inputFiles())


@pytest.mark.parametrize("kind", ["quadtree", "rtree"])
def test_density_of_many_places_by_tiles(spark, monkeypatch, kind):
    places = [(i % 83 * 1.5, (i * i) % 97 * 1.1) for i in range(900)] + [(3.0 + i / 500, 4.0 + i % 9 / 700) for i in range(300)]
    p = iterate.cut(spark.createDataFrame([(i, x, y) for i, (x, y) in enumerate(places)], "id long, x double, y double"))
    monkeypatch.setattr(descent, "TILE", 100)
    for most, upper in ((0, 2), (10**6, 9)):
        monkeypatch.setattr(descent, "MOST_COUNTED", most)
        monkeypatch.setattr(quadtree, "MOST_KEYS", most)
        monkeypatch.setattr(quadtree, "UPPER", upper)
        if not most:
            monkeypatch.setattr(descent.Held, "of", never)  # the driver holds no points
        tree = (quadtree if kind == "quadtree" else rtree).build(p, 8)
        nodes = sorted(map(tuple, tree.nodes.select("node", "parent", "level", "nc", "is_leaf", *tree.bounds).collect()), key=repr)
        leaves = sorted(map(tuple, tree.leaf_points.select("leaf", "id").collect()))
        found = [sorted(map(tuple, tree_query.rho(tree, d, contain=c).collect())) for d in (0.4, 3.0, 40.0) for c in (True, False)]
        if not most:
            first = nodes, leaves, found
            monkeypatch.undo()
    assert first == (nodes, leaves, found)
    assert found[2] == sorted(map(tuple, exact.rho(p, 3.0).collect()))


@pytest.mark.parametrize("name", ["cutoff_clusters", "pair_scores_tau_docs", "pair_scores_truth_docs"])
def test_empty_texts(spark, tmp_path, name):
    odd = "UNION ALL SELECT -2, '', 'en', 's', 0 UNION ALL SELECT 5000, '', 'en', 's', 0"
    duckdb.sql(f"COPY (SELECT * FROM '/root/testdata/sf0.001/documents.parquet' {odd}) TO '{tmp_path}/documents.parquet' (FORMAT parquet)")
    same_as_sql(spark, str(tmp_path), name)
