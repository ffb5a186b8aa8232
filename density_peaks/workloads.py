"""Registered queries: each method, variant, baseline, measure and experiment over the given tables.

QUERIES holds the Spark plans, ORACLES the DuckDB SQL of those that SQL can express. Views
and parameters are those of FIXTURES.md over whole tables.
"""

from collections.abc import Callable, Sequence
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from density_peaks import assign, baselines, cost, decide, density, dependent, exact, grid, metrics, pipeline, points, quality, spots, sqltext, streaming
from density_peaks.index import chist, nlist, quadtree, rnlist, rtree, tree_query
from density_peaks.iterate import cut
from density_peaks.schemas import VECTOR, Space
from density_peaks.sqltext import box_part, dep_part, diagonal, label_part, pairs, rho_part, score_select, top_part

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

PART, BLOB = "P_part", "P_blob15"
D_PART, D_BLOB, TAU_PART = 4.0, 20.0, 8.0
DEP_COLUMNS = ["id", "rho", "delta", "mu", "is_top"]


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def pts(spark: SparkSession, sf: str, view: str = PART) -> DataFrame:
    return points.view(spark, sf, view)


def union(dfs: Sequence[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), dfs)


def rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in columns})


def rho_sql(view: str, d_c: float, metric: str = "euclidean", **how) -> str:
    return f"WITH {pairs(view, metric)}, {rho_part(d_c, **how)} SELECT * FROM r"


def dep_sql(view: str, d_c: float, tie: str = "strict") -> str:
    return f"WITH {pairs(view)}, {rho_part(d_c)}, {dep_part(tie)} SELECT id, rho, round(delta, 6) AS delta, mu, is_top FROM dep"


def dep_out(df: DataFrame) -> DataFrame:
    return rounded(df.select(DEP_COLUMNS), "delta")


# ---- density ---------------------------------------------------------------------------


@query("rho_bruteforce_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return exact.rho(pts(spark, sf), D_PART)


@query("rho_pair_matrix", f"WITH {pairs(PART)}, {rho_part(D_PART)}, {dep_part()} SELECT id, rho, round(delta, 6) AS delta, mu, is_top FROM dep")
def _(spark, sf):
    return dep_out(exact.PairMatrix(pts(spark, sf)).run(D_PART))


@query("rho_list_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return nlist.rho(nlist.build(pts(spark, sf)), D_PART)


def _ch(spark, sf, d_c, w, view=PART):
    lists = cut(nlist.build(pts(spark, sf, view)))
    return chist.rho(cut(chist.build(lists, w)), lists, d_c, w)


@query("rho_ch_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return _ch(spark, sf, D_PART, 1.5)


@query("rho_ch_edge_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return _ch(spark, sf, D_PART, 2.0)


@query("rho_ch_first_bin", rho_sql(PART, 1.0))
def _(spark, sf):
    return _ch(spark, sf, 1.0, 4.0)


@query("rho_ch_beyond", rho_sql(PART, 5000.0))
def _(spark, sf):
    return _ch(spark, sf, 5000.0, 4.0)


@query("rho_rn_part", f"WITH {pairs(PART)}, {rho_part(D_PART)} SELECT *, true AS is_exact FROM r")
def _(spark, sf):
    return rnlist.rho(rnlist.build(pts(spark, sf), TAU_PART), D_PART, TAU_PART)


@query("rho_rn_beyond_tau", f"WITH {pairs(PART)}, {rho_part(16.0, cap=TAU_PART)} SELECT *, false AS is_exact FROM r")
def _(spark, sf):
    return rnlist.rho(rnlist.build(pts(spark, sf), TAU_PART), 16.0, TAU_PART)


@query("rho_rn_ch_part", rho_sql(PART, D_PART))
def _(spark, sf):
    lists = cut(rnlist.build(pts(spark, sf), TAU_PART))
    return chist.rho(chist.build(lists, 1.5), lists, D_PART, 1.5)


@query("rho_grid_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return density.rho(pts(spark, sf), D_PART)


@query("rho_grid_salted", rho_sql(PART, D_PART))
def _(spark, sf):
    return grid.rho(pts(spark, sf), D_PART, hot=3)


@query("rho_grid_contained", rho_sql(PART, D_PART))
def _(spark, sf):
    return grid.rho_contained(pts(spark, sf), D_PART)


@query("rho_quadtree_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf), D_PART, "quadtree")


@query("rho_rtree_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf), D_PART)


@query("rho_range_search_part", rho_sql(PART, D_PART))
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf), D_PART, contain=False)


@query("rho_root_shortcut", rho_sql(BLOB, 600.0))
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf, BLOB), 600.0)


@query("rho_quadtree_events", rho_sql("P_events", 5.0))
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf, "P_events"), 5.0, "quadtree", 64)


@query("rho_rtree_orders", rho_sql("P_orders", 50.0))
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf, "P_orders"), 50.0, capacity=128)


_CELLS = f"p AS ({points.sql('P_lineitem')}), a AS (SELECT *, floor(x / 5e0)::BIGINT AS i, floor(y / 5e0)::BIGINT AS j FROM p), b AS (SELECT a.*, i + di AS ni, j + dj AS nj FROM a, (SELECT unnest([-1, 0, 1]) AS di), (SELECT unnest([-1, 0, 1]) AS dj))"


@query("rho_rtree_lineitem", f"WITH {_CELLS}, n AS (SELECT b.id, count(*) AS n FROM b JOIN a ON a.i = b.ni AND a.j = b.nj AND a.id <> b.id AND sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) < 5e0 GROUP BY b.id) SELECT p.id, coalesce(n, 0)::BIGINT AS rho FROM p LEFT JOIN n USING (id)")
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf, "P_lineitem"), 5.0, capacity=256)


@query("rho_count_self", rho_sql(PART, D_PART, count_self=True))
def _(spark, sf):
    return exact.rho(pts(spark, sf), D_PART, count_self=True)


@query("rho_manhattan", rho_sql(PART, D_PART, "manhattan"))
def _(spark, sf):
    return pipeline.tree_rho(pts(spark, sf), D_PART, space=Space(metric="manhattan"))


@query("rho_chebyshev", rho_sql(PART, D_PART, "chebyshev"))
def _(spark, sf):
    return grid.rho(pts(spark, sf), D_PART, Space(metric="chebyshev"))


SWEEP = [1.0, 2.0, 4.0, 8.0]


@query("rho_sweep", f"WITH {pairs(PART)}, s AS (SELECT unnest([1e0, 2e0, 4e0, 8e0]) AS d_c) SELECT d_c, p.id, count(d.dist)::BIGINT AS rho FROM s CROSS JOIN p LEFT JOIN d ON d.id = p.id AND d.dist < s.d_c GROUP BY ALL")
def _(spark, sf):
    return nlist.rho_sweep(nlist.build(pts(spark, sf)), SWEEP)


_EMB = f"p AS ({points.sql('P_emb')}), d AS (SELECT a.id, b.id AS nbr, sqrt(list_sum(list_transform(list_zip(a.vec, b.vec), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS dist FROM p a JOIN p b ON a.id <> b.id)"


@query("rho_embeddings_list", f"WITH {_EMB}, {rho_part(1.2)} SELECT * FROM r")
def _(spark, sf):
    return nlist.rho(nlist.build(pts(spark, sf, "P_emb"), VECTOR), 1.2)


@query("delta_embeddings_ch", f"WITH {_EMB}, {rho_part(1.2)}, {dep_part('by_id')} SELECT id, rho, round(delta, 4) AS delta, mu, is_top FROM dep")
def _(spark, sf):
    lists = cut(nlist.build(pts(spark, sf, "P_emb"), VECTOR))
    found = nlist.delta(lists, cut(chist.rho(chist.build(lists, 0.05), lists, 1.2, 0.05)), "by_id")
    return rounded(found.select(DEP_COLUMNS), "delta", digits=4)


@query("sql_rho", rho_sql(PART, D_PART))
def _(spark, sf):
    pts(spark, sf).createOrReplaceTempView("density_points")
    return spark.sql(sqltext.spark_rho("density_points", D_PART))


# ---- dependent distance ----------------------------------------------------------------


def _dep(spark, sf, index: str, view: str = BLOB, d_c: float = D_BLOB, tie: str = "strict", **how) -> DataFrame:
    return pipeline.dependent(pipeline.build(pts(spark, sf, view), index, **how), d_c, tie)


@query("delta_bruteforce", dep_sql(PART, D_PART))
def _(spark, sf):
    return dep_out(exact.run(pts(spark, sf), D_PART))


@query("delta_list", dep_sql(BLOB, D_BLOB))
def _(spark, sf):
    return dep_out(_dep(spark, sf, "list"))


@query("delta_ch", dep_sql(BLOB, D_BLOB))
def _(spark, sf):
    return dep_out(_dep(spark, sf, "ch", w=3.0))


@query("delta_by_id", dep_sql(PART, D_PART, "by_id"))
def _(spark, sf):
    return dep_out(_dep(spark, sf, "rtree", PART, D_PART, "by_id"))


def _rn_sql(view: str, d_c: float, tau: float) -> str:
    return f"WITH {pairs(view)}, {rho_part(d_c)}, {dep_part(tau=tau, cap=diagonal())} SELECT id, rho, round(delta, 6) AS delta, mu, is_top, is_capped FROM dep"


@query("delta_rn_capped", _rn_sql(BLOB, D_BLOB, 30.0))
def _(spark, sf):
    return rounded(_dep(spark, sf, "rn", tau=30.0), "delta")


@query("delta_rn_repaired", dep_sql(BLOB, D_BLOB))
def _(spark, sf):
    p = pts(spark, sf, BLOB)
    return dep_out(rnlist.repair(_dep(spark, sf, "rn", tau=30.0), rtree.build(p)))


@query("delta_quadtree", dep_sql(BLOB, D_BLOB))
def _(spark, sf):
    return dep_out(_dep(spark, sf, "quadtree"))


@query("delta_rtree", dep_sql(PART, D_PART))
def _(spark, sf):
    return dep_out(_dep(spark, sf, "rtree", PART, D_PART))


def _local(spark, sf, order: str, kind: str) -> DataFrame:
    same = spots.merge(pts(spark, sf, PART))
    tree = pipeline.over_spots(same, kind)
    return rounded(same.spread(tree_query.delta_local(tree, cut(tree_query.rho(tree, D_PART)), order=order)).select("id", "delta", "mu"), "delta")


_LOCAL = f"WITH {pairs(PART)}, {rho_part(D_PART)}, {dep_part()} SELECT id, CASE WHEN mu IS NOT NULL THEN round(delta, 6) END AS delta, mu FROM dep"


@query("delta_quadtree_stack", _LOCAL)
def _(spark, sf):
    return _local(spark, sf, "stack", "quadtree")


@query("delta_quadtree_heap", _LOCAL)
def _(spark, sf):
    return _local(spark, sf, "heap", "quadtree")


@query("delta_rtree_stack", _LOCAL)
def _(spark, sf):
    return _local(spark, sf, "stack", "rtree")


@query("delta_peak", f"WITH {pairs(PART)}, {rho_part(D_PART)}, t AS (SELECT id FROM r WHERE rho = (SELECT max(rho) FROM r)) SELECT d.id, round(max(d.dist), 6) AS far FROM d JOIN t USING (id) GROUP BY d.id")
def _(spark, sf):
    tree = rtree.build(pts(spark, sf))
    r = cut(tree_query.rho(tree, D_PART))
    top = r.join(r.agg(F.max("rho").alias("rho")), "rho", "left_semi")
    return rounded(tree_query.farthest(tree, top), "far")


@query("delta_peak_scan", f"WITH {pairs(PART)}, {rho_part(D_PART)}, t AS (SELECT id FROM r WHERE rho = (SELECT max(rho) FROM r)) SELECT d.id, round(max(d.dist), 6) AS far FROM d JOIN t USING (id) GROUP BY d.id")
def _(spark, sf):
    r = cut(density.rho(pts(spark, sf), D_PART))
    return rounded(dependent.peak_delta(pts(spark, sf), r.join(r.agg(F.max("rho").alias("rho")), "rho", "left_semi")), "far")


def _ablation(spark, sf, **off) -> DataFrame:
    same = spots.merge(pts(spark, sf))
    tree = pipeline.over_spots(same)
    return dep_out(same.dependent(tree_query.delta(tree, cut(tree_query.rho(tree, D_PART)), **off)))


@query("delta_no_density_prune", dep_sql(PART, D_PART))
def _(spark, sf):
    return _ablation(spark, sf, density_prune=False)


@query("delta_no_distance_prune", dep_sql(PART, D_PART))
def _(spark, sf):
    return _ablation(spark, sf, distance_prune=False)


_KNN = f"WITH {pairs(PART)} SELECT id, nbr, round(dist, 6) AS dist, pos::INT AS pos FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY dist, nbr) AS pos FROM d) WHERE pos <= {{k}}"


@query("nearest_neighbour", _KNN.format(k=1))
def _(spark, sf):
    return rounded(tree_query.nearest(rtree.build(pts(spark, sf))), "dist")


@query("knn_join", _KNN.format(k=5))
def _(spark, sf):
    return rounded(tree_query.nearest(rtree.build(pts(spark, sf)), 5), "dist")


# ---- index content ---------------------------------------------------------------------


@query("nlist_build", f"WITH {pairs('P_supp')} SELECT id, (row_number() OVER (PARTITION BY id ORDER BY dist, nbr) - 1)::INT AS pos, nbr, round(dist, 6) AS dist FROM d")
def _(spark, sf):
    return rounded(nlist.long_form(nlist.build(pts(spark, sf, "P_supp"))), "dist")


@query("nlist_probes", f"WITH {pairs(BLOB)}, {rho_part(D_BLOB)}, {dep_part()}, n AS (SELECT id, nbr, row_number() OVER (PARTITION BY id ORDER BY dist, nbr) AS pos, count(*) OVER (PARTITION BY id) AS entries FROM d) SELECT dep.id, CASE WHEN mu IS NULL THEN max(entries) ELSE max(pos) FILTER (nbr = mu) END AS probes, max(entries) AS entries FROM dep JOIN n USING (id) GROUP BY dep.id, mu")
def _(spark, sf):
    lists = cut(nlist.build(pts(spark, sf, BLOB)))
    return nlist.probes(lists, nlist.delta(lists, cut(nlist.rho(lists, D_BLOB))))


_HIST = "SELECT id, bin, sum(n) OVER (PARTITION BY id ORDER BY bin)::BIGINT AS cum, round(lo, 6) AS min_dist, round(hi, 6) AS max_dist FROM (SELECT id, floor(dist / 2000e0)::BIGINT AS bin, count(*) AS n, min(dist) AS lo, max(dist) AS hi FROM d GROUP BY ALL)"


@query("chist_build", f"WITH {pairs('P_supp')} {_HIST}")
def _(spark, sf):
    return rounded(chist.build(nlist.build(pts(spark, sf, "P_supp")), 2000.0), "min_dist", "max_dist")


@query("chist_dense", f"WITH {pairs('P_supp')}, m AS (SELECT id, max(floor(dist / 2000e0))::BIGINT AS last FROM d GROUP BY id), b AS (SELECT id, unnest(range(last + 1)) AS bin FROM m), c AS (SELECT b.id, b.bin, count(d.dist) AS cum FROM b JOIN d ON b.id = d.id AND floor(d.dist / 2000e0) <= b.bin GROUP BY ALL UNION ALL SELECT b.id, b.bin, 0 FROM b WHERE NOT EXISTS (SELECT 1 FROM d WHERE d.id = b.id AND floor(d.dist / 2000e0) <= b.bin)) SELECT id, bin::INT AS bin, cum FROM c")
def _(spark, sf):
    dense = chist.dense(chist.build(nlist.build(pts(spark, sf, "P_supp")), 2000.0))
    return dense.select("id", F.posexplode("cum").alias("bin", "cum"))


@query("chist_list_reads", f"WITH {pairs(PART)}, h AS (SELECT id, count(*) FILTER (floor(dist / 1.5e0) = floor(4e0 / 1.5e0)) AS n, min(dist) FILTER (floor(dist / 1.5e0) = floor(4e0 / 1.5e0)) AS lo, max(dist) FILTER (floor(dist / 1.5e0) = floor(4e0 / 1.5e0)) AS hi FROM d WHERE floor(dist / 1.5e0) <= floor(4e0 / 1.5e0) GROUP BY id) SELECT id, CASE WHEN n = 0 OR 4e0 <= lo OR hi < 4e0 THEN 0 ELSE n END AS entries FROM h")
def _(spark, sf):
    return chist.list_reads(chist.build(rnlist.build(pts(spark, sf), 16.0), 1.5), D_PART, 1.5)


_RN = f"WITH {pairs(PART)} SELECT id, nbr, round(dist, 6) AS dist FROM d WHERE dist < {TAU_PART}e0"


@query("rnlist_build", _RN)
def _(spark, sf):
    return rounded(nlist.long_form(rnlist.build(pts(spark, sf), TAU_PART)).drop("pos"), "dist")


@query("rnlist_from_nlist", _RN)
def _(spark, sf):
    return rounded(nlist.long_form(rnlist.from_nlist(nlist.build(pts(spark, sf)), TAU_PART)).drop("pos"), "dist")


@query("eps_pairs", f"WITH {pairs('P_cust')} SELECT id, nbr, round(dist, 6) AS dist FROM d WHERE dist < 300e0")
def _(spark, sf):
    return rounded(grid.eps_join(pts(spark, sf, "P_cust"), pts(spark, sf, "P_cust"), 300.0), "dist")


def _quad_sql(view: str, capacity: int, depth: int, select: str) -> str:
    n = 1 << depth
    bits = lambda c, s: " + ".join(f"((({c} >> {b}) & 1) << {2 * b + s})" for b in range(depth))
    return (
        f"WITH p AS ({points.sql(view)}), g AS (SELECT min(x) AS x0, min(y) AS y0, greatest(max(x) - min(x), max(y) - min(y), 1e-300) AS side FROM p), "
        f"q AS (SELECT id, least({n - 1}, floor((x - x0) / side * {n}e0))::BIGINT AS cx, least({n - 1}, floor((y - y0) / side * {n}e0))::BIGINT AS cy FROM p, g), "
        f"k AS (SELECT id, {bits('cx', 0)} + {bits('cy', 1)} AS key FROM q), "
        f"e AS (SELECT l AS level, (1::BIGINT << (2 * l)) + (key >> (2 * ({depth} - l))) AS node, count(*) AS nc FROM k, (SELECT unnest(range({depth + 1}))::INT AS l) GROUP BY ALL), "
        f"t AS (SELECT e.node, e.level, e.nc, e.nc <= {capacity} OR e.level = {depth} AS is_leaf FROM e LEFT JOIN e f ON f.node = (e.node >> 2) AND f.level = e.level - 1 WHERE e.level = 0 OR f.nc > {capacity}) {select}"
    )


@query("quadtree_leaf_counts", _quad_sql(BLOB, 32, 16, "SELECT node, level, nc FROM t WHERE is_leaf"))
def _(spark, sf):
    return quadtree.build(pts(spark, sf, BLOB)).nodes.where("is_leaf").select("node", "level", "nc")


@query("quadtree_levels", _quad_sql(PART, 8, 16, "SELECT level, count(*) AS nodes, count(*) FILTER (is_leaf) AS leaves, sum(nc)::BIGINT AS objects FROM t GROUP BY level"))
def _(spark, sf):
    return quadtree.build(pts(spark, sf), 8).nodes.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.count_if("is_leaf").alias("leaves"), F.sum("nc").alias("objects"))


def _rtree_sql(view: str, m: int, select: str) -> str:
    return (
        f"WITH p AS ({points.sql(view)}), n AS (SELECT ceil(sqrt(ceil(count(*) / {m}e0)))::BIGINT AS s FROM p), r AS (SELECT id, x, y, (row_number() OVER (ORDER BY x, id) - 1) // ({m} * s) AS slice FROM p, n), "
        f"l AS (SELECT id, x, y, slice, (row_number() OVER (PARTITION BY slice ORDER BY y, id) - 1) // {m} AS cut FROM r), "
        f"b AS (SELECT row_number() OVER (ORDER BY slice, cut) - 1 AS leaf, min(x) AS lo_x, min(y) AS lo_y, max(x) AS hi_x, max(y) AS hi_y, count(*) AS nc FROM l GROUP BY slice, cut) {select}"
    )


@query("rtree_leaf_mbr", _rtree_sql(BLOB, 32, "SELECT leaf AS node, lo_x, lo_y, hi_x, hi_y, nc FROM b"))
def _(spark, sf):
    return rtree.build(pts(spark, sf, BLOB)).nodes.where("is_leaf").select("node", "lo_x", "lo_y", "hi_x", "hi_y", "nc")


@query("rtree_height", _rtree_sql(PART, 32, ", h AS (SELECT ceil(ln(count(*)) / ln(4) - 1e-9)::INT AS height, count(*) AS leaves, sum(nc)::BIGINT AS objects FROM b) SELECT * FROM h"))
def _(spark, sf):
    tree = rtree.build(pts(spark, sf))
    return tree.nodes.where("is_leaf").agg(F.lit(tree.height).alias("height"), F.count(F.lit(1)).alias("leaves"), F.sum("nc").alias("objects"))


def _packed_sql(capacity: int = 32, fanout: int = 4) -> str:
    """CTEs of a packed R-tree over p: leaves by slices, and nodes (up from the leaves, place, parent, nc, box) of all levels above."""
    return (
        f"s AS (SELECT ceil(count(*) / {capacity}e0)::BIGINT AS leaves FROM p), "
        f"w AS (SELECT leaves, ceil(sqrt(leaves) - 1e-9)::BIGINT AS across, (SELECT min(h) FROM range(0, 40) t(h) WHERE pow({fanout}, h) >= leaves) AS height FROM s), "
        f"a AS (SELECT p.*, (row_number() OVER (ORDER BY x, id) - 1) // ({capacity} * across) AS slice, across FROM p, w), "
        f"l AS (SELECT *, slice * across + (row_number() OVER (PARTITION BY slice ORDER BY y, id) - 1) // {capacity} AS leaf FROM a), "
        f"k AS (SELECT up, leaf // pow({fanout}, up)::BIGINT AS place, count(*) AS nc, min(x) AS lo_x, max(x) AS hi_x, min(y) AS lo_y, max(y) AS hi_y FROM l, (SELECT unnest(range(0, height + 1)) AS up FROM w) GROUP BY ALL)"
    )


@query("rtree_report", f"WITH p AS ({points.sql(BLOB)}), {_packed_sql()}, o AS (SELECT a.up, sum(greatest(least(a.hi_x, b.hi_x) - greatest(a.lo_x, b.lo_x), 0) * greatest(least(a.hi_y, b.hi_y) - greatest(a.lo_y, b.lo_y), 0)) AS overlap FROM k a JOIN k b ON a.up = b.up AND a.place // 4 = b.place // 4 AND a.place < b.place GROUP BY a.up) SELECT (height - up)::INT AS level, nodes, objects, round(coverage, 6) AS coverage, round(coalesce(overlap, 0e0), 6) AS overlap FROM (SELECT up, count(*) AS nodes, sum(nc)::BIGINT AS objects, sum((hi_x - lo_x) * (hi_y - lo_y)) AS coverage FROM k GROUP BY up) LEFT JOIN o USING (up), w")
def _(spark, sf):
    return rounded(rtree.report(rtree.build(pts(spark, sf, BLOB))), "coverage", "overlap")


@query("rtree_three_axes", "WITH p AS (SELECT p_partkey AS id, p_size::DOUBLE AS x, p_retailprice AS y, (p_partkey % 97)::DOUBLE AS z FROM part) SELECT a.id, count(b.id)::BIGINT AS rho FROM p a LEFT JOIN p b ON a.id <> b.id AND sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) + (a.z - b.z) * (a.z - b.z)) < 10e0 GROUP BY a.id")
def _(spark, sf):
    p = table(spark, sf, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").cast("double").alias("x"), F.col("p_retailprice").alias("y"), (F.col("p_partkey") % 97).cast("double").alias("z"))
    return pipeline.tree_rho(p, 10.0, space=Space(("x", "y", "z")))


@query("quadtree_insert", rho_sql("P_cust", 600.0))
def _(spark, sf):
    p = pts(spark, sf, "P_cust")
    late = F.pmod(F.xxhash64("id"), F.lit(3)) == 0
    return tree_query.rho(quadtree.insert(quadtree.build(p.where(~late)), p.where(late)), 600.0)


# ---- centers, assignment ---------------------------------------------------------------

_BLOB_DEP = f"{pairs(BLOB)}, {rho_part(D_BLOB)}, {dep_part()}"


@query("decision_graph", f"WITH {_BLOB_DEP} SELECT id, rho, round(delta, 6) AS delta, round(rho * delta, 5) AS gamma FROM dep")
def _(spark, sf):
    return rounded(rounded(decide.decision_graph(_dep(spark, sf, "list")), "delta"), "gamma", digits=5)


@query("worked_example_graph", f"WITH {pairs('P_supp')}, {rho_part(1500.0)}, {dep_part('by_id')} SELECT id, rho, round(delta, 6) AS delta, mu, is_top FROM dep")
def _(spark, sf):
    return dep_out(_dep(spark, sf, "ch", "P_supp", 1500.0, "by_id", w=400.0))


@query("centers_threshold", f"WITH {_BLOB_DEP} SELECT id FROM dep WHERE rho >= 20 AND delta >= 40e0")
def _(spark, sf):
    return decide.centers(_dep(spark, sf, "rtree"), 20, 40.0)


@query("centers_topk", f"WITH {_BLOB_DEP}, {top_part(15)} SELECT id FROM c")
def _(spark, sf):
    return decide.centers_top(_dep(spark, sf, "list"), 15)


@query("outliers", f"WITH {_BLOB_DEP} SELECT id, rho, round(delta, 6) AS delta FROM dep WHERE rho <= 3 AND delta >= 8e0")
def _(spark, sf):
    return rounded(decide.outliers(_dep(spark, sf, "list"), 3, 8.0), "delta")


_BLOB_LABELS = f"WITH RECURSIVE {_BLOB_DEP}, {top_part(15)}, {label_part()}"


@query("assign_clusters", f"{_BLOB_LABELS} SELECT id, cluster, depth::INT AS depth, is_center FROM l")
def _(spark, sf):
    return pipeline.label(_dep(spark, sf, "rtree"), k=15)


@query("cluster_rtree", f"{_BLOB_LABELS} SELECT id, cluster, depth::INT AS depth, is_center FROM l")
def _(spark, sf):
    return pipeline.cluster(pts(spark, sf, BLOB), D_BLOB, "rtree", k=15)


@query("cluster_by_hand", f"WITH RECURSIVE {_BLOB_DEP}, c AS (SELECT unnest([0, 1, 2, 3, 4]) AS id), {label_part()} SELECT id, cluster, depth::INT AS depth, is_center FROM l")
def _(spark, sf):
    return pipeline.label(_dep(spark, sf, "list"), ids=[0, 1, 2, 3, 4])


@query("sql_cluster", f"{_BLOB_LABELS} SELECT id, cluster FROM l")
def _(spark, sf):
    _dep(spark, sf, "list").createOrReplaceTempView("density_dependent")
    return spark.sql(sqltext.spark_cluster("density_dependent", 15))


@query("cluster_sizes", f"{_BLOB_LABELS} SELECT cluster, count(*) AS n FROM l GROUP BY cluster")
def _(spark, sf):
    return pipeline.label(_dep(spark, sf, "list"), k=15).groupBy("cluster").agg(F.count(F.lit(1)).alias("n"))


@query("cluster_depth", f"{_BLOB_LABELS} SELECT cluster, max(depth)::INT AS depth, round(avg(depth), 6) AS mean_depth FROM l GROUP BY cluster")
def _(spark, sf):
    return pipeline.label(_dep(spark, sf, "list"), k=15).groupBy("cluster").agg(F.max("depth").alias("depth"), F.round(F.avg("depth"), 6).alias("mean_depth"))


# ---- measures and experiments ----------------------------------------------------------


def _tau_scores(spark, sf, view: str, d_c: float, k: int, taus: Sequence[float]) -> DataFrame:
    """Quality of cut lists against the full method, with the same box of centers for all radii.

    Full lists are quadratic, and so are lists of a wide radius; what cut lists answer comes from the tree, cut at the radius.
    """
    p = cut(pts(spark, sf, view))
    index, cap = pipeline.build(p, "rtree"), rnlist.diagonal(p)
    dep = pipeline.dependent(index, d_c, "by_id")
    box, out = decide.thresholds_of_top(dep, k), []
    truth = cut(pipeline.label(dep, *box))
    for tau in taus:
        got = rnlist.from_dependent(dep if d_c <= tau else pipeline.dependent(index, tau, "by_id"), tau, cap)
        out.append(quality.pair_scores(truth, pipeline.label(cut(got), *box)).withColumn("tau", F.lit(tau)))
    return rounded(union(out), "precision", "recall", "f1")


def _tau_sql(view: str, d_c: float, k: int, taus: Sequence[float]) -> str:
    parts, sel = [f"{pairs(view)}, {rho_part(d_c)}, {dep_part('by_id', name='g')}, {box_part('g', k, 'g', 'gc')}, {label_part('g', 'gc', 'gl')}"], []
    for i, tau in enumerate(taus):
        cap = tau if d_c > tau else None
        parts.append(f"{rho_part(d_c, cap=cap, name=f'r{i}')}, {dep_part('by_id', tau, diagonal(), f'r{i}', f'e{i}')}, {box_part('g', k, f'e{i}', f'c{i}')}, {label_part(f'e{i}', f'c{i}', f'l{i}')}")
        sel.append(f"SELECT {tau}e0 AS tau, tp, fp, fn, round(precision, 6) AS precision, round(recall, 6) AS recall, round(f1, 6) AS f1 FROM ({score_select('gl', f'l{i}')})")
    return f"WITH RECURSIVE {', '.join(parts)} {' UNION ALL '.join(sel)}"


@query("pair_scores_tau", _tau_sql(BLOB, D_BLOB, 15, [40.0, 20.0, 10.0]))
def _(spark, sf):
    return _tau_scores(spark, sf, BLOB, D_BLOB, 15, [40.0, 20.0, 10.0])


@query("pair_scores_tau_docs", _tau_sql("P_docs", 0.25, 6, [8.0, 1.0, 0.25]))
def _(spark, sf):
    return _tau_scores(spark, sf, "P_docs", 0.25, 6, [8.0, 1.0, 0.25])


@query("pair_scores_tau_blob100", _tau_sql("P_blob100", 20.0, 100, [60.0, 20.0, 10.0]))
def _(spark, sf):
    return _tau_scores(spark, sf, "P_blob100", 20.0, 100, [60.0, 20.0, 10.0])


@query("pair_scores_tau_orders")
def _(spark, sf):
    # full lists of this view would be quadratic: the tree gives the reference, a distance join the cut lists
    p = cut(pts(spark, sf, "P_orders"))
    dep = pipeline.dependent(pipeline.build(p, "rtree", capacity=128), 50.0, "by_id")
    box, out, cap = decide.thresholds_of_top(dep, 6), [], rnlist.diagonal(p)
    truth = cut(pipeline.label(dep, *box))
    for tau in (200.0, 100.0, 50.0):
        got = pipeline.dependent(pipeline.build(p, "rn", tau=tau), 50.0, "by_id").withColumn("delta", F.when(F.col("is_capped"), F.lit(cap)).otherwise(F.col("delta")))
        out.append(quality.pair_scores(truth, pipeline.label(got, *box)).withColumn("tau", F.lit(tau)))
    return rounded(union(out), "precision", "recall", "f1")


def _truth_sql(view: str, d_c: float, k: int) -> str:
    return f"WITH RECURSIVE {pairs(view)}, {rho_part(d_c)}, {dep_part('by_id')}, {top_part(k)}, {label_part()}, g AS (SELECT id, truth AS cluster FROM p) SELECT tp, fp, fn, round(precision, 6) AS precision, round(recall, 6) AS recall, round(f1, 6) AS f1 FROM ({score_select('g', 'l')})"


def _truth(spark, sf, view: str, d_c: float, k: int) -> DataFrame:
    p = pts(spark, sf, view)
    found = pipeline.label(_dep(spark, sf, "rtree", view, d_c, "by_id"), k=k)
    return rounded(quality.pair_scores(p.select("id", F.col("truth").alias("cluster")), found), "precision", "recall", "f1")


@query("pair_scores_truth_docs", _truth_sql("P_docs", 0.25, 6))
def _(spark, sf):
    return _truth(spark, sf, "P_docs", 0.25, 6)


@query("pair_scores_truth_blob", _truth_sql(BLOB, D_BLOB, 15))
def _(spark, sf):
    return _truth(spark, sf, BLOB, D_BLOB, 15)


@query("pair_scores_truth_blob100", _truth_sql("P_blob100", 20.0, 100))
def _(spark, sf):
    return _truth(spark, sf, "P_blob100", 20.0, 100)


@query("contingency", f"{_BLOB_LABELS} SELECT p.truth AS g, l.cluster AS c, count(*) AS n FROM p JOIN l USING (id) GROUP BY ALL")
def _(spark, sf):
    p = pts(spark, sf, BLOB).select("id", F.col("truth").alias("cluster"))
    return quality.contingency(p, pipeline.label(_dep(spark, sf, "list"), k=15))


@query("pair_scores_udaf", _truth_sql(BLOB, D_BLOB, 15).replace("SELECT tp, fp, fn,", "SELECT tp,").replace("round(precision, 6) AS precision, round(recall, 6) AS recall, round(f1, 6) AS f1", "round(precision, 6) AS precision, round(recall, 6) AS recall").replace("tp::DECIMAL(38,0) AS tp", "tp::BIGINT AS tp"))
def _(spark, sf):
    @F.pandas_udf("long")
    def pairs_in(n: pd.Series) -> int:
        return int((n * (n - 1) // 2).sum())

    found = pipeline.label(_dep(spark, sf, "list", tie="by_id"), k=15)
    t = cut(quality.contingency(pts(spark, sf, BLOB).select("id", F.col("truth").alias("cluster")), found))
    one = t.groupBy("g").agg(F.sum("n").alias("n")).agg(pairs_in("n").alias("gp"))
    two = t.groupBy("c").agg(F.sum("n").alias("n")).agg(pairs_in("n").alias("cp"))
    s = t.agg(pairs_in("n").alias("tp")).join(one).join(two)
    return s.select("tp", F.round(F.col("tp") / F.col("cp"), 6).alias("precision"), F.round(F.col("tp") / F.col("gp"), 6).alias("recall"))


@query("probe_fraction", f"WITH {_BLOB_DEP}, n AS (SELECT id, nbr, row_number() OVER (PARTITION BY id ORDER BY dist, nbr) AS pos, count(*) OVER (PARTITION BY id) AS entries FROM d), b AS (SELECT dep.id, CASE WHEN mu IS NULL THEN max(entries) ELSE max(pos) FILTER (nbr = mu) END AS probes, max(entries) AS entries FROM dep JOIN n USING (id) GROUP BY dep.id, mu) SELECT sum(probes)::BIGINT AS probes, sum(entries)::BIGINT AS entries, round(sum(probes) / sum(entries), 6) AS fraction FROM b")
def _(spark, sf):
    lists = cut(nlist.build(pts(spark, sf, BLOB)))
    return rounded(cost.probe_fraction(nlist.probes(lists, nlist.delta(lists, cut(nlist.rho(lists, D_BLOB))))), "fraction")


@query("cutoff_clusters", " UNION ALL ".join(f"SELECT * FROM (WITH RECURSIVE {pairs('P_docs')}, {rho_part(d)}, {dep_part('by_id')}, {box_part('dep', 6, 'dep', 'c')}, {label_part()} SELECT {d}e0 AS d_c, count(DISTINCT cluster) AS clusters, count(*) FILTER (is_center) AS centers, max(depth)::INT AS depth FROM l)" for d in (0.25, 0.5, 1.0, 2.0)))
def _(spark, sf):
    index, out = pipeline.build(pts(spark, sf, "P_docs"), "rtree"), []
    for d, dep in pipeline.sweep(index, [0.25, 0.5, 1.0, 2.0], "by_id").items():
        found = pipeline.label(dep, *decide.thresholds_of_top(dep, 6))
        out.append(found.agg(F.count_distinct("cluster").alias("clusters"), F.count_if("is_center").alias("centers"), F.max("depth").alias("depth")).select(F.lit(d).alias("d_c"), "*"))
    return union(out)


@query("cutoffs_rtree", " UNION ALL ".join(f"SELECT * FROM (WITH {pairs(BLOB)}, {rho_part(d)} SELECT {d}e0 AS d_c, id, rho FROM r)" for d in (6.0, 12.0, 20.0, 600.0)))
def _(spark, sf):
    tree = rtree.build(pts(spark, sf, BLOB))
    return union([tree_query.rho(tree, d).select(F.lit(d).alias("d_c"), "id", "rho") for d in (6.0, 12.0, 20.0, 600.0)])


WIDTHS, CUTOFFS = (3.0, 4.0, 7.0, 10.0), (6.0, 12.0, 20.0)


@query("widths_cutoffs", " UNION ALL ".join(f"SELECT * FROM (WITH {pairs(BLOB)}, {rho_part(d)} SELECT w, {d}e0 AS d_c, sum(rho)::BIGINT AS total, max(rho) AS most FROM r, (SELECT unnest([3e0, 4e0, 7e0, 10e0]) AS w) GROUP BY w)" for d in CUTOFFS))
def _(spark, sf):
    lists, out = cut(nlist.build(pts(spark, sf, BLOB))), []
    for w in WIDTHS:
        hist = cut(chist.build(lists, w))
        out += [chist.rho(hist, lists, d, w).agg(F.sum("rho").alias("total"), F.max("rho").alias("most")).select(F.lit(w).alias("w"), F.lit(d).alias("d_c"), "total", "most") for d in CUTOFFS]
    return union(out)


@query("widths_memory", f"WITH {pairs(BLOB)}, s AS (SELECT unnest([3e0, 4e0, 7e0, 10e0]) AS w) SELECT w, sum(b)::BIGINT AS bins, sum(m)::BIGINT AS dense_bins FROM (SELECT w, id, count(DISTINCT floor(dist / w)) AS b, max(floor(dist / w)) + 1 AS m FROM d, s GROUP BY w, id) GROUP BY w")
def _(spark, sf):
    return chist.size_report(cut(nlist.build(pts(spark, sf, BLOB))), list(WIDTHS))


TAUS = (40.0, 30.0, 20.0)


@query("taus_memory", " UNION ALL ".join(f"SELECT * FROM (WITH {pairs(BLOB)} SELECT {t}e0 AS tau, count(*)::BIGINT AS entries, count(*)::BIGINT * 16 AS bytes FROM d WHERE dist < {t}e0)" for t in TAUS))
def _(spark, sf):
    return union([cost.list_bytes(rnlist.build(pts(spark, sf, BLOB), t)).select(F.lit(t).alias("tau"), "entries", "bytes") for t in TAUS])


MEMORY_VIEWS = ((BLOB, 4.0), ("P_blob100", 5.0), (PART, 2.0), ("P_cust", 150.0), ("P_docs", 0.25))


def _memory_sql(view: str, w: float) -> str:
    """Bytes of each index: entries of 16, bins of 40 beside the lists, nodes of 72 and a leaf number of 8 a point."""
    return (
        f"SELECT * FROM (WITH {pairs(view)}, {_packed_sql()}, "
        "q0 AS (SELECT min(x) AS x0, min(y) AS y0, greatest(max(x) - min(x), max(y) - min(y), 1e-300) AS side FROM p), "
        "c AS (SELECT least(65535, greatest(0, floor((x - x0) / side * 65536e0)))::BIGINT AS i, least(65535, greatest(0, floor((y - y0) / side * 65536e0)))::BIGINT AS j FROM p, q0), "
        "g AS (SELECT level, i >> (16 - level) AS i, j >> (16 - level) AS j, count(*) AS nc FROM c, (SELECT unnest(range(0, 17))::INT AS level) GROUP BY ALL), "
        "t AS (SELECT count(*) AS nodes FROM g LEFT JOIN g u ON u.level = g.level - 1 AND u.i = g.i >> 1 AND u.j = g.j >> 1 WHERE g.level = 0 OR u.nc > 32), "
        "e AS (SELECT count(*) * 16 AS list FROM d), n AS (SELECT count(*) * 8 AS own FROM p), "
        f"b AS (SELECT 40 * count(*) AS bins FROM (SELECT DISTINCT id, floor(dist / {w!r}) FROM d)) "
        f"SELECT '{view}' AS view, unnest(['list', 'ch', 'quadtree', 'rtree']) AS \"index\", unnest([list, list + bins, t.nodes * 72 + own, (SELECT count(*) FROM k) * 72 + own])::BIGINT AS bytes FROM e, b, t, n)"
    )


@query("index_memory", " UNION ALL ".join(_memory_sql(v, w) for v, w in MEMORY_VIEWS))
def _(spark, sf):
    out = []
    for view, w in MEMORY_VIEWS:
        p = cut(pts(spark, sf, view))
        lists = cut(nlist.build(p))
        sizes = {"list": cost.list_bytes(lists), "ch": cost.hist_bytes(chist.build(lists, w)), "quadtree": cost.tree_bytes(quadtree.build(p)), "rtree": cost.tree_bytes(rtree.build(p))}
        base = sizes["list"].select("bytes").withColumnRenamed("bytes", "list_bytes")
        for kind, s in sizes.items():
            b = s.select("bytes").join(base).select((F.col("bytes") + (F.col("list_bytes") if kind == "ch" else 0)).alias("bytes"))
            out.append(b.select(F.lit(view).alias("view"), F.lit(kind).alias("index"), "bytes"))
    return union(out)


@query("all_methods_agree", " UNION ALL ".join(f"SELECT * FROM (WITH {pairs(v)}, {rho_part(d)}, {dep_part('by_id')} SELECT '{v}' AS view, {k}::INT AS methods, count(*) AS objects, sum(rho)::BIGINT AS rho_sum, sum(mu)::BIGINT AS mu_sum FROM dep)" for v, d, k in ((BLOB, D_BLOB, 5), ("P_cust", 600.0, 5))))
def _(spark, sf):
    out = []
    for view, d in ((BLOB, D_BLOB), ("P_cust", 600.0)):
        got = [_dep(spark, sf, kind, view, d, "by_id").select("id", "rho", F.round("delta", 6).alias("delta"), "mu") for kind in ("brute", "list", "ch", "quadtree", "rtree")]
        same = reduce(lambda a, b: a.intersect(b), got[1:], got[0])
        out.append(same.agg(F.lit(view).alias("view"), F.lit(len(got)).alias("methods"), F.count(F.lit(1)).alias("objects"), F.sum("rho").alias("rho_sum"), F.sum("mu").alias("mu_sum")))
    return union(out)


@query("pruning_ablation")
def _(spark, sf):
    rows, tree = [], rtree.build(pts(spark, sf, BLOB))
    stats: dict = {}
    r = cut(tree_query.rho(tree, D_BLOB, stats=stats))
    rows.append(("rho", "contained shortcut", *(int(stats[k]) for k in ("node_pairs", "distances"))))
    tree_query.rho(tree, D_BLOB, contain=False, stats=(stats := {}))
    rows.append(("rho", "plain range search", *(int(stats[k]) for k in ("node_pairs", "distances"))))
    for name, off in (("both", {}), ("no density pruning", {"density_prune": False}), ("no distance pruning", {"distance_prune": False})):
        tree_query.delta(tree, r, stats=(stats := {}), **off)
        rows.append(("delta", name, *(int(stats[k]) for k in ("node_pairs", "distances"))))
    return spark.createDataFrame(rows, "quantity string, pruning string, node_pairs long, distances long")


@query("visit_orders")
def _(spark, sf):
    same = spots.merge(pts(spark, sf, BLOB))
    tree = pipeline.over_spots(same)
    r, out = cut(tree_query.rho(tree, D_BLOB)), []
    for o in ("stack", "heap"):  # points of a spot go the same way
        found = tree_query.delta_local(tree, r, order=o).join(same.spots.select("id", spots.WEIGHT), "id")
        out.append(found.agg(F.lit(o).alias("order"), *[F.sum(F.col(c) * F.col(spots.WEIGHT)).alias(c) for c in ("visited", "distances")]))
    return union(out)


# ---- other clusterings -----------------------------------------------------------------

_EPS = f"WITH RECURSIVE {pairs(PART)}, n AS (SELECT p.id, count(d.dist) + 1 AS n FROM p LEFT JOIN d ON d.id = p.id AND dist < 2e0 GROUP BY p.id), core AS (SELECT id FROM n WHERE n >= {{m}}), e AS (SELECT d.id, d.nbr, d.dist FROM d WHERE dist < 2e0), k AS (SELECT id AS a, id AS b FROM core UNION SELECT k.a, e.nbr FROM k JOIN e ON k.b = e.id WHERE e.nbr IN (SELECT id FROM core)), l AS (SELECT a AS id, min(b) AS cluster FROM k GROUP BY a)"


@query("dbscan_labels", _EPS.format(m=12) + ", b AS (SELECT e.id, arg_min(l.cluster, {'a': e.dist, 'b': e.nbr}) AS cluster FROM e JOIN l ON l.id = e.nbr WHERE e.id NOT IN (SELECT id FROM core) GROUP BY e.id) SELECT p.id, coalesce(l.cluster, b.cluster) AS cluster, l.id IS NOT NULL AS is_core FROM p LEFT JOIN l ON l.id = p.id LEFT JOIN b ON b.id = p.id")
def _(spark, sf):
    return baselines.dbscan(pts(spark, sf), 2.0, 12)


@query("eps_components", f"WITH RECURSIVE {pairs('P_cust')}, k AS (SELECT id AS a, id AS b FROM p UNION SELECT k.a, d.nbr FROM k JOIN d ON k.b = d.id WHERE d.dist < 150e0) SELECT a AS id, min(b) AS cluster FROM k GROUP BY a")
def _(spark, sf):
    return baselines.linkage_cut(pts(spark, sf, "P_cust"), 150.0)


@query("kmeans_sizes")
def _(spark, sf):
    return baselines.kmeans(pts(spark, sf, BLOB), 15).groupBy("cluster").agg(F.count(F.lit(1)).alias("n"))


# ---- operators around the methods ------------------------------------------------------


@query("points_in_box", f"SELECT id, x, y FROM ({points.sql(BLOB)}) WHERE x BETWEEN 0e0 AND 150e0 AND y < 120e0")
def _(spark, sf):
    return pts(spark, sf, BLOB).where("x between 0 and 150 and y < 120").select("id", "x", "y")


@query("dup_points", f"SELECT x, y, count(*) AS weight, min(id) AS id FROM ({points.sql(PART)}) GROUP BY x, y HAVING count(*) > 1")
def _(spark, sf):
    return pts(spark, sf).groupBy("x", "y").agg(F.count(F.lit(1)).alias("weight"), F.min("id").alias("id")).where("weight > 1")


@query("cluster_attributes", f"WITH RECURSIVE {pairs(PART)}, {rho_part(D_PART)}, {dep_part('by_id')}, {top_part(6)}, {label_part()} SELECT l.cluster, part.p_brand, count(*) AS n FROM l JOIN part ON part.p_partkey = l.id GROUP BY ALL")
def _(spark, sf):
    found = pipeline.label(_dep(spark, sf, "list", PART, D_PART, "by_id"), k=6)
    return found.join(table(spark, sf, "part"), F.col("id") == F.col("p_partkey")).groupBy("cluster", "p_brand").agg(F.count(F.lit(1)).alias("n"))


@query("isolated_objects", f"WITH {pairs(BLOB)}, {rho_part(6.0)} SELECT id FROM r WHERE rho = 0")
def _(spark, sf):
    p = pts(spark, sf, BLOB)
    return density.rho(p, 6.0, method="rtree").where("rho = 0").select("id")


@query("orphans", f"WITH {pairs(BLOB)}, {rho_part(D_BLOB)}, {dep_part(tau=20.0, cap=diagonal())} SELECT id, rho FROM dep WHERE is_capped")
def _(spark, sf):
    return _dep(spark, sf, "rn", tau=20.0).where("is_capped").select("id", "rho")


@query("asof_events", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS earlier_id, lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS earlier_value FROM events")
def _(spark, sf):
    before = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.lag("event_id").over(before).alias("earlier_id"), F.lag("value").over(before).alias("earlier_value"))


@query("interval_pairs", "SELECT a.event_id AS id, b.event_id AS nbr FROM events a JOIN events b ON a.event_id < b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 AND abs(a.value - b.value) < 1e0")
def _(spark, sf):
    e = table(spark, sf, "events").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "value").withColumn("slot", F.floor(F.col("t") / F.lit(600_000_000)).cast("long"))
    other = e.select(F.col("event_id").alias("nbr"), F.col("t").alias("u"), F.col("value").alias("v"), F.explode(F.array(F.col("slot") - 1, F.col("slot"), F.col("slot") + 1)).alias("slot"))
    near = (F.abs(F.col("t") - F.col("u")) <= 600_000_000) & (F.abs(F.col("value") - F.col("v")) < 1.0)
    return e.join(other, "slot").where(near & (F.col("event_id") < F.col("nbr"))).select(F.col("event_id").alias("id"), "nbr")


@query("cluster_stats", f"{_BLOB_LABELS} SELECT l.cluster, count(*) AS n, round(avg(p.x), 6) AS mean_x, round(avg(p.y), 6) AS mean_y, min(r.rho) AS least, max(r.rho) AS most, arg_max(r.id, {{'a': r.rho, 'b': -r.id}}) AS densest FROM l JOIN p USING (id) JOIN r USING (id) GROUP BY l.cluster")
def _(spark, sf):
    p = pts(spark, sf, BLOB)
    dep = _dep(spark, sf, "list")
    all_ = pipeline.label(dep, k=15).join(p, "id").join(dep.select("id", "rho"), "id")
    return all_.groupBy("cluster").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("x"), 6).alias("mean_x"), F.round(F.avg("y"), 6).alias("mean_y"), F.min("rho").alias("least"), F.max("rho").alias("most"), F.max_by("id", F.struct("rho", -F.col("id"))).alias("densest"))


@query("density_cube", f"WITH {pairs('P_cust')}, {rho_part(600.0)} SELECT c_nationkey AS nation, c_mktsegment AS segment, count(*) AS n, sum(rho)::BIGINT AS total FROM r JOIN customer ON c_custkey = id GROUP BY CUBE (c_nationkey, c_mktsegment)")
def _(spark, sf):
    r = density.rho(pts(spark, sf, "P_cust"), 600.0).join(table(spark, sf, "customer"), F.col("id") == F.col("c_custkey"))
    return r.cube(F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("n"), F.sum("rho").alias("total"))


@query("density_percentiles")
def _(spark, sf):
    r = density.rho(pts(spark, sf, BLOB), D_BLOB, method="rtree")
    return r.agg(F.percentile_approx("rho", [0.25, 0.5, 0.75, 0.99]).alias("quantiles"), F.approx_count_distinct("rho").alias("levels"))


@query("rho_rank", f"WITH {pairs('P_cust')}, {rho_part(600.0)} SELECT id, c_nationkey AS nation, rho, rank() OVER (PARTITION BY c_nationkey ORDER BY rho DESC)::INT AS place, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY rho DESC, id)::INT AS quarter FROM r JOIN customer ON c_custkey = id")
def _(spark, sf):
    r = density.rho(pts(spark, sf, "P_cust"), 600.0).join(table(spark, sf, "customer"), F.col("id") == F.col("c_custkey"))
    by = Window.partitionBy("c_nationkey")
    return r.select("id", F.col("c_nationkey").alias("nation"), "rho", F.rank().over(by.orderBy(F.desc("rho"))).alias("place"), F.ntile(4).over(by.orderBy(F.desc("rho"), "id")).alias("quarter"))


@query("nlist_gap", f"WITH {pairs('P_supp')} SELECT id, nbr, round(dist - lag(dist) OVER (PARTITION BY id ORDER BY dist, nbr), 6) AS gap FROM d")
def _(spark, sf):
    long = nlist.long_form(nlist.build(pts(spark, sf, "P_supp")))
    return rounded(long.select("id", "nbr", (F.col("dist") - F.lag("dist").over(Window.partitionBy("id").orderBy("dist", "nbr"))).alias("gap")), "gap")


@query("topk_per_cluster", f"{_BLOB_LABELS} SELECT cluster, id, pos::INT AS pos FROM (SELECT l.cluster, l.id, row_number() OVER (PARTITION BY l.cluster ORDER BY r.rho DESC, l.id) AS pos FROM l JOIN r USING (id)) WHERE pos <= 3")
def _(spark, sf):
    dep = _dep(spark, sf, "list")
    own = pipeline.label(dep, k=15).join(dep.select("id", "rho"), "id")
    return own.withColumn("pos", F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("rho"), "id"))).where("pos <= 3").select("cluster", "id", "pos")


_TWO = f"WITH {pairs(BLOB)}, {rho_part(12.0, name='r1')}, {dep_part(r='r1', name='e1')}, {rho_part(20.0, name='r2')}, {dep_part(r='r2', name='e2')}, {top_part(15, 'e1', 'c1')}, {top_part(15, 'e2', 'c2')}"


def _two(spark, sf):
    index = pipeline.build(pts(spark, sf, BLOB), "rtree")
    return [cut(decide.centers_top(pipeline.dependent(index, d), 15)) for d in (12.0, 20.0)]


@query("centers_common", f"{_TWO} SELECT id FROM c1 INTERSECT SELECT id FROM c2")
def _(spark, sf):
    a, b = _two(spark, sf)
    return a.intersect(b)


@query("centers_new", f"{_TWO} SELECT id FROM c2 EXCEPT SELECT id FROM c1")
def _(spark, sf):
    a, b = _two(spark, sf)
    return b.exceptAll(a)


@query("docs_features", f"SELECT id, round(x, 3) AS x, round(y, 3) AS y, truth FROM ({points.sql('P_docs')})")
def _(spark, sf):
    return pts(spark, sf, "P_docs")


@query("events_points", f"SELECT id, x, y FROM ({points.sql('P_events')})")
def _(spark, sf):
    return pts(spark, sf, "P_events")


@query("props_k_density", "SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("bisect_udf", rho_sql(PART, D_PART))
def _(spark, sf):
    # lists of spots, which hold every distance below a radius above the cutoff, with the weights at them
    @F.pandas_udf("long")
    def below(dists: pd.Series, weights: pd.Series) -> pd.Series:
        return pd.Series([int(np.sum(w[: np.searchsorted(d, D_PART, "left")])) for d, w in zip(dists, weights, strict=True)], dtype="int64")

    same = spots.merge(pts(spark, sf))
    long = rnlist.long(same.spots, D_PART + 1).join(same.spots.select(F.col("id").alias("nbr"), F.col(spots.WEIGHT).alias("n")), "nbr")
    lists = long.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("dist", "nbr", "n"))).alias("l")).select("id", below("l.dist", "l.n").alias("near"))
    return same.rho(same.spots.join(lists, "id", "left").select("id", (F.coalesce("near", F.lit(0)) + F.col(spots.WEIGHT) - 1).alias("rho")))


@query("disc_cells", f"WITH p AS ({points.sql('P_supp')}), o AS (SELECT unnest([-1, 0, 1]) AS o) SELECT id, floor(x / 500e0)::BIGINT + a.o AS cx, floor(y / 500e0)::BIGINT + b.o AS cy FROM p, o a, o b")
def _(spark, sf):
    from pyspark.sql.functions import udtf

    @udtf(returnType="cx: bigint, cy: bigint")
    class DiscCells:
        def eval(self, x: float, y: float, side: float):
            import math

            for i in (-1, 0, 1):
                for j in (-1, 0, 1):
                    yield math.floor(x / side) + i, math.floor(y / side) + j

    spark.udtf.register("disc_cells", DiscCells)
    pts(spark, sf, "P_supp").createOrReplaceTempView("disc_points")
    return spark.sql("SELECT id, cx, cy FROM disc_points, LATERAL disc_cells(x, y, 500D)")


@query("haversine_rho", "WITH p AS (SELECT c_custkey AS id, c_nationkey * 14e0 - 170e0 AS x, c_acctbal / 120e0 AS y FROM customer) SELECT a.id, count(b.id)::BIGINT AS rho FROM p a LEFT JOIN p b ON a.id <> b.id AND 2 * 6371.0088e0 * asin(least(1e0, sqrt(sin(radians(b.y - a.y) / 2) * sin(radians(b.y - a.y) / 2) + cos(radians(a.y)) * cos(radians(b.y)) * sin(radians(b.x - a.x) / 2) * sin(radians(b.x - a.x) / 2)))) < 777.7e0 GROUP BY a.id")
def _(spark, sf):
    p = table(spark, sf, "customer").select(F.col("c_custkey").alias("id"), (F.col("c_nationkey") * 14.0 - 170.0).alias("x"), (F.col("c_acctbal") / 120.0).alias("y"))
    return exact.rho(p, 777.7, Space(metric="haversine"))


@query("classify_nodes", _rtree_sql(BLOB, 32, ", q AS (SELECT a.leaf AS q, b.leaf AS n, sqrt(greatest(b.lo_x - a.hi_x, a.lo_x - b.hi_x, 0e0) * greatest(b.lo_x - a.hi_x, a.lo_x - b.hi_x, 0e0) + greatest(b.lo_y - a.hi_y, a.lo_y - b.hi_y, 0e0) * greatest(b.lo_y - a.hi_y, a.lo_y - b.hi_y, 0e0)) AS lo, sqrt(greatest(abs(b.hi_x - a.lo_x), abs(a.hi_x - b.lo_x)) * greatest(abs(b.hi_x - a.lo_x), abs(a.hi_x - b.lo_x)) + greatest(abs(b.hi_y - a.lo_y), abs(a.hi_y - b.lo_y)) * greatest(abs(b.hi_y - a.lo_y), abs(a.hi_y - b.lo_y))) AS hi FROM b a, b) SELECT CASE WHEN hi < 60e0 THEN 'contained' WHEN lo >= 60e0 THEN 'discarded' ELSE 'explored' END AS test, count(*) AS n FROM q GROUP BY 1"))
def _(spark, sf):
    tree = rtree.build(pts(spark, sf, BLOB))
    leaves = tree.nodes.where("is_leaf")
    q = leaves.select(*[F.col(b).alias(f"q_{b}") for b in tree.bounds])
    four = tree.lo("q_"), tree.hi("q_"), tree.lo(), tree.hi()
    both = q.join(leaves).select(metrics.box_min(*four, tree.space).alias("lo"), metrics.box_max(*four, tree.space).alias("hi"))
    return both.groupBy(tree_query.classify(F.col("lo"), F.col("hi"), 60.0).alias("test")).agg(F.count(F.lit(1)).alias("n"))


# ---- streams ---------------------------------------------------------------------------


@query("stream_cell_density", "SELECT floor((epoch_us(ts) - 1704067200000000) / 3600000000e0 / 6e0)::BIGINT AS cell_x, floor(value / 10e0)::BIGINT AS cell_y, count(*) AS n FROM events GROUP BY ALL")
def _(spark, sf):
    return streaming.replay(streaming.cell_density(streaming.events(spark, sf), 6.0, 10.0), "complete")


def _centers(spark: SparkSession, sf: str) -> DataFrame:
    """A center for each event type: the mean of its events, under its smallest id."""
    e = pts(spark, sf, "P_events").join(table(spark, sf, "events").select(F.col("event_id").alias("id"), "event_type"), "id")
    return e.groupBy("event_type").agg(F.min("id").alias("id"), F.round(F.avg("x"), 3).alias("x"), F.round(F.avg("y"), 3).alias("y")).select("id", "x", "y")


@query("stream_label", f"WITH p AS ({points.sql('P_events')}), c AS (SELECT min(p.id) AS id, round(avg(x), 3) AS x, round(avg(y), 3) AS y FROM p JOIN events ON event_id = p.id GROUP BY event_type) SELECT p.id AS event_id, arg_min(c.id, {{'a': sqrt((p.x - c.x) * (p.x - c.x) + (p.y - c.y) * (p.y - c.y)), 'b': c.id}}) AS cluster FROM p, c GROUP BY p.id")
def _(spark, sf):
    return streaming.replay(streaming.label(streaming.events(spark, sf), cut(_centers(spark, sf))))


@query("stream_sessions", "WITH e AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, epoch_us(min(ts)) AS start_us, epoch_us(max(ts) + INTERVAL 6 HOUR) AS end_us, count(*) AS n FROM s GROUP BY user_id, k")
def _(spark, sf):
    s = streaming.replay(streaming.sessions(streaming.events(spark, sf)), "complete")
    return s.select("user_id", F.unix_micros("start").alias("start_us"), F.unix_micros("end").alias("end_us"), "n")


@query("stream_windows", "SELECT epoch_us(date_trunc('day', ts)) AS start_us, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def _(spark, sf):
    w = streaming.replay(streaming.windows(streaming.events(spark, sf)), "complete")
    return w.select(F.unix_micros("start").alias("start_us"), "event_type", "n", F.round("total", 4).alias("total"))


@query("stream_sliding", "SELECT epoch_us(date_trunc('day', ts) - to_days(o)) AS start_us, event_type, count(*) AS n FROM events, (SELECT unnest([0, 1])::INT AS o) GROUP BY ALL")
def _(spark, sf):
    w = streaming.replay(streaming.windows(streaming.events(spark, sf), "2 days", "1 day"), "complete")
    return w.select(F.unix_micros("start").alias("start_us"), "event_type", "n")


@query("stream_distinct", "SELECT DISTINCT event_id FROM events")
def _(spark, sf):
    return streaming.replay(streaming.distinct_events(streaming.events(spark, sf)).select("event_id"))


@query("stream_stateful_cells", "SELECT concat(floor((epoch_us(ts) - 1704067200000000) / 3600000000e0 / 24e0)::BIGINT, ':', floor(value / 20e0)::BIGINT) AS cell, count(*) AS n, min(event_id) AS first_event, max(event_id) AS last_event FROM events GROUP BY 1")
def _(spark, sf):
    return streaming.replay(streaming.running_cells(streaming.events(spark, sf), 24.0, 20.0), "update")


@query("stream_reindex", rho_sql("P_events", 5.0))
def _(spark, sf):
    got: list[DataFrame] = []

    def reindex(batch: DataFrame, n: int) -> None:
        x = (F.unix_micros("ts") - F.lit(1704067200000000)) / F.lit(3600000000.0)
        p = cut(batch.select(F.col("event_id").alias("id"), F.round(x, 4).alias("x"), F.col("value").alias("y")))
        got.append(cut(pipeline.tree_rho(p, 5.0, capacity=64)))

    streaming.replay(streaming.events(spark, sf), each=reindex)
    return got[-1]
