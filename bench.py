"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", str(os.cpu_count() or 8))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    from density_peaks import cost, exact, grid, pipeline, points
    from density_peaks.index import chist, nlist, quadtree, rnlist, rtree, tree_query
    from density_peaks.iterate import cut

    times: dict[str, float] = {}
    facts: dict[str, float] = {}

    def run(name: str, fn):
        t = time.perf_counter()
        out = fn()
        times[name] = round(time.perf_counter() - t, 3)
        return out

    def aside(name: str, fn):
        """A comparison that does not count to the total."""
        out, seconds = cost.timed(fn)
        facts[f"{name}_s"] = round(seconds, 3)
        return out

    def whole(df):
        cost.force(df)
        return df

    view = lambda name: cut(points.view(spark, sf_dir, name).select("id", "x", "y"))
    small, events, lines = view("P_blob15"), view("P_events"), view("P_lineitem")
    facts |= {"n_blob15": small.count(), "n_events": events.count(), "n_lineitem": lines.count()}

    # the skewed view: cut lists with and without histograms, grid, trees
    lists = run("events_rn_build_tau2", lambda: cut(rnlist.build(events, 2.0)))
    hist = run("events_rn_ch_build", lambda: cut(chist.packed(lists, 0.25)))
    facts["events_list_bytes"] = cost.list_bytes(lists).first()["bytes"]
    facts["events_hist_bytes"] = cost.packed_hist_bytes(hist).first()["bytes"]
    run("events_rn_rho_1", lambda: whole(nlist.rho(lists, 1.0)))
    run("events_rn_ch_rho_1", lambda: whole(chist.rho_packed(hist, 1.0, 0.25)))
    run("events_grid_rho_1", lambda: whole(grid.rho(events, 1.0)))
    quad = run("events_quadtree_build", lambda: quadtree.build(events, 128))
    tree = run("events_rtree_build", lambda: rtree.build(events, 128))
    facts["events_rtree_bytes"] = cost.tree_bytes(tree).first()["bytes"]
    rho = run("events_rtree_rho_1", lambda: cut(tree_query.rho(tree, 1.0)))
    run("events_quadtree_rho_1", lambda: whole(tree_query.rho(quad, 1.0)))
    run("events_rtree_delta", lambda: whole(tree_query.delta(tree, rho, "by_id")))
    run("events_quadtree_delta", lambda: whole(tree_query.delta(quad, rho, "by_id")))

    # 600 000 points on the packed tree, cutoff to clusters
    big = run("lineitem_rtree_build", lambda: rtree.build(lines, 256))
    big_rho = run("lineitem_rtree_rho_3", lambda: cut(tree_query.rho(big, 3.0)))
    dep = run("lineitem_rtree_delta", lambda: cut(tree_query.delta(big, big_rho, "by_id")))
    run("lineitem_assign", lambda: whole(pipeline.label(dep, k=10)))
    run("blob15_cluster", lambda: whole(pipeline.cluster(small, 20.0, "rtree", k=15)))

    # the original method beside indices over the same points, and what histograms save
    near = aside("blob15_rtree_build", lambda: rtree.build(small))
    aside("blob15_brute_rho", lambda: exact.rho(small, 20.0))
    aside("blob15_grid_rho", lambda: grid.rho(small, 20.0))
    aside("blob15_rtree_rho", lambda: tree_query.rho(near, 20.0))
    for d_c in (0.5, 1.0, 2.0):
        for _ in range(2):  # the second time counts
            aside(f"events_list_rho_{d_c}", lambda: nlist.rho(lists, d_c))
            aside(f"events_hist_rho_{d_c}", lambda: chist.rho_packed(hist, d_c, 0.25))
        facts[f"events_hist_gain_{d_c}"] = round(cost.gain(facts[f"events_list_rho_{d_c}_s"], facts[f"events_hist_rho_{d_c}_s"]), 3)

    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "facts": facts, "sf": sf_dir.rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
