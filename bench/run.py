"""The experiments: generated against handwritten programs, fused against unfused ones, models, number of sources.

python bench/run.py [folder of tables] [runs]: prints Markdown rows (edges, edge-work ratio, steps, mean seconds).
"""

from __future__ import annotations

import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

from pyspark.sql import SparkSession

from walkfold import graphs as G
from walkfold import usecases as U
from walkfold.baselines import handwritten as H
from walkfold.baselines import unfused as X
from walkfold.exec.metrics import RunMetrics


def timed(run, runs: int) -> tuple[RunMetrics, float]:
    took, m = 0.0, RunMetrics()
    for _ in range(runs):
        m = RunMetrics()
        at = time.perf_counter()
        run(m).write.format("noop").mode("overwrite").save()
        took += time.perf_counter() - at
    return m, took / runs


def compare(name: str, a, b, runs: int) -> None:
    (x, s), (y, t) = timed(a, runs), timed(b, runs)
    print(f"| {name} | {y.edges_processed} | {x.edges_processed} | {100 * x.edges_processed / max(1, y.edges_processed):.0f}% | {y.n_steps} / {x.n_steps} | {t:.2f} / {s:.2f} | {t / s:.2f} |", flush=True)


def main(sf_dir: str, runs: int) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.checkpoint.dir", "file:///tmp/walkfold-bench").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    g1, g3, g4, g7 = (b(spark, sf_dir) for b in (G.part_hop, G.cust_supp, G.user_relay, G.page_link))
    s1, s3, s4 = (G.top_sources(g, 16) for g in (g1, g3, g4))
    print("| case | edges H | edges S | S / H | steps H / S | seconds H / S | H / S |\n| --- | --- | --- | --- | --- | --- | --- |")
    print("| generated (S) against handwritten (H) | | | | | | |")
    compare("SSSP part_hop", lambda m: U.sssp(g1, s1[0], metrics=m), lambda m: H.sssp(g1, s1[0], metrics=m), runs)
    compare("WP part_hop", lambda m: U.widest_path(g1, s1[0], metrics=m), lambda m: H.wp(g1, s1[0], metrics=m), runs)
    compare("BFS cust_supp", lambda m: U.bfs_tree(g3, s3[0], metrics=m), lambda m: H.bfs(g3, s3[0], metrics=m), runs)
    compare("CC cust_supp", lambda m: U.connected_components(g3, metrics=m), lambda m: H.cc(g3, metrics=m), runs)
    compare("CC cust_supp, H initialises in step 1", lambda m: U.connected_components(g3, metrics=m), lambda m: H.cc(g3, metrics=m, init_in_step=True), runs)
    compare("PR page_link", lambda m: U.page_rank(g7, metrics=m), lambda m: H.pr(g7, metrics=m), runs)
    print("| fused (S) against unfused (H) | | | | | | |")
    unit = G.unit(g1)
    for name, g, by in (("weighted", g1, "weight"), ("unweighted", unit, "length")):
        compare(f"WSP {name}", lambda m, g=g, by=by: U.widest_shortest(g, s1[0], by, metrics=m), lambda m, g=g, by=by: X.widest_shortest(g, s1[0], by, metrics=m), runs)
        compare(f"NWR {name}", lambda m, g=g: U.narrow_wide_ratio(g, s1[0], metrics=m), lambda m, g=g: X.narrow_wide_ratio(g, s1[0], metrics=m), runs)
    compare("Radius, 2 sources", lambda m: U.radius(g1, s1[:2], metrics=m), lambda m: X.radius(g1, s1[:2], metrics=m), runs)
    compare("DRR cust_supp", lambda m: U.diameter_radius_ratio(g3, s3[:2], metrics=m), lambda m: X.diameter_radius_ratio(g3, s3[:2], metrics=m), runs)
    compare("Trust user_relay", lambda m: U.trust(g4, s4[:2], metrics=m), lambda m: X.trust(g4, s4[:2], metrics=m), runs)
    compare("RDS part_hop", lambda m: U.radius_trust_floor(g1, s1[0], s1[:2], metrics=m), lambda m: X.radius_trust_floor(g1, s1[0], s1[:2], metrics=m), runs)
    print("| radius by number of sources, fused (S) against unfused (H) | | | | | | |")
    for k in (1, 2, 4, 8, 16):
        compare(f"Radius, {k} sources", lambda m, k=k: U.radius(g1, s1[:k], metrics=m), lambda m, k=k: X.radius(g1, s1[:k], metrics=m), 1)
    print("| models (S) against push (H), SSSP | | | | | | |")
    for model in ("pull", "auto_switch", "async"):
        compare(model, lambda m, x=model: U.sssp(g1, s1[0], model=x, metrics=m), lambda m: U.sssp(g1, s1[0], model="push", metrics=m), runs)


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1", int(sys.argv[2]) if len(sys.argv) > 2 else 1)
