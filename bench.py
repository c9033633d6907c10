"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line."""

from __future__ import annotations

import json
import os
import statistics
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Patterns in a batch: a Spark job takes longer than a pattern, so a pattern's time is its share of a batch.
BATCH = 1000
RUNS = 1


def main() -> None:
    conf = {"spark.sql.shuffle.partitions": str(2 * int(CPUS)), "spark.driver.memory": "12g", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC"}
    spark = SparkSession.builder.master(f"local[{CPUS}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")

    from bitgraph.operators.graph import open_graph
    from bitgraph.plans import workloads
    from bitgraph.plans.graph_queries import engine_of

    times: dict[str, float] = {}
    notes: dict[str, float] = {}

    def once(name: str, f) -> None:
        began = time.perf_counter()
        f()
        times[name] = round(time.perf_counter() - began, 3)

    def warm(name: str, f) -> None:
        """The median of runs after a first one."""
        f().write.format("noop").mode("overwrite").save()
        seconds = []
        for _ in range(RUNS):
            began = time.perf_counter()
            f().write.format("noop").mode("overwrite").save()
            seconds.append(time.perf_counter() - began)
        times[name] = round(statistics.median(seconds), 3)

    star = open_graph(spark, SF_DIR, "star")
    once("prepare_star", lambda: star.ids.count())
    once("build_tree_star", lambda: star.index())
    once("build_tree_star_auto", lambda: star.index("auto", "auto"))
    n = star.ids.count()
    notes["facts"] = n
    notes["tree_bits_per_fact"] = round(star.index("auto", "auto").size_bits() / n, 2)
    notes["tree_over_column_partitions"] = round(star.index("auto", "auto").size_bits() / (64 * n), 4)
    facts = star.scratch.keep(star.ids.orderBy(F.xxhash64("s_id", "p_id", "o_id")).limit(BATCH))
    for shape, positions in workloads.SHAPES.items():
        if shape == "p":
            warm("pattern_p", lambda: star.index().match(p=1))
            continue
        bindings = star.scratch.keep(facts.select(*[f"{c}_id" for c in positions]).distinct())
        for engine in ("tree", "tree_pidx", "colpart_os"):
            if engine == "tree_pidx" and "p" in positions:
                continue
            warm(f"pattern_{shape}_{engine}", lambda: engine_of(star, engine).match_batch(bindings))  # noqa: B023
        notes[f"ms_per_pattern_{shape}"] = round(1000 * times[f"pattern_{shape}_tree"] / bindings.count(), 4)
    constants = star.scratch.keep(workloads.anchors(star))
    for name in ("a_ss", "b_oo", "c_so", "d1_so", "e2_ss", "f2_so"):
        for engine in ("tree", "tree_pidx"):
            warm(f"join_{name}_{engine}", lambda: workloads.run_join(star, workloads.TEMPLATES[name], engine_of(star, engine), constants=constants))  # noqa: B023
        notes[f"ms_per_join_{name}"] = round(100 * times[f"join_{name}_tree"], 2)  # ten joins a run
    print(json.dumps({"metric": "seconds of headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": float(Path(SF_DIR).name.removeprefix("sf") or 0) if Path(SF_DIR).name.startswith("sf") else SF_DIR, "notes": notes}))


if __name__ == "__main__":
    main()
