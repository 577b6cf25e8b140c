"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

from weftgraph import api, metrics
from weftgraph.operators import baselines
from weftgraph.plans import planner
from weftgraph.plans.patterns import named
from weftgraph.plans.planner import Configuration
from weftgraph.sources.graphs import graph

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.sql.shuffle.partitions", str(4 * int(CPUS))).config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def run(name: str, f) -> object:
        began = time.perf_counter()
        out = f()
        times[name] = round(time.perf_counter() - began, 3)
        print(f"{name}: {times[name]} s, {out}", file=sys.stderr, flush=True)
        return out

    total = time.perf_counter()
    for d in ("d1", "d2", "d3"):
        run(f"build_{d}", lambda d=d: graph(spark, SF, d).stats())
    for d in ("d1", "d2"):
        g = graph(spark, SF, d)
        for n in ("triangle", "k4", "w1", "w2", "w3", "w4"):
            p = named(n)
            c = planner.choose_iep(p, g.stats())
            fast = run(f"iep_{n}_{d}", lambda g=g, p=p, c=c: api.count(g, p, c, method="iep").first()["n"])
            slow = run(f"enumerate_{n}_{d}", lambda g=g, p=p, c=c: api.count(g, p, Configuration(p, c.order, c.restrictions), method="enumerate").first()["n"])
            assert fast == slow, (n, d, fast, slow)
    for n in ("w5", "w6"):
        run(f"iep_{n}_d1", lambda n=n: api.count(graph(spark, SF, "d1"), named(n), method="iep").first()["n"])
    g = graph(spark, SF, "d1")
    for n in ("w1", "w2"):
        ours = run(f"planned_{n}_d1", lambda n=n: api.count(g, named(n), method="enumerate").first()["n"])
        for b in ("single_set", "motif_dataframe", "loop_compiler"):
            assert run(f"{b}_{n}_d1", lambda n=n, b=b: baselines.BASELINES[b](g, named(n)).first()["n"]) == ours
    dense = graph(spark, SF, "d3")
    for g, n in ((graph(spark, SF, "d2"), "star3"), (graph(spark, SF, "d2"), "path4"), *((dense, x) for x in ("triangle", "tailed", "diamond", "w2", "w3"))):
        p = named(n)
        c = planner.choose_iep(p, g.stats())
        fast = run(f"iep_{n}_{g.name}", lambda g=g, p=p, c=c: api.count(g, p, c, method="iep").first()["n"])
        slow = metrics.timed(g, lambda g=g, p=p, c=c: api.count(g, p, Configuration(p, c.order, c.restrictions), method="enumerate"), 60)
        times[f"enumerate_{n}_{g.name}"] = round(slow.seconds, 3)
        print(f"enumerate_{n}_{g.name}: {slow}", file=sys.stderr, flush=True)
        assert slow.status != "ok" or slow.value == fast
    print(json.dumps({"metric": "total_seconds", "value": round(time.perf_counter() - total, 3), "unit": "sec", "queries": times, "sf": SF}))


if __name__ == "__main__":
    main()
