"""The experiment workloads in full, from the command line: one JSON line a measurement.

    python -m weftgraph.workloads overall SF_DIR [SECONDS]   every pattern x graph x method, each with a time limit
    python -m weftgraph.workloads iep SF_DIR [SECONDS]       every pattern x graph, enumerated and by inclusion-exclusion
    python -m weftgraph.workloads regret SF_DIR              the seven-vertex patterns on the smallest graph: selected against least loop work
    python -m weftgraph.workloads scaling SF_DIR [SECONDS]   two patterns on the largest graph in sessions of 1, 2, 4 and all cores

The registered queries run the cells of these grids that end in seconds on small tables.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys

from pyspark.sql import SparkSession

GRAPHS = ("d1", "d2", "d3")


def session(cores: int | None = None) -> SparkSession:
    cores = cores or os.cpu_count() or 1
    builder = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(4 * cores))
    spark = builder.config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def say(**row) -> None:
    print(json.dumps(row), flush=True)


def overall(sf: str, seconds: float) -> None:
    from .plans.patterns import WORKLOAD
    from .queries import experiments

    spark = session()
    for d in GRAPHS:
        for n in WORKLOAD:
            for pattern, graph, method, count, _, took, status in experiments.overall(spark, sf, [(n, d)], seconds):
                say(workload="overall", pattern=pattern, graph=graph, method=method, n=count, seconds=round(took, 3), status=status)


def iep(sf: str, seconds: float) -> None:
    from . import metrics
    from .plans.patterns import WORKLOAD, named
    from .sources.graphs import graph

    spark = session()
    for d in GRAPHS:
        for n in WORKLOAD:
            for method, t in zip(("enumerate", "iep"), metrics.iep_speedup(graph(spark, sf, d), named(n), seconds), strict=True):
                say(workload="iep", pattern=n, graph=d, method=method, n=t.value, seconds=round(t.seconds, 3), status=t.status)


def regret(sf: str, seconds: float) -> None:
    from . import metrics
    from .plans.patterns import named
    from .sources.graphs import graph

    spark = session()
    for n in ("w5", "w6"):
        g = graph(spark, sf, "d1")
        meter, found = metrics.LoopWork(g), metrics.configurations(g, named(n))
        works = [meter.of(c) for c in found]
        say(workload="regret", pattern=n, graph="d1", configurations=len(found), selected=works[0], least=min(works), most=max(works), rank_correlation=metrics.rank_corr([c.cost for c in found], works))


def one_scale(sf: str, seconds: float, cores: int) -> None:
    from . import api, metrics
    from .plans.patterns import named
    from .sources.graphs import graph

    spark = session(cores)
    g = graph(spark, sf, "d3")
    g.stats()
    for n in ("w1", "w2"):
        t = metrics.timed(g, lambda n=n: api.count(g, named(n), method="iep"), seconds)
        say(workload="scaling", pattern=n, graph="d3", cores=cores, n=t.value, seconds=round(t.seconds, 3), status=t.status)


def scaling(sf: str, seconds: float) -> None:
    for cores in sorted({1, 2, 4, os.cpu_count() or 1}):
        subprocess.run([sys.executable, "-m", "weftgraph.workloads", "one_scale", sf, str(seconds), str(cores)], check=True)


def main(args: list[str]) -> None:
    name, sf, *rest = args
    seconds = float(rest[0]) if rest else 60.0
    if name == "one_scale":
        one_scale(sf, seconds, int(rest[1]))
    else:
        {"overall": overall, "iep": iep, "regret": regret, "scaling": scaling}[name](sf, seconds)


if __name__ == "__main__":
    main(sys.argv[1:])
