"""Headline queries, timed: load, sample (or measure) and write, as one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1) and BENCH_CPUS (default 4) choose tables and
cores.  ``python bench.py workers`` runs the samplers on 1, 2, 4 and 8 cores, ``python bench.py
volume`` on three table sizes with the number of sampled vertices held; both print tables
of the mean of BENCH_RUNS (default 3) runs.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
RUNS = int(os.environ.get("BENCH_RUNS", "3"))


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def write(sample) -> None:
    """Both tables of a sample go to a sink that takes all rows and keeps none."""
    sample.vertices.write.format("noop").mode("overwrite").save()
    sample.edges.write.format("noop").mode("overwrite").save()


def samplers(share: float, walkers: int, target: int | None = None) -> dict:
    from gsample.operators import samplers as S
    from gsample.operators import walk as W

    return {
        "rv": lambda g: S.random_vertex(g, share, source="fast"),
        "rv_join": lambda g: S.random_vertex(g, share, strategy="join", source="fast"),
        "re": lambda g: S.random_edge(g, share, source="fast"),
        "rvn": lambda g: S.random_vertex_neighborhood(g, share, source="fast"),
        "rvn_join": lambda g: S.random_vertex_neighborhood(g, share, strategy="join", source="fast"),
        "rw": lambda g: W.random_walk(g, target=target or 700, walkers=walkers, source="fast"),
    }


def timed(f) -> float:
    began = time.perf_counter()
    f()
    return round(time.perf_counter() - began, 3)


def headline() -> None:
    from gsample.operators import metrics as M
    from gsample.sources.graphs import GRAPHS

    spark = session(CPUS)
    load = lambda name: GRAPHS[name](spark, SF)
    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    load("commerce").edges.count()  # starts the workers
    jobs = {f"{n}_commerce": (lambda f=f: write(f(load("commerce")))) for n, f in samplers(0.0376, 35).items()}
    jobs |= {
        "triangles_co_purchase": lambda: noop(M.triangle_count(load("co_purchase"))),
        "local_clustering_co_purchase": lambda: noop(M.average_local_clustering(load("co_purchase"))),
        "wcc_commerce": lambda: noop(M.wcc_count(load("commerce"))),
        "degrees_commerce": lambda: noop(M.degree_stats(load("commerce"))),
        "doc_overlap": lambda: noop(load("doc_overlap").edges),
    }
    try:
        from gsample.llm.queries import QUERIES
    except ImportError:
        QUERIES = {}
    jobs |= {n: (lambda f=f: noop(f(spark, SF))) for n, f in QUERIES.items()}
    times = {n: timed(f) for n, f in jobs.items()}
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": SF, "cpus": CPUS}))


def workers() -> None:
    """Seconds and speedup by cores; each number of cores is a process of its own."""
    import subprocess

    if len(sys.argv) > 2:
        from gsample.operators.compare import timed_run
        from gsample.sources.graphs import GRAPHS

        spark = session(sys.argv[2])
        load = lambda: GRAPHS["commerce"](spark, SF)
        write(samplers(0.0376, 35)["rv"](load()))  # starts the workers
        for n, f in samplers(0.0376, 35).items():
            print(json.dumps({"method": n, "workers": int(sys.argv[2]), "seconds": timed_run(load, f, write, RUNS)}), flush=True)
        return
    rows = []
    for c in ("1", "2", "4", "8"):
        out = subprocess.run([sys.executable, __file__, "workers", c], capture_output=True, text=True).stdout
        rows += [json.loads(x) for x in out.splitlines() if x.startswith("{")]
    from gsample.operators.compare import speedup

    spark = session("2")
    speedup(spark.createDataFrame(rows)).orderBy("method", "workers").show(99)


def volume() -> None:
    """Seconds by size at about 700 sampled vertices."""
    from gsample.operators.compare import timed_run, volume_series
    from gsample.sources.graphs import GRAPHS

    spark, rows = session(CPUS), []
    write(samplers(0.37, 35)["rv"](GRAPHS["commerce"](spark, "/root/testdata/sf0.001")))  # starts the workers
    for sf, share in (("0.001", 0.37), ("0.01", 0.0376), ("0.1", 0.00376)):
        d = f"/root/testdata/sf{sf}"
        edges = GRAPHS["commerce"](spark, d).edges.count()
        for n, f in samplers(share, 35).items():
            rows.append({"method": n, "edges": edges, "seconds": timed_run(lambda d=d: GRAPHS["commerce"](spark, d), f, write, RUNS)})
    volume_series(spark.createDataFrame(rows)).orderBy("method", "edges").show(99)


if __name__ == "__main__":
    {"workers": workers, "volume": volume}.get((sys.argv[1:] or ["headline"])[0], headline)()
