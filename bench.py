"""Headline queries on one machine; prints one JSON line.

Each strategy answers a shortest-path query on every snapshot of the trade graph
under a script of additions and deletions (0.22 % of the edges a step). Strategies
that loop over snapshots run on a short window; ``together`` ones on 64 snapshots.
``ms_per_snapshot`` makes the two comparable, and the counters say how much work
was done whatever the machine.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from chronopath.functions.algebra import ALGEBRAS
from chronopath.plans import evolve
from chronopath.plans import strategies as S
from chronopath.sources import graphs
from chronopath.storage import store

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
SHORT, LONG = 4, 64


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("OFF")
    times, work, per_snapshot = {}, {}, {}

    def timed(name, run):
        began = time.perf_counter()
        out = run()
        times[name] = round(time.perf_counter() - began, 2)
        return out

    edges = timed("graph_trade", lambda: store(graphs.trade(spark, SF_DIR), "trade"))
    n_edges = edges.count()
    batch = 2 * round(0.0022 * n_edges / 2)
    lives = {n: store(evolve.scripted(edges, n, batch), "lifetimes") for n in (SHORT, LONG)}
    source = edges.agg({"src": "min"}).first()[0]

    def strategy(name, algebra, n):
        def run():
            results, stats = S.run(name, lives[n], S.PathQuery(source, ALGEBRAS[algebra], tuple(range(n))))
            results.write.format("noop").mode("overwrite").save()
            return stats

        key = f"{name}_{algebra}_{n}"
        stats = timed(key, run)
        per_snapshot[key] = round(1000 * times[key] / n, 1)
        work[key] = {k: {"ms": round(stats.phase_ms[k]), "rounds": w.rounds, "evaluations": w.evaluations} for k, w in stats.work.items()}

    for name in ("stream_inc", "core_share", "residual_share"):
        strategy(name, "shortest", SHORT)
    for name in ("recompute_together", "core_conc", "residual_conc"):
        strategy(name, "shortest", LONG)
    for algebra in ("hops", "widest", "narrowest", "likeliest"):
        strategy("residual_conc", algebra, LONG)
    print(json.dumps({"metric": "residual_conc_shortest_64_snapshots", "value": times[f"residual_conc_shortest_{LONG}"], "unit": "sec", "queries": times, "sf": os.path.basename(SF_DIR.rstrip("/")), "edges": n_edges, "batch": batch, "ms_per_snapshot": per_snapshot, "work": work}))
    spark.stop()


if __name__ == "__main__":
    main()
