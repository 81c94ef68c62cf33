"""Times the methods on the workloads at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line.

Snapshots, batches and old ranks are made before the clock starts, and the edges of a run over all of them are laid out and kept; marking,
lookups, rounds and stop tests are timed. All rounds are distributed ones. Besides seconds: speedups over the cold run, and rows that cold
scanned over rows that the method scanned, as geometric means over workloads, by batch size.
"""

from __future__ import annotations

import json
import math
import os
import time

from incrank.plans import planner
from incrank.plans.methods import run_method
from incrank.plans.prepared import prepared
from incrank.session import local_session
from incrank.sources.workloads import TEMPORAL

STATIC = ("order_chain", "turn_chain", "web_links", "geo_tree")
#: (batch as a share of the edges, workloads, methods); cold's time on a workload is measured once, on its largest batch.
PLAN = (
    (1e-3, (*TEMPORAL, *STATIC), ("cold", "frontier", "pruned")),
    (1e-3, ("event_flow", "part_flow", "order_chain"), ("warm", "reach")),
    (1e-4, TEMPORAL, ("pruned",)),
    (1e-5, TEMPORAL, ("frontier", "pruned")),
)
#: No run starts after so many seconds, so that a slow machine still gives its line; what is left out is listed.
LIMIT = float(os.environ.get("BENCH_LIMIT", "900"))


def geomean(xs: list[float]) -> float:
    return round(math.exp(sum(math.log(x) for x in xs) / len(xs)), 2) if xs else 0.0


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "4"))
    spark = local_session(cpus, max(8, cpus))
    began, seconds, scanned, left_out = time.perf_counter(), {}, {}, []
    for f, names, methods in PLAN:
        for w in names:
            if time.perf_counter() - began > LIMIT:
                left_out += [f"{m}/{w}/{f:.0e}" for m in methods]
                continue
            p = prepared(spark, sf_dir, w, f)
            p.new.laid(planner.partitions(p.new.n_edges, max(8, cpus), cpus)).count()
            if not seconds:
                for m in ("cold", "pruned"):
                    run_method(m, p.old, p.new, p.delta, p.table).drop()  # starts workers, compiles code
            for m in methods:
                run = run_method(m, p.old, p.new, p.delta, p.table)
                seconds[f"{m}/{w}/{f:.0e}"], scanned[f"{m}/{w}/{f:.0e}"] = run.seconds, max(1, run.rows_scanned)
                run.drop()
            p.new.release()

    def over_cold(table: dict[str, float], m: str, f: float) -> float:
        return geomean([table[f"cold/{w}/1e-03"] / table[k] for w in (*TEMPORAL, *STATIC) if (k := f"{m}/{w}/{f:.0e}") in table and f"cold/{w}/1e-03" in table])

    ratios = lambda table: {f"{m}/{f:.0e}": r for f, _, ms in PLAN for m in ms if m != "cold" and (r := over_cold(table, m, f))}
    each = {k: round(seconds[f"cold/{k.split('/')[1]}/1e-03"] / s, 2) for k, s in seconds.items() if not k.startswith("cold/") and f"cold/{k.split('/')[1]}/1e-03" in seconds}
    print(json.dumps({
        "metric": "rank maintenance, all methods, one batch", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": {k: round(v, 3) for k, v in seconds.items()}, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1],
        "speedup_over_cold": ratios(seconds), "scanned_cold_over": ratios(scanned), "speedup_each": each, "left_out": left_out, "wall": round(time.perf_counter() - began, 1),
    }))


if __name__ == "__main__":
    main()
