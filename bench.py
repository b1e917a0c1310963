"""Times the headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS] and prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
#: Budgeted miner against per-item projection, partitioning and in-memory growth, with shares at which each table has work to do.
SHARES = {"w1": 0.001, "w2": 0.4, "w5": 0.35, "w6": 0.01, "w7": 0.01}
ROOM = {"w1": 60_000, "w2": 60_000, "w5": 20_000, "w6": 20, "w7": 100_000}


def main() -> None:
    from fimspark.plans import accuracy, baselines, budget, miner
    from fimspark.session import local_session, stage
    from fimspark.sources import synth
    from fimspark.sources.baskets import WORKLOADS

    spark = local_session(CPUS, 2 * int(CPUS) if CPUS.isdigit() else 8, "8g")
    spark.sparkContext.setLogLevel("ERROR")
    times, notes = {}, {}

    def timed(name: str, f):
        began = time.perf_counter()
        out = f()
        times[name] = round(time.perf_counter() - began, 3)
        return out

    small = stage(WORKLOADS["w6"](spark, SF_DIR))  # start workers and compile, for all methods alike
    miner.mine_budgeted(small, 0.01, 20).fi.count()
    miner.mine_per_item(small, 0.01).fi.count()
    baselines.partitioned(small, 0.01, 4).fi.count()
    for w, share in SHARES.items():
        tx = stage(WORKLOADS[w](spark, SF_DIR))
        room = ROOM[w]
        n = timed(f"budgeted_{w}", lambda: miner.mine_budgeted(tx, share, room).fi.count())
        timed(f"per_item_{w}", lambda: miner.mine_per_item(tx, share).fi.count())
        timed(f"partitioned_{w}", lambda: baselines.partitioned(tx, share, 4).fi.count())
        timed(f"in_memory_{w}", lambda: baselines.in_memory(tx, share).fi.count())
        result = miner.mine_budgeted(tx, share, room, measure=True)
        per_item = miner.mine_per_item(tx, share, measure=True)
        est = [(g.est_nodes, g.real_nodes) for g in accuracy.group_estimates(spark, result, budget.usable_nodes(room)).collect() if g.est_nodes]
        notes[w] = {
            "itemsets": n,
            "groups": len(result.groups),
            "cells": result.ledger.cells("ranked"),
            "written_cells": {p: result.ledger.cells(p) for p in ("collapsed", "pairs", "pilot rows", "head", "projected", "projected again")},
            "per_item_written_cells": per_item.ledger.written(),
            "est_over_real": [round(e / r, 2) for e, r in est if r][:8],
            "most_nodes_held": result.counters.held,
            "node_budget": room,
        }
    for rows in (4_000, 12_000, 40_000):  # the published curve: rows times ten, 10,000 items, baskets of 100, patterns of 20, 1.5 %
        tx = stage(synth.baskets(spark, rows, 10_000, 100, 20, 2000, corruption=0.5))
        n = timed(f"scale_{rows}", lambda: miner.mine_budgeted(tx, 0.015, 200_000).fi.count())
        notes[f"scale_{rows}"] = {"itemsets": n}
    sums = {m: sum(times[f"{m}_{w}"] for w in SHARES) for m in ("budgeted", "per_item", "partitioned", "in_memory")}
    notes["budgeted_over_per_item"] = round(sums["budgeted"] / sums["per_item"], 2)
    print(json.dumps({"metric": "sum of headline query times", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": SF_DIR.rstrip("/").rpartition("sf")[2], "notes": notes}))


if __name__ == "__main__":
    main()
