"""Headline timings: one JSON line. BENCH_SF_DIR and BENCH_CPUS choose tables and cores.

All eight motifs: weights, draws, extension, the error over five seeded runs, the exact count beside them. Then windows that grow
until the exact counters no longer end in time, the window samplers at several times our time, and the
same estimate on fewer cores (each in a process of its own; BENCH_SCALING=0 leaves these out).
"""

from __future__ import annotations

import json
import os
import re
import statistics
import subprocess
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession

from tmotif.functions.motif import EIGHT, motif
from tmotif.operators import baselines, exact
from tmotif.operators.incidence import ranked_incidence
from tmotif.operators.measures import guarded, relative_error, speedup
from tmotif.operators.sampling import sample_paths
from tmotif.plans.estimate import completions, estimate_seeds, heuristic_samples, pilot, prepare, summary
from tmotif.sources.graph import TemporalGraph, nation_graph, reply_graph
from tmotif.sources.io import staged

HOUR = 3_600_000_000
K, SEEDS = 100_000, range(42, 47)
#: Draws of the rare motifs are set by the heuristic, up to so many.
MOST = 400_000
#: Seconds after which an exact counter or a window sampler is ended.
PATIENCE = 15.0


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def one_estimate(tg: TemporalGraph, name: str, delta: int, k: int):
    """Everything from the edges to the estimate of one motif."""
    m = motif(name)
    p = prepare(tg, delta, m.anchor().cls)
    paths = sample_paths(tg, p.centers, p.w_total, delta, p.cls, k, lists=p.lists)
    return summary(completions(p, m, m.anchor(), paths), m, delta, p.w_total, k=k).first()


def scaling(sf_dir: str, cpus: str) -> None:
    """Prints the seconds of the second of two estimates: the first one starts the machine."""
    tg = reply_graph(session(cpus), sf_dir, 12).staged()
    for _ in range(2):
        began = time.time()
        one_estimate(tg, "M4-0", 6 * HOUR, K)
    print(json.dumps({"seconds": time.time() - began}))


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    if len(sys.argv) == 3 and sys.argv[1] == "--cores":
        return scaling(sf_dir, sys.argv[2])
    spark = session(cpus)
    times: dict[str, float] = {}
    cells: list[dict] = []

    def timed(name: str, run):
        began = time.time()
        out = run()
        times[name] = round(time.time() - began, 3)
        return out

    def bounded(name: str, run) -> dict:
        status, seconds, value = guarded(spark, run, PATIENCE)
        times[name] = round(seconds, 3)
        spark._jvm.System.gc()  # shuffle files of a run that was ended go
        return {"status": status, "seconds": round(seconds, 3), "value": value}

    def ratio(truth: dict, mine: float) -> dict:
        """Times over ours; a run that was ended gives a lower bound."""
        return {"exact": truth["value"], "exact_seconds": truth["seconds"], "exact_status": truth["status"], "speedup": round(truth["seconds"] / mine, 3)}

    tg = timed("load_view", lambda: reply_graph(spark, sf_dir, 12).staged())
    delta, ready = int(1.5 * HOUR), {}
    lists = timed("lists", lambda: staged(ranked_incidence(tg, delta), "lists"))
    one_estimate(tg, "TRI", delta, 1_000)  # starts the machine
    for name in EIGHT:
        m = motif(name)
        cls = m.anchor().cls
        if cls not in ready:
            ready[cls] = timed(f"preprocess_{cls}", lambda cls=cls: prepare(tg, delta, cls, lists=lists))
        p, k = ready[cls], K
        guess = timed(f"pilot_{name}", lambda m=m, p=p: pilot(tg, m, delta, 20_000, prepared=p)) if len(m.edges) > 6 else {"c": 0}
        if guess["c"]:
            k = min(MOST, max(K, heuristic_samples(guess["b"], guess["w"], guess["c"])))
        elif len(m.edges) > 6:
            k = MOST
        row = timed(f"estimate_{name}", lambda m=m, p=p, k=k: summary(completions(p, m, m.anchor(), sample_paths(tg, p.centers, p.w_total, delta, p.cls, k, lists=lists)), m, delta, p.w_total, k=k).first())
        seconds = times[f"preprocess_{cls}"] + times["lists"] + times[f"estimate_{name}"] + times.get(f"pilot_{name}", 0)
        truth = bounded(f"exact_{name}", lambda name=name: exact.exact_frontier(tg, name, delta).first()["count"])
        cell = {"view": "F12", "motif": name, "delta_hours": 1.5, "w_total": int(row["w_total"]), "k": k, "estimate": row["estimate"], "stderr": row["stderr"], "hit_rate": row["hit_rate"], "valid_rate": row["valid_rate"], "seconds": round(seconds, 3)} | ratio(truth, seconds)
        if truth["value"]:
            runs = timed(f"five_seeds_{name}", lambda m=m, p=p, k=k: estimate_seeds(tg, m, delta, k, SEEDS, prepared=p).collect())
            errors = [relative_error(r["estimate"], truth["value"]) for r in runs]
            cell |= {"mean_error": round(statistics.mean(errors), 5), "std_error": round(statistics.stdev(errors), 5)}
        for variant in "AE" if name == "M4-0" and truth["value"] else "":
            got = bounded(f"windows_{variant}", lambda variant=variant: baselines.estimate_windows(tg, "M4-0", delta, 40, variant=variant).first()["estimate"])
            cell[f"windows_{variant}"] = {"seconds": got["seconds"], "status": got["status"], "rel_error": round(relative_error(got["value"], truth["value"]), 5) if got["value"] is not None else None}
        cells.append(cell)
    for hours, names in ((6, ("M4-0", "M4-5")), (24, ("M4-0",))):
        for name in names:
            window = hours * HOUR
            row = timed(f"estimate_{name}_{hours}h", lambda name=name, window=window: one_estimate(tg, name, window, K))
            mine = times[f"estimate_{name}_{hours}h"]
            truth = bounded(f"exact_{name}_{hours}h", lambda name=name, window=window: exact.exact_frontier(tg, name, window).first()["count"])
            cell = {"view": "F12", "motif": name, "delta_hours": hours, "w_total": int(row["w_total"]), "k": K, "estimate": row["estimate"], "stderr": row["stderr"], "seconds": mine} | ratio(truth, mine)
            if truth["value"]:
                cell["rel_error"] = round(relative_error(row["estimate"], truth["value"]), 5)
            cells.append(cell)
    nation = timed("load_nation", lambda: nation_graph(spark, sf_dir).staged())
    row = timed("nation_estimate_M4-0", lambda: one_estimate(nation, "M4-0", 7, K))
    truth = bounded("nation_exact_M4-0", lambda: exact.exact_frontier(nation, "M4-0", 7).first()["count"])
    cells.append({"view": "N", "motif": "M4-0", "delta_days": 7, "w_total": int(row["w_total"]), "k": K, "estimate": row["estimate"], "stderr": row["stderr"], "seconds": times["nation_estimate_M4-0"]} | ratio(truth, times["nation_estimate_M4-0"]))
    spark.stop()
    cores = {}
    if os.environ.get("BENCH_SCALING", "1") != "0":
        for n in (x for x in ("1", "4") if int(x) < int(cpus)):
            got = subprocess.run([sys.executable, __file__, "--cores", n], capture_output=True, text=True, timeout=240, check=False)
            line = next((x for x in got.stdout.splitlines() if x.startswith('{"seconds"')), None)
            cores[n] = round(json.loads(line)["seconds"], 3) if line else None
        cores[cpus] = times["estimate_M4-0_6h"]
    first = [c for c in cells if c.get("delta_hours") == 1.5]
    long = [c for c in cells if c.get("delta_hours") != 1.5]
    mean = lambda some: round(speedup([c["exact_seconds"] for c in some], [c["seconds"] for c in some])[1], 3)
    scale = re.search(r"sf([0-9.]+)", sf_dir)
    print(json.dumps({"metric": "temporal motif estimates, total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": float(scale[1]) if scale else None, "cpus": int(cpus), "speedup_geometric_mean": mean(first), "speedup_geometric_mean_long_windows": mean(long), "patience": PATIENCE, "seconds_by_cores": cores, "cells": cells}))


if __name__ == "__main__":
    main()
