"""Runs the comparison of methods on a workload: stepsizes on the first seed, results on the others.

    python experiments.py tab_logistic /root/testdata/sf0.01 --rounds 200 --seeds 1 2 3 4 5 6 --out tab_logistic.jsonl

Batches and the snapshot's probability follow the theory, with L from the data for
the logistic loss.  Every run has ten measures or more.  One line is printed for
each method and eps: medians and spreads over the seeds at equal coordinates sent
(uncompressed runs have rounds/20 rounds), and for the compressed methods also at
the uncompressed number of rounds.  A chosen step at the edge of the grid is marked.
"""

from __future__ import annotations

import argparse
import json
import os
import sys
import time
from statistics import median

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
# Spark's Python workers start from any folder
os.environ["PYTHONPATH"] = os.pathsep.join(filter(None, [ROOT, os.environ.get("PYTHONPATH")]))


def main() -> None:
    from pyspark.sql import SparkSession

    from hushgrad.fl import experiments, train, workloads

    p = argparse.ArgumentParser()
    p.add_argument("workload", choices=sorted(workloads.WORKLOADS))
    p.add_argument("sf_dir")
    p.add_argument("--rounds", type=int, default=200)
    p.add_argument("--eps", type=float, nargs="*")
    p.add_argument("--steps", type=float, nargs="*", default=list(workloads.STEPS))
    p.add_argument("--seeds", type=int, nargs="*", default=[1, 2, 3, 4, 5, 6])
    p.add_argument("--methods", nargs="*", default=list(workloads.COMPARED))
    p.add_argument("--out")
    a = p.parse_args()
    cpus = os.environ.get("BENCH_CPUS", str(os.cpu_count()))
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    names = [c.split()[0] for c in train.TRACE.split(", ")]
    w = workloads.WORKLOADS[a.workload]
    began = time.time()
    samples, test, sizes = workloads.prepare(spark, a.workload, a.sf_dir)
    L = experiments.smoothness(w, samples)
    ready = time.time()
    eps = a.eps or w.eps
    search = experiments.advance(samples, test, w, experiments.runs(w, sizes, a.methods, eps, a.steps, a.rounds, a.seeds[:1], L=L))
    searched = time.time()
    best = {(r["method"], r["eps"]): r["step"] for r in experiments.compare(spark.createDataFrame(search, train.TRACE)).collect()}
    # all finals share their jobs too
    final = [r for (method, e), step in best.items() for r in experiments.runs(w, sizes, [method], [e], [step], a.rounds, a.seeds[1:] or a.seeds, L=L)]
    trace = [dict(zip(names, row, strict=True)) for row in experiments.advance(samples, test, w, final)]
    done = time.time()
    lines = []
    for (method, e), step in sorted(best.items()):
        rows = [r for r in trace if r["method"] == method and r["eps"] == e]
        end = max(r["round"] for r in rows)
        early = max((r["round"] for r in rows if r["round"] <= max(1, a.rounds // 20)), default=0)
        line = {"workload": a.workload, "method": method, "eps": e, "step": step, "edge": step in (min(a.steps), max(a.steps)), "rounds": end, "seeds": len({r["run"] for r in rows})}
        for when, t in (("", end), ("early_", early)):
            at = [r for r in rows if r["round"] == t]
            line[f"{when}round"], line[f"{when}coords"] = t, at[0]["coords_sent"]
            for k in ("mean_grad_sq", "grad_sq", "loss", "accuracy", "clipped_share"):
                line[f"{when}{k}"] = round(median(r[k] for r in at), 6)
            line[f"{when}spread"] = round(max(r["mean_grad_sq"] for r in at) - min(r["mean_grad_sq"] for r in at), 6)
        lines.append(line)
    lines.append({"workload": a.workload, "sf": os.path.basename(a.sf_dir), "L": L, "samples": sum(sizes.values()), "seconds_prepare": round(ready - began, 1), "seconds_search": round(searched - ready, 1), "runs_search": len(a.methods) * len(eps) * len(a.steps), "seconds_final": round(done - searched, 1), "runs_final": len(final)})
    for line in lines:
        print(json.dumps(line), flush=True)
    if a.out:
        with open(a.out, "w") as f:
            f.writelines(json.dumps(x) + "\n" for x in lines)
    workloads.release(samples, test)


if __name__ == "__main__":
    main()
