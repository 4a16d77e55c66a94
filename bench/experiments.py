"""Run the grid of experiments on a small scale factor and print its tables as Markdown.

    python bench/experiments.py [sf_dir] [queries] [cores]

Approaches x six queries x fourteen webs; the shares of cells at least a tenth worse or better than first come, first served, over all webs,
dense ones and sparse ones; relative response times on the corpus-like web; routing policies; wall clock by batch size, cold and cached.
"""

from __future__ import annotations

import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

from pyspark.sql import functions as F  # noqa: E402

from webtraverse import queries as core  # noqa: E402
from webtraverse.operators import metrics  # noqa: E402
from webtraverse.plans import experiments, rounds  # noqa: E402
from webtraverse.plans.approaches import APPROACHES, COMPARED, LITERAL_HYBRIDS  # noqa: E402
from webtraverse.plans.query import SIX, WORKLOAD  # noqa: E402
from webtraverse.session import durable, local_session  # noqa: E402
from webtraverse.sources import testweb  # noqa: E402

MEASURES = ("relRT1st", "relRT50", "relRTCmpl")


def worse_better(frame, title):
    rows = metrics.compare_to_baseline(frame.where("n_solutions > 0")).collect()
    by = {(r["approach"], r["measure"]): r for r in rows}
    print(f"\n### {title}\n\n| approach | " + " | ".join(f"{m} worse / better % (of cells)" for m in MEASURES) + " |\n| --- | --- | --- | --- |")
    for a in (*COMPARED, *LITERAL_HYBRIDS):
        cells = [by.get((a, m)) for m in MEASURES]
        if all(cells):
            print(f"| {a} | " + " | ".join(f"{c['pct_worse']} / {c['pct_better']} ({c['n_cells']})" for c in cells) + " |")
    sys.stdout.flush()


def main():
    sf = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.001"
    names = tuple(sys.argv[2].split(",")) if len(sys.argv) > 2 else SIX
    cores = int(sys.argv[3]) if len(sys.argv) > 3 else os.cpu_count()
    spark = local_session(cores, max(16, 4 * cores), **{"spark.ui.showConsoleProgress": "false", "spark.sql.adaptive.coalescePartitions.enabled": "false"})
    spark.sparkContext.setLogLevel("ERROR")
    began = time.time()
    approaches = (*(a for a in APPROACHES if a not in ("pagerank", "breadth_first")), *LITERAL_HYBRIDS)
    cells = durable(experiments.grid(spark, sf, names, testweb.WEBS, approaches, runs=1), "cells")
    print(f"Grid of {cells.count()} executions in {time.time() - began:.0f} s on {cores} cores; {cells.where('n_solutions > 0').select('web_id', 'query').distinct().count()} of {14 * len(names)} cells have a solution.")
    dense = [w.web_id for w in testweb.WEBS if w.dense]
    worse_better(cells, "All webs")
    worse_better(cells.where(F.col("web_id").isin(dense)), "Dense webs")
    worse_better(cells.where(~F.col("web_id").isin(dense)), "Sparse webs")
    print("\n### Relative response times on the corpus-like web (first / median / last)\n\n| approach | " + " | ".join(names) + " |\n| --- |" + " --- |" * len(names))
    got = {(r["approach"], r["query"]): r for r in cells.where("web_id = 'w62_47'").collect()}
    for a in approaches:
        print(f"| {a} | " + " | ".join(" / ".join(f"{r[m]:.4f}" for m in MEASURES) if (r := got[a, q])["n_solutions"] else "no solution" for q in names) + " |")
    print("\n### Routing policies, first query of the list, corpus-like web\n\n| routing | routed partials | first / last |\n| --- | --- | --- |")
    routed = experiments.grid(spark, sf, names[:1], (testweb.CORPUS_LIKE,), ("fifo",), experiments.routing_names(names[0])).collect()
    for r in sorted(routed, key=lambda r: r["routing"]):
        print(f"| {r['routing']} | {r['routed']} | " + (f"{r['relRT1st']:.4f} / {r['relRTCmpl']:.4f} |" if r["n_solutions"] else "no solution |"))
    print("\n### Routing by approach, corpus-like web: from least to most over the nine policies\n\n| query | approach | routed partials | relRT1st | relRT50 | relRTCmpl |\n| --- | --- | --- | --- | --- | --- |")
    measures = ("routed", *MEASURES)
    for q in (q for q in ("q1", "q4", "q6") if q in names):
        t = time.time()
        held = experiments.grid(spark, sf, (q,), (testweb.CORPUS_LIKE,), core.INTERMEDIATE, experiments.routing_names(q, static=False))
        ends = held.groupBy("approach").agg(*[f(m).alias(f"{n}_{m}") for m in measures for n, f in (("lo", F.min), ("hi", F.max))])
        for r in ends.orderBy("approach").collect():
            print(f"| {q} | {r['approach']} | {r['lo_routed']}..{r['hi_routed']} | " + " | ".join(f"{r['lo_' + m]:.4f}..{r['hi_' + m]:.4f}" if r["lo_" + m] is not None else "no solution" for m in MEASURES) + " |")
        print(f"<!-- {q}: {time.time() - t:.0f} s -->", flush=True)
    print("\n### Batched engine, second query, corpus-like web\n\n| batch | rounds | seconds | lookups | first / last |\n| --- | --- | --- | --- | --- |")
    web = core.web_of(spark, sf)
    for batch in (10, 40, 1000):
        t = time.time()
        out = rounds.traverse(web, WORKLOAD["q2"], APPROACHES["partial_rel1"], batch=batch)
        rt = metrics.response_times(out.solutions, out.lookups).first()
        print(f"| {batch} | {out.rounds} | {time.time() - t:.1f} | {out.lookups} | " + (f"{rt['relRT1st']:.4f} / {rt['relRTCmpl']:.4f} |" if rt else "no solution |"), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
