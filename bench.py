"""Headline queries, timed. BENCH_SF_DIR names the tables, BENCH_CPUS the threads; prints one line of JSON."""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

from pyspark.sql import SparkSession  # noqa: E402


#: The index and the settings of the headline search.
N_C, SETTING, PHI_REF, PHI_R, QUANTIZED_PHI_C = 1024, {"phi_c": 16}, 10, 5, 1
DEADLINE = float(os.environ.get("BENCH_DEADLINE", "480"))


def timed(action) -> float:
    began = time.perf_counter()
    action()
    return round(time.perf_counter() - began, 3)


def main() -> None:
    started = time.perf_counter()
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from dataclasses import replace

    from unionlake.operators import index as ix
    from unionlake.operators import matching as mt
    from unionlake.operators import search as se
    from unionlake.plans import workload_queries as wq
    from unionlake.sources.shared import written

    times: dict[str, float] = {}
    details: dict[str, object] = {}
    copies, k, n_queries = 33, 20, 80
    cols, sets, queries = wq.planted(spark, sf, copies, n_queries)
    sets = sets.persist()
    n_sets, q = sets.count(), len(queries)
    mt.top_k_scan(sets.limit(200), queries, 0.3, k, "base")[0].count()  # workers start before the clock does
    # whole calls: a scan has run, with all its passes, when its answer is written
    for _, prune, evals, seconds, over_none, over_base, share in wq.prune_rows("planted", sets, queries, 0.3, k):
        times[f"scan_{prune}_s_per_query"] = seconds
        details |= {f"scan_{prune}_evaluations": evals, f"scan_{prune}_speedup_over_none": over_none, f"scan_{prune}_speedup_over_base": over_base, f"scan_{prune}_recall": share}
    built: list[ix.Index] = []
    times["index_build"] = timed(lambda: built.append(ix.build(cols, 64, N_C, 4, spherical=True)) or built[0].sets.write.format("noop").mode("overwrite").save())
    index = built[0]
    index.sets, index.counts = index.sets.persist(), index.counts.persist()
    index.sets.count(), index.counts.count()
    truth = written(mt.top_k_scan(sets, queries, 0.3, k, "lossless")[0], "truth")
    plan = se.Plan(k=k, tau=0.3, **SETTING, phi_ref=PHI_REF * k, phi_r=PHI_R * k)
    for name, prune, run in (("quantized", "base", se.quantized), ("quantized_plus", "lossless", se.quantized), ("staged", "base", se.staged), ("staged_plus", "lossless", se.staged)):
        at = replace(plan, prune=prune, phi_c=QUANTIZED_PHI_C) if run is se.quantized else replace(plan, prune=prune)
        share, evals, seconds = wq.measured(lambda run=run, at=at: run(index, queries, at), truth, q)
        times[f"{name}_s_per_query"] = seconds
        details |= {f"{name}_recall": share, f"{name}_evaluations": evals}
    try:
        from unionlake.llm import queries as llm
    except ImportError:
        llm = None
    if llm is not None:
        for key, f in llm.queries().items():
            times[key] = timed(lambda f=f: f(spark, sf).write.format("noop").mode("overwrite").save())
    few = dict(list(queries.items())[:20])

    def grid() -> list[list]:
        rows = wq.grid_rows(index, cols, truth.where(truth["query_id"].isin(list(few))), few, plan, (8, 32), (5, 20), (2,))
        details["pareto"] = [list(r) for r in rows if not any(o[2] >= r[2] and o[4] <= r[4] and (o[2] > r[2] or o[4] < r[4]) for o in rows)]
        return rows

    # the other tables of the experiments; one that would begin after DEADLINE seconds is named as not measured
    more = {
        "grid": grid,
        "storage_and_build": lambda: wq.storage_and_build(spark, sf, 5).collect(),
        "scalability": lambda: wq.scalability(spark, sf, (8, 33), (10, 30), 20).collect(),
        "prune_lakes": lambda: wq.prune_lakes(spark, f"{os.path.dirname(sf.rstrip('/'))}/sf0.01").collect(),
    }
    for name, run in more.items():
        details[name] = [list(r) for r in run()] if time.perf_counter() - started < DEADLINE else "not measured: no time left"
    print(json.dumps({"metric": "headline_seconds", "value": round(sum(v for name, v in times.items() if name != "scan_listing_s_per_query"), 3), "unit": "sec", "queries": times, "sf": sf, "sets": n_sets, "n_queries": q, "details": details}))
    spark.stop()


if __name__ == "__main__":
    main()
