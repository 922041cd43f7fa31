"""Speed-up and scale-up runs: how the time of an iteration moves with the cores and with the data, for the methods and their baselines.

    python -m fixflow.experiments --sf /root/testdata/sf0.1 --methods bgd,bgd_inmem --cores 1,2,4,8
    python -m fixflow.experiments --sf /root/testdata/sf0.1 --methods rank,rank_two_job --cores 8 --copies 1,2,4
    python -m fixflow.experiments --sf /root/testdata/sf0.1 --methods rank --cores 2,4,8 --copies 1,2,4 --paired

Each number of cores has a session of its own (local[k]; with --master, spark.cores.max). Data grow by disjoint copies; copied graphs are dealt out by a hash of
their edges, so no copy stays together. --paired takes the k-th number of copies with the k-th number of cores (scale-up) instead of all pairs. A session first runs
each method once on the smallest data, which isn't counted. Every line is a JSON object; the last ones hold speed-up, scale-up and cost.
"""

from __future__ import annotations

import argparse
import json
import subprocess
import sys
import time

from .functions.measures import cost_optimal, machine_seconds, scaleup, speedup

ITERATIONS = {"bgd": 5, "bgd_inmem": 5, "rank": 10, "rank_supersteps": 10, "rank_hash_sort": 10, "rank_sorted": 10, "rank_two_job": 10}


def inputs(spark, sf: str, method: str, copies: int):
    from pyspark.sql import functions as F

    from .sources.tables import duplicate_graph, duplicate_records, graph, training

    if method.startswith("bgd"):
        return duplicate_records(training(spark, sf, "x_lineitem"), copies).persist()
    edges = duplicate_graph(graph(spark, sf, "g_part_supp"), copies)
    return edges.repartition(F.xxhash64("src", "dst")).persist()


def once(method: str, data, iterations: int) -> None:
    from .baselines.runs import inmem_bgd, two_job_rank
    from .tasks.graphs import pagerank, pagerank_supersteps
    from .tasks.learning import bgd

    dense = ["x0", "x1", "x2", "x3"]
    if method == "bgd":
        bgd(data, dense, iterations=iterations)
    elif method == "bgd_inmem":
        inmem_bgd(data, dense, iterations=iterations)
    else:
        options = {"rank_supersteps": {}, "rank_hash_sort": {"exchange": "hash_sort"}, "rank_sorted": {"exchange": "sorted"}}
        if method == "rank":
            ranks = pagerank(data, iterations=iterations)[0]
        elif method == "rank_two_job":
            ranks = two_job_rank(data, iterations=iterations)
        else:
            ranks = pagerank_supersteps(data, iterations=iterations, **options[method])[0]
        ranks.write.format("noop").mode("overwrite").save()


def measure(sf: str, methods: list[str], cores: int, copies: list[int], master: str | None) -> None:
    """One session: a line for each method and number of copies, with the seconds of an iteration. Loading the data isn't counted."""
    from .runtime import get_spark

    conf = {"spark.sql.shuffle.partitions": str(max(cores, 8)), "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false"}
    spark = get_spark(master or f"local[{cores}]", **conf, **({"spark.cores.max": str(cores)} if master else {"spark.driver.memory": "8g"}))
    spark.sparkContext.setLogLevel("ERROR")
    for method in methods:
        for k, n in enumerate([min(copies), *copies]):
            data = inputs(spark, sf, method, n)
            rows = data.count()
            began = time.perf_counter()
            once(method, data, ITERATIONS[method] if k else 1)
            seconds = (time.perf_counter() - began) / ITERATIONS[method]
            spark.catalog.clearCache()
            if k:
                print(json.dumps({"method": method, "cores": cores, "copies": n, "rows": rows, "seconds": round(seconds, 3)}), flush=True)


def summary(points: list[dict]) -> list[dict]:
    """Speed-up and cost where the data stay the same, scale-up where data per core or the number of cores stays the same."""
    out = []
    for method in sorted({p["method"] for p in points}):
        mine = [p for p in points if p["method"] == method]
        for n in sorted({p["copies"] for p in mine}):
            same = [(p["cores"], p["seconds"]) for p in mine if p["copies"] == n]
            if len(same) > 1:
                cost = {m: round(machine_seconds(m, s), 3) for m, s in sorted(same)}
                out.append({"method": method, "copies": n, "speedup": [(m, round(a, 2), round(b, 2)) for m, a, b in speedup(same)], "core_seconds": cost, "cost_optimal_cores": cost_optimal(same)})
        for name, key in (("scaleup_same_data_per_core", lambda p: p["copies"] / p["cores"]), ("growth_same_cores", lambda p: p["cores"])):
            for v in sorted({key(p) for p in mine}):
                grown = [(p["copies"], p["seconds"]) for p in mine if key(p) == v]
                if len(grown) > 1:
                    out.append({"method": method, name: round(v, 4), "points": [(n, round(r, 2)) for n, r in scaleup(grown)]})
    return out


def main() -> None:
    a = argparse.ArgumentParser(description=__doc__, formatter_class=argparse.RawDescriptionHelpFormatter)
    a.add_argument("--sf", default="/root/testdata/sf0.1")
    a.add_argument("--methods", default="bgd,rank,rank_two_job")
    a.add_argument("--cores", default="1,2,4,8")
    a.add_argument("--copies", default="1")
    a.add_argument("--paired", action="store_true")
    a.add_argument("--master")
    a.add_argument("--session", action="store_true", help="measure in this process, with one number of cores")
    o = a.parse_args()
    cores, copies = [int(x) for x in o.cores.split(",")], [int(x) for x in o.copies.split(",")]
    if o.session:
        return measure(o.sf, o.methods.split(","), cores[0], copies, o.master)
    if o.paired and len(cores) != len(copies):
        a.error("--paired needs as many numbers of copies as of cores")
    points: list[dict] = []
    for k, c in enumerate(cores):
        part = [copies[k]] if o.paired else copies
        call = [sys.executable, "-m", "fixflow.experiments", "--session", "--sf", o.sf, "--methods", o.methods, "--cores", str(c), "--copies", ",".join(map(str, part))]
        done = subprocess.run(call + (["--master", o.master] if o.master else []), stdout=subprocess.PIPE, text=True, check=True)
        for line in done.stdout.splitlines():
            if line.startswith("{"):
                print(line, flush=True)
                points.append(json.loads(line))
    for x in summary(points):
        print(json.dumps(x), flush=True)


if __name__ == "__main__":
    main()
