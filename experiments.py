"""The experiments with their times: one JSON line per run. Threads differ by process, so that each has a fresh JVM.

    python experiments.py /root/testdata/sf0.01 build insert delete knn mixed --threads 1 4
"""

from __future__ import annotations

import argparse
import json
import subprocess
import sys

from pyspark.sql import SparkSession

from kdforest import measures, workloads
from kdforest.operators import tree as kd
from kdforest.shared import written
from kdforest.sources.pointsets import point_set

KINDS = ("build", "insert", "delete", "knn", "k", "mixed")


def session(threads: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{threads}]").config("spark.sql.shuffle.partitions", threads).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def rows_of(spark: SparkSession, sf_dir: str, kind: str, sets: list[str], structures: list[str], rules: list[str], percents: list[int]) -> list[dict]:
    out = []
    for name in sets:
        points, d = point_set(spark, sf_dir, name)
        points = written(points, "points")
        n = points.count()
        for structure in structures:
            for rule in rules:
                own = {"kind": kind, "points": name, "structure": structure, "rule": rule}
                if kind == "build":
                    out.append(own | {"n": n, "seconds": measures.timed(lambda: workloads.make(spark, structure, d, rule).insert(points), 1, 3)})  # noqa: B023
                elif kind in ("insert", "delete"):
                    for percent in percents:
                        _, steps = workloads.stepped(spark, points, d, structure, percent, kind == "delete", rule)
                        out.append(own | {"percent": percent, "n": n, "seconds": sum(s["seconds"] for s in steps), "moved": sum(s["moved"] for s in steps)})
                elif kind == "knn":
                    out.append(own | workloads.graph(spark, points, d, structure, rule=rule))
                elif kind == "k":
                    index = workloads.make(spark, structure, d, rule)
                    for b in workloads.insert_slices(points, 20):
                        index.insert(b)
                    queries = kd.as_queries(points, d)
                    out += [own | {"k": k, "n": n, "seconds": workloads.clock(lambda: workloads.done(index.knn(queries, k)))} for k in range(2, 12)]  # noqa: B023
                else:
                    for arrival in ("hash", "sorted"):
                        out += [own | {"arrival": arrival} | s for s in workloads.mixed(spark, points, d, structure, arrival=arrival, rule=rule)]
    return out


def main() -> None:
    p = argparse.ArgumentParser()
    p.add_argument("sf_dir")
    p.add_argument("kinds", nargs="+", choices=KINDS)
    p.add_argument("--threads", nargs="+", type=int, default=[8])
    p.add_argument("--sets", nargs="+", default=["ord2"])
    p.add_argument("--structures", nargs="+", default=list(workloads.STRUCTURES))
    p.add_argument("--rules", nargs="+", default=["object"])
    p.add_argument("--percents", nargs="+", type=int, default=[10])
    a = p.parse_args()
    if len(a.threads) > 1:
        rows = []
        for t in a.threads:
            more = [x for k in ("sets", "structures", "rules", "percents") for x in (f"--{k}", *map(str, getattr(a, k)))]
            got = subprocess.run([sys.executable, __file__, a.sf_dir, *a.kinds, "--threads", str(t), *more], capture_output=True, text=True, check=True).stdout
            rows += [json.loads(x) for x in got.splitlines() if x.startswith("{")]
        for r in rows:
            print(json.dumps(r))
        timed = [r for r in rows if "seconds" in r]
        found = measures.speedups([{k: v for k, v in r.items() if isinstance(v, str) or k in ("threads", "seconds")} for r in timed])
        print(json.dumps({"speedup_mean": found["mean"], "speedup_largest": found["largest"]}))
        return
    spark = session(a.threads[0])
    for kind in a.kinds:
        for r in rows_of(spark, a.sf_dir, kind, a.sets, a.structures, a.rules, a.percents):
            if "seconds" in r:
                r["per_second"] = round(measures.throughput(r["n"], r["seconds"]), 1)
            print(json.dumps(r | {"threads": a.threads[0]}), flush=True)


if __name__ == "__main__":
    main()
