"""Times of the headline queries at BENCH_SF_DIR on local[BENCH_CPUS]; prints one line of JSON."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402

from rowblock.functions import fixtures  # noqa: E402
from rowblock.matrix import NarrowMatrix  # noqa: E402
from rowblock.operators import gram as g  # noqa: E402
from rowblock.operators import householder, svd  # noqa: E402
from rowblock.plans import costmodel as cm  # noqa: E402
from rowblock.plans import experiments as ex  # noqa: E402
from rowblock.qr import qr  # noqa: E402
from rowblock.staging import Stage  # noqa: E402

METHODS = (("cholesky", 0), ("rtree", 0), ("cholesky", 1), ("rtree", 1), ("direct", 0))


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), int(os.environ.get("BENCH_CPUS", "8"))
    os.environ.setdefault("OMP_NUM_THREADS", "1")
    os.environ.setdefault("OPENBLAS_NUM_THREADS", "1")
    conf = {"spark.sql.shuffle.partitions": str(cpus), "spark.driver.memory": "8g", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC"}
    spark = SparkSession.builder.master(f"local[{cpus},8]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    queries: dict[str, float] = {}
    facts: dict[str, object] = {}
    qr(fixtures.raw4(spark, sf_dir), "direct").q.write.format("noop").mode("overwrite").save()  # compiles, starts workers
    for n in (4, 10, 25, 50, 100):
        # each shape is a matrix in storage, dealt to as many files as there are cores
        stage, made = Stage(spark), fixtures.cheb(spark, sf_dir, n)
        stored = stage.write(made.df.repartition(cpus), "a")
        nm = NarrowMatrix(stored, made.keys, made.cols, None, n)
        bandwidth = ex.measure_bandwidth(nm, stage)
        rows = nm.df.count()
        for method, ir in METHODS:
            name = method + ("+ir" if ir else "")
            best = 1e9
            for _ in range(2):
                began = time.perf_counter()
                res = qr(nm, method, refine=ir)
                res.q.write.parquet(f"{res.stage.path}/q")
                best = min(best, time.perf_counter() - began)
                res.release()
            queries[f"{name}_{n}"] = round(best, 3)
            bound = cm.lower_bound(name, rows, n, cpus, cm.Cluster(bandwidth["beta_r"], bandwidth["beta_w"], cpus, cpus))
            facts[f"multiple_{name}_{n}"] = round(best / bound, 2)
            facts[f"mflops_{name}_{n}"] = round(cm.flop_rate(rows, n, best) / 1e6, 1)
        state = householder.factor(nm, "one_pass", 4)
        queries[f"householder_{n}"] = round(sum(state.seconds) * n / len(state.seconds), 3)
        t = ex.direct_step_times(nm)
        facts[f"step_shares_{n}"] = [round(x / sum(t.values()), 3) for x in t.values()]
        if n == 25:
            began = time.perf_counter()
            svd.svd(nm).u.write.format("noop").mode("overwrite").save()
            queries["svd_left_25"] = round(time.perf_counter() - began, 3)
        for strategy in ("entry_sym", "tree"):
            began = time.perf_counter()
            g.to_numpy(g.gram(nm, strategy), n)
            queries[f"gram_{strategy}_{n}"] = round(time.perf_counter() - began, 3)
        stage.release()
    made = fixtures.cheb(spark, sf_dir, 10)
    for p, seconds, overhead, _ in ex.fault_sweep(NarrowMatrix(made.df.repartition(4 * cpus), made.keys, made.cols, None, 10)):
        queries[f"direct_faults_{p:g}"] = round(seconds, 3)
        facts[f"fault_overhead_{p:g}"] = round(overhead, 3)
    print(json.dumps({"metric": "sum of all queries", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "facts": facts, "sf": sf_dir.rpartition("/sf")[2], "cpus": cpus}))
    spark.stop()


if __name__ == "__main__":
    main()
