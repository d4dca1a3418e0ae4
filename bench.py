"""Headline experiments; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.warehouse.dir", "/tmp/rulemat-bench/warehouse")
        .config("spark.checkpoint.dir", os.environ.get("BENCH_SHARED", "/tmp/rulemat-bench/shared"))  # one machine
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from rulemat.engine import Config, Reasoner
    from rulemat.engine.metrics import slope
    from rulemat.lang import parse_program
    from rulemat.workloads import datasets, rulesets

    out: dict[str, float] = {}
    extra: dict[str, object] = {}

    started, limit = time.perf_counter(), float(os.environ.get("BENCH_LIMIT", "240"))

    def timed(name: str, run: object) -> object:
        if time.perf_counter() - started > limit:  # later cases are left out and named
            extra.setdefault("left_out", []).append(name)
            return None
        began = time.perf_counter()
        got = run()
        out[name] = round(time.perf_counter() - began, 3)
        return got

    wide = Config(parallel_nodes=4)
    n = int(os.environ.get("BENCH_NODES", "1000"))
    warm = Reasoner(spark, rulesets.RS1, datasets.chain(spark, sf, 20))
    warm.materialise()

    # rule sets 2 and 3: single updates against recomputation
    full = Reasoner(spark, rulesets.RS2, datasets.trade(spark, sf, n), wide)
    timed("rs2_scratch", full.materialise)
    extra["rs2_facts"] = sum(s.rows for s in full.state.bag().stores.values())
    extra["rs2_store_rows"] = {name: st.rows for name, st in sorted(full.state.bag().stores.items())}
    three = Reasoner(spark, rulesets.RS3, datasets.trade(spark, sf, n), wide)
    timed("rs3_scratch", three.materialise)
    for rid in ("r6", "r10n"):
        f = three.fork()
        timed(f"rs3_delete_{rid}", lambda f=f, rid=rid: f.delete_rules([rid]))
        timed(f"rs3_insert_{rid}", lambda f=f, rid=rid: f.insert_rules(list(parse_program(rulesets.RS3).only([rid]))))
    for name in ("r18", "r4", "r10_r15_r18", "r10_r15_r17", "r17", "r3", "r2"):
        ids = rulesets.UPDATES[name]
        f = full.fork()
        timed(f"rs2_delete_{name}", lambda f=f, ids=ids: f.delete_rules(ids))
        timed(f"rs2_insert_{name}", lambda f=f, ids=ids: f.insert_rules(list(parse_program(rulesets.RS2).only(ids))))

    # rule set 1 over chains of growing length, and one fact more or less
    points = []
    for size in (50, 100, 200, 400):
        r = Reasoner(spark, rulesets.RS1, datasets.chain(spark, sf, size))
        timed(f"rs1_scratch_n{size}", r.materialise)
        if f"rs1_scratch_n{size}" in out:
            points.append((size, out[f"rs1_scratch_n{size}"]))
    if len(points) > 1:
        extra["rs1_exponent"] = round(slope(points), 2)
    pair = spark.createDataFrame([(399, 400)], "a long, b long")
    timed("rs1_insert_fact", lambda: r.insert_facts("hasNeighbour", pair))
    timed("rs1_delete_fact", lambda: r.delete_facts("hasNeighbour", pair))
    timed("rs1_delete_symmetric", lambda: r.fork().delete_rules(["r2"]))
    timed("rs1_delete_transitive", lambda: r.fork().delete_rules(["r3"]))
    whole = {"rs1": out.get("rs1_scratch_n400"), "rs2": out.get("rs2_scratch"), "rs3": out.get("rs3_scratch")}
    speedups = {k: round(whole[k[:3]] / max(v, 1e-3), 1) for k, v in out.items() if "scratch" not in k and whole[k[:3]]}
    print(json.dumps({"metric": "rs2_scratch_plus_updates", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "speedup": speedups, "sf": os.path.basename(sf.rstrip("/")), **extra}))
    spark.stop()


if __name__ == "__main__":
    main()
