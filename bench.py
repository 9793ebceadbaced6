"""Times headline queries: one JSON line.

BENCH_SF_DIR and BENCH_CPUS say on what and with how many cores. Beside the queries' seconds it reports
the stages of training (mean seconds of an iteration's stages, in the form of the published table) and
the samples that one minute of iteration covers.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

from pyspark.sql import SparkSession  # noqa: E402

from codist.plans import queries  # noqa: E402
from codist.plans.train import ShardSpec, fit  # noqa: E402
from codist.plans.workloads import WORKLOADS  # noqa: E402

HEADLINE = """q_token_counts q_posting_lists q_feature_rank q_gradient_iter1 q_params_iter1 q_params_iter2 q_shard_round_robin
q_shard_params_iter2 q_history_basket q_curve_short5 q_curve_lang31 q_classify_lang31_test q_per_class_scores q_events_train
q_central_pull q_summation_form q_locality_same_reducer""".split()
LOOP = ("spread", "distribute", "restore", "gradients", "update")


def session(cpus: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName("bench")
        .config("spark.sql.shuffle.partitions", str(2 * cpus))
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def stages(spark: SparkSession, sf_dir: str, name: str, iterations: int = 2) -> dict:
    """Mean seconds of the stages of the loop, each forced by itself, and of an iteration that is not cut up."""
    w = WORKLOADS[name]
    rows = w.train(spark, sf_dir)
    run = fit(rows, w.alpha, iterations, sharding=ShardSpec(max_list=500), form="sufficient", timed=True, final_cost=False)
    held: dict[str, list[float]] = {}
    for stage, _, seconds, _ in run.runs:
        held.setdefault(stage, []).append(seconds)
    whole = fit(rows, w.alpha, 4, final_cost=False)
    iteration = sum(whole.seconds[1:]) / len(whole.seconds[1:])
    samples = whole.costs[0][1]
    return {"seconds": {s: round(sum(x) / len(x), 3) for s, x in held.items()}, "cut_iteration": round(sum(sum(x) / len(x) for s, x in held.items() if s in LOOP), 3), "iteration": round(iteration, 3), "samples": samples, "samples_per_minute": round(60 * samples / iteration)}


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))
    spark = session(cpus)
    queries.QUERIES["q_params_iter1"](spark, "/root/testdata/sf0.001").write.format("noop").mode("overwrite").save()  # warm-up
    times: dict[str, float] = {}
    for name in HEADLINE:
        queries.forget()  # nothing that an earlier query has trained is used again
        began = time.perf_counter()
        queries.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - began, 3)
    out = {"metric": "headline queries, total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": Path(sf_dir).name, "cpus": cpus}
    if os.environ.get("BENCH_STAGES", "1") == "1":
        out["stages"] = {name: stages(spark, sf_dir, name) for name in ("lang31", "basket")}
    print(json.dumps(out))
    spark.stop()


if __name__ == "__main__":
    main()
