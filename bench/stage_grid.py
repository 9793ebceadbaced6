"""Stage times by resources, in the form of the published table: python bench/stage_grid.py [WORKLOAD...]

Cores 1, 3 and 6 stand for the published node counts, which have that ratio; four mappers (least splits of a
scan) and three reducers (partitions of an exchange) for each core, as published. Medians of three iterations,
each stage forced by itself. Prints a line for each setting, with speedup and efficiency over one core, and
one with the line through (cores, speedup).
"""

from __future__ import annotations

import json
import sys
from statistics import correlation, linear_regression, median

from common import in_own_spark, settings

CODE = """
w = WORKLOADS[{name!r}]
rows = w.train(spark, {sf!r})
fit(rows, w.alpha, 1, sharding=ShardSpec(500), form="sufficient", timed=True)
run = fit(rows, w.alpha, 3, sharding=ShardSpec(500), form="sufficient", timed=True)
print(json.dumps(run.runs))
"""


def main() -> None:
    for name in sys.argv[1:] or ("lang31", "basket"):
        base, points = None, []
        for cores in (1, 3, 6):
            runs = in_own_spark(CODE.format(name=name, sf=settings()), cores, 3 * cores, mappers=4 * cores)
            held: dict[str, list[float]] = {}
            for stage, _, seconds, _ in runs:
                held.setdefault(stage, []).append(seconds)
            times = {s: round(median(x), 3) for s, x in held.items()}
            loop = sum(times[s] for s in ("spread", "distribute", "restore", "gradients", "update"))
            base = base or loop
            points.append((cores, base / loop))
            print(json.dumps({"workload": name, "cores": cores, "mappers": 4 * cores, "reducers": 3 * cores, "stages": times, "iteration": round(loop, 3), "speedup": round(base / loop, 2), "efficiency": round(base / loop / cores, 2)}), flush=True)
        x, y = zip(*points)
        fit = linear_regression(x, y)
        print(json.dumps({"workload": name, "slope": round(fit.slope, 3), "r2": round(correlation(x, y) ** 2, 3)}), flush=True)


if __name__ == "__main__":
    main()
