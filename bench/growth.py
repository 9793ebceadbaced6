"""Growth with samples and with features: python bench/growth.py

Sizes sf0.001 to sf0.1 at fixed cores, then copies of every feature under another name, so that
features and entries grow while samples stay.
"""

from __future__ import annotations

import json

from common import in_own_spark

CODE = """
w = WORKLOADS["lang31"]
rows = w.train(spark, {sf!r})
if {copies} > 1:
    rows = rows.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit({copies})))).withColumn("f", F.concat("f", F.lit("#"), F.col("k").cast("string"))).drop("k")
fit(rows, w.alpha, 1)
began = time.time()
out = fit(rows, w.alpha, 2, final_cost=False)
print(json.dumps({{"seconds": round(time.time() - began, 2), "features": out.params.count(), "entries": rows.count(), "samples": out.costs[0][1]}}))
"""


def main() -> None:
    for sf, copies in (("sf0.001", 1), ("sf0.01", 1), ("sf0.1", 1), ("sf0.01", 4), ("sf0.01", 16)):
        print(json.dumps({"sf": sf, "copies": copies} | in_own_spark(CODE.format(sf=f"/root/testdata/{sf}", copies=copies), 4, 12)), flush=True)


if __name__ == "__main__":
    main()
