"""Sharded against unsharded training and placement policies: python bench/skew.py"""

from __future__ import annotations

import json

from common import in_own_spark, settings

CODE = """
from codist.operators import shard, skew
from codist.plans import cost
w = WORKLOADS["lang31"]
rows = w.train(spark, {sf!r})
fit(rows, w.alpha, 1)
out = {{}}
for name, spec in {{"unsharded": None, **{{p: ShardSpec(100, p, slots=8) for p in shard.POLICIES}}}}.items():
    began = time.time()
    fit(rows, w.alpha, 2, sharding=spec, final_cost=False)
    split = shard.unsplit(rows) if spec is None else shard.split_final(rows, 100, spec.policy, slots=8, racks=2)
    load = skew.partition_load(split, F.xxhash64("f", F.to_json("shard_path")), 12).first()
    longest = skew.balance(split).first()["longest"]
    place = {{r["place"]: round(r["share"], 3) for r in cost.locality(split, 8, 2, aligned=name.endswith("aligned")).collect()}}
    out[name] = {{"seconds": round(time.time() - began, 2), "longest": longest, "imbalance": round(load["imbalance"], 3), "places": place}}
print(json.dumps(out))
"""


def main() -> None:
    for name, row in in_own_spark(CODE.format(sf=settings()), 4, 12).items():
        print(json.dumps({"policy": name} | row), flush=True)


if __name__ == "__main__":
    main()
