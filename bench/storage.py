"""Bytes and seconds of stage tables by codec, and of persisting once or twice: python bench/storage.py"""

from __future__ import annotations

import json

from common import in_own_spark, settings

CODE = """
from pyspark import StorageLevel
from codist.plans.storage import shared_dir
w = WORKLOADS["lang31"]
rows = w.train(spark, {sf!r}).persist(); rows.count()
out = {{}}
def size_of(path):
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(at).getLength()
for codec in ("none", "snappy", "lz4", "zstd"):
    path = shared_dir(spark) + "/bench_" + codec
    began = time.time()
    rows.write.mode("overwrite").option("compression", codec).parquet(path)
    took = time.time() - began
    began = time.time()
    spark.read.parquet(path).agg(F.sum("x")).collect()
    out[codec] = {{"write_s": round(took, 2), "read_s": round(time.time() - began, 2), "bytes": size_of(path)}}
rows.unpersist()  # or the next plans are served from it
for name, level in (("one replica", StorageLevel.MEMORY_AND_DISK), ("two replicas", StorageLevel.MEMORY_AND_DISK_2)):
    held = w.train(spark, {sf!r})
    began = time.time()
    held.persist(level).count()
    out[name] = {{"persist_s": round(time.time() - began, 2)}}
    held.unpersist()
print(json.dumps(out))
"""


def main() -> None:
    for name, row in in_own_spark(CODE.format(sf=settings()), 4, 12).items():
        print(json.dumps({"setting": name} | row), flush=True)


if __name__ == "__main__":
    main()
