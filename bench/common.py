"""Runs one measurement in a Spark of its own, so that each setting begins alike."""

from __future__ import annotations

import json
import os
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]


def in_own_spark(code: str, cores: int, partitions: int, memory: str = "4g", mappers: int = 1) -> dict:
    head = f"""
import sys, time, json
sys.path.insert(0, {str(ROOT)!r})
from pyspark.sql import SparkSession, functions as F
spark = (SparkSession.builder.master("local[{cores}]").config("spark.sql.shuffle.partitions", "{partitions}").config("spark.sql.files.minPartitionNum", "{mappers}").config("spark.driver.memory", "{memory}")
    .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC")
    .config("spark.sql.adaptive.coalescePartitions.enabled", "false").getOrCreate())
spark.sparkContext.setLogLevel("OFF")
from codist.plans.train import ShardSpec, fit
from codist.plans.workloads import WORKLOADS
"""
    env = os.environ | {"PYTHONPATH": f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"}
    out = subprocess.run([sys.executable, "-c", head + code], env=env, capture_output=True, text=True, timeout=1800)
    if out.returncode:
        raise RuntimeError(out.stderr[-2000:])
    return json.loads(out.stdout.strip().splitlines()[-1])


def settings(default_sf: str = "/root/testdata/sf0.1") -> str:
    return os.environ.get("BENCH_SF_DIR", default_sf)
