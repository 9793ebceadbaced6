"""The entry module with and without the training-text subpackage."""

import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
SAY = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); print(len(q), 'pipeline' in q, sum(x.startswith('op') for x in q), set(o) <= set(q))"


def told(where):
    done = subprocess.run([sys.executable, "-c", SAY], cwd=where, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "HOME": str(where)})
    assert done.returncode == 0, done.stderr
    return done.stdout.split()


@pytest.mark.parametrize("left", ["pipeline", "nothing", "empty folder"])
def test_core_stands_alone(tmp_path, left):
    here = tmp_path / "copy"
    shutil.copytree(ROOT, here, ignore=shutil.ignore_patterns(".git", "__pycache__"))
    whole = told(here) if (here / "codist/llm").exists() else None
    shutil.rmtree(here / "codist/llm", ignore_errors=True)
    shutil.rmtree(here / "tests/llm", ignore_errors=True)
    if left == "empty folder":
        (here / "codist/llm/__pycache__").mkdir(parents=True)
    if left != "pipeline":
        (here / "corpus_pipeline.py").unlink(missing_ok=True)
    count, pipeline, operators, twins = told(here)
    assert (pipeline, operators, twins) == ("False", "0", "True") and int(count) > 100
    if whole and (ROOT / "corpus_pipeline.py").exists():
        assert int(whole[0]) == int(count) + 11 and whole[1:3] == ["True", "10"]
