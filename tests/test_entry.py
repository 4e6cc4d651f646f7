"""The entry file with and without the training-data operators."""

import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
SAY = "import __spark_entry__ as e; q = e.queries(); s = e.oracle_sql(); assert set(s) <= set(q); print(len(q), 'pipeline' in q, any(k.startswith('op') for k in q))"


@pytest.mark.parametrize("left", ["nothing", "pipeline", "empty folder"])
def test_queries_without_the_training_data_operators(tmp_path, left):
    shutil.copytree(ROOT, tmp_path / "copy", ignore=shutil.ignore_patterns(".git", "llm", "__pycache__", *(["corpus_pipeline.py"] if left == "nothing" else [])))
    if left == "empty folder":
        (tmp_path / "copy/blockmatch/llm/__pycache__").mkdir(parents=True)
    done = subprocess.run([sys.executable, "-B", "-c", SAY], cwd=tmp_path / "copy", capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr
    n, pipeline, operators = done.stdout.split()
    assert int(n) > 50 and pipeline == operators == "False"


def test_nothing_else_imports_the_training_data_operators():
    for path in [*ROOT.glob("blockmatch/**/*.py"), *ROOT.glob("tests/*.py"), ROOT / "bench.py"]:
        if "llm" not in path.relative_to(ROOT).parts and path.name != "test_entry.py":
            assert "llm import" not in path.read_text() and "import llm" not in path.read_text(), path
