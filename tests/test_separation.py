"""The library without its training-data part."""

import os
import shutil
import subprocess
import sys

REPO = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def run(folder: str, code: str) -> str:
    done = subprocess.run([sys.executable, "-c", code], cwd=folder, capture_output=True, text=True, env={**os.environ, "PYTHONPATH": folder}, timeout=300)
    assert done.returncode == 0, done.stderr
    return done.stdout.strip()


def test_without_training_data_part(tmp_path):
    """With the two folders gone, with and without the pipeline's file, all other queries are there and the tests can be collected."""
    copy = str(tmp_path / "repo")
    shutil.copytree(REPO, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", ".pytest_cache", "llm"))
    count = "import __spark_entry__ as e; q = e.queries(); o = e.oracle_sql(); assert not [n for n in q if n[:2] == 'op' or n == 'pipeline']; assert set(o) <= set(q); print(len(q))"
    assert int(run(copy, count)) > 100
    found = subprocess.run([sys.executable, "-m", "pytest", "--collect-only", "-q", "tests"], cwd=copy, capture_output=True, text=True, timeout=300)
    assert found.returncode == 0, found.stdout + found.stderr
    if os.path.exists(f"{copy}/corpus_pipeline.py"):
        os.remove(f"{copy}/corpus_pipeline.py")
    assert int(run(copy, count)) > 100
