"""The entry module with and without the training-data subpackage."""

import os
import shutil
import subprocess
import sys

import pytest

REPO = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


@pytest.mark.parametrize("gone", [("equiscale/llm", "tests/llm"), ("equiscale/llm", "tests/llm", "corpus_pipeline.py"), ("corpus_pipeline.py",)])
def test_entry_without_the_subpackage(tmp_path, gone):
    copy = tmp_path / "repo"
    shutil.copytree(REPO, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", ".pytest_cache", "spark-warehouse"))
    for path in gone:
        at = copy / path
        shutil.rmtree(at) if at.is_dir() else at.unlink(missing_ok=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'adaptive_zipf_100' in q and set(e.oracle_sql()) <= set(q); print(sum(k.startswith('op') for k in q), 'pipeline' in q)"
    env = {**os.environ, "PYTHONPATH": str(copy), "PYTHONDONTWRITEBYTECODE": "1"}
    out = subprocess.run([sys.executable, "-c", code], cwd=copy, env=env, capture_output=True, text=True, check=True).stdout.split()
    kept = (copy / "equiscale/llm").is_dir()
    assert (int(out[0]) == 10) == kept and out[1] == "False"
