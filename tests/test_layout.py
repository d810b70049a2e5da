"""The library without the training-data subpackage."""

import os
import shutil
import subprocess
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
SAY = "import __spark_entry__ as e; print(*e.queries()); print(*e.oracle_sql())"


@pytest.mark.parametrize("gone", [("fieldloom/llm", "tests/llm"), ("fieldloom/llm", "tests/llm", "corpus_pipeline.py"), ("corpus_pipeline.py",)])
def test_entry_imports_without_the_subpackage(tmp_path, gone):
    to = tmp_path / "copy"
    shutil.copytree(ROOT, to, ignore=shutil.ignore_patterns(".git", "__pycache__", ".pytest_cache", "spark-warehouse"))
    for name in gone:
        path = to / name
        if path.is_dir():
            shutil.rmtree(path)
        elif path.exists():
            path.unlink()
    out = subprocess.run([sys.executable, "-B", "-c", SAY], cwd=to, env=os.environ | {"PYTHONPATH": str(to)}, capture_output=True, text=True)
    assert out.returncode == 0, out.stderr
    names, twins = (line.split() for line in out.stdout.splitlines())
    assert "pipeline" not in names and set(twins) <= set(names) and len(names) > 300
    if "fieldloom/llm" in gone:
        assert not [n for n in names if n.startswith("op") and n[2:3].isdigit()]
