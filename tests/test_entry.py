"""The entry module works in a copy of the repository without the optional parts."""

from __future__ import annotations

import os
import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent
SAY = "import __spark_entry__ as e; q, s = e.queries(), e.oracle_sql(); assert set(s) <= set(q); print(len(q), 'pipeline' in q, any(n.startswith('op1_') for n in q))"


def said(folder: Path) -> str:
    got = subprocess.run([sys.executable, "-c", SAY], cwd=folder, env=os.environ | {"PYTHONPATH": str(folder)}, capture_output=True, text=True, timeout=120)
    assert got.returncode == 0, got.stderr
    return got.stdout


@pytest.mark.parametrize("gone", [("tileaqp/llm", "corpus_pipeline.py", "tests/llm"), ("tileaqp/llm", "tests/llm"), ("corpus_pipeline.py",)])
def test_entry_without_optional_parts(tmp_path, gone):
    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse"))
    for name in gone:
        path = copy / name
        shutil.rmtree(path, ignore_errors=True) if path.is_dir() else path.unlink(missing_ok=True)
    count, pipeline, first = said(copy).split()
    assert int(count) > 100 and pipeline == "False" and first == str("tileaqp/llm" not in gone and (ROOT / "tileaqp/llm").exists())


def test_other_import_errors_are_not_hidden(tmp_path):
    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse"))
    (copy / "corpus_pipeline.py").write_text("import no_such_module_anywhere\n")
    got = subprocess.run([sys.executable, "-c", SAY], cwd=copy, env=os.environ | {"PYTHONPATH": str(copy)}, capture_output=True, text=True, timeout=120)
    assert got.returncode and "no_such_module_anywhere" in got.stderr
