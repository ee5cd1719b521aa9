"""The engine and its entry without the subpackage of training-data operators."""

import os
import shutil
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]


def test_entry_without_the_subpackage(tmp_path):
    ignored = shutil.ignore_patterns("llm", "__pycache__", ".git", ".pytest_cache")
    shutil.copytree(ROOT, tmp_path / "copy", ignore=ignored)
    said = subprocess.run(
        [sys.executable, "-B", "-c", "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()), *e.queries())"],
        cwd=tmp_path / "copy", env=os.environ | {"PYTHONPATH": str(tmp_path / "copy")}, capture_output=True, text=True, timeout=120,
    )
    assert said.returncode == 0, said.stderr
    names = said.stdout.split()[2:]
    assert "wcc_basket" in names and "pipeline" not in names and not any(n.startswith("op1_") for n in names)


def test_nothing_outside_imports_it():
    for path in (ROOT / "subgraph_engine").rglob("*.py"):
        if "llm" not in path.relative_to(ROOT).parts:
            assert "subgraph_engine.llm" not in path.read_text(), path
