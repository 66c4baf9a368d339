from __future__ import annotations

import os
import shutil
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def _listed(folder: str) -> list[str]:
    code = "import __spark_entry__ as e; print(*e.queries()); assert set(e.oracle_sql()) <= set(e.queries())"
    run = subprocess.run([sys.executable, "-B", "-c", code], cwd=folder, env=os.environ | {"PYTHONPATH": folder}, capture_output=True, text=True)
    assert not run.returncode, run.stderr
    return run.stdout.split()


def test_the_entry_lists_its_queries_without_a_session():
    assert len(_listed(ROOT)) > 100


def test_the_entry_lists_its_queries_without_the_training_data_operators(tmp_path):
    for name in ("mapforge", "__spark_entry__.py"):
        source = os.path.join(ROOT, name)
        shutil.copytree(source, tmp_path / name, ignore=shutil.ignore_patterns("llm", "__pycache__")) if os.path.isdir(source) else shutil.copy(source, tmp_path)
    names = _listed(str(tmp_path))
    assert len(names) > 100 and "pipeline" not in names and not any(n.startswith("op") and n[2].isdigit() for n in names)
