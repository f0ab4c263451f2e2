"""The driver's contract holds with and without the pipeline operators."""

import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]


def test_nothing_outside_imports_the_pipeline_operators():
    for p in (ROOT / "kmfold").rglob("*.py"):
        if "llm" not in p.parts:
            assert "kmfold.llm" not in p.read_text(), p


def test_entry_works_without_the_pipeline_operators(tmp_path):
    import shutil

    shutil.copytree(ROOT / "kmfold", tmp_path / "kmfold", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 100 and not any(k.startswith('op') for k in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
