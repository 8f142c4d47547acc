"""What is left when the text operators are taken away."""

import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent

SCRIPT = """
import __spark_entry__ as e, importlib, bench
names = set(e.queries())
assert names and not any(k.startswith("op") or k == "pipeline" for k in names), names
assert set(e.oracle_sql()) <= names
for f in {modules}:
    importlib.import_module(f)
print("fine")
"""


@pytest.mark.parametrize("pipeline", [True, False])
def test_without_the_text_operators(tmp_path, pipeline):
    """The rest imports and registers its queries, whether or not the pipeline's file is still there."""
    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", "*.json"))
    if not pipeline:
        (copy / "corpus_pipeline.py").unlink(missing_ok=True)
    modules = [".".join(p.relative_to(copy).with_suffix("").parts) for p in (copy / "walkrank").rglob("*.py") if p.name != "__init__.py"]
    assert modules and not any(".llm" in m for m in modules)
    run = subprocess.run([sys.executable, "-B", "-c", SCRIPT.format(modules=modules)], cwd=copy, capture_output=True, text=True, timeout=120, env={"PATH": "/usr/bin:/bin", "HOME": str(tmp_path)})
    assert run.stdout.strip() == "fine", run.stderr
