"""The core stands without the training-data operators: neither their folders nor the pipeline are needed."""

import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
NAMES = "import __spark_entry__ as e; q = e.queries(); print(len(q), 'pipeline' in q, any(n.startswith('op1_') for n in q), set(e.oracle_sql()) <= set(q))"


@pytest.mark.parametrize("with_pipeline", [True, False])
def test_entry_without_the_folders(tmp_path, with_pipeline):
    copy = tmp_path / "copy"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", ".pytest_cache"))
    if not with_pipeline:
        (copy / "corpus_pipeline.py").unlink(missing_ok=True)
    run = subprocess.run([sys.executable, "-c", NAMES], cwd=copy, capture_output=True, text=True, timeout=120)
    assert run.returncode == 0, run.stderr[-2000:]
    n, pipeline, llm, known = run.stdout.split()
    assert int(n) > 120 and (pipeline, llm, known) == ("False", "False", "True")


def test_core_does_not_import_the_operators():
    for path in (ROOT / "fimspark").rglob("*.py"):
        if "llm" not in path.relative_to(ROOT).parts:
            assert "llm" not in path.read_text(), path
