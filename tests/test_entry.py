"""The entry module without the training-data folders, in a copy of the repository."""

import os
import shutil
import subprocess
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


@pytest.mark.parametrize("gone", [("dynreach/llm", "tests/llm"), ("corpus_pipeline.py",), ("dynreach/llm", "tests/llm", "corpus_pipeline.py")])
def test_imports_without(gone, tmp_path):
    copy = tmp_path / "copy"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "*.json", "*.txt"))
    for name in gone:
        path = copy / name
        shutil.rmtree(path) if path.is_dir() else path.unlink(missing_ok=True)
    code = "import __spark_entry__ as e; q = e.queries(); print(len(q), 'pipeline' in q, any(n.startswith('op1_') for n in q), set(e.oracle_sql()) <= set(q))"
    out = subprocess.run([sys.executable, "-B", "-c", code], cwd=copy, env=os.environ | {"PYTHONPATH": str(copy)}, capture_output=True, text=True, check=True)
    n, pipeline, ops, sound = out.stdout.split()[-4:]
    assert int(n) > 200 and pipeline == "False" and sound == "True"
    if "dynreach/llm" in gone:
        assert ops == "False"


def test_other_missing_modules_are_errors(tmp_path):
    copy = tmp_path / "copy"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "*.json", "*.txt"))
    (copy / "corpus_pipeline.py").write_text("import no_such_module_at_all\n")
    out = subprocess.run([sys.executable, "-B", "-c", "import __spark_entry__"], cwd=copy, env=os.environ | {"PYTHONPATH": str(copy)}, capture_output=True, text=True)
    assert out.returncode and "no_such_module_at_all" in out.stderr
