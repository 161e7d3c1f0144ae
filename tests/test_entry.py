import os
import shutil
import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]


def names(where):
    code = "import __spark_entry__ as e; print(len(e.oracle_sql()) > 200, *e.queries())"
    return subprocess.run([sys.executable, "-c", code], cwd=where, env=os.environ | {"PYTHONPATH": str(where)}, capture_output=True, text=True, check=True).stdout.split()


def test_engine_works_without_the_pipeline_operators(tmp_path):
    """With the operators' folders deleted, and with the pipeline file left or deleted, the other queries are all there."""
    copy = tmp_path / "copy"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse"))
    full = set(names(copy))
    shutil.rmtree(copy / "keyhop" / "llm")
    shutil.rmtree(copy / "tests" / "llm")
    left = set(names(copy))
    (copy / "corpus_pipeline.py").unlink()
    assert "True" in left and names(copy)[0] == "True" and left == set(names(copy))
    assert all(n == "pipeline" or n.startswith("op") and n[2].isdigit() for n in full - left)
    found = subprocess.run(["grep", "-rlE", "keyhop.llm|corpus_pipeline", "keyhop", "--include=*.py"], cwd=copy, capture_output=True, text=True).stdout
    assert found == ""


def test_only_the_entry_names_the_operators():
    outside = [p for p in (ROOT / "keyhop").rglob("*.py") if "llm" not in p.parts]
    assert not [p for p in outside if "keyhop.llm" in p.read_text()]
