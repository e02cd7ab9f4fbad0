"""The driver contract: stable queries, each oracle for a query, and a package that stands without the corpus folder."""

import os
import subprocess
import sys

import __spark_entry__ as E
import pytest

from .conftest import ROOT


def test_entry_and_names(spark):
    assert E.entry(spark).count() > 0
    assert set(E.oracle_sql()) <= set(E.queries()) and len(E.queries()) > 100


@pytest.mark.parametrize("script", [True, False])
def test_the_rest_stands_without_the_corpus_folder(tmp_path, script):
    """With the folders gone, with or without the script at the top, queries remain, and so do the other tests."""
    parts = [f"{ROOT}/mjoin", f"{ROOT}/tests", f"{ROOT}/__spark_entry__.py", *([f"{ROOT}/corpus_pipeline.py"] if script and os.path.exists(f"{ROOT}/corpus_pipeline.py") else [])]
    subprocess.run(["cp", "-r", *parts, tmp_path], check=True)
    subprocess.run(["rm", "-rf", tmp_path / "mjoin/llm", tmp_path / "tests/llm"], check=True)
    code = "import __spark_entry__ as e; print(len(e.queries()), any(k.startswith('op1_') or k == 'pipeline' for k in e.queries()), len(e.oracle_sql()))"
    plain = {"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)}
    said = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=plain, capture_output=True, text=True)
    assert said.returncode == 0 and said.stdout.split()[1] == "False" and int(said.stdout.split()[2]) > 90, said.stderr
    tests = subprocess.run([sys.executable, "-m", "pytest", "tests/test_plan.py", "tests/test_partition.py", "-x", "-q", "--collect-only"], cwd=tmp_path, env=os.environ | {"PYTHONPATH": str(tmp_path)}, capture_output=True, text=True)
    assert tests.returncode == 0, tests.stdout


def test_nothing_else_imports_the_corpus_folder():
    """But for the two top modules, no line outside the folder names it."""
    found = subprocess.run(["grep", "-rlE", r"(from|import) .*\bllm\b", f"{ROOT}/mjoin", "--include=*.py"], capture_output=True, text=True).stdout.split()
    assert all("/mjoin/llm/" in f for f in found)
