"""The driver contract, and the registry with the corpus operators absent."""

import os
import shutil
import subprocess
import sys

import pytest

import __spark_entry__ as entry

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_contract(spark):
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 60
    assert entry.entry(spark).count() > 0


@pytest.mark.parametrize("lost", ["folders", "package"])
def test_entry_without_the_corpus_operators(tmp_path, lost):
    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 60 and not any(n[:2] == 'op' or n == 'pipeline' for n in q); assert set(e.oracle_sql()) <= set(q)"
    if lost == "folders":
        shutil.rmtree(copy / "aggnear/llm", ignore_errors=True)
        shutil.rmtree(copy / "tests/llm", ignore_errors=True)
        (copy / "corpus_pipeline.py").unlink(missing_ok=True)
    else:
        code = "import sys; sys.modules['xxhash'] = None; " + code
    subprocess.run([sys.executable, "-B", "-c", code], cwd=copy, check=True, timeout=120)
