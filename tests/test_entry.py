"""The entry module with and without the corpus operators."""

import os
import shutil
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def names(folder: str) -> tuple[set[str], set[str]]:
    code = "import __spark_entry__ as e; print(*e.queries()); print(*e.oracle_sql())"
    out = subprocess.run([sys.executable, "-c", code], cwd=folder, capture_output=True, text=True, check=True, env=os.environ | {"PYTHONPATH": folder})
    queries, sql = out.stdout.strip().split("\n")[-2:]
    return set(queries.split()), set(sql.split())


def test_without_corpus_operators(tmp_path):
    bare = tmp_path / "bare"
    shutil.copytree(ROOT, bare, ignore=shutil.ignore_patterns(".git", "llm", "__pycache__", "spark-warehouse"))
    queries, sql = names(str(bare))  # corpus_pipeline.py is still there, but what it needs is not
    assert "broom_estimate" in queries and "hybrid_estimate" in sql
    assert not [n for n in queries | sql if n == "pipeline" or n[:2] == "op" and n[2].isdigit()]
    os.remove(bare / "corpus_pipeline.py") if os.path.exists(bare / "corpus_pipeline.py") else None
    assert names(str(bare)) == (queries, sql)
    if os.path.isdir(os.path.join(ROOT, "biclique_spark", "llm")):
        whole, _ = names(ROOT)
        assert whole > queries and "pipeline" in whole and sum(n[:2] == "op" and n[2].isdigit() for n in whole) == 10
