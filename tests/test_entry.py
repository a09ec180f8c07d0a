"""The entry points with and without the corpus operators."""

import os
import shutil
import subprocess
import sys

import pytest

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


@pytest.mark.parametrize("gone", [["incwalk/llm", "tests/llm"], ["incwalk/llm", "tests/llm", "corpus_pipeline.py"]])
def test_the_rest_survives_without_the_corpus_operators(tmp_path, gone):
    tree = tmp_path / "tree"
    shutil.copytree(ROOT, tree, ignore=shutil.ignore_patterns(".git", "__pycache__"))
    for name in gone:
        path = tree / name
        if path.is_dir():
            shutil.rmtree(path)
        elif path.exists():
            path.unlink()
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert 'walk_visits' in q and set(o) <= set(q); assert not any(n.startswith('op') and n[2].isdigit() or n == 'pipeline' for n in q)"
    subprocess.run([sys.executable, "-c", code], cwd=tree, check=True, env={k: v for k, v in os.environ.items() if k != "PYTHONPATH"})
