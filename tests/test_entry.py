import os
import pathlib
import shutil
import subprocess
import sys

import __spark_entry__ as entry

ROOT = pathlib.Path(__file__).resolve().parents[1]


def test_contract(spark):
    names = entry.queries()
    assert set(entry.oracle_sql()) <= set(names)
    assert entry.entry(spark).count() == 10


def test_the_rest_stands_without_the_corpus_operators(tmp_path):
    for left in ((), ("corpus_pipeline.py",)):
        copy = tmp_path / f"copy{len(left)}"
        shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", *(() if left else ("corpus_pipeline.py",))))
        assert not (copy / "waypoint/llm").exists() and (copy / "corpus_pipeline.py").exists() == bool(left)
        said = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert set(q) == set(o) and 'pipeline' not in q and len(q) > 100; print(len(q))"
        done = subprocess.run([sys.executable, "-B", "-c", said], cwd=copy, capture_output=True, text=True, env={k: v for k, v in os.environ.items() if k != "PYTHONPATH"})
        assert done.returncode == 0, done.stderr
        (copy / "waypoint/llm/__pycache__").mkdir(parents=True)  # a folder without modules is no subpackage
        assert subprocess.run([sys.executable, "-B", "-c", said], cwd=copy, capture_output=True).returncode == 0


def test_no_other_module_uses_the_corpus_operators():
    for f in (ROOT / "waypoint").rglob("*.py"):
        if "llm" not in f.relative_to(ROOT).parts:
            assert "waypoint.llm" not in f.read_text(), f
