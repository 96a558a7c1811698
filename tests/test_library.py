"""The library imports without its training-data subpackage, and nothing else in it imports that."""

import pathlib
import shutil
import subprocess
import sys

ROOT = pathlib.Path(__file__).resolve().parent.parent


def test_nothing_imports_llm():
    for p in (ROOT / "elastipool").rglob("*.py"):
        if "llm" not in p.relative_to(ROOT / "elastipool").parts:
            assert "elastipool.llm" not in p.read_text() and "from .llm" not in p.read_text(), p


def test_entry_has_queries_and_sql():
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and "elastic_results" in q


def test_entry_without_the_training_data_folders(tmp_path):
    """With those folders deleted, with and without the pipeline's file, the entry offers all other queries."""
    for name in ("elastipool", "tests"):
        shutil.copytree(ROOT / name, tmp_path / name, ignore=shutil.ignore_patterns("llm", "__pycache__"))
    for name in ("__spark_entry__.py", "corpus_pipeline.py", "bench.py"):
        if (ROOT / name).exists():
            shutil.copy(ROOT / name, tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert set(e.oracle_sql()) <= set(q) and 'pipeline' not in q and len(q) > 150, q"
    for _ in range(2):
        done = subprocess.run([sys.executable, "-B", "-c", code], cwd=tmp_path, env={"PATH": "/usr/bin:/bin"}, capture_output=True, text=True, timeout=120)
        assert done.returncode == 0, done.stderr
        (tmp_path / "corpus_pipeline.py").unlink(missing_ok=True)
