"""The driver's contract, with and without the corpus operators."""

import shutil
import subprocess
import sys

from conftest import ROOT


def test_entry(spark):
    import __spark_entry__

    df = __spark_entry__.entry(spark)
    assert df.columns == ["doc_id", "lang", "cluster"] and df.count() == 200
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_rest_stands_without_the_corpus_operators(tmp_path):
    shutil.copytree(ROOT, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "spark-warehouse", "__pycache__"))
    code = "import __spark_entry__ as e, bench; q = e.queries(); assert 'q_fit_nystrom' in q and not any(n.startswith('op') or n == 'pipeline' for n in q), q"
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", capture_output=True, text=True, env={"PATH": "/usr/bin:/bin"})
    assert done.returncode == 0, done.stderr


def test_core_does_not_import_the_corpus_operators():
    for f in (ROOT / "landmark_kkm").rglob("*.py"):
        if "llm" not in f.parts:
            assert "landmark_kkm.llm" not in f.read_text(), f
