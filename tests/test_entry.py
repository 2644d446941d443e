"""The driver's contract."""

from __future__ import annotations

import os
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_tables_of_queries_need_no_session():
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; assert set(e.oracle_sql()) <= set(e.queries()); print(len(e.queries()))"], cwd=ROOT, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr
    assert int(done.stdout) > 200


def test_entry_gives_rows(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).columns == ["user_id", "life_no", "begin_ts", "end_ts", "n_wrangle"]


def test_without_the_training_data_part(tmp_path):
    """What is left when its folder and the pipeline file are deleted, or a library of theirs is missing."""
    import shutil

    for gone in (("nbflow/llm", "corpus_pipeline.py"), ()):
        copy = tmp_path / f"copy{len(gone)}"
        shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__"))
        for name in gone:
            shutil.rmtree(copy / name) if (copy / name).is_dir() else (copy / name).unlink()
        block = "" if gone else "import sys; sys.modules['xxhash'] = None; "
        done = subprocess.run([sys.executable, "-c", f"{block}import __spark_entry__ as e; assert not [n for n in e.queries() if n[:2] == 'op' and n[2].isdigit() or n == 'pipeline']; print(len(e.queries()))"], cwd=copy, capture_output=True, text=True, timeout=120, env={**os.environ, "PYTHONPATH": str(copy)})
        assert done.returncode == 0, done.stderr
        assert int(done.stdout) > 200
