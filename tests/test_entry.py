import os
import shutil
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_entry_runs(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_entry_without_training_data_operators(tmp_path):
    """Without the subpackage and the pipeline file everything else is still there."""
    shutil.copytree(ROOT, f"{tmp_path}/r", ignore=lambda d, names: [n for n in names if n in ("llm", "corpus_pipeline.py", ".git", "__pycache__")])
    code = "import __spark_entry__ as e; q = e.queries(); o = e.oracle_sql(); assert len(q) > 80 and not [n for n in q if n.startswith('op') or n == 'pipeline'] and set(o) <= set(q)"
    env = os.environ | {"PYTHONPATH": f"{tmp_path}/r"}
    assert subprocess.run([sys.executable, "-c", code], cwd=f"{tmp_path}/r", env=env, timeout=120).returncode == 0
