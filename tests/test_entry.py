"""The driver's contract: importable without a session, and without the training-data operators."""

import os
import shutil
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
CODE = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert set(o) <= set(q), set(o) - set(q); print(len(q), sum(k[:2] == 'op' and k[2].isdigit() for k in q))"


def counts(folder):
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    run = subprocess.run([sys.executable, "-c", CODE], cwd=folder, env=env, capture_output=True, text=True, timeout=120)
    assert run.returncode == 0, run.stderr[-1500:]
    return tuple(map(int, run.stdout.split()))


def test_queries_need_no_session():
    assert counts(ROOT)[0] >= 240


def test_rest_stands_alone(tmp_path):
    shutil.copytree(os.path.join(ROOT, "clipforge"), tmp_path / "clipforge", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(os.path.join(ROOT, "__spark_entry__.py"), tmp_path)
    n, ops = counts(tmp_path)
    assert n >= 240 and ops == 0


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
