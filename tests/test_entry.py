"""The driver contract, with and without the training-data operators."""

import os
import shutil
import subprocess
import sys

from tests.conftest import ROOT

CHECK = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert set(o) <= set(q), set(o) - set(q); print(len(q), sum(n.startswith('op') for n in q), 'pipeline' in q)"


def run(folder):
    out = subprocess.run([sys.executable, "-c", CHECK], cwd=folder, capture_output=True, text=True, env=os.environ | {"PYTHONPATH": folder}, check=True)
    return out.stdout.split()[-3:]


def test_entry_without_the_operators(tmp_path):
    shutil.copytree(f"{ROOT}/prefbook", f"{tmp_path}/prefbook", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{ROOT}/__spark_entry__.py", tmp_path)
    n, ops, pipeline = run(str(tmp_path))
    assert int(n) > 100 and ops == "0" and pipeline == "False"


def test_entry(spark):
    import __spark_entry__ as e

    rows = e.entry(spark).collect()
    assert len(rows) == 7 and set(e.oracle_sql()) <= set(e.queries())


def test_nothing_else_imports_the_operators():
    for folder, _, names in os.walk(f"{ROOT}/prefbook"):
        if "/llm" in folder or "__pycache__" in folder:
            continue
        for name in names:
            with open(f"{folder}/{name}") as f:
                assert "prefbook.llm" not in f.read(), f"{folder}/{name}"
