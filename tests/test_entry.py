"""The entry's surface must be readable without a Spark session, as a driver may list queries before it starts one."""

import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent
LIST = "import __spark_entry__ as e; from pyspark.sql import SparkSession; q = e.queries(); assert set(e.oracle_sql()) <= set(q); assert SparkSession.getActiveSession() is None; print(len(q))"


def test_queries_listed_without_a_session():
    out = subprocess.run([sys.executable, "-c", LIST], cwd=ROOT, capture_output=True, text=True, timeout=120)
    assert out.returncode == 0, out.stderr
    assert int(out.stdout) > 200
