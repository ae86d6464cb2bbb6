"""The driver's contract before a session exists."""

import subprocess
import sys
from pathlib import Path


def test_queries_and_sql_are_readable_without_a_session():
    root = Path(__file__).resolve().parents[1]
    code = "import __spark_entry__ as e; from pyspark.sql import SparkSession; q = e.queries(); o = e.oracle_sql(); assert q and set(o) <= set(q), set(o) - set(q); assert SparkSession.getActiveSession() is None"
    done = subprocess.run([sys.executable, "-c", code], cwd=root, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr
