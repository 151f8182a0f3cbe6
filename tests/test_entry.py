"""The driver's contract loads in a fresh interpreter, before any session exists."""

import os
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
PROBE = """
import sys
sys.path.insert(0, {root!r})
import __spark_entry__ as e
from pyspark import SparkContext
known, twins = e.queries(), e.oracle_sql()
assert SparkContext._active_spark_context is None
assert known and set(twins) <= set(known), set(twins) - set(known)
assert all(isinstance(s, str) and s.strip() for s in twins.values())
print(len(known), len(twins))
"""


def test_loads_without_a_session():
    done = subprocess.run([sys.executable, "-c", PROBE.format(root=ROOT)], capture_output=True, text=True, timeout=120, cwd="/")
    assert done.returncode == 0, done.stderr
