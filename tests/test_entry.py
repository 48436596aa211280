"""The driver's entry points load without a session, and give what they promise."""

import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def test_entry_points_need_no_session():
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 150 and set(o) <= set(q), (len(q), set(o) - set(q)); print(len(q), len(o))"
    got = subprocess.run([sys.executable, "-c", code], cwd=ROOT, capture_output=True, text=True, timeout=120)
    assert got.returncode == 0, got.stderr[-800:]


def test_flagship(spark):
    import __spark_entry__ as e

    rows = e.entry(spark).collect()
    assert {r["layer"] for r in rows} == {0, 1} and sum(r["hits"] for r in rows) > 0 and all(0 <= r["hit_rate"] <= 1 for r in rows)
