"""The registry loads before any session runs."""

import subprocess
import sys
from pathlib import Path


def test_loads_without_a_session():
    root = Path(__file__).resolve().parents[2]
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()) >= len(e.oracle_sql()) > 150)"], cwd=root, capture_output=True, text=True, check=False)
    assert done.stdout.strip() == "True", done.stderr
