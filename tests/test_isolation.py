"""The library imports without the training-data subpackage."""

import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def test_nothing_outside_imports_llm():
    for path in (ROOT / "clustercost").rglob("*.py"):
        if "llm" not in path.parts:
            assert "llm" not in path.read_text(), path


def test_entry_imports_without_llm(tmp_path):
    for name in ("clustercost", "__spark_entry__.py"):
        subprocess.run(["cp", "-r", str(ROOT / name), str(tmp_path)], check=True)
    subprocess.run(["rm", "-rf", str(tmp_path / "clustercost/llm")], check=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'pivot_cost_emb' in q and not any(x.startswith('op1_') for x in q) and e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
