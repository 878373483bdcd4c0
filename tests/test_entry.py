"""The driver contract, with and without the operators' subpackage."""

import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent


def test_entry_and_names(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    rows = e.entry(spark)
    assert rows.count() > 0 and "question" in rows.columns


@pytest.mark.parametrize("blocked", [["anchorscope.llm", "corpus_pipeline"], ["xxhash", "anchorscope.llm.queries"]])
def test_entry_without_operators(blocked):
    code = f"""
import sys
sys.path.insert(0, {str(ROOT)!r})
for name in {blocked!r}:
    sys.modules[name] = None  # importing it raises ImportError
import __spark_entry__ as e
assert not any(k.startswith('op') for k in e.queries()) and len(e.queries()) > 50
"""
    subprocess.run([sys.executable, "-c", code], check=True)
