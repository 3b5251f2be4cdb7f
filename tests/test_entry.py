"""The driver contract, and that the training-data operators are optional."""

import subprocess
import sys
from pathlib import Path

import __spark_entry__ as entry

ROOT = Path(__file__).resolve().parents[1]


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 210 and {r.id for r in rows} >= {0}


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_imports_without_the_optional_parts():
    code = "import sys; sys.modules['redgraph.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; n = e.queries(); assert n and not [k for k in n if k.startswith('op') or k == 'pipeline']"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)
