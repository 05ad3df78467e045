"""The driver's contract."""

import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def test_entry_runs(spark):
    import __spark_entry__ as e

    df = e.entry(spark)
    assert df.columns == ["dst", "k", "s"] and df.count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_entry_imports_without_the_text_operators(tmp_path):
    code = """
import sys
class Gone:
    def find_spec(self, name, path=None, target=None):
        if name == "corpus_pipeline" or name.startswith("fullgraph.llm"):
            raise ModuleNotFoundError(f"No module named {name!r}", name=name)
sys.meta_path.insert(0, Gone())
import __spark_entry__ as e
assert "agg_hybrid" in e.queries() and not any(q.startswith("op") or q == "pipeline" for q in e.queries())
"""
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)
