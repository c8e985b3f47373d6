"""The driver's contract, and the library without its llm part."""

import subprocess
import sys
from pathlib import Path

import __spark_entry__ as entry_module

ROOT = Path(__file__).resolve().parent.parent


def test_entry(spark):
    rows = {r.motif: r.n for r in entry_module.entry(spark).collect()}
    assert rows == {"tri_cycle": 146, "lollipop": 90, "quad_cycle": 83}


def test_queries_and_oracles_match():
    q, o = entry_module.queries(), entry_module.oracle_sql()
    assert set(o) <= set(q) and len(q) > 200
    assert {k for k in q if k not in o} <= {k for k in q if k.startswith("op") or k == "pipeline"}


def test_nothing_else_needs_the_llm_part(tmp_path):
    """A copy without the llm folder and the pipeline still imports and lists the other queries."""
    code = f"""
import sys
sys.path.insert(0, {str(ROOT)!r})
class Gone:
    def find_spec(self, name, path=None, target=None):
        if name.startswith("motifspark.llm") or name == "corpus_pipeline":
            raise ModuleNotFoundError(name, name=name)
sys.meta_path.insert(0, Gone())
import __spark_entry__ as e
assert not [k for k in e.queries() if k.startswith("op")] and "comine_C3_msg" in e.queries() and e.oracle_sql()
"""
    subprocess.run([sys.executable, "-c", code], check=True, cwd=tmp_path, timeout=120)
    for f in (ROOT / "motifspark").rglob("*.py"):
        if "llm" not in f.parts:
            assert "motifspark.llm" not in f.read_text() and "from .llm" not in f.read_text()
