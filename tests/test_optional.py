"""The engine works without the training-data operators."""

import subprocess
import sys
from pathlib import Path

CODE = """
import sys
class Gone:
    def find_spec(self, name, path=None, target=None):
        if name in ("corpus_pipeline", "rulegraph.llm"):
            raise ModuleNotFoundError(name, name=name)
sys.meta_path.insert(0, Gone())
import __spark_entry__ as e
assert "facts_trade" in e.queries() and not any(k.startswith("op") for k in e.queries())
assert "facts_trade" in e.oracle_sql() and "op4_decontamination" not in e.oracle_sql()
"""


def test_entry_without_the_subpackage():
    subprocess.run([sys.executable, "-c", CODE], check=True, cwd=Path(__file__).resolve().parent.parent)
