"""The library works without the training-data subpackage."""

import subprocess
import sys

CODE = """
import sys
class Gone:
    def find_spec(self, name, path=None, target=None):
        if name == 'corpus_pipeline' or name.startswith('blockrecover.llm'):
            raise ModuleNotFoundError(name)
sys.meta_path.insert(0, Gone())
import __spark_entry__ as e
assert e.queries() and not any(k.startswith(('op1_', 'pipeline')) for k in e.queries())
assert set(e.oracle_sql()) <= set(e.queries())
"""


def test_entry_without_subpackage():
    import os

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    subprocess.run([sys.executable, "-c", CODE], cwd=root, check=True, timeout=120)
