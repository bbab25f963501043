"""The driver's contract holds before any Spark session exists, with or without the training-data operators."""

import os
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_imports_without_a_session():
    code = "import __spark_entry__ as e; q = e.queries(); s = e.oracle_sql(); assert set(s) <= set(q) and len(q) > 90, (len(q), set(s) - set(q))"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True, timeout=120)


def test_library_stands_alone():
    code = (
        "import sys; sys.modules['tplforge.llm'] = None; sys.modules['corpus_pipeline'] = None\n"
        "import __spark_entry__ as e; assert not [k for k in e.queries() if k == 'pipeline' or k[:2] == 'op' and k[2].isdigit()]"
    )
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True, timeout=120)
