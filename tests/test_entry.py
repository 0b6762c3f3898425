"""The registry works as it stands, and without the training-data operators."""

import subprocess
import sys

from tests.conftest import ROOT


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert len(e.queries()) > 200 and set(e.oracle_sql()) <= set(e.queries())


def test_library_needs_no_llm(tmp_path):
    code = "import sys; sys.modules['triplefed.llm'] = None; import __spark_entry__ as e; q = e.queries(); print(len(q), any(k.startswith('op') for k in q))"
    out = subprocess.run([sys.executable, "-c", code], cwd=ROOT, capture_output=True, text=True)
    assert out.returncode == 0, out.stderr
    assert out.stdout.split()[1] == "False"
