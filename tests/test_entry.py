"""The registry answers, and holds without the subpackage of training-data operators."""

import subprocess
import sys

import __spark_entry__ as entry


def test_entry(spark):
    assert entry.entry(spark).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_without_operators():
    code = "import sys; sys.modules['sparsetri.llm'] = None; import __spark_entry__ as e; assert 'six_pass_estimate_geo' in e.queries() and not any(k.startswith('op') and k[2].isdigit() for k in e.queries())"
    assert subprocess.run([sys.executable, "-c", code], cwd=entry.__file__.rsplit("/", 1)[0]).returncode == 0
