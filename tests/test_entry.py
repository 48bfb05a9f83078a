"""The driver's contract: names match, and importing needs neither a session nor the optional operators."""

import subprocess
import sys

import __spark_entry__


def test_oracles_belong_to_queries():
    q, o = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(o) <= set(q) and len(q) > 100


def test_entry_runs(spark):
    assert __spark_entry__.entry(spark).count() == 1


def test_import_without_the_optional_operators():
    code = "import sys; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; assert 'pipeline' not in e.queries() and e.queries()"
    assert subprocess.run([sys.executable, "-c", code], cwd=__spark_entry__.__file__.rsplit("/", 1)[0], capture_output=True).returncode == 0
