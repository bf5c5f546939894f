import subprocess
import sys
from pathlib import Path

REPO = Path(__file__).resolve().parents[1]


def test_every_oracle_has_a_query():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_imports_without_the_training_data_operators():
    code = "import sys; sys.modules['densecount.llm'] = None; import __spark_entry__ as e; assert not any(q.startswith('op') for q in e.queries()); assert len(e.queries()) > 60"
    subprocess.run([sys.executable, "-c", code], cwd=REPO, check=True)


def test_entry_runs(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
