import os
import subprocess
import sys

REPO = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_entry_runs(spark):
    import __spark_entry__ as e

    rows = e.entry(spark).collect()
    assert len(rows) == 36


def test_every_oracle_has_its_query():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries()) and len(e.queries()) > 150


def test_the_rest_works_without_the_training_data_folders(tmp_path):
    copy = tmp_path / "repo"
    subprocess.run(["cp", "-r", REPO, copy], check=True)
    for gone in ("joinsynth/llm", "tests/llm", "corpus_pipeline.py"):
        subprocess.run(["rm", "-rf", copy / gone], check=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'pipeline' not in q and not any(n.startswith('op1_') for n in q) and 's02_max_degree_two_tables' in q; e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], check=True, cwd=copy)
    assert "joinsynth.llm" not in subprocess.run(["grep", "-rn", "llm", copy / "joinsynth", "--include=*.py"], capture_output=True, text=True).stdout
