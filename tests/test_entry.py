import os
import subprocess
import sys

import twins  # beside this file

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_queries_and_twins_import_without_java_or_jars():
    code = "import zipfile; zipfile.ZipFile = None; import __spark_entry__ as e; q, s = e.queries(), e.oracle_sql(); assert len(q) > 150 and set(s) <= set(q)"
    env = os.environ | {"JAVA_HOME": "/nowhere", "PYTHONPATH": ROOT}
    assert subprocess.run([sys.executable, "-c", code], cwd=ROOT, env=env, capture_output=True, timeout=120).returncode == 0


def test_main_results_equal_their_twins(spark, sf):
    """Of the main methods here; ``python tests/twins.py SF_DIR`` compares every query."""
    import __spark_entry__ as entry

    con, made, sqls = twins.views(sf), entry.queries(), entry.oracle_sql()
    for name in ("stop_words", "naive_epts", "cutoff_apply", "swp_epts", "word_stream_topk", "align_wcw", "w13_lead_rank"):
        assert twins.differ(spark, con, made[name], sqls[name], sf) == "", name
