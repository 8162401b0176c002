"""Executors need no copy of the package: workers start in a folder from which it can't be imported."""

import os
import subprocess
import sys

REPO = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

SCRIPT = """
import sys

sys.path.insert(0, sys.argv[1])
from pyspark.sql import SparkSession

from levcut.llm.queries import QUERIES

spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").getOrCreate()
spark.sparkContext.setLogLevel("ERROR")


def absent(batches):
    try:
        import levcut
    except ModuleNotFoundError:
        yield from batches


assert spark.range(3).mapInArrow(absent, "id long").count() == 3, "the workers can import the package"
for name, query in QUERIES.items():
    assert query(spark, sys.argv[2]).count() > 0, name
print("all ran")
"""


def test_queries_run_where_workers_lack_the_package(tmp_path):
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    script = tmp_path / "run.py"
    script.write_text(SCRIPT)
    run = subprocess.run([sys.executable, str(script), REPO, "/root/testdata/sf0.001"], cwd=tmp_path, env=env, capture_output=True, text=True, timeout=600)
    assert "all ran" in run.stdout, run.stderr[-3000:]
