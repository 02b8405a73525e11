"""Shuffle files of what is written and read again."""

import subprocess
import sys
from pathlib import Path

CODE = """
import sys
from pathlib import Path
from pyspark.sql import SparkSession
root = Path(sys.argv[1])
b = SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").config("spark.local.dir", str(root / "local")).config("spark.sql.warehouse.dir", str(root / "w"))
spark = b.config("spark.checkpoint.dir", f"file://{root}/shared").config("spark.sql.shuffle.partitions", "4").getOrCreate()
from kinetrace.llm import storage
given = spark.conf.get(storage.CLEANUP, None)
rows = storage.written(spark.range(200000).selectExpr("id % 50000 AS k").groupBy("k").count(), "counts")
assert rows.count() == 50000 and spark.conf.get(storage.CLEANUP, None) == given
print("left", sum(p.stat().st_size for p in root.glob("local/**/shuffle_0_*.data")))
"""


def test_shuffle_files_go_with_the_computation(tmp_path):
    root = str(Path(__file__).parent.parent.parent)
    out = subprocess.run([sys.executable, "-c", CODE, str(tmp_path)], capture_output=True, text=True, timeout=90, cwd=root, env={**__import__("os").environ, "PYTHONPATH": root, "SPARK_LOCAL_DIRS": str(tmp_path / "local")})
    assert out.stdout.split("left")[-1].strip() == "0", out.stderr[-2000:]
