"""All operators and the pipeline where workers have no copy of the package on their path."""

import os
import subprocess
import sys

import pytest

REPO = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

SCRIPT = """
import sys
from pyspark.sql import SparkSession
sys.path.insert(0, {repo!r})  # the driver's path only
spark = (SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
         .config("spark.checkpoint.dir", {folder!r}).getOrCreate())
spark.sparkContext.setLogLevel("OFF")

def reach(batches):
    import importlib.util
    import pyarrow as pa
    for b in batches:
        yield pa.RecordBatch.from_pydict({{"found": [importlib.util.find_spec("ruleclosure") is not None]}})

assert not spark.range(1).mapInArrow(reach, "found boolean").first()[0], "workers see the package"
import __spark_entry__
for name in sorted(__spark_entry__.queries()):
    if name in {names!r} or name.startswith("op") and name[2:3].isdigit():
        __spark_entry__.queries()[name](spark, {sf!r}).write.format("noop").mode("overwrite").save()
        print("ran", name, flush=True)
"""


@pytest.mark.parametrize("names", [("pipeline",)])
def test_workers_need_no_package(tmp_path, sf, names):
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    script = SCRIPT.format(repo=REPO, folder=str(tmp_path / "shared"), sf=sf, names=names)
    done = subprocess.run([sys.executable, "-c", script], cwd=tmp_path, env=env, capture_output=True, text=True, timeout=600, check=False)
    ran = [x for x in done.stdout.splitlines() if x.startswith("ran ")]
    assert done.returncode == 0 and len(ran) == 11, done.stderr[-3000:]
