"""release() on executors of their own: the heap that a step filled is given back."""

import os
import subprocess
import sys
from importlib.util import find_spec
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent

RUN = r"""
import re
from pathlib import Path
from pyspark.sql import SparkSession, functions as F
from probgraph.runtime import release, ship

conf = {"spark.master": "local-cluster[2,1,1000]", "spark.executor.memory": "1000m", "spark.driver.host": "127.0.0.1", "spark.ui.enabled": "false", "spark.sql.shuffle.partitions": "2", "spark.sql.adaptive.enabled": "false"}
conf |= {"spark.executor.extraJavaOptions": "-XX:+UseG1GC -XX:ActiveProcessorCount=2"}
spark = SparkSession.builder.config(map=conf).getOrCreate()
spark.sparkContext.setLogLevel("ERROR")
ship(spark)

def own(batches):
    # the memory of the executor's JVM, which the workers' daemon is a child of
    import os, time
    import pyarrow as pa
    for _ in batches:
        pass
    time.sleep(1)  # so that each executor gets one of the tasks
    daemon = int(Path(f"/proc/{os.getppid()}/stat").read_text().rpartition(")")[2].split()[1])
    mb = int(re.search(r"\nPss_Anon:\s+(\d+)", Path(f"/proc/{daemon}/smaps_rollup").read_text())[1]) // 1024
    yield pa.RecordBatch.from_arrays([pa.array([daemon]), pa.array([mb])], names=["pid", "mb"])

def memory():
    return {r.pid: r.mb for r in spark.range(0, 2, 1, 2).mapInArrow(own, "pid long, mb long").collect()}

# each task gathers some 300 MB in one row and drops it
spark.range(0, 60, 1, 2).select((F.col("id") % 2).alias("k"), F.repeat(F.col("id").cast("string"), 2_000_000).alias("x")).groupBy("k").agg(F.max(F.length("x")), F.length(F.concat_ws("", F.collect_list("x")))).collect()
before = memory()
release(spark)
after = memory()
print("MB", sorted(before.items()), sorted(after.items()))
assert len(before) == len(after) == 2 and set(before) == set(after)
print("GIVEN", min(before[k] - after[k] for k in before))
spark.stop()
"""


def test_executors_give_back_their_heap(tmp_path):
    home = tmp_path / "home"
    (home / "work").mkdir(parents=True)
    for p in Path(find_spec("pyspark").origin).parent.iterdir():  # executors' logs go to work in Spark's home
        if p.name != "work":
            (home / p.name).symlink_to(p)
    env = os.environ | {"PYTHONPATH": f"{ROOT}:{os.environ.get('PYTHONPATH', '')}", "PYSPARK_PYTHON": sys.executable, "SPARK_HOME": str(home), "SPARK_SCALA_VERSION": "2.13", "SPARK_LOCAL_IP": "127.0.0.1", "SPARK_LOCAL_DIRS": str(tmp_path), "TMPDIR": str(tmp_path)}
    (tmp_path / "run.py").write_text(RUN)
    ran = subprocess.run([sys.executable, str(tmp_path / "run.py")], env=env, cwd=tmp_path, capture_output=True, text=True, timeout=150)
    assert ran.returncode == 0, ran.stderr[-2000:]
    assert int(ran.stdout.rpartition("GIVEN")[2]) >= 100, ran.stdout
