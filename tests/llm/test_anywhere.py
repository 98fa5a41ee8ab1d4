"""Workers need not have this package: its queries run where only the driver can import it."""

import os
import subprocess
import sys
from pathlib import Path

from llm_helpers import SF

REPO = Path(__file__).parents[2]
SCRIPT = f"""
import sys
sys.path.insert(0, {str(REPO)!r})
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").getOrCreate()

def importable(batches):
    import importlib.util
    import pandas as pd
    for b in batches:
        yield pd.DataFrame({{"x": [importlib.util.find_spec("finegrain") is not None]}})

assert not spark.range(1).mapInPandas(importable, "x boolean").first().x
import __spark_entry__
for name, query in __spark_entry__.queries().items():
    if name.startswith("op") or name in ("pipeline", "coupled_loss_r2", "reconstruct_r2", "dct_basis", "cube_planted"):
        assert query(spark, {SF!r}).count() > 0, name
        print("done", name)
"""


def test_queries_run_on_workers_without_the_package(tmp_path):
    (tmp_path / "script.py").write_text(SCRIPT)
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    own = [p for p in os.environ.get("PYTHONPATH", "").split(":") if p and not (Path(p) / "finegrain").exists()]
    out = subprocess.run([sys.executable, "script.py"], cwd=tmp_path, env=env | {"PYTHONPATH": ":".join(own)}, capture_output=True, text=True, timeout=600)
    assert out.returncode == 0, out.stderr[-3000:]
    assert out.stdout.count("done op") == 10 and "done pipeline" in out.stdout
