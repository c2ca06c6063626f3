"""Shared files between stages: every intermediate goes to the folder that the cluster names in spark.checkpoint.dir."""

from __future__ import annotations

import atexit
import contextlib
import os
import shutil
import tempfile
import time
import uuid
import zipfile
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
_SHIPPED: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of the session as a URI; a folder of this process only where none is set, which only local mode may do."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("spark.checkpoint.dir names no folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        path = tempfile.mkdtemp(prefix="keyless-")
        atexit.register(shutil.rmtree, path, ignore_errors=True)
        _OWN[app] = "file://" + path
    return _OWN[app]


BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
ROWS = 1000
#: Seconds of a job after which its shuffle files are worth freeing at once.
COLLECT_AFTER = 3.0


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = ROWS) -> Iterator[None]:
    """Arrow batches of whole texts are kept small while intermediates are written; the session's own setting holds again after."""
    before = spark.conf.get(BATCH)
    if not 0 < int(before) <= rows:
        spark.conf.set(BATCH, str(rows))
    try:
        yield
    finally:
        spark.conf.set(BATCH, before)


def settled(docs: DataFrame, ws: Workspace) -> DataFrame:
    """``docs`` where its rows are read from files and at most filtered and projected, so that a second reading numbers them alike;
    else a written copy."""
    plan = docs._jdf.queryExecution().optimizedPlan()
    nodes, calm = [plan], True
    while nodes and calm:
        node = nodes.pop()
        calm = node.nodeName() in ("Project", "Filter", "LogicalRelation", "RelationV2", "LocalRelation", "LogicalRDD") and node.deterministic()
        nodes += [node.children().apply(i) for i in range(node.children().size())]
    return docs if calm and docs.inputFiles() else ws.keep(docs, "input")


def ship(spark: SparkSession) -> None:
    """Give the package to the Python workers, once for an application."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    top = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    folder = tempfile.mkdtemp(prefix="keyless-code-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    target = os.path.join(folder, "keyless_code.zip")
    with zipfile.ZipFile(target, "w") as z:
        for base, _, names in os.walk(os.path.join(top, "keyless")):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(base, n)
                    z.write(full, os.path.relpath(full, top))
    spark.sparkContext.addPyFile(target)
    _SHIPPED.add(app)


class Workspace:
    """A fresh folder below the shared one; ``keep`` writes a DataFrame there and reads it back, which cuts the lineage."""

    def __init__(self, spark: SparkSession, name: str):
        ship(spark)
        self.spark = spark
        self.path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"

    def keep(self, df: DataFrame, name: str, batch: int = ROWS, **options) -> DataFrame:
        target = f"{self.path}/{name}"
        began = time.monotonic()
        with small_batches(self.spark, batch):
            df.write.options(**({"compression": "zstd"} | options)).parquet(target)
        if time.monotonic() - began > COLLECT_AFTER:
            # shuffle files of a finished job go when the driver collects its garbage, which would else be much later
            self.spark.sparkContext._jvm.System.gc()
        return self.spark.read.schema(df.schema).parquet(target)

    def drop(self, name: str) -> None:
        """Remove what ``keep`` wrote under the name, once nothing will read it again."""
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df
