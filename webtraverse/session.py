"""Sessions, and the package on the executors."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()


def local_session(cores: int = 8, partitions: int = 8, **conf: str) -> SparkSession:
    """A session for tests and benches; a cluster brings its own."""
    builder = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", partitions)
    for key, value in {"spark.ui.enabled": "false", "spark.sql.session.timeZone": "UTC", "spark.driver.memory": "8g", "spark.sql.adaptive.enabled": "true", **conf}.items():
        builder = builder.config(key, value)
    return builder.getOrCreate()


def ship_package(spark: SparkSession) -> None:
    """Send this package to Python workers, once for an application, so that no executor must have it installed."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    home = os.path.dirname(os.path.abspath(__file__))
    if not os.path.isdir(home):  # it runs from a zip that was shipped already
        _shipped.add(app)
        return
    path = os.path.join(tempfile.mkdtemp(prefix="webtraverse-"), "webtraverse_code.zip")
    with zipfile.ZipFile(path, "w") as z:
        for top, _, names in os.walk(home):
            for name in sorted(names):
                if name.endswith(".py"):
                    full = os.path.join(top, name)
                    z.write(full, os.path.join("webtraverse", os.path.relpath(full, home)))
    spark.sparkContext.addPyFile(path)
    _shipped.add(app)


_own_dir: str | None = None


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: ``spark.checkpoint.dir``; a folder of our own only where that is unset and one process does all the work."""
    global _own_dir
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share: a local one would lose what other executors wrote")
    if _own_dir is None:
        _own_dir = "file://" + tempfile.mkdtemp(prefix="webtraverse-")
    return _own_dir


def durable(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: cuts the lineage and outlives executors."""
    spark, schema = df.sparkSession, df.schema
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = spark.read.schema(schema).parquet(path)
    back._durable_path = path
    return back


def discard(df: DataFrame | None) -> None:
    """Delete a table written by ``durable`` which nothing reads any more."""
    path = getattr(df, "_durable_path", None)
    if path:
        jvm = df.sparkSession.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
