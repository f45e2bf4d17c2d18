"""Getting the package's Python code to executors."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application.

    Functions given to Arrow operators are pickled by reference, so workers
    must be able to import the package; the driver's file server delivers it.
    """
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = os.path.dirname(os.path.abspath(__file__))
    folder = tempfile.mkdtemp(prefix="arcfield-code-")
    path = os.path.join(folder, "arcfield_code.zip")
    with zipfile.ZipFile(path, "w") as z:
        for base, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(base, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(root)))
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path for ``name`` in the folder that driver and executors share.

    The folder is ``spark.checkpoint.dir``.  Where that is unset, a local
    session (tests) gets a temporary one and a cluster an error: executors would
    not see the driver's.  Paths go when the application ends.
    """
    import uuid

    conf = spark.sparkContext.getConf()
    root = conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if root is None:
        held = spark.sparkContext.getCheckpointDir()
        if held is None:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
            spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="arcfield-checkpoint-"))
            held = spark.sparkContext.getCheckpointDir()
        root = held
    path = f"{root.rstrip('/')}/arcfield/{name}-{uuid.uuid4().hex[:12]}"
    jvm = spark.sparkContext._jvm
    hadoop = jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def save(df, name: str, *, sort: tuple[str, ...] = ()):
    """Write ``df`` as Parquet in the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch(spark, name)
    if sort:
        df = df.sortWithinPartitions(*sort)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_path(spark: SparkSession, path: str) -> None:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def plan_bytes(df, text: str) -> int:
    """Bytes of input behind a plan.

    For filters and projections over files this is Catalyst's estimate, the
    bytes on storage.  Estimates of other plans multiply through joins, or say
    nothing; there the bytes of column ``text`` are summed.
    """
    import re

    from pyspark.sql import functions as F

    plan = df._jdf.queryExecution().optimizedPlan()
    nodes = re.findall(r"^[\s:+\-]*(\w+)", plan.toString(), re.M)
    if set(nodes) <= {"Project", "Filter", "Relation", "RelationV2"}:
        return int(plan.stats().sizeInBytes())
    return int(df.agg(F.sum(F.octet_length(text))).first()[0] or 0)
