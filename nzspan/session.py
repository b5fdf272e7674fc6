"""Session helpers: shipping the package to executors, durable checkpoints, sessions for tests."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def local_session(cores: int | str = 8, partitions: int = 8, memory: str = "12g") -> SparkSession:
    """A local session with the settings that the tests and the bench use."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("nzspan")
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def ship(spark: SparkSession) -> None:
    """Send this package's source to the Python workers, once per application."""
    context = spark.sparkContext
    if context.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    folder = tempfile.mkdtemp(prefix="nzspan-")
    target = os.path.join(folder, "nzspan.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as out:
        for path in sorted(root.rglob("*.py")):
            out.write(path, Path("nzspan") / path.relative_to(root))
    context.addPyFile(target)
    _SHIPPED.add(context.applicationId)


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share, spark.checkpoint.dir. A local session may do without the setting; others must have it."""
    context = spark.sparkContext._jsc.sc()
    known = context.getCheckpointDir()
    if known.isDefined():
        return str(known.get())
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="nzspan-checkpoints-")
    spark.sparkContext.setCheckpointDir(folder)
    return str(context.getCheckpointDir().get())


def checkpointed(df: DataFrame) -> DataFrame:
    """df, written to the shared folder and cut from its lineage; it keeps its placement."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def release(df: DataFrame) -> None:
    """Delete the files of a checkpointed DataFrame that nothing reads any more."""
    spark = df.sparkSession
    for rdd in _checkpoints(df._jdf.queryExecution().logical()):
        where = spark._jvm.org.apache.hadoop.fs.Path(rdd)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def _checkpoints(plan) -> list[str]:
    """Folders that a plan's own leaf was checkpointed to."""
    if plan.getClass().getSimpleName() != "LogicalRDD":
        return []
    file = plan.rdd().getCheckpointFile()
    return [file.get()] if file.isDefined() else []


def written(df: DataFrame, name: str) -> DataFrame:
    """df, written as Parquet into the shared folder and read again; columns keep their statistics."""
    import uuid

    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._written_to = path
    return out


def settle(spark: SparkSession) -> None:
    """Let go of what nothing refers to any more: the driver's garbage, and with it shuffles on the executors' disks."""
    import gc

    gc.collect()  # the references that Python holds come first
    spark._jvm.System.gc()
    trim(spark)


def trim(spark: SparkSession) -> bool:
    """Return to the system what the driver's JVM has freed outside its heap; whether that JVM can."""
    from py4j.protocol import Py4JError

    jvm, gateway = spark._jvm, spark.sparkContext._gateway
    try:
        kinds, values = gateway.new_array(jvm.java.lang.Class, 4), gateway.new_array(jvm.java.lang.Object, 4)
        for k, name in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[k] = jvm.java.lang.Class.forName(name)
        values[0], values[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        # by the interface's method, since the server's own class is closed to reflection
        jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethod("invoke", kinds).invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), values)
    except Py4JError:  # before Java 17.0.9, or another system
        return False
    return True


def few_rows(df: DataFrame) -> DataFrame:
    """df, of as many rows as there are parts at most, held by the driver, so that its size is known to all plans that read it."""
    return df.sparkSession.createDataFrame(df.collect(), df.schema)


def discard(*tables: DataFrame) -> None:
    """Delete the files of tables from written(); only once nothing that is still to run reads them."""
    for df in tables:
        if path := getattr(df, "_written_to", None):
            where = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
            df._written_to = None
