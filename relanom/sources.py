"""Reading and writing tables; every reader keeps the file's own types."""

from __future__ import annotations

import gc
import tempfile
import uuid

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    """Temporary views for SQL users."""
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def shared(spark: SparkSession) -> str:
    """The folder that all nodes share if the session names one, a local one on a single machine only."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all nodes share")
    return where.rstrip("/") if where else tempfile.mkdtemp(prefix="relanom-")


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written to the shared folder and read back: a short plan, columns that can be left out, no copy in memory."""
    path = f"{shared(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    let_go(df.sparkSession)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def let_go(spark: SparkSession) -> None:
    """Shuffle files and broadcasts that no plan needs any more go when the driver collects its garbage: here, not whenever its heap is full."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    trim(spark)


def trim(spark: SparkSession) -> str | None:
    """What the driver's JVM says of handing back native memory that it has freed; None where it can't (an older Java)."""
    context = spark.sparkContext
    jvm, java = context._jvm, context._gateway.jvm.java
    named = java.lang.Class.forName
    try:
        kinds, args = context._gateway.new_array(java.lang.Class, 4), context._gateway.new_array(java.lang.Object, 4)
        for i, kind in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[i] = named(kind)
        args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        # Through the interface: the server's own class is not open to reflection.
        return named("javax.management.MBeanServer").getMethod("invoke", kinds).invoke(java.lang.management.ManagementFactory.getPlatformMBeanServer(), args)
    except Py4JJavaError:
        return None


def drop_stored(*tables: DataFrame) -> None:
    """Delete tables made by ``stored`` that nothing reads any more."""
    for df in tables:
        spark = df.sparkSession
        for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


FORMATS = ("parquet", "orc", "json", "csv")


def read(spark: SparkSession, path: str, form: str = "parquet", schema: str | None = None) -> DataFrame:
    """A file or folder in one of ``FORMATS``; text formats need an explicit schema, so no file is read twice to guess it."""
    if form not in FORMATS:
        raise ValueError(f"no format {form}")
    if form in ("json", "csv") and schema is None:
        raise ValueError(f"{form} needs a schema")
    reader = spark.read.format(form)
    return (reader.schema(schema) if schema else reader).options(**({"header": True} if form == "csv" else {})).load(path)


def save(df: DataFrame, path: str, partitions: list[str] | None = None, form: str = "parquet") -> None:
    writer = df.write.mode("overwrite").format(form).options(**({"header": True} if form == "csv" else {}))
    (writer.partitionBy(*partitions) if partitions else writer).save(path)


def save_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table of the warehouse, bucketed and sorted by a key, so that joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(table)
