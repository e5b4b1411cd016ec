"""Tables that cut lineage between levels, in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where that is unset, on one machine."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.gettempdir() + "/traincube-scratch"
    return folder


def stored(df: DataFrame) -> DataFrame:
    """Write ``df`` once as Parquet and return a reader of it; the files go when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/traincube-{uuid.uuid4().hex}"
    df.write.parquet(path)
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    return spark.read.schema(df.schema).parquet(path)


def bytes_of(table: DataFrame) -> int:
    """Bytes of the files that a table from stored() is read from."""
    spark = table.sparkSession
    conf, total = spark._jsc.hadoopConfiguration(), 0
    for name in table.inputFiles():
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        total += path.getFileSystem(conf).getFileStatus(path).getLen()
    return total
