"""Tables that cut lineage, kept in the folder the cluster shares.

The folder is the session's ``spark.checkpoint.dir``; only where that is unset (tests) a folder
of this process is made and registered as the checkpoint directory.
"""

from __future__ import annotations

import atexit
import contextlib
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own: dict[str, str] = {}


def shared_root(spark: SparkSession) -> str:
    """The shared folder of the session, as a URI or path."""
    sc = spark.sparkContext
    root = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    known = sc._jsc.sc().getCheckpointDir()
    if known.isDefined():
        return known.get().rstrip("/")
    if sc.applicationId not in _own:
        _own[sc.applicationId] = "file://" + tempfile.mkdtemp(prefix="evenbox-")
        sc.setCheckpointDir(_own[sc.applicationId])
    return _own[sc.applicationId]


def _delete(spark: SparkSession, path: str) -> None:
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


def _quiet_delete(spark: SparkSession, path: str) -> None:
    try:
        _delete(spark, path)
    except Exception:  # noqa: BLE001 - the session is gone at exit; the folder is scratch
        pass


#: bytes of a batch that goes to a Python worker at once, however long its rows are
BATCH_BYTES = 8 << 20


@contextlib.contextmanager
def small_batches(spark: SparkSession, most: int = BATCH_BYTES):
    """Plans made inside hand rows to Python workers in batches of bounded bytes."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key, None)
    spark.conf.set(key, str(most))
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


class Scratch:
    """A private folder below the shared one: ``write`` a frame and get it back without lineage."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.path = f"{shared_root(spark)}/evenbox-{label}-{uuid.uuid4().hex[:12]}"
        atexit.register(_quiet_delete, spark, self.path)

    def at(self, name: str) -> str:
        return f"{self.path}/{name}"

    def write(self, df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
        with small_batches(self.spark):
            df.write.mode("overwrite").option("compression", codec).parquet(self.at(name))
        return self.read(name, df.schema)

    def read(self, name: str, schema=None) -> DataFrame:
        reader = self.spark.read
        return (reader.schema(schema) if schema is not None else reader).parquet(self.at(name))

    def drop(self, *names: str) -> None:
        """Delete tables, and let Spark's cleaner find the shuffle files of plans that are gone."""
        for name in names:
            _delete(self.spark, self.at(name))
        gc.collect()
        self.spark._jvm.System.gc()


#: the column that names a row, where doc_ids are null or repeated
ROW = "_evenbox_row"


def numbered(df: DataFrame, scratch: Scratch) -> DataFrame:
    """``df`` with a number of its own for each row. Where doc_ids are all there and all different they are the numbers; else rows are
    numbered and written, so that a row keeps its number."""
    if dict(df.dtypes).get("doc_id") == "bigint":
        rows, ids = df.agg(F.count("*"), F.count_distinct("doc_id")).first()
        if rows == ids:
            return df.withColumn(ROW, F.col("doc_id"))
    return scratch.write(df.withColumn(ROW, F.monotonically_increasing_id()), "numbered")


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
