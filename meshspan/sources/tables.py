"""Reading and writing tables, and saved iteration state."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_source(spark: SparkSession, fmt: str, path: str, schema: StructType | str | None = None, **options) -> DataFrame:
    """Any of Spark's file formats; text formats need a schema (nothing is inferred from data)."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def stream_table(spark: SparkSession, path: str, schema: StructType | str, glob: str = "*.parquet", files_per_batch: int = 64) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", glob).parquet(path)


def write_result(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", partition_by: str | None = "node") -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(partition_by) if partition_by and partition_by in df.columns else writer).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str = "node") -> None:
    """Table bucketed by a key, so that later joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def stored_by(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """Like :func:`stored`, as a table bucketed by a key: grouping by it or joining on it moves no row."""
    path = f"{scratch_dir(df.sparkSession)}/meshspan-{uuid.uuid4().hex}"
    name = f"meshspan_{uuid.uuid4().hex}"
    if not _STORED:
        atexit.register(_remove_stored)
    _STORED.append(path)
    df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).option("path", f"{path}/{name}").saveAsTable(name)
    out = df.sparkSession.table(name)
    out.stored_at = path
    return out


def scratch_dir(spark: SparkSession) -> str:
    """Shared folder for intermediate tables: spark.checkpoint.dir of the session, else the context's
    checkpoint directory, else (local master only) a temporary folder."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    known = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not root and known.isDefined():
        root = known.get()
    if not root:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = tempfile.mkdtemp(prefix="meshspan-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


_STORED: list[str] = []


@contextlib.contextmanager
def session_conf(spark: SparkSession, values: dict[str, str]):
    """Settings of the session for the jobs that are started inside; then they are as before."""
    before = {k: spark.conf.get(k, None) for k in values}
    for k, v in values.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def executors(spark: SparkSession) -> int:
    """How many executors there are just now; 1 for a local master."""
    return max(1, spark.sparkContext._jsc.sc().getExecutorMemoryStatus().size() - 1)


def stored(df: DataFrame, name: str = "state", **options) -> DataFrame:
    """Write into the scratch folder and read back: cuts lineage and survives lost executors, since the
    files lie in shared storage. The files are removed when the driver's Python ends. ``options``: of the writer."""
    path = f"{scratch_dir(df.sparkSession)}/meshspan-{uuid.uuid4().hex}"
    if not _STORED:
        atexit.register(_remove_stored)
    _STORED.append(path)
    df.write.options(**options).parquet(f"{path}/{name}")
    out = df.sparkSession.read.schema(df.schema).parquet(f"{path}/{name}")
    out.stored_at = path
    return out


def _remove(session: SparkSession, path: str) -> None:
    context = session.sparkContext
    with contextlib.suppress(Exception):
        where = context._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(context._jsc.hadoopConfiguration()).delete(where, True)


def released(df: DataFrame) -> None:
    """Delete the files of a table that :func:`stored` returned, once nothing reads it any more."""
    path = getattr(df, "stored_at", None)
    if path in _STORED:
        _STORED.remove(path)
        _remove(df.sparkSession, path)


def _remove_stored() -> None:
    """Best effort: a session that is gone leaves its folder to whoever owns it."""
    session = SparkSession.getActiveSession()
    for path in _STORED if session is not None else ():
        _remove(session, path)


def save_state(basis: DataFrame, t: int, path: str) -> None:
    basis.withColumn("t", F.lit(t)).write.mode("append").partitionBy("t").parquet(path)


def resume(spark: SparkSession, path: str) -> tuple[DataFrame, int]:
    """The basis of the last saved step, and that step."""
    states = spark.read.parquet(path)
    last = states.agg(F.max("t")).first()[0]
    return states.where(F.col("t") == last).drop("t"), int(last)
