"""Scans with explicit schemas, sinks, and the shared folder that long plans are cut at."""

from __future__ import annotations

import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Columns of the text tables, as DDL.
SCHEMAS = {
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "labels": "doc_id BIGINT, quality INT, toxic INT",
    "pages": "page_id BIGINT, url STRING, html STRING",
    "benchmark": "item_id BIGINT, text STRING",
    "conversations": "conv_id BIGINT, turn BIGINT, role STRING, text STRING",
}


def scan(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table; only the named columns are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_corpus(spark: SparkSession, path: str, kind: str = "parquet", schema: StructType | str | None = None, **options) -> DataFrame:
    """Documents from Parquet, ORC, CSV, JSON lines or plain text. A line of text is a document; its id is a hash of the file, of the
    line and of the line's number among equal lines of the file, so it is the same however the files are split for reading."""
    if kind == "text":
        lines = spark.read.text(path, **options).select(F.input_file_name().alias("file"), F.col("value").alias("text"))
        same = Window.partitionBy("file", "text").orderBy(F.lit(0))
        return lines.withColumn("nth", F.row_number().over(same)).select(F.xxhash64("file", "text", "nth").alias("doc_id"), "text")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def require(df: DataFrame, schema: StructType | str) -> DataFrame:
    """df if it has the schema's columns with their types, else an error that names what is wrong."""
    wanted = StructType.fromDDL(schema) if isinstance(schema, str) else schema
    have = dict(df.dtypes)
    wrong = [f"{f.name}: {have.get(f.name, 'missing')} in place of {f.dataType.simpleString()}" for f in wanted if have.get(f.name) != f.dataType.simpleString()]
    if wrong:
        raise TypeError("; ".join(wrong))
    return df


def write_partitioned(df: DataFrame, path: str, *by: str, mode: str = "overwrite") -> None:
    """Parquet in folders by column; rows of one folder come from few tasks, so files stay large."""
    df.repartition(*by).write.mode(mode).partitionBy(*by).parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int = 32) -> None:
    """A table bucketed and sorted by key: later joins on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def write_view_json(view: DataFrame, path: str) -> None:
    """A topic view as JSON lines, a line a topic."""
    view.groupBy("k").agg(F.sort_array(F.collect_list(F.struct("kind", "rank", "text", "score"))).alias("items")).write.mode("overwrite").json(path)


def drain(df: DataFrame) -> None:
    """Run the plan and keep nothing, for timing."""
    df.write.format("noop").mode("overwrite").save()


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder; a local one only where none is set."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="phraseworks-"))
        folder = spark.sparkContext.getCheckpointDir()
    return folder.rstrip("/")


#: Seconds of a write after which the shuffle files of ended plans are let go: Spark deletes them once the driver's JVM has collected
#: their handles, which on its own may take until the heap is full.
SLOW = 2.0


def settle(df: DataFrame, label: str) -> DataFrame:
    """df written to the shared folder as Parquet and read back: the plan ends here, and lost executors lose nothing."""
    path = f"{shared_folder(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    begin = time.monotonic()
    df.write.parquet(path, compression="zstd")
    if time.monotonic() - begin > SLOW:
        df.sparkSession._jvm.System.gc()
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._settled_at = path
    return out


def discard(df: DataFrame) -> None:
    """Delete the table that ``settle`` wrote for df, once nothing reads it any more; other DataFrames stay as they are."""
    path, spark = getattr(df, "_settled_at", None), df.sparkSession
    if path:
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
