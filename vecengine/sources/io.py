"""Tables in, tables and indexes out."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_written: list[tuple[SparkSession, str]] = []
READERS = ("parquet", "orc", "json", "csv")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a folder of this machine only in local mode, where it may be unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    own = getattr(shared_dir, "own", None)
    if own is None:
        own = shared_dir.own = "file://" + tempfile.mkdtemp(prefix="vecengine-")
    return own


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder. ``release`` deletes it, at the latest when Python ends."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def staged(df: DataFrame, name: str) -> DataFrame:
    """Written to the shared folder and read again: lineage ends here."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def staged_together(frames: list[DataFrame], name: str) -> list[DataFrame]:
    """All staged at the same time, for frames of few tasks each, which would leave cores idle one after the other."""
    with ThreadPoolExecutor(min(8, max(1, len(frames)))) as pool:
        return list(pool.map(lambda df: staged(df, name), frames))


def release() -> None:
    """Delete all staged tables, when no result that reads them is needed any more."""
    while _written:
        spark, path = _written.pop()
        try:
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
        except Exception:  # the session may be gone: its folder goes with it
            return


atexit.register(release)


def write_any(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite") -> None:
    if fmt not in READERS:
        raise ValueError(f"format must be one of {READERS}")
    writer = df.write.mode(mode)
    (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)


def read_any(spark: SparkSession, path: str, fmt: str = "parquet", schema=None) -> DataFrame:
    if fmt not in READERS:
        raise ValueError(f"format must be one of {READERS}")
    reader = spark.read.schema(schema) if schema is not None else spark.read
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def save_index(codes: DataFrame, path: str, cell: str = "cell", version: int = 0) -> None:
    """Codes by cell, one folder each, so that a search reads the probed cells only."""
    codes.withColumn("model_version", F.lit(version)).repartition(cell).write.mode("overwrite").partitionBy(cell).parquet(path)


def load_index(spark: SparkSession, path: str, version: int | None = None) -> DataFrame:
    """A stored index; codes of another model version than asked for are refused."""
    df = spark.read.parquet(path)
    if version is not None and df.where(F.col("model_version") != version).limit(1).count():
        raise ValueError("the index holds codes of another model version")
    return df


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """embeddings as (id, vec double, label)."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label")


def base(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors(spark, sf_dir).where("id % 10 <> 0").select("id", "vec")


def held_out(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors(spark, sf_dir).where("id % 10 = 0").select(F.col("id").alias("qid"), "vec")
