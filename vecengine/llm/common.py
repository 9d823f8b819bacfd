"""Helpers shared by the text and vector operators of this package."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows and bytes of an Arrow batch: what a task holds on both sides of the pipe to Python.
BATCH_ROWS, BATCH_BYTES = 1_000, 8 << 20
_written: list[tuple[SparkSession, str, DataFrame]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from spark.checkpoint.dir.

    Only where the session names none, in local mode (tests), a folder of this
    machine is used; a cluster without a shared folder is refused.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    own = getattr(shared_dir, "own", None)
    if own is None:
        own = shared_dir.own = "file://" + tempfile.mkdtemp(prefix="vecengine-")
    return own


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back.

    This cuts the lineage: a lost executor costs the running stage only.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    _written.append((spark, path, back))
    return back


def discard(*tables: DataFrame) -> None:
    """Delete staged tables that only finished steps have read.

    A collection on the driver then lets Spark's cleaner remove the shuffle
    files of those steps as well.
    """
    gone = [w for w in _written if any(w[2] is t for t in tables)]
    _written[:] = [w for w in _written if not any(w is g for g in gone)]
    for spark, path, _ in gone:
        _delete(spark, path)
    if gone:
        gone[0][0]._jvm.System.gc()


def _delete(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def release(keep: int = 0) -> None:
    """Delete the staged tables, but for the last ``keep``."""
    drop = _written[: len(_written) - keep]
    del _written[: len(drop)]
    for spark, path, _ in drop:
        try:
            _delete(spark, path)
        except Exception:  # the session may be gone: its folder goes with it
            return


atexit.register(release)


def small_batches(spark: SparkSession) -> None:
    """Bound the session's Arrow batches; smaller bounds that are set stay."""
    for key, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        key = f"spark.sql.execution.arrow.{key}"
        now = spark.conf.get(key).rstrip("b")
        if not now.isdigit() or not 0 < int(now) <= most:
            spark.conf.set(key, str(most))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crc_mod(col: str, mod: int):
    """crc32 of the id written as text, modulo ``mod`` (null ids: null)."""
    return F.crc32(F.col(col).cast("string")) % F.lit(mod)


def components(edges: DataFrame) -> DataFrame:
    """Connected components of ``edges(a, b)``: one row (id, comp) per endpoint.

    comp is the smallest id reachable. Each round takes the smallest label
    among a vertex and its neighbours, then follows one pointer; rounds are
    written to the shared folder. Loops and repeated edges do no harm; an
    empty table gives an empty one.
    """
    both = staged(
        edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        .where("a <> b").distinct(),
        "cc-edges",
    )
    labels = staged(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.first("a")).alias("comp")), "cc-labels")
    old = [labels]
    while True:
        heard = both.join(labels, both.b == labels.id).groupBy(both.a.alias("id")).agg(F.min("comp").alias("near"))
        step = labels.join(heard, "id", "left").select("id", F.col("comp").alias("old"), F.least("comp", "near").alias("comp"))
        jump = labels.select(F.col("id").alias("at"), F.col("comp").alias("root"))
        new = staged(
            step.join(jump, step.comp == jump["at"], "left")
            .select("id", "old", F.least(F.col("comp"), F.col("root")).alias("comp")),
            "cc-labels",
        )
        discard(*old)
        labels, old = new.select("id", "comp"), [new]
        if new.where("comp <> old").limit(1).count() == 0:
            discard(both)
            return labels
