"""What several operators share: the folder that all executors see, written tables, word rules."""

from __future__ import annotations

import gc
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def scratch(spark: SparkSession) -> str:
    """The shared folder of ``spark.checkpoint.dir``; where that is unset, a temporary one, on a local master only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors see")
        folder = Path(tempfile.mkdtemp(prefix="rangecut-")).as_uri()
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder: its lineage ends there and lost executors take nothing along."""
    path = f"{scratch(df.sparkSession)}/rangecut/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    found = df.sparkSession.read.schema(df.schema).parquet(path)
    found._rangecut_path = path
    return found


def forget(df: DataFrame, steps: bool = True) -> None:
    """Deletes a table of ``written`` that nothing reads any more.

    Spark removes the shuffle files of finished steps once the driver's garbage
    collector finds their plans; an iteration over large shuffles would fill
    disks before that happens by itself, so with ``steps`` it is asked to look now.
    """
    path = getattr(df, "_rangecut_path", None)
    if path:
        jvm = df.sparkSession._jvm
        hadoop = jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(hadoop, True)
        if steps:
            gc.collect()
            jvm.System.gc()


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def held_out(doc_id: Column, folds: int, fold: int) -> Column:
    """True where crc32 of the id as text leaves ``fold``; a null id is held out."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds)) == fold, F.lit(True))


def labelled_rows(docs: DataFrame, labels: DataFrame, label: str, at_most: int, where: Column | None = None) -> DataFrame:
    """doc_id, label, text of at most ``at_most`` labelled documents, those whose id hashes lowest; the same ones at every run.

    Only the labels are sampled, before the join, so the sampled ids are a
    small table whatever the size of ``docs``. Of rows with one id the least
    text counts, of several labels the largest.
    """
    known = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull())
    if where is not None:
        known = known.where(where)
    ids = (
        known.groupBy("doc_id")
        .agg(F.max(F.col(label).cast("int")).alias("label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(at_most)
    )
    return (
        docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
        .join(F.broadcast(ids), "doc_id")
        .groupBy("doc_id", "label")
        .agg(F.min("text").alias("text"))
    )


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, at_most: int, where: Column | None = None) -> list[tuple[str, int]]:
    """(text, label) of ``labelled_rows``, in the order of their ids."""
    rows = labelled_rows(docs, labels, label, at_most, where).collect()
    return [(r.text, r.label) for r in sorted(rows, key=lambda r: r.doc_id)]
