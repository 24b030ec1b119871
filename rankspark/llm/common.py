"""Helpers shared by the training-data operators: tables, shared storage, Arrow batches, labelled samples."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankspark import shipping

#: Rows of an Arrow batch that are held as Python objects at once.
SLICE_ROWS = 256
#: Bytes of an Arrow batch of texts, where the session still has Spark's default: a task holds each batch several times, in
#: the JVM's direct memory and in the worker. A longer text is a batch of its own.
BATCH_KEY, BATCH_DEFAULT, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", "67108864b", 2 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    shipping.ensure(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. A local folder of our own serves only a local master."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if folder:
        return folder
    if not spark.sparkContext.master.startswith("local") or "cluster" in spark.sparkContext.master:
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    folder = tempfile.mkdtemp(prefix="rankspark-")
    spark.sparkContext.setCheckpointDir(folder)
    return folder


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write df as a Parquet table in the shared folder and read it back: lineage ends here, and a lost
    executor costs no more than a re-read."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/rankspark/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: What a worker process keeps from one task to the next: of one owner at a time.
_HELD: dict[str, object] = {}


def held(owner: str, make: Callable):
    """What `make` returned in this worker for `owner`, made anew where another owner came between."""
    if owner not in _HELD:
        release()
        _HELD[owner] = make()
    return _HELD[owner]


def release() -> None:
    """Forget what the worker keeps and give its memory back; workers live on from one operator to the next."""
    if _HELD:
        _HELD.clear()
        gc.collect()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc only
        if trim is not None:
            trim(0)


def mapped(df: DataFrame, run: Callable, schema: str) -> DataFrame:
    """df.mapInArrow over batches of at most BATCH_BYTES, or of what the session was set to."""
    conf = df.sparkSession.conf
    if conf.get(BATCH_KEY, BATCH_DEFAULT) == BATCH_DEFAULT:
        conf.set(BATCH_KEY, BATCH_BYTES)
    return df.mapInArrow(run, schema)


def slices(batches: Iterator[pa.RecordBatch], rows: int = SLICE_ROWS, owner: str | None = None) -> Iterator[pa.RecordBatch]:
    """Batches of at most `rows` rows. What the worker keeps for another owner than this is released first."""
    if owner not in _HELD:
        release()
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def crc(column: str = "doc_id"):
    return F.crc32(F.col(column).cast("string").cast("binary"))


def bounded(texts: DataFrame, keys: list[str], rows: int) -> DataFrame:
    """At most `rows` rows of a written table of (keys..., text), by smallest hash of doc_id: equal rows count once, and the
    bound holds however many rows share a doc_id. Keys and text hashes are ranked, never texts."""
    hashed = texts.withColumn("th", F.xxhash64("text"))
    picked = hashed.select(*keys, "th").distinct().orderBy(F.xxhash64("doc_id"), *keys, "th").limit(rows)
    return hashed.join(F.broadcast(picked), [*keys, "th"], "left_semi").dropDuplicates([*keys, "th"]).select(*keys, "text")


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, rows: int, folds: int = 5) -> DataFrame:
    """At most `rows` labelled documents outside the held-out fold, by smallest hash of the id: (doc_id, text, y).

    Labels are bounded first, so broadcasting them is safe at any size; what they meet is bounded again, since one id may
    stand in many rows. The sample is a written table of its own: reading it again does not read the documents."""
    picked = (
        labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull())
        .select("doc_id", F.col(label).cast("int").alias("y"))
        .where(crc() % folds != 0)
        .distinct()
        .orderBy(F.xxhash64("doc_id"), "doc_id", "y")
        .limit(rows)
    )
    met = stored(docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(picked), "doc_id"), "labelled")
    return stored(bounded(met, ["doc_id", "y"], rows), "sample").select("doc_id", "text", "y")


def gathered(df: DataFrame, features: Callable, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Feature matrix, labels and ids of a bounded labelled sample, in the order of ids; only numbers reach the driver."""

    def run(batches):
        for b in slices(batches):
            x = np.array([features(t) for t in b.column(1).to_pylist()], dtype=np.float64).reshape(b.num_rows, width)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(list(x), pa.list_(pa.float64()))], ["doc_id", "y", "x"])

    rows = mapped(df.select("doc_id", "text", "y"), run, "doc_id long, y int, x array<double>").toArrow()
    ids, y = rows["doc_id"].to_numpy(), rows["y"].to_numpy()
    x = np.array(rows["x"].to_pylist(), dtype=np.float64).reshape(len(ids), width)
    order = np.lexsort((y, ids))
    return x[order], y[order].astype(np.float64), ids[order]


def scored(docs: DataFrame, features: Callable, width: int, predict: Callable, cut: float, folds: int = 5) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs: one pass, no shuffle."""

    def run(batches):
        for b in slices(batches):
            x = np.array([features(t) for t in b.column(1).to_pylist()], dtype=np.float64).reshape(b.num_rows, width)
            p = np.clip(predict(x), 0.0, 1.0)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(p), pa.array((p >= cut).astype(np.int32))], ["doc_id", "score", "predicted"])

    out = mapped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, score double, predicted int")
    return out.select("doc_id", F.coalesce(crc() % folds == 0, F.lit(False)).alias("held_out"), "score", "predicted")
