"""Shared plumbing: a shared work folder, tables that cut lineage, connected components."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: One word: a run of characters other than ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
NO_ID = -(2**63)


def shared_folder(spark: SparkSession) -> str:
    """A fresh folder under ``spark.checkpoint.dir``.  Where neither the session nor its
    context names one, a folder of this machine is set once if the session runs on this machine
    alone; on a cluster that is an error, since executors would not see each other's files."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        if known.isDefined():
            base = known.get()
        elif spark.sparkContext.master.startswith("local") and not spark.sparkContext.master.startswith("local-cluster"):
            base = "file://" + tempfile.mkdtemp(prefix="phasewarp-")
            spark.sparkContext.setCheckpointDir(base)
        else:
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return f"{base.rstrip('/')}/llm-{uuid.uuid4().hex}"


def stored(df: DataFrame, folder: str, name: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back: lineage ends there and
    survives lost executors."""
    path = f"{folder}/{name}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only; null counts as empty."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, UPPER.lower())


def release() -> None:
    """Hand freed memory back to the system at the end of a Python task: idle workers are kept for
    the next stage and would otherwise hold what this one needed."""
    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


def first_of_each(rows: DataFrame, keys: list[str], columns: list[str]) -> DataFrame:
    """One row of each key from ``rows(columns, keys, n)``, n the rows of the key: of repeated rows
    the one whose other columns sort first as JSON, by a minimum that combines before the shuffle,
    so no task holds the rows of a key."""
    others = F.to_json(F.struct(*[F.col(c) for c in columns if c != "text"], F.xxhash64("text").alias("_h")))
    many = rows.filter("n > 1").groupBy(*keys).agg(F.min_by(F.struct(*columns), others).alias("_r")).select("_r.*")
    return rows.filter("n = 1").select(*columns).unionByName(many)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def components(edges: DataFrame, folder: str, most_rounds: int = 60) -> DataFrame:
    """Connected components of ``edges(a, b)`` (any orderable type) by alternating star
    contractions, each round written to the shared folder; returns ``(node, root)`` with the
    smallest node of the component as root, for nodes that have an edge.

    A round maps every link onto the least neighbour of its ends, so hubs need only a minimum
    per node (combined before the shuffle) and a join that adaptive execution can split.
    """
    spark = edges.sparkSession
    now = stored(
        edges.filter(F.col("a") != F.col("b"))
        .select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo"))
        .distinct(),
        folder,
        "links-0",
    )
    print_of = None
    for k in range(1, most_rounds + 1):
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo") % 1000003)).first()
        if seen[0] == 0 or seen == print_of:
            break
        print_of = seen
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionAll(
            now.select(F.col("lo").alias("u"), F.col("hi").alias("v"))
        )
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        outer = both.filter("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        low = outer.groupBy("hi").agg(F.min("lo").alias("m"))
        inner = (
            outer.join(low, "hi")
            .select(F.when(F.col("lo") == F.col("m"), F.col("hi")).otherwise(F.col("lo")).alias("hi"), F.col("m").alias("lo"))
            .filter("hi != lo")
            .distinct()
        )
        fresh = stored(inner, folder, f"links-{k}")
        discard(spark, f"{folder}/links-{k - 1}")
        now = fresh
    else:
        raise RuntimeError(f"components: no fixpoint after {most_rounds} rounds")
    return now.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionAll(
        now.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct()
    )
