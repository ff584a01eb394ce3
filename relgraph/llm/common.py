"""What the corpus operators share: Arrow text as bytes, written tables, link components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space of the contracts: 0x20 and 0x09 to 0x0D.
BLANKS = b" \t\n\x0b\x0c\r"
#: bytes.translate table that lower-cases A to Z and nothing else.
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))

#: Setting by which Spark deletes the shuffle files of a finished SQL execution.
CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


#: Rows of a batch that travels between Spark and Python, where a row may hold a long document.
BATCH_ROWS = 1000


def modest(spark: SparkSession) -> None:
    """Let Spark hand documents to Python a few at a time, as each batch is held several times over on its way."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the given folder, through Spark's own reader so that any store works."""
    modest(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; only a local session that names none gets one of its own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="corpus-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def staged(df: DataFrame, tag: str, codec: str | None = None) -> DataFrame:
    """Write a frame to the shared folder and read it back: lineage ends here and lost executors cost nothing.

    codec names the compression of the written table, where the session's own is not to be taken."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/staged-{tag}-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEAN, None)
    spark.conf.set(CLEAN, "true")  # the job's shuffle files go when it ends
    try:
        df.write.parquet(path, compression=codec)
    finally:
        spark.conf.unset(CLEAN) if before is None else spark.conf.set(CLEAN, before)
    found = spark.read.schema(df.schema).parquet(path)
    found._folder = path
    return found


def discard(*frames: DataFrame) -> None:
    """Remove the folders of written frames that nothing will read again."""
    for frame in frames:
        context = frame.sparkSession.sparkContext
        path = context._jvm.org.apache.hadoop.fs.Path(frame._folder)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def slices(batches: Iterator[pa.RecordBatch], text: str, limit: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Cut batches so that one piece holds about `limit` bytes of text; a longer document stands alone."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False)
        ends, start = np.cumsum(size.astype(np.int64)), 0
        while start < batch.num_rows:
            base = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, base + limit, side="right")))
            yield batch.slice(start, stop - start)
            start = stop


def as_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column (null: empty) and the n+1 borders of its rows within them."""
    column = pc.fill_null(column, "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    column = column.cast(pa.large_binary())
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    _, off, data = column.buffers()
    borders = np.frombuffer(off, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[borders[0] : borders[-1]], borders - borders[0]


def texts(column: pa.Array) -> list[bytes]:
    return [x or b"" for x in column.cast(pa.large_binary()).to_pylist()]


_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def joined_names(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Hash of two neighbouring strings from their hashes."""
    x = a * _A
    x += b
    x ^= x >> np.uint64(31)
    x *= _B
    x ^= x >> np.uint64(29)
    return x


def local_roots(n: int, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Smallest index that each of n nodes reaches over the links left-right."""
    root = np.arange(n)
    while len(left):
        a, b = root[left], root[right]
        low = np.minimum(a, b)
        np.minimum.at(root, a, low)
        np.minimum.at(root, b, low)
        while True:
            up = root[root]
            if (up == root).all():
                break
            root = up
        differ = root[left] != root[right]
        left, right = left[differ], right[differ]
    return root


def components(links: DataFrame, rounds: int = 40) -> DataFrame:
    """Smallest node that each linked node reaches: (node, component), for nodes on at least one link.

    links: (a, b) of long ids in either order; loops and repeats do no harm. Works by moving every
    node's links to its smallest neighbour, from larger neighbours and from smaller ones in turn,
    until the links form stars. Nothing but a count and a checksum comes to the driver, each round is
    written to the shared folder, and hubs are split by Spark's skew join as their least neighbour
    comes from a pre-aggregated minimum. No links: no rows.
    """
    spark = links.sparkSession
    edges = staged(
        links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links"
    )
    seen = None
    for _ in range(rounds):
        both = edges.select("u", "v").union(edges.select(F.col("v"), F.col("u")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        far = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        far = far.where("u <> v").distinct()
        low = far.groupBy("u").agg(F.min("v").alias("m"))
        near = far.join(low, "u").select("v", "m", "u")
        near = near.select(F.col("v").alias("u"), F.col("m").alias("v")).union(near.select("u", F.col("m").alias("v")))
        edges = staged(near.where("u <> v").distinct(), "links")
        mark = edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"links did not settle in {rounds} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(
        edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
