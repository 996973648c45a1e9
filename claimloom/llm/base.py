"""What the training-data operators share: tables, a shared working folder, written intermediate tables."""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
import pyarrow.compute  # noqa: F401  (pa.compute)
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ASCII_SPACE = b" \t\n\r\x0b\x0c"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. A folder of our own serves local sessions only."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    known = spark.sparkContext.getCheckpointDir()
    if known:
        return known.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    import tempfile

    own = f"file://{tempfile.mkdtemp(prefix='claimloom-')}"
    spark.sparkContext.setCheckpointDir(own)
    return own


def written(df: DataFrame, name: str) -> DataFrame:
    """df written as Parquet in the shared folder and read again: lineage ends here, and a lost executor costs nothing."""
    path = f"{shared_dir(df.sparkSession)}/claimloom/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._written_path = path  # for forget()
    return out


def forget(df: DataFrame) -> None:
    """Delete the files of a written() table that is no longer needed."""
    path = getattr(df, "_written_path", None)
    if path:
        spark = df.sparkSession
        jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
        jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


BROADCAST_ROWS = 1 << 18


def unsent(df: DataFrame, rows: int | None = None) -> DataFrame:
    """df for a side of a join that must not be broadcast: Spark's estimates are sizes on disk or in compressed shuffles, far
    below those in the driver's memory. With its counted rows, a small df is left to the planner."""
    return df if rows is not None and rows <= BROADCAST_ROWS else df.hint("merge")


def text_volume(docs: DataFrame, text: str = "text") -> tuple[int, int]:
    """Rows and UTF-8 bytes of a text column; sizes the partitions of the operators that follow."""
    row = docs.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.octet_length(text)), F.lit(0)).alias("b")).first()
    return int(row["n"]), int(row["b"])


def as_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """UTF-8 bytes of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


def safe_slices(text: bytes, limit: int = 1 << 20) -> Iterator[bytes]:
    """Pieces of at most about limit bytes, cut in front of ASCII white space only."""
    start = 0
    while len(text) - start > limit:
        cut = start + limit
        while cut < len(text) and text[cut] not in ASCII_SPACE:
            cut += 1
        yield text[start:cut]
        start = cut
    yield text[start:] if start else text


def small_batches(batches: Iterable[pa.RecordBatch], column: str, limit: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about limit bytes of one column (one row at least)."""
    for batch in batches:
        col = batch.column(batch.schema.get_field_index(column))
        size = col.nbytes
        if size <= limit or batch.num_rows <= 1:
            yield batch
            continue
        lengths = pa.compute.fill_null(pa.compute.binary_length(col), 0).to_pylist()
        start, held = 0, 0
        for i, n in enumerate(lengths):
            if held and held + n > limit:
                yield batch.slice(start, i - start)
                start, held = i, 0
            held += n
        yield batch.slice(start)


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished queries now rather than when the driver next collects garbage."""
    import gc

    gc.collect()
    spark._jvm.System.gc()
