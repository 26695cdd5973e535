"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import os
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: UTF-8 bytes of text that a worker holds as Python strings at a time.
SLICE_BYTES = 16 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a temporary one where it is unset (tests on one machine)."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = found.get() if found.isDefined() else None
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="gleanwork-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


#: Tables written inside the temporary() blocks that are open, innermost last.
_OPEN: list[list[DataFrame]] = []


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write df to a table in the shared folder and read it back: lineage is cut and lost executors cost nothing.

    Inside temporary() the table is deleted when the block ends, unless it is kept.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/gleanwork/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._gleanwork_path = path
    if _OPEN:
        _OPEN[-1].append(out)
    return out


@contextlib.contextmanager
def temporary() -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Delete the tables that materialise() writes inside the block; the block's value marks one that is to stay.

    A kept table belongs to the block around this one, if there is one.
    """
    kept: list[DataFrame] = []

    def keep(df: DataFrame) -> DataFrame:
        kept.append(df)
        return df

    _OPEN.append([])
    try:
        yield keep
    finally:
        written = _OPEN.pop()
        for df in written:
            if not any(df is k for k in kept):
                discard(df)
        if _OPEN:
            _OPEN[-1] += kept


def small(df: DataFrame, rows: int) -> bool:
    """Whether df, a written table, has at most so many rows."""
    return df.limit(rows + 1).count() <= rows


def discard(df: DataFrame) -> None:
    """Delete a table that materialise() wrote and that no later plan reads."""
    path = getattr(df, "_gleanwork_path", None)
    if path:
        jvm = df.sparkSession.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def slices(batch: pa.RecordBatch, text: str) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that the texts of each piece are at most SLICE_BYTES, or one row."""
    col = batch.column(batch.schema.get_field_index(text))
    if batch.num_rows == 0 or col.nbytes <= SLICE_BYTES:
        yield batch
        return
    sizes = pa.compute.binary_length(col).fill_null(0).to_numpy(zero_copy_only=False)
    start = held = 0
    for i, n in enumerate(sizes):
        if held and held + n > SLICE_BYTES:
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += int(n)
    yield batch.slice(start)


def map_text(df: DataFrame, keys: list[str], text: str, schema: T.StructType, work: Callable[[Iterable[tuple[list[list], list]]], Iterator[list[list]]]) -> DataFrame:
    """Run work over (key columns, texts) blocks in each partition; it yields lists of output columns in schema's order."""
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def blocks():
            for b in batches:
                for piece in slices(b, text):
                    yield [piece.column(i).to_pylist() for i in range(len(keys))], piece.column(len(keys)).to_pylist()

        for cols in work(blocks()):
            yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, f.type) for c, f in zip(cols, arrow)], schema=arrow)

    return df.select(*keys, df[text].cast("string").alias(text)).mapInArrow(run, schema)


def total_bytes(df: DataFrame, column: str) -> int:
    """One small job: the UTF-8 bytes of a column, to check a side before it is broadcast."""
    return df.selectExpr(f"coalesce(sum(octet_length({column})), 0) AS n").first()["n"]


def local_threads() -> None:
    os.environ.setdefault("OMP_NUM_THREADS", "1")
