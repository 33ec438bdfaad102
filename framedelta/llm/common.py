"""What the training-data operators share: code shipping, shared folder, Arrow batches."""

from __future__ import annotations

import io
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PACKAGE = Path(__file__).resolve().parents[1]


_state: dict = {}
_owner: list = [None]


def worker_state(key, make: Callable):
    """make(), kept in this worker process until another operator's task begins: workers outlive stages, their tables must not add up."""
    if key not in _state:
        _state.clear()
        _state[key] = make()
    return _state[key]


def enter(owner: str) -> None:
    """A task of `owner` begins in this worker: what other operators left goes."""
    if _owner[0] != owner:
        _owner[0] = owner
        _state.clear()
        give_back()


def give_back() -> None:
    """Return freed memory of Arrow and of the C heap to the system; neither does so by itself between stages."""
    import ctypes

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application."""
    sc = spark.sparkContext
    if getattr(sc, "_framedelta_shipped", False):
        return
    buf = io.BytesIO()
    with zipfile.ZipFile(buf, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(PACKAGE.rglob("*.py")):
            z.write(p, str(p.relative_to(PACKAGE.parent)))
    folder = tempfile.mkdtemp(prefix="framedelta-code-")
    path = os.path.join(folder, f"framedelta_{uuid.uuid4().hex[:8]}.zip")
    Path(path).write_bytes(buf.getvalue())
    sc.addPyFile(path)
    sc._framedelta_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Where that is unset only a local master (tests) may go on, with a folder of its own."""
    known = spark.conf.get("spark.checkpoint.dir", None)
    if known:
        return known.rstrip("/")
    sc = spark.sparkContext
    if not (sc.master == "local" or sc.master.startswith("local[")):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if not getattr(sc, "_framedelta_shared", None):
        sc._framedelta_shared = "file://" + tempfile.mkdtemp(prefix="framedelta-shared-")
    return sc._framedelta_shared


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write df as Parquet in the shared folder and read it back."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def delete(spark: SparkSession, path: str) -> None:
    """Remove a file or folder of any file system Spark knows."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bucket_of(col: Column, n: int) -> Column:
    """crc32 of the value as text, modulo n: the fold of a row (null ids: fold of the empty text)."""
    return F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary")) % n


def texts(column: pa.ChunkedArray | pa.Array) -> list[str]:
    """The column's strings, null as the empty string."""
    return [x or "" for x in column.to_pylist()]


def raw_texts(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    """The column's UTF-8 bytes, null as the empty string."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def slices(batch: pa.RecordBatch, column: str = "text", most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows of about `most` bytes of text each, so that memory follows bytes and not rows."""
    import numpy as np

    col = batch.column(column)
    if not batch.num_rows:
        return
    sizes = np.asarray([0 if n is None else n for n in pa.compute.binary_length(col.cast(pa.binary())).to_pylist()])
    at, run = 0, 0
    for i, n in enumerate(sizes.tolist()):
        if run and run + n > most:
            yield batch.slice(at, i - at)
            at, run = i, 0
        run += n
    yield batch.slice(at)


def map_batches(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """mapInArrow over a task's batches. Each plan made here is an owner of worker tables; a task frees what an earlier owner left.

    Spark keeps a Python process for each such map of a stage's tasks and uses all of them in turn from then on, each with tables of its own: no stage should hold two.
    """
    ship(df.sparkSession)
    owner = uuid.uuid4().hex

    def run(batches):
        import pyarrow.compute  # noqa: F401

        enter(owner)
        yield from fn(batches)
        give_back()

    return df.mapInArrow(run, schema)


def map_text(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str) -> DataFrame:
    """map_batches over byte-bounded slices."""
    return map_batches(df, lambda batches: (fn(part) for b in batches for part in slices(b)), schema)
