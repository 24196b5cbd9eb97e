"""Shared helpers: free column names, the shared work folder, file access from executors, byte-level text kernels."""

from __future__ import annotations

import atexit
import ctypes
import tempfile
import threading
import uuid
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, the word separators of every operator here.
SPACE = b" \t\n\v\f\r"
#: UTF-8 continuation bytes: bytes without them count code points.
CONTINUATION = bytes(range(0x80, 0xC0))


def free_name(names, base: str) -> str:
    """A column name that no entry of `names` equals, without regard to case."""
    taken, name = {n.lower() for n in names}, base
    while name.lower() in taken:
        name += "_"
    return name


def rows_of(df: DataFrame, **picked: str | Column) -> DataFrame:
    """Only the named inputs, under internal names: extra columns of the caller never clash with ours."""
    return df.select(*[(F.col(f"`{c}`") if isinstance(c, str) else c).alias(name) for name, c in picked.items()])


def text_bytes(col: str) -> Column:
    """The UTF-8 bytes of a text; null counts as empty."""
    return F.coalesce(F.col(f"`{col}`"), F.lit("")).cast("binary")


def shared_root(spark: SparkSession) -> str:
    """The folder that the driver and all executors share (spark.checkpoint.dir); a temporary one in local mode only."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is unset: on a cluster it must name a folder that all executors share")
        root = _local_root()
    return root.rstrip("/")


_ROOTS: list[str] = []


def _local_root() -> str:
    if not _ROOTS:
        _ROOTS.append("file://" + tempfile.mkdtemp(prefix="sizeprofile-"))
    return _ROOTS[0]


def work_path(spark: SparkSession, label: str) -> str:
    """A new path below the shared folder; it is removed when the driver's Python ends."""
    path = f"{shared_root(spark)}/sizeprofile-{label}-{uuid.uuid4().hex}"
    atexit.register(remove_path, spark, path)
    for made in getattr(_SCOPES, "open", ()):
        made.append((label, path))
    return path


_SCOPES = threading.local()


@contextmanager
def scratch(spark: SparkSession, *kept: str):
    """Paths made inside are removed when the block ends, but for those with a label in `kept`, which a lazy result still reads."""
    made: list[tuple[str, str]] = []
    _SCOPES.open = [*getattr(_SCOPES, "open", ()), made]
    try:
        yield
    finally:
        _SCOPES.open = _SCOPES.open[:-1]
        for label, path in made:
            if label not in kept:
                remove_path(spark, path)


def remove_path(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # noqa: BLE001  at exit the gateway may be gone; the folder is temporary
        pass


def written(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage by a table in the shared folder, which survives lost executors."""
    path = work_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def file_store(uri: str):
    """(pyarrow filesystem, path) of a URI, on the driver or an executor."""
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), uri
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def put_file(folder: str, name: str, write) -> str:
    """Write folder/name under an attempt-unique name and rename it: a reader never sees half a file."""
    store, path = file_store(folder)
    store.create_dir(path, recursive=True)
    part = f"{path}/.{name}.{uuid.uuid4().hex}"
    with store.open_output_stream(part) as out:
        write(out)
    store.move(part, f"{path}/{name}")
    return f"{folder}/{name}"


def batches_of(schema: pa.Schema, rows, most: int = 4096, most_bytes: int = 16 << 20, weigh=None):
    """Turn an iterator of tuples into record batches of bounded size."""
    kept, held = [], 0
    for row in rows:
        kept.append(row)
        held += weigh(row) if weigh else 0
        if len(kept) >= most or held >= most_bytes:
            yield _batch(schema, kept)
            kept, held = [], 0
    if kept:
        yield _batch(schema, kept)


def _batch(schema: pa.Schema, rows: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(col, type=f.type) for col, f in zip(zip(*rows), schema)], schema=schema)


def mixed64(x: np.ndarray) -> np.ndarray:
    """Finalise 64-bit values so that every output bit depends on every input bit (xor-shift and multiply)."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def bitmap_of(wanted: DataFrame, column: str) -> np.ndarray:
    """A bitmap of a column of hashes, of at most 8 MB at any size of the data; false hits only cost work."""
    n = wanted.count()
    bits = 20
    while bits < 26 and (1 << bits) < 16 * n:
        bits += 1
    slots = wanted.select(F.pmod(column, F.lit(1 << bits)).alias("slot"))
    words = slots.groupBy(F.expr("slot div 64").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(slot % 64 as int))")).alias("bits")).toArrow()
    out = np.zeros(1 << (bits - 6), dtype=np.int64)
    out[words.column("word").to_numpy()] = words.column("bits").to_numpy()
    return out


def in_bitmap(bitmap: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Which of the 64-bit values may be in the bitmap."""
    slot = x.view(np.uint64) & np.uint64(len(bitmap) * 64 - 1)
    return (bitmap[(slot >> np.uint64(6)).astype(np.int64)].view(np.uint64) >> (slot & np.uint64(63))) & np.uint64(1) == 1


def texts_of(batch: pa.RecordBatch, col: str) -> list[bytes]:
    """The texts of a column as UTF-8 bytes; null is empty."""
    return [x or b"" for x in batch.column(batch.schema.get_field_index(col)).cast(pa.binary()).to_pylist()]


def mapped(df: DataFrame, added: dict[str, str], kernel, drop: tuple[str, ...] = ()) -> DataFrame:
    """Add columns (name: Spark type) that `kernel()` makes; it returns a function from a batch to their arrays.

    Input columns of the same names (in any case) are replaced. All other columns pass through untouched.
    """
    gone = {n.lower() for n in (*added, *drop)}
    keep = [c for c in df.columns if c.lower() not in gone]
    made = df.select(*[F.col(f"`{c}`") for c in keep], *[F.lit(None).cast(t).alias(n) for n, t in added.items()])
    names = [*keep, *added]

    def run(batches):
        release_held()
        one = kernel()
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([*[batch.column(batch.schema.get_field_index(c)) for c in keep], *one(batch)], names=names)

    return df.mapInArrow(run, made.schema)


def kept_in_process(key, make):
    """An object that a reused Python worker keeps from task to task (kernels themselves are unpickled for each task)."""
    import sys

    held = sys.__dict__.setdefault("_sizeprofile_held", {})
    if key not in held:
        held.clear()  # one at a time: memory stays bounded
        held[key] = make()
    return held[key]


def release_held() -> None:
    """Kernels that keep nothing call this first, so that a reused worker gives back what an earlier stage kept."""
    import sys

    sys.__dict__.get("_sizeprofile_held", {}).clear()
    give_back()


def give_back() -> None:
    """Return freed memory to the system: allocators keep it, and a worker that waits for its next task would still count."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not the GNU C library
        pass


def slices(batch: pa.RecordBatch, most_bytes: int = 4 << 20):
    """The rows of a batch, in order, in parts of about `most_bytes` (a larger row is a part of its own)."""
    at = 0
    while at < batch.num_rows:
        n = max(1, (batch.num_rows - at) * most_bytes // max(1, batch.slice(at).nbytes))
        while n > 1 and batch.slice(at, n).nbytes > 2 * most_bytes:
            n //= 2
        yield batch.slice(at, n)
        at += n


def lean(run):
    """A mapInArrow function that takes its batches in slices, keeps nothing of earlier tasks and gives back what it freed."""

    def sliced(batches):
        release_held()
        try:
            yield from run(part for b in batches for part in slices(b))
        finally:
            give_back()

    return sliced
