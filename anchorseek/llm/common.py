"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space of the contracts (\x20 and \x09-\x0D).
WORD = r"[^\x20\x09-\x0D]+"
SPACE = r"[\x20\x09-\x0D]+"
#: Runs of letters, digits and everything beyond ASCII.
ALNUM_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

UPPER_ASCII = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER_ASCII = "abcdefghijklmnopqrstuvwxyz"

#: Byte tables for bytes.translate: A-Z lowered; and that with every separator of ALNUM_WORD as a space.
LOWER_BYTES = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
ALNUM_BYTES = bytes(
    b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256)
)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one of our own only where none is configured and all run on
    one machine."""
    set_dir = spark.conf.get("spark.checkpoint.dir", None)
    if set_dir:
        return set_dir
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and the executors share")
    own = tempfile.mkdtemp(prefix="anchorseek-")
    spark.sparkContext.setCheckpointDir(own)
    return own


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/anchorseek/{uuid.uuid4().hex}/{tag}"


def settled(df: DataFrame, tag: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write df once to the shared folder and read it back: cuts lineage, survives lost executors."""
    path = fresh_path(df.sparkSession, tag)
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._settled = path
    return out


def discard(*frames: DataFrame) -> None:
    """Remove settled tables that nothing will read again; other frames are left alone."""
    for df in frames:
        path = getattr(df, "_settled", None)
        if path:
            where = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path).getParent()
            where.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(where, True)


def lower_ascii(col):
    """Lower-case A-Z only."""
    return F.translate(col, UPPER_ASCII, LOWER_ASCII)


def bind(value, use):
    """use(value) with value computed once per row, though used several times inside higher-order functions."""
    return F.element_at(F.transform(F.array(value), use), 1)


def words_of(text, separators: str = SPACE):
    """Array of words between the given separators; null text has none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), separators), lambda w: w != F.lit(""))


def parts_of(batch, column: str, rows: int, size: int = 8 << 20):
    """Parts of a batch of at most `rows` rows and, where they have several, about `size` bytes of a string column."""
    import numpy as np
    import pyarrow.compute as pc

    held = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), np.int64))
    first = 0
    while first < batch.num_rows:
        base = held[first - 1] if first else 0
        last = min(first + rows, max(first + 1, int(np.searchsorted(held, base + size, side="right"))))
        yield batch.slice(first, last - first)
        first = last


#: What a Python worker keeps from task to task, by name.
KEPT: dict = {}


def kept(name: str, make):
    """The worker's own copy of something costly, made once."""
    if name not in KEPT:
        KEPT[name] = make()
    return KEPT[name]


def release(but: str = "") -> None:
    """Forget what other work has left in this worker."""
    for name in [n for n in KEPT if n != but]:
        del KEPT[name]


def lean(run, keeps: str = ""):
    """A function for mapInArrow that hands its task's memory back to the system when the task ends.

    Python workers stay between tasks; without this each keeps the most that any task of it has used. Only
    what is kept under the name `keeps` stays for the next task of the same kind.
    """

    def wrapped(batches):
        import ctypes
        import gc

        import pyarrow as pa

        release(keeps)
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # another C library
                pass

    return wrapped
