"""What the corpus operators share: scratch tables, word and white-space rules."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space as the contracts define it.
SPACE = " \t\n\x0b\x0c\r"
#: A word is a run of anything else.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: The letters that ``lower_ascii`` folds.
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

FOLD_BYTES = bytes.maketrans(UPPER.encode(), LOWER.encode())


def lower_ascii(text: Column) -> Column:
    """A-Z folded to a-z; every other letter stays."""
    return F.translate(text, UPPER, LOWER)


def scratch_dir(spark: SparkSession) -> str:
    """The shared folder of the session; a temporary one where none is named, and only in local mode."""
    context = spark.sparkContext
    held = context._jsc.sc().getCheckpointDir()
    if held.isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and context.master.split("[")[0] != "local":
            raise RuntimeError("spark.checkpoint.dir names no shared folder")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="scratch-"))
        held = context._jsc.sc().getCheckpointDir()
    return held.get()


#: Rows and bytes of an Arrow batch: a task holds a few of them, in the JVM and in Python.
BATCH_ROWS, BATCH_BYTES = 1000, 8 << 20


def modest_batches(spark: SparkSession) -> None:
    """Long texts in batches of the default size would fill an executor; the session gets smaller ones."""
    for setting, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        name = f"spark.sql.execution.arrow.{setting}"
        digits = "".join(c for c in spark.conf.get(name) if c.isdigit())
        if not digits or not 0 < int(digits) <= most:
            spark.conf.set(name, str(most))


def keep(df: DataFrame) -> DataFrame:
    """Write ``df`` once as compressed Parquet in the shared folder and read it back.

    Cuts the lineage: a lost executor costs a reread, not a recomputation, and
    whatever a step decided stays decided.  Its shuffle files go when it is written.
    """
    spark = df.sparkSession
    modest_batches(spark)
    path = f"{scratch_dir(spark)}/kept-{uuid.uuid4().hex}"
    clean = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(clean, None)
    spark.conf.set(clean, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.unset(clean) if before is None else spark.conf.set(clean, before)
    kept = spark.read.schema(df.schema).parquet(path)
    kept._kept_at = path
    if _open:
        _open[-1].append(kept)
    return kept


#: Tables that were written within each of the temporaries() that are open, innermost last.
_open: list[list[DataFrame]] = []


@contextmanager
def temporaries() -> Iterator[list[DataFrame]]:
    """On leaving, what ``keep`` wrote inside goes, but for the tables in the list that is given.

    The result of an operator reads some of its tables after it returns: those
    belong in the list.
    """
    spared: list[DataFrame] = []
    _open.append([])
    try:
        yield spared
    finally:
        written = _open.pop()
        paths = {x._kept_at for x in spared}
        for kept in written:
            if kept._kept_at not in paths:
                discard(kept)
            elif _open:
                _open[-1].append(kept)


def discard(kept: DataFrame) -> None:
    """Delete what ``keep`` wrote; nothing may read it any more."""
    spark = kept.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(kept._kept_at)
    path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def pieces(batches: Iterator[pa.RecordBatch], rows: int = 256) -> Iterator[pa.RecordBatch]:
    """The batches in slices of few rows, so that a task holds few texts and results at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
        del batch
        give_back()


def give_back() -> None:
    """Return what a worker has freed to the system: workers live on, and each keeps its high-water mark otherwise."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words_of(text: str | None) -> list[bytes]:
    """The words of a text as UTF-8 (``bytes.split`` cuts at exactly that white space)."""
    return (text or "").encode("utf-8", "surrogatepass").split()


def folded_words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(FOLD_BYTES).split()
