"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Fixed value: the white space characters of every contract, [\x20\x09-\x0D].
SPACES = " \t\n\x0b\x0c\r"
SPACE_CLASS = r"[\x20\x09-\x0D]"
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
ROWS = 1000
#: Of this process: the operator whose tasks it runs, and how each operator lets go of what it keeps between tasks.
_running: list[str] = []
_kept: dict[str, Callable[[], None]] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(c: Column) -> Column:
    """Lower-cases A-Z and nothing else (``lower`` would also fold other alphabets)."""
    return F.translate(c, _UPPER, _UPPER.lower())


def set_aside(docs: DataFrame, own: list[str]) -> DataFrame:
    """``docs`` whose columns named as one of ``own`` (in any case) are called ``input_`` and their name, in the same order.

    An operator that passes columns through calls it before it adds its own.
    """
    taken, clash = {c.lower() for c in [*docs.columns, *own]}, {c.lower() for c in own}
    names = []
    for name in docs.columns:
        if name.lower() in clash:
            while name.lower() in taken:
                name = f"input_{name}"
            taken.add(name.lower())
        names.append(name)
    return docs if names == docs.columns else docs.toDF(*names)


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Evaluates ``value`` once and hands it to ``body``.

    Catalyst may inline a projected column into a lambda, which then computes it
    once per element; a lambda variable is bound once per row.
    """
    return F.transform(F.array(value), body)[0]


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share; where none is named a local session makes one and a cluster is asked for it."""
    known = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if known:
        return known
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    made = tempfile.mkdtemp(prefix="fragmap-checkpoint-")
    spark.sparkContext.setCheckpointDir(made)
    return made


def checkpoint(df: DataFrame) -> DataFrame:
    """Cuts the lineage through the shared folder; Spark removes the files once unreferenced."""
    spark = df.sparkSession
    where = shared_dir(spark)
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(where)
    return df.checkpoint()


def work_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"


def remove_path(spark: SparkSession, path: str) -> None:
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jvm_path, True)


def stored(df: DataFrame, label: str) -> DataFrame:
    """Writes ``df`` as Parquet in the shared folder and reads it back."""
    path = work_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Deletes what ``stored`` wrote for ``df``; nothing may read it any more."""
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        remove_path(df.sparkSession, folder)


def keep(operator: str, let_go: Callable[[], None]) -> None:
    """Says how to let go of what ``operator`` keeps in this process from task to task."""
    _kept[operator] = let_go


def begin(operator: str) -> None:
    """The first step of a task. Spark uses a Python worker again for other operators: what
    those keep in it goes, and what they freed goes back to the system."""
    if _running != [operator]:
        _running[:] = [operator]
        for other in [o for o in _kept if o != operator]:
            _kept.pop(other)()
        release()


def sliced(operator: str, batches: Iterator[pa.RecordBatch], rows: int = ROWS) -> Iterator[pa.RecordBatch]:
    """``begin``, and the batches in parts of at most ``rows`` rows, so that what is made of them at once is small."""
    begin(operator)
    for batch in batches:
        for first in range(0, max(batch.num_rows, 1), rows):
            yield batch.slice(first, rows)


def release() -> None:
    """Gives memory that this Python process no longer uses back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
    if trim:
        trim(0)
