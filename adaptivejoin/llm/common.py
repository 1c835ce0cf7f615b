"""Pieces that several operators of this package share."""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Callable, Iterator
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a maximal run of code points other than the six ASCII white-space characters.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
SPACES = " \t\n\x0b\f\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    """Array of the words of a text; null gives an empty array."""
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), SPACES, " " * 6), " ", -1), "")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; a temporary one only where that is unset and all
    run in one process. A cluster without it is refused: its machines would not see each other's files."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.sparkContext.master
        if not (master == "local" or master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = f"file://{tempfile.mkdtemp(prefix='shared-')}"
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder.rstrip("/")


def release_memory() -> None:
    """Give back what a worker has freed: it serves other steps after this one, and allocators keep free memory by default."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only where the C library has it
        ctypes.CDLL("libc.so.6").malloc_trim(0)


_held: dict[str, Any] = {}


def held(name: str, make: Callable[[], Any]) -> Any:
    """A large object that a worker keeps between tasks, such as a model. It keeps one: what another step left goes first, since a
    worker serves many steps and their tables would add up."""
    if name not in _held:
        _held.clear()
        release_memory()
        _held[name] = make()
    return _held[name]


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int) -> Iterator[None]:
    """Fewer texts at a time on their way to the workers while the steps in here run; afterwards the session is as before."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def release_shuffles(spark: SparkSession) -> None:
    """Let go of the shuffle files of steps whose results are saved: Spark deletes them when the driver collects their handles."""
    import gc
    import time

    gc.collect()
    time.sleep(1)  # the events of the last step are still being told
    spark._jvm.System.gc()


class Workspace:
    """Intermediate tables of one run, written to the shared folder so that lost executors cost no recomputation."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        self.count = 0

    def save(self, df: DataFrame, label: str = "t") -> DataFrame:
        """Write ``df`` once and return a frame that reads it back, without its lineage."""
        path = f"{self.root}/{label}-{self.count}"
        self.count += 1
        df.write.parquet(path)
        saved = self.spark.read.schema(df.schema).parquet(path)
        saved._workspace_path = path
        return saved

    def drop(self, df: DataFrame | None) -> None:
        """Delete a table of this workspace that no later step reads."""
        path = getattr(df, "_workspace_path", None)
        if path:
            jvm = self.spark._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)


def row_keyed(docs: DataFrame, work: Workspace) -> DataFrame:
    """(row, row_key): the columns of ``docs`` in a struct, and a hash of the file and the place in it that a row was read from, the
    same whenever it is read. What is not read from files as it stands is saved first."""
    plan = docs._jdf.queryExecution().analyzed().toString()
    plain = all(line.lstrip("+- :").startswith(("Project", "Filter", "Relation")) for line in plan.splitlines())
    rows = docs if plain and " parquet" in plan else work.save(docs, "docs")
    place = F.xxhash64(rows.metadataColumn("_metadata").getField("file_path"), rows.metadataColumn("_metadata").getField("row_index"))
    return rows.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), place.alias("row_key"))


def columns_of_row(names: list[str]) -> list[Column]:
    """The columns that ``row_keyed`` has put into ``row``."""
    return [F.col("row").getField(c).alias(c) for c in names]
