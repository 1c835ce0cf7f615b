"""A keyed store on files: built once by hash of the key and sorted, read by several keys at a time."""

from __future__ import annotations

import atexit
import bisect
import contextlib
import hashlib
import tempfile
import threading
import uuid
from collections import OrderedDict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from adaptivejoin.functions.hashing import portable_hash


#: Row groups of the store of joins by key, and how many of them its side keeps: what lies there already is not read from disk for each
#: call. Callers keep nothing of it, every call comes to the store and takes its value anew.
CALL_BLOCK, CALL_BLOCKS = 1 << 16, 1 << 10


def build_store(df: DataFrame, key: str, homes: int, path: str, block_bytes: int = 1 << 20) -> DataFrame:
    """Write ``df`` dealt by home and sorted by key within; row-group statistics then find a key without reading the rest."""
    dealt = df.withColumn("home", F.pmod(portable_hash(F.col(key)), F.lit(homes)).cast("int")).repartition(homes, "home").sortWithinPartitions("home", key)
    dealt.write.option("parquet.block.size", block_bytes).partitionBy("home").parquet(path)
    return df.sparkSession.read.parquet(path)


def _home_files(path: str, home: int) -> list[tuple]:
    """(file system, path) of the files of one home of a built store."""
    from pyarrow import fs

    where, root = fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)
    return [(where, f.path) for f in where.get_file_info(fs.FileSelector(f"{root}/home={home}", allow_not_found=True)) if f.path.endswith(".parquet")]


class FileStore:
    """A client of a built store: finds keys by the statistics of row groups and reads these alone. ``blocks`` row groups are kept, the
    least recently used going first; 0 reads anew every time. A thread has files of its own."""

    def __init__(self, path: str, key: str, homes: int, columns: tuple[str, ...], blocks: int = 0):
        self.path, self.key, self.homes, self.columns, self.blocks = path, key, homes, list(columns), blocks
        self.own = threading.local()
        self.calls = 0

    def _home(self, key) -> int:
        return int(hashlib.md5(str(key).encode()).hexdigest()[:15], 16) % self.homes

    def _groups(self, home: int) -> list[tuple]:
        """(least key, greatest key, file, row group) of a home, in order."""
        known = self.own.__dict__.setdefault("known", {})
        if home not in known:
            import pyarrow.parquet as pq

            found = []
            for where, f in _home_files(self.path, home):
                file = pq.ParquetFile(where.open_input_file(f))
                at = file.schema_arrow.names.index(self.key)
                for g in range(file.metadata.num_row_groups):
                    s = file.metadata.row_group(g).column(at).statistics
                    found.append((s.min, s.max, file, g))
            known[home] = sorted(found, key=lambda x: (x[0], x[1]))
        return known[home]

    def _read(self, home: int, i: int) -> tuple[np.ndarray, list[pa.Array]]:
        """Keys and columns of a row group, as they were read: a call makes Python values of what it asks for."""
        kept: OrderedDict = self.own.__dict__.setdefault("kept", OrderedDict())
        if (home, i) in kept:
            kept.move_to_end((home, i))
            return kept[home, i]
        _, _, file, g = self._groups(home)[i]
        t = file.read_row_group(g, [self.key, *self.columns])
        got = t[self.key].to_numpy(), [t[c].combine_chunks() for c in self.columns]
        if self.blocks:
            kept[home, i] = got
            while len(kept) > self.blocks:
                kept.popitem(last=False)
        return got

    def get_many(self, keys: list) -> list:
        """The value of each key as a tuple, or None; keys of one row group read it once."""
        self.calls += 1
        out: list = [None] * len(keys)
        wanted: dict = {}
        for place, k in enumerate(keys):
            if k is not None:
                home = self._home(k)
                groups = self._groups(home)
                i = bisect.bisect_right(groups, k, key=lambda g: g[0]) - 1
                if i >= 0 and groups[i][1] >= k:
                    wanted.setdefault((home, i), []).append((place, k))
        for (home, i), asked in wanted.items():
            own, columns = self._read(home, i)
            for place, k in asked:
                at = bisect.bisect_left(own, k)
                if at < len(own) and own[at] == k:
                    out[place] = tuple(c[at].as_py() for c in columns)
        return out

    def call_many(self, requests: list, call) -> list:
        """Compute requests: ``call(key, params, value)`` where the value is, only results come back."""
        values = self.get_many([k for k, _ in requests])
        return [call(k, params, v) for (k, params), v in zip(requests, values, strict=True)]


_scratch: dict[str, str] = {}


def _forget(spark: SparkSession, folder: str) -> None:
    with contextlib.suppress(Exception):  # the session may have gone before
        where = spark._jvm.org.apache.hadoop.fs.Path(folder)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in a folder of this application, in the folder that all machines share; it is deleted when the application ends."""
    app = spark.sparkContext.applicationId
    if app not in _scratch:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder:
            if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            folder = f"file://{tempfile.mkdtemp(prefix='scratch-')}"
        _scratch[app] = f"{folder.rstrip('/')}/scratch-{app}"
        atexit.register(_forget, spark, _scratch[app])
    return f"{_scratch[app]}/{name}-{uuid.uuid4().hex}"


def spooled(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once and read back: several steps read it, and a lost executor costs none of its lineage."""
    path = shared_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class KeyedStoreSource(DataSource):
    """``spark.read.format("keyed_store")`` over a built store: one partition a home, the options name its path, its number of homes,
    and its columns of the key and of an integer value."""

    @classmethod
    def name(cls) -> str:
        return "keyed_store"

    def schema(self) -> str:
        return "key long, home int, value long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"], int(self.options.get("homes", 4)), self.options["key"], self.options["value"])


class _Reader(DataSourceReader):
    def __init__(self, path: str, homes: int, key: str, value: str):
        self.path, self.homes, self.key, self.value = path, homes, key, value

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.homes)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        import pyarrow.parquet as pq

        home = partition.value
        for where, path in _home_files(self.path, home):
            with where.open_input_file(path) as file:
                for batch in pq.ParquetFile(file).iter_batches(columns=[self.key, self.value]):
                    key, value = (batch.column(c).cast(pa.int64()) for c in (self.key, self.value))
                    yield pa.RecordBatch.from_arrays([key, pa.repeat(pa.scalar(home, pa.int32()), len(key)), value], names=["key", "home", "value"])


def client_join(spark: SparkSession, folder: str, mode) -> DataFrame:
    """(key, result) of the skewed accesses through a store client in the workers, which read the built store by key."""
    from adaptivejoin.plans import workloads as X
    from adaptivejoin.sources.prefetch import prefetch_map

    probe, homes, path = X.zipf_probe(spark, folder, 1.0), 8, shared_path(spark, "store")
    values = X.part_store(spark, folder).select("skey", "p_size", F.floor("p_retailprice").cast("long").alias("price"))
    build_store(values, "skey", homes, path, CALL_BLOCK)

    def apply(row: dict, value) -> dict | None:
        return {"key": row["key"], "result": (row["key"] * 31 + row["qty"] * 7 + value[0] * value[1]) % 1000003} if value else None

    return prefetch_map(probe.select("key", "qty"), "key", lambda: FileStore(path, "skey", homes, ("p_size", "price"), CALL_BLOCKS), apply, "key long, result long", mode)


def shipped_join(spark: SparkSession, folder: str, mode) -> DataFrame:
    """The same with compute requests: the call runs at the client's store and only results come back."""
    from adaptivejoin.plans import workloads as X
    from adaptivejoin.sources.prefetch import Ship, prefetch_map

    probe, homes, path = X.zipf_probe(spark, folder, 1.0), 8, shared_path(spark, "store")
    build_store(X.part_store(spark, folder).select("skey", "p_size", F.floor("p_retailprice").cast("long").alias("price")), "skey", homes, path, CALL_BLOCK)

    def call(key, qty, value):
        return (key * 31 + qty * 7 + value[0] * value[1]) % 1000003 if value else None

    def plan(rows: list[dict]) -> list:
        return [Ship(r["key"], r["qty"]) for r in rows]

    apply = lambda row, result: {"key": row["key"], "result": result} if result is not None else None
    return prefetch_map(probe.select("key", "qty"), "key", lambda: FileStore(path, "skey", homes, ("p_size", "price"), CALL_BLOCKS), apply, "key long, result long", mode, plan, call)
