"""Store calls ahead of the rows that need them: a producer plans, a pool fetches in batches, the consumer keeps the order."""

from __future__ import annotations

import queue
import threading
from collections.abc import Callable, Iterator
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T


@dataclass(frozen=True)
class AccessMode:
    """``sync``: one blocking call after the other; ``async``: ``pool`` connections, ``batch`` keys a call, ``depth`` batches ahead."""

    kind: str = "async"
    batch: int = 256
    pool: int = 4
    depth: int = 8


class MemoryStore:
    """A store client over a dictionary; counts its calls."""

    def __init__(self, values: dict):
        self.values, self.calls = values, 0

    def get_many(self, keys: list) -> list:
        self.calls += 1
        return [self.values.get(k) for k in keys]


@dataclass(frozen=True)
class Ship:
    """A compute request: the call runs at the store, with these parameters."""

    key: object
    params: object


class ResultSlots:
    """The result of each place in order; places that ask for a value already on its way share its fetch. What every place before has
    consumed is forgotten, so that no more is held than is on its way."""

    def __init__(self, client, mode: AccessMode, pool: ThreadPoolExecutor, call: Callable | None = None):
        self.client, self.mode, self.pool, self.call = client, mode, pool, call
        self.flying: dict = {}
        self.lock = threading.Lock()

    def submit(self, requests: list) -> list[tuple | None]:
        """(future, index) of each request: a key to fetch, or a call to ship; None for a key that is null."""
        ships = [(i, r) for i, r in enumerate(requests) if isinstance(r, Ship)]
        with self.lock:
            known = {k: self.flying[k] for k in requests if not isinstance(k, Ship) and k in self.flying}
            new = [k for k in dict.fromkeys(k for k in requests if not isinstance(k, Ship)) if k not in known and k is not None]
            for part in self._parts(new):
                f: Future = self.pool.submit(self.client.get_many, part)
                for j, k in enumerate(part):
                    known[k] = self.flying[k] = (f, j)
        places = [None if isinstance(r, Ship) else known.get(r) for r in requests]
        for part in self._parts(ships):
            f = self.pool.submit(self.client.call_many, [(r.key, r.params) for _, r in part], self.call)
            for j, (i, _) in enumerate(part):
                places[i] = (f, j)
        return places

    def _parts(self, items: list) -> Iterator[list]:
        for i in range(0, len(items), self.mode.batch):
            yield items[i : i + self.mode.batch]

    def landed(self, requests: list, places: list) -> None:
        """Forget the fetches that these places have consumed."""
        with self.lock:
            for k, p in zip(requests, places, strict=True):
                if p is not None and not isinstance(k, Ship) and self.flying.get(k) is p:
                    del self.flying[k]


def prefetch_map(df: DataFrame, key: str, connect: Callable, apply: Callable, schema: str, mode: AccessMode = AccessMode(), plan: Callable | None = None, call: Callable | None = None) -> DataFrame:
    """``apply(row, result)`` of every row, in order: a row, several (a list), or None for a row that goes. Batches and streams alike.

    ``plan(rows)`` names the request of each row ahead of time, on a thread of its own: a key to fetch the stored value of, or ``Ship``
    to run ``call(key, params, value)`` at the store; by default the value of column ``key`` is fetched.
    """
    from pyspark.sql.pandas.types import to_arrow_schema

    fields = to_arrow_schema(T.StructType.fromDDL(schema))  # of a batch whose values are all null, nothing could be inferred

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        client = connect()
        ahead = plan or (lambda rows: [r[key] for r in rows])

        def out(rows):
            made = [x for r in rows if r is not None for x in (r if isinstance(r, list) else [r])]
            if made:
                yield pa.RecordBatch.from_pylist(made, schema=fields)

        def one(request):
            if isinstance(request, Ship):
                return client.call_many([(request.key, request.params)], call)[0]
            return client.get_many([request])[0] if request is not None else None

        if mode.kind == "sync":
            for batch in batches:
                rows = batch.to_pylist()
                yield from out([apply(r, one(x)) for r, x in zip(rows, ahead(rows), strict=True)])
            return
        planned: queue.Queue = queue.Queue(mode.depth)
        stop = threading.Event()

        def put(item) -> bool:
            """False once the consumer has gone: a producer never waits for it for good."""
            while not stop.is_set():
                try:
                    planned.put(item, timeout=0.2)
                    return True
                except queue.Full:
                    continue
            return False

        with ThreadPoolExecutor(mode.pool) as pool:
            slots = ResultSlots(client, mode, pool, call)

            def produce():
                try:
                    for batch in batches:
                        rows = batch.to_pylist()
                        requests = ahead(rows)
                        if not put((rows, requests, slots.submit(requests))):
                            return
                    put(None)
                except BaseException as e:  # noqa: BLE001  the consumer raises it
                    put(e)

            thread = threading.Thread(target=produce, daemon=True)
            thread.start()
            try:
                while (item := planned.get()) is not None:
                    if isinstance(item, BaseException):
                        raise item
                    rows, requests, places = item
                    yield from out([apply(r, p[0].result()[p[1]] if p else None) for r, p in zip(rows, places, strict=True)])
                    slots.landed(requests, places)
            finally:
                stop.set()
                thread.join()

    return df.mapInArrow(run, schema)
