"""Helpers shared by the training-data operators: scratch folders, input shaping, range bounds."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from functools import wraps

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Stands for a null id wherever a key must be joined or ordered; it sorts before every other id.
NULL_KEY = -(2**63)


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder the session names in spark.checkpoint.dir.

    Where the setting is absent, a temporary folder is made and registered, but only if driver and executors
    are one process (tests, a laptop); on a cluster, which could not read it, that is an error.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="crowding-"))
        root = spark.sparkContext.getCheckpointDir()
    if "://" not in root and not root.startswith("file:"):
        root = f"file://{root}"
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back: computed once, and any executor may be lost."""
    path = scratch(df.sparkSession, name)
    with dropped_shuffles(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextmanager
def dropped_shuffles(spark: SparkSession):
    """Shuffle files of what runs inside go when it has ended, not when the driver next collects garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    if before is None or not spark.conf.isModifiable(key):
        yield
        return
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def keyed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(key, text): null ids become NULL_KEY, null texts empty; every other column is left behind."""
    return docs.select(
        F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_KEY)).alias("key"),
        F.coalesce(F.col(text_col), F.lit("")).alias("text"),
    )


def unkey(col: str = "key") -> "F.Column":
    """The id that keyed() replaced."""
    return F.when(F.col(col) != NULL_KEY, F.col(col))


def range_bounds(keys: DataFrame, col: str, parts: int) -> list[int]:
    """At most parts - 1 cut points of a numeric column, for a deterministic range bucket of any row; 8 bytes a part."""
    if parts <= 1:
        return []
    got = keys.agg(F.percentile_approx(col, [i / parts for i in range(1, parts)], min(20 * parts, 1_000_000)).alias("b")).first()["b"]
    return sorted(set(got or []))


def bucket_of(col: str, bounds: list[int]) -> "F.Column":
    """Number of bounds that are not above the value: the range bucket."""
    if not bounds:
        return F.lit(0)
    lits = F.array(*[F.lit(b) for b in bounds])
    return F.size(F.filter(lits, lambda b: b <= F.col(col)))


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def utf8(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """A string column as bytes, nulls as empty."""
    return [b or b"" for b in batch.column(name).cast(pa.binary()).to_pylist()]


def slices(batches: Iterator[pa.RecordBatch], rows: int = 512, chars: int = 32 << 20) -> Iterator[pa.RecordBatch]:
    """Smaller batches, so that what is held at a time stays bounded also with long texts."""
    for b in batches:
        step = rows if b.nbytes <= chars else max(1, rows * chars // b.nbytes)
        for i in range(0, b.num_rows, step):
            yield b.slice(i, step)


def open_fs(uri: str):
    """pyarrow filesystem and path of a URI that all executors reach (file, hdfs, s3, gcs)."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:", "file://", 1))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def join_counted(rows: DataFrame, side: DataFrame, key: str, total: int, least: int = 200, groups: int = 20_000) -> DataFrame:
    """rows joined with side, which has one row a key and n, how many of the total rows have it. Sides of keys with many
    rows, `groups` of them at most, are broadcast, so that no task gets all rows of a key; n is left out."""
    many = F.col("n") >= max(least, -(-total // groups))
    large = side.filter(many).drop("n")
    rest = rows.join(F.broadcast(large.select(key)), key, "left_anti")
    return rows.join(F.broadcast(large), key).unionByName(rest.join(side.filter(~many).drop("n"), key))


def unused(df: DataFrame, name: str) -> str:
    """A column name that df does not have, whatever the case."""
    there = {c.lower() for c in df.columns}
    while name.lower() in there:
        name += "_"
    return name


class Bounded:
    """A cache of a worker, bounded by the bytes its entries take as told by those who fill it.

    Entries are in a young half and an old one. When the young half is full it becomes the old one, and what was old
    is dropped, but for what has been found again meanwhile.
    """

    def __init__(self, limit: int):
        self.limit, self.held = limit // 2, 0
        self.young: dict = {}
        self.old: dict = {}

    def find(self, key):
        """The entry, or None. One found in the old half is young again."""
        got = self.young.get(key)
        if got is None and (got := self.old.get(key)) is not None:
            self.young[key] = got
        return got

    def keep(self, key, value, size: int) -> None:
        self.held += size
        if self.held > self.limit:
            # the old dictionary is emptied for reuse, so that whoever holds the young one's get still asks the young one
            self.old = dict(self.young)
            self.young.clear()
            self.held = size
        self.young[key] = value

    def forget(self) -> None:
        self.young.clear()
        self.old = {}
        self.held = 0


_holder: list = [None, None]


def claim(name: str, clear) -> None:
    """Called where an operator begins in a worker: the caches that another one left there are emptied first."""
    if _holder[0] != name:
        if _holder[1] is not None:
            _holder[1]()
            _give_back()
        _holder[:] = [name, clear]


def _give_back() -> None:
    gc.collect()
    release()


def release() -> None:
    """Hand memory that is free again back to the system, as a worker waits for its next task with what it has."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: it keeps what it has
        pass


def released(run):
    """run over batches, with memory handed back when its task ends."""

    @wraps(run)
    def task(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return task
