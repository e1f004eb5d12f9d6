"""What the operators of this subpackage have in common: shared folder, worker paths, text columns."""

from __future__ import annotations

import atexit
import ctypes
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

PACKAGE_ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def prepare(spark: SparkSession) -> None:
    """Let Python workers import this package also where only the driver's sys.path has it."""
    env = spark.sparkContext.environment
    known = env.get("PYTHONPATH", "")
    if PACKAGE_ROOT not in known.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (PACKAGE_ROOT, known) if x)


def unused(columns: list[str], *names: str) -> list[str]:
    """The names, each with underscores in front until no column is called so, in any case of letters."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out


def without(df: DataFrame, *names: str) -> DataFrame:
    """df without the columns that results of these names replace."""
    low = {n.lower() for n in names}
    return df.select(*[F.col(f"`{c}`") for c in df.columns if c.lower() not in low])


def shared_folder(spark: SparkSession, label: str) -> str:
    """A new folder's URI under spark.checkpoint.dir, which driver and executors share.

    Only a local session without that setting (tests) gets one, in the temp folder of its one machine.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "sheetgraph-checkpoints")
        if spark.sparkContext.getCheckpointDir() is None:
            spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/sheetgraph/{label}-{uuid.uuid4().hex[:12]}"


def file_system(uri: str):
    """pyarrow file system and path of a URI, for workers that write their own file formats."""
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), uri
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


class Scratch:
    """Intermediate tables written as parquet to the shared folder: they cut lineage and outlive executors.

    remove() deletes them all; what a driver process leaves is deleted when it ends.
    """

    def __init__(self, spark: SparkSession, label: str):
        self.spark, self.root, self.count = spark, shared_folder(spark, label), 0
        atexit.register(self._at_exit)

    def _delete(self, path: str) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)

    def _at_exit(self) -> None:
        if self.spark.sparkContext._jsc is not None:  # after stop() the folder is the cluster's to clear
            self.remove()

    def remove(self) -> None:
        atexit.unregister(self._at_exit)
        self._delete(self.root)

    def keep(self, df: DataFrame) -> DataFrame:
        self.count += 1
        path = f"{self.root}/t{self.count}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._sheetgraph_path = path
        return out

    def drop(self, *frames: DataFrame) -> None:
        """Delete tables whose readers have all run."""
        for df in frames:
            self._delete(df._sheetgraph_path)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def give_back() -> None:
    """Return freed memory to the system: workers stay between tasks, and an executor's limit counts them."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # a system without it
        pass


_held: dict[str, dict] = {}


def held(owner: str) -> dict:
    """What an operator's worker keeps between its tasks; it goes when a task of another operator makes room."""
    return _held.setdefault(owner, {})


def make_room(owner: str) -> None:
    """Drop what other operators have left in this worker, which an executor's limit still counts."""
    others = [x for name, x in _held.items() if name != owner and x]
    for x in others:
        x.clear()
    if others:
        give_back()


def map_arrow(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema: str) -> DataFrame:
    """mapInArrow with per-task state: make() is called once in each task, its result for each batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for batch in batches:
            if batch.num_rows:
                yield step(batch)
            del batch
            give_back()
        del step
        give_back()

    return df.mapInArrow(run, schema)


def texts_of(column: pa.Array) -> list[str]:
    """A batch's texts as str; null counts as the empty text."""
    return ["" if x is None else x for x in column.to_pylist()]


def hash_text(column: str | F.Column) -> F.Column:
    """128 bits that stand for a text in grouping; null and empty differ."""
    c = F.col(column) if isinstance(column, str) else column
    return F.when(c.isNull(), F.lit("null")).otherwise(F.md5(F.encode(c, "UTF-8")))


def runs_of(texts: list[str], most: int = 2_000_000) -> Iterator[list[str]]:
    """Consecutive parts of a batch's texts, of `most` characters or one text: their word lists fit in memory."""
    start = size = 0
    for k, t in enumerate(texts):
        if size and size + len(t) > most:
            yield texts[start:k]
            start, size = k, 0
        size += len(t)
    if start < len(texts):
        yield texts[start:]
