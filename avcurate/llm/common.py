"""Shared pieces of the training-data operators: staging in the shared folder and column hygiene."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Hashable, Iterator
from contextlib import contextmanager
from functools import reduce

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Only where it is unset and the master is a single JVM (tests) a local folder is made.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    spark.conf.set("spark.checkpoint.dir", made := "file://" + tempfile.mkdtemp(prefix="avcurate-"))
    return made


_STAGED: list[list[str]] = []


@contextmanager
def staging(spark: SparkSession) -> Iterator[None]:
    """Tables that are staged inside are removed at the end: results must be written or read by then."""
    _STAGED.append([])
    try:
        yield
    finally:
        jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
        for path in _STAGED.pop():
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(conf).delete(at, True)


def stage(df: DataFrame, tag: str, compression: str = "snappy") -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/staged/{tag}-{uuid.uuid4().hex}"
    for opened in _STAGED:
        opened.append(path)
    df.write.option("compression", compression).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def n_parts(df: DataFrame, at_least: int = 1) -> int:
    """Shuffle partitions of the session, as a count to deal rows to explicitly."""
    return max(at_least, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def spread(df: DataFrame) -> DataFrame:
    """Deal a scan of few, large splits evenly; rows stay in place when there are splits enough for the cores."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df if df.rdd.getNumPartitions() >= cores else df.repartition(cores)


def text_or_empty(col: str = "text"):
    return F.coalesce(F.col(col), F.lit(""))


def renamed(df: DataFrame, keep: tuple[str, ...] = ("doc_id", "text")) -> DataFrame:
    """The same columns under names c0, c1, ... but for ``keep``, so that no helper column can clash."""
    return df.toDF(*[c if c in keep and df.columns.index(c) == i else f"c{i}" for i, c in enumerate(df.columns)])


def parts_of(batch: pa.RecordBatch, column: str, most_rows: int = 4096, most_bytes: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """A batch in slices of bounded rows and bytes of ``column`` (strings or binary); a longer value is a slice of its own."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
    lo = held = 0
    for i, n in enumerate(sizes):
        if i > lo and (held + n > most_bytes or i - lo >= most_rows):
            yield batch.slice(lo, i - lo)
            lo, held = i, 0
        held += n
    if lo < len(sizes):
        yield batch.slice(lo)


def map_values(rows: DataFrame, column: str, make: Callable[[], Callable[[list], list[list]]], added: str, most_bytes: int = 8 << 20) -> DataFrame:
    """The rows without ``column`` and with the columns ``added`` (DDL), which a function of the list of its values gives.

    ``make`` runs once a task. All other columns pass through Arrow as they are, so that no id loses a digit.
    """
    new = to_arrow_schema(StructType.fromDDL(added))
    others = [c for c in rows.columns if c != column]
    schema = StructType([f for f in rows.schema if f.name != column] + StructType.fromDDL(added).fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = make()
        for b in batches:
            for part in parts_of(b, column, most_bytes=most_bytes):
                made = f(part.column(column).to_pylist())
                arrays = [part.column(c) for c in others] + [pa.array(list(v), t) for v, t in zip(made, new.types)]
                yield pa.RecordBatch.from_arrays(arrays, names=others + new.names)

    return rows.mapInArrow(run, schema)


_KEPT: list[tuple[Hashable, object]] = []


def kept(key: Hashable, make: Callable[[], object]):
    """What a worker process keeps from task to task (a tokenizer, a model with its cache): one thing at a time.

    Workers outlive stages; what an earlier stage kept is given back before the next is made.
    """
    if not _KEPT or _KEPT[0][0] != key:
        release()
        _KEPT.append((key, make()))
    return _KEPT[0][1]


def fresh(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The same function of batches, in a worker process that has given back what earlier stages kept."""

    def begin(batches: Iterator) -> Iterator:
        release()
        yield from run(batches)

    return begin


def release() -> None:
    """Give back what this worker process keeps, to the system too where its C library can."""
    _KEPT.clear()
    gc.collect()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # another C library
        pass
