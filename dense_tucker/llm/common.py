"""Shared plumbing: cluster-visible storage, Arrow batches and the held-out rule."""

from __future__ import annotations

import tempfile
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows a side may have to be broadcast; beyond it a shuffled join is used.
BROADCAST_ROWS = 2_000_000
#: Text bytes that one numpy pass works on (a longer single text makes a longer pass).
PASS_BYTES = 2 << 20
#: Longest text, in bytes, that a model is fitted on: with the number of texts it bounds what reaches the driver.
TRAIN_TEXT_BYTES = 32 << 10
_made: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """Folder that driver and executors share: the session's setting. Only a local session may go without; it gets one of its own."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root is None:
        root = spark.sparkContext.getCheckpointDir()
    if root is None:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = tempfile.mkdtemp(prefix="corpus-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write once to the shared folder and read back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    _made.append(path)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _delete(spark: SparkSession, folder: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def discard(df: DataFrame) -> None:
    """Delete the files of a table made by materialise() that nothing needs any more."""
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        for path in [p for p in _made if folder.endswith(p.split("://")[-1].lstrip("/"))]:
            _delete(df.sparkSession, path)
            _made.remove(path)


def marked() -> int:
    """How many tables materialise() has made and nothing has deleted: a mark for clear()."""
    return len(_made)


def clear(spark: SparkSession, since: int = 0, keep: DataFrame | None = None) -> None:
    """Delete the tables made since a mark, but for the one that `keep` reads. Answers that still read them must have been written before."""
    kept = {f.rsplit("/", 1)[0] for f in keep.inputFiles()} if keep is not None else set()
    for path in _made[since:]:
        if not any(k.endswith(path.split("://")[-1].lstrip("/")) for k in kept):
            _delete(spark, path)
            _made.remove(path)


def unused(df: DataFrame, name: str) -> str:
    """The name, or a longer one that no column of the table has."""
    taken = {c.lower() for c in df.columns}
    while name in taken:
        name = f"_{name}"
    return name


def slices(batch: pa.RecordBatch, column: int, limit: int = PASS_BYTES) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose texts hold about `limit` bytes together (a longer single text makes a longer part)."""
    lengths = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    ends = np.cumsum(lengths, dtype=np.int64)
    first = 0
    while first < batch.num_rows:
        last = max(first + 1, int(np.searchsorted(ends, (ends[first - 1] if first else 0) + limit, "right")))
        yield batch.slice(first, last - first)
        first = last


def training_texts(docs: DataFrame, labels: DataFrame, most: int, longest: int = TRAIN_TEXT_BYTES) -> pa.Table:
    """doc_id, label and text of at most `most` labelled documents, by ascending doc_id: those with the least hashed ids.

    `labels` has doc_id and label; an id with several labels has none. Of rows that share an id the least text counts. Texts of
    over `longest` bytes are left out, so most * longest bounds the bytes that come to the driver.
    """
    sure = labels.where("doc_id is not null and label is not null").groupBy("doc_id").agg(F.min("label").alias("label"), F.max("label").alias("__most")).where("label = __most")
    some = sure.select("doc_id", "label").orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).where(F.col("text").isNotNull() & (F.octet_length("text") <= longest)).join(F.broadcast(some), "doc_id")
    return rows.groupBy("doc_id").agg(F.first("label").alias("label"), F.min("text").alias("text")).orderBy("doc_id").toArrow()


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2


def held_out_py(doc_id: int | None) -> bool:
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 4 == 2


def broadcast_if_small(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint behind a count; larger sides join by shuffle."""
    return F.broadcast(df) if df.count() <= limit else df


def texts_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and each text's first and end byte; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(0, np.int64), np.zeros(0, np.int64)
    column = column.cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    raw = column.buffers()[2]
    whole = np.frombuffer(raw, np.uint8) if raw is not None else np.zeros(0, np.uint8)
    low, high = int(offsets[0]), int(offsets[-1])
    return whole[low:high], offsets[:-1] - low, offsets[1:] - low


def passes(starts: np.ndarray, ends: np.ndarray, limit: int = PASS_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose texts hold about `limit` bytes together."""
    first = 0
    while first < len(starts):
        last = int(np.searchsorted(ends, starts[first] + limit, "right"))
        last = max(last, first + 1)
        yield first, last
        first = last


def map_texts(
    df: DataFrame, schema: str, work: Callable[[np.ndarray, np.ndarray, np.ndarray], dict], keep: tuple[str, ...] = ("doc_id",), text: str = "text"
) -> DataFrame:
    """Per text: `work(bytes, starts, ends)` gives one array for each new column. Only `keep` and the text are read."""
    kept = df.select(*keep, F.col(text).alias("__text"))
    prefix = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields[:-1])

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            data, starts, ends = texts_of(batch.column(batch.num_columns - 1))
            for a, b in passes(starts, ends):
                low, high = int(starts[a]), int(ends[b - 1])
                made = work(data[low:high], starts[a:b] - low, ends[a:b] - low)
                columns = [batch.column(i).slice(a, b - a) for i in range(batch.num_columns - 1)]
                names = list(batch.schema.names[:-1]) + list(made)
                arrays = columns + [v if isinstance(v, pa.Array) else pa.array(v) for v in made.values()]
                yield pa.RecordBatch.from_arrays(arrays, names=names)

    return kept.mapInArrow(run, f"{prefix}, {schema}")
