"""Concatenate-and-cut packing: two-pass prefix sums give every text its place in one endless id row.

Pass 1 encodes each partition's texts once, writes their ids to the shared folder and notes how many ids
came before in the partition. The partition totals (one row each) are summed on the driver into offsets.
Pass 2 cuts the row at fixed windows without any shuffle and gives a boundary record for every piece.
Only the last sequence can be short. Null texts are empty (the end id alone); an empty table gives no piece;
repeated rows are packed as often as they occur; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bpe
from .common import materialise, passes, texts_of


def encode_table(docs: DataFrame, tokenizer: str, end_id: int = 1, text: str = "text", key: str = "doc_id", place: Callable[[pa.Array, list[bytes]], np.ndarray] | None = None) -> DataFrame:
    """doc_id, part, before (ids before it in the partition), n (ids with the end id), ids (little-endian), size (bytes of an id), and place(keys, ids) if given."""

    def run(batches):
        from pyspark import TaskContext

        coder, part, before = bpe.encoder(tokenizer), TaskContext.get().partitionId(), 0
        end = np.asarray([end_id], coder.width).tobytes()
        size = coder.width.itemsize
        for batch in batches:
            data, starts, ends = texts_of(batch.column(1))
            for a, b in passes(starts, ends):
                low, high = int(starts[a]), int(ends[b - 1])
                ids, counts = coder.encode_bytes(data[low:high], starts[a:b] - low, ends[a:b] - low)
                raw, at = ids.tobytes(), np.concatenate([[0], np.cumsum(counts)]) * size
                n = counts + 1
                keys, blobs = batch.column(0).slice(a, b - a), [raw[at[i] : at[i + 1]] + end for i in range(b - a)]
                yield pa.RecordBatch.from_arrays(
                    [
                        keys,
                        pa.array(np.full(b - a, part, np.int32)),
                        pa.array(before + np.cumsum(n) - n),
                        pa.array(n),
                        pa.array(blobs, pa.binary()),
                        pa.array(np.full(b - a, size, np.int32)),
                        *([] if place is None else [pa.array(place(keys, blobs))]),
                    ],
                    names=["doc_id", "part", "before", "n", "ids", "size"] + ([] if place is None else ["place"]),
                )
                before += int(n.sum())

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, part int, before long, n long, ids binary, size int" + ("" if place is None else ", place int"))


def prefix_offsets(totals: list[tuple[int, int]]) -> dict[int, int]:
    """Exclusive prefix sums of (partition, total) in order of the partition."""
    out, run = {}, 0
    for part, total in sorted(totals):
        out[part] = run
        run += total
    return out


def pack(docs: DataFrame, tokenizer: str, length: int = 2048, end_id: int = 1, text: str = "text", with_ids: bool = False) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, first, last (and ids).

    `first` and `last` say whether the document begins or ends with this piece.
    """
    encoded = materialise(encode_table(docs, tokenizer, end_id, text), "packed-ids")
    base = prefix_offsets([(r[0], r[1]) for r in encoded.groupBy("part").agg(F.sum("n")).collect()])
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            keys, parts, before, n, blobs, sizes = (batch.column(i) for i in range(6))
            counts = n.to_numpy()
            at = before.to_numpy() + np.fromiter((base[p] for p in parts.to_pylist()), np.int64, len(parts))
            first = at // length
            pieces = (at + counts - 1) // length - first + 1
            row = np.repeat(np.arange(len(counts)), pieces)
            step = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
            sequence = first[row] + step
            begin = np.maximum(sequence * length, at[row])
            stop = np.minimum((sequence + 1) * length, (at + counts)[row])
            start, size = begin - at[row], stop - begin
            crcs, slices = [], []
            seen, wide = -1, b""
            for r, s, c in zip(row.tolist(), start.tolist(), size.tolist(), strict=True):
                if r != seen:
                    seen, wide = r, np.frombuffer(blobs[r].as_buffer(), f"<u{sizes[r].as_py()}").astype("<u4").tobytes()
                piece = wide[4 * s : 4 * (s + c)]
                crcs.append(zlib.crc32(piece))
                if with_ids:
                    slices.append(piece)
            arrays = [keys.take(pa.array(row)), pa.array(start), pa.array(size), pa.array(crcs, pa.int64()), pa.array(counts[row]), pa.array(sequence), pa.array(begin % length), pa.array(start == 0), pa.array(start + size == counts[row])]
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "first", "last"]
            if with_ids:
                arrays.append(pa.array(slices, pa.binary()))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    schema = f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, first boolean, last boolean"
    return encoded.select("doc_id", "part", "before", "n", "ids", "size").mapInArrow(run, schema + (", ids binary" if with_ids else ""))
