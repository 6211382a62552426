"""A keyed store of token ids: shards of raw id payload, each with a minimal perfect hash over its keys.

A shard is one row (and one row group) of the store's table: a run of documents in ascending key order, their ids one after the
other, and an index of constant-time access: a collision-free bit hash in levels (keys that collide at one
level go on to the next), whose rank, from counts stored for every 64 bits, numbers the slots 0..n-1; each slot stores a 32-bit
fingerprint of its key, the position and the number of ids. A directory gives each shard's first and last key and the number
of ids before it. All files are written by Spark's writer, so any store that Spark can write will do.

Documents are dealt out by ranges of the key; a key that fills several ranges is dealt over several tasks, and a shard may end inside a
key, so no task or shard grows with one key. Such a key has a slot in each of its shards, and lookup() gives one piece for each.
Null texts hold the end id alone. Records of one key are in a row, in any order. Null keys come first and have no slot. An empty table
gives an empty store. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import lexing
from .common import new_folder
from .packing import encode_table

#: Payload bytes after which a shard ends, at the end of a document.
SHARD_BYTES = 1 << 20
_SCHEMA = "part int, shard int, first_key long, last_key long, n_docs int, before long, n_ids long, width int, doc_ids binary, counts binary, payload binary, levels binary, bits binary, ranks binary, fingerprints binary, positions binary, lengths binary"


def _hash(keys: np.ndarray, seed: int) -> np.ndarray:
    return lexing.mix(keys.astype(np.int64).view(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15) % (1 << 64)))


def build_index(keys: np.ndarray, gamma: float = 1.5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Level sizes, bits (64 to a number) and the number of set bits before each of these, of a minimal perfect hash of distinct int64 keys."""
    levels, bits, left = [], [], keys
    while len(left):
        size = max(8, int(gamma * len(left)))
        slot = (_hash(left, len(levels) + 1) % np.uint64(size)).astype(np.int64)
        alone = np.bincount(slot, minlength=size) == 1
        levels.append(size)
        bits.append(alone)
        left = left[~alone[slot]]
    flat = np.concatenate(bits) if bits else np.zeros(0, bool)
    packed = np.packbits(np.append(flat, np.zeros(-len(flat) % 64, bool)), bitorder="little").view("<u8")
    counts = np.bitwise_count(packed).astype(np.int64)
    return np.asarray(levels, np.int64), packed, (np.cumsum(counts) - counts).astype(np.int32)


def find_slots(keys: np.ndarray, levels: np.ndarray, bits: np.ndarray, ranks: np.ndarray, probes: list[int] | None = None) -> np.ndarray:
    """Slot of each key; any number or -1 for keys that are not in the index (the fingerprint tells). Reads one number of bits and one rank for a key and level."""
    out, left, base = np.full(len(keys), -1, np.int64), np.arange(len(keys)), 0
    for level, size in enumerate(levels.tolist(), 1):
        if not len(left):
            break
        at = base + (_hash(keys[left], level) % np.uint64(size)).astype(np.int64)
        word, bit = bits[at >> 6], (at & 63).astype(np.uint64)
        if probes is not None:
            probes.append(len(left))
        hit = (word >> bit) & np.uint64(1) == 1
        before = word & ((np.uint64(1) << bit) - np.uint64(1))
        out[left[hit]] = (ranks[at >> 6] + np.bitwise_count(before))[hit]
        left, base = left[~hit], base + size
    return out


def _fingerprint(keys: np.ndarray) -> np.ndarray:
    return (_hash(keys, 0) >> np.uint64(32)).astype(np.uint32)


@dataclass
class TokenStore:
    spark: SparkSession
    path: str

    def shards(self) -> DataFrame:
        return self.spark.read.schema(_SCHEMA).parquet(self.path)

    def directory(self) -> DataFrame:
        """part, shard, first_key, last_key, n_docs, n_ids, before (in the part), without payload columns."""
        return self.shards().select("part", "shard", "first_key", "last_key", "n_docs", "n_ids", "before")

    def part_offsets(self) -> dict[int, int]:
        """Ids before each part, from one row for each part."""
        run, out = 0, {}
        for part, total in sorted((r[0], r[1]) for r in self.directory().groupBy("part").agg(F.sum("n_ids")).collect()):
            out[part], run = run, run + total
        return out

    def records(self, with_ids: bool = False) -> DataFrame:
        """Every document read back through its shard's index: doc_id, start, n_tokens, ids_crc32 (and ids)."""
        offsets = self.part_offsets()

        def run(batches):
            for batch in batches:
                for row in (batch.slice(i, 1).to_pylist()[0] for i in range(batch.num_rows)):
                    keys = np.frombuffer(row["doc_ids"], np.int64)
                    counts = np.frombuffer(row["counts"], np.int64)
                    wide = np.frombuffer(row["payload"], f"<u{row['width']}").astype("<u4")
                    base = offsets[row["part"]] + row["before"]
                    begin = _positions(row, keys, counts)
                    raw = wide.tobytes()
                    pieces = [raw[4 * a : 4 * (a + n)] for a, n in zip(begin.tolist(), counts.tolist(), strict=True)]
                    null = np.zeros(len(keys), bool) if row["first_key"] is not None else _nulls(row, len(keys))
                    arrays = [pa.array(keys, mask=null), pa.array(base + begin), pa.array(counts), pa.array([zlib.crc32(p) for p in pieces], pa.int64())]
                    names = ["doc_id", "start", "n_tokens", "ids_crc32"]
                    if with_ids:
                        arrays, names = [*arrays, pa.array(pieces, pa.binary())], [*names, "ids"]
                    yield pa.RecordBatch.from_arrays(arrays, names=names)

        return self.shards().mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long" + (", ids binary" if with_ids else ""))

    def lookup(self, keys: list[int]) -> DataFrame:
        """Pieces of the given keys (a query-sized list) in (part, shard) order: doc_id, part, shard, n_tokens, ids.

        The directory tells which shards can hold a key; only their row groups are read, and of each only the slots of its keys.
        """
        wanted = np.unique(np.asarray(keys, np.int64))
        asked = self.spark.createDataFrame([(int(k),) for k in wanted], "key long")
        near = self.directory().where("last_key is not null").join(F.broadcast(asked), F.expr("key >= coalesce(first_key, -9223372036854775807L - 1) and key <= last_key"))
        places = [(r[0], r[1]) for r in near.select("part", "shard").distinct().collect()]  # no more than keys and the shards of those that span several
        by_part: dict[int, list[int]] = {}
        for part, shard in places:
            by_part.setdefault(part, []).append(shard)
        some = F.lit(False)
        for part, shards in by_part.items():
            some = some | ((F.col("part") == part) & F.col("shard").isin(shards))

        def run(batches):
            for batch in batches:
                for row in (batch.slice(i, 1).to_pylist()[0] for i in range(batch.num_rows)):
                    first = row["first_key"] if row["first_key"] is not None else -(1 << 63)
                    near = wanted[np.searchsorted(wanted, first) : np.searchsorted(wanted, row["last_key"], "right")]
                    at, n = _access(row, near)
                    hit = at >= 0
                    size = row["width"]
                    blobs = [np.frombuffer(row["payload"][size * a : size * (a + k)], f"<u{size}").astype("<u4").tobytes() for a, k in zip(at[hit].tolist(), n[hit].tolist(), strict=True)]
                    place = [pa.array(np.full(len(blobs), row[c], np.int32)) for c in ("part", "shard")]
                    yield pa.RecordBatch.from_arrays([pa.array(near[hit]), *place, pa.array(n[hit]), pa.array(blobs, pa.binary())], names=["doc_id", "part", "shard", "n_tokens", "ids"])

        return self.shards().where(some).mapInArrow(run, "doc_id long, part int, shard int, n_tokens long, ids binary")


def _index(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return np.frombuffer(row["levels"], np.int64), np.frombuffer(row["bits"], "<u8"), np.frombuffer(row["ranks"], np.int32)


def _access(row: dict, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First id in the payload and number of ids of each key; -1 where the shard has no such key."""
    slots = find_slots(keys, *_index(row))
    prints = np.frombuffer(row["fingerprints"], np.uint32)
    good = slots >= 0
    good[good] = prints[slots[good]] == _fingerprint(keys[good])
    at, n = np.full(len(keys), -1, np.int64), np.zeros(len(keys), np.int64)
    at[good] = np.frombuffer(row["positions"], np.int64)[slots[good]]
    n[good] = np.frombuffer(row["lengths"], np.int64)[slots[good]]
    return at, n


def _nulls(row: dict, n: int) -> np.ndarray:
    """Null keys stand first; the index has the others."""
    distinct = len(np.frombuffer(row["fingerprints"], np.uint32))
    keys = np.frombuffer(row["doc_ids"], np.int64)
    if not distinct:
        return np.ones(n, bool)
    known = _access(row, keys)[0]
    first = int(known[known >= 0].min())
    return np.cumsum(np.frombuffer(row["counts"], np.int64)) <= first


def _positions(row: dict, keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """First id of every record: the index's position of its key, and the earlier records of the same key."""
    run = np.cumsum(counts) - counts
    if row["first_key"] is None:
        return run
    new = np.ones(len(keys), bool)
    new[1:] = keys[1:] != keys[:-1]
    at, _ = _access(row, keys[new])
    head = np.flatnonzero(new)
    return at[np.cumsum(new) - 1] + run - run[head][np.cumsum(new) - 1]


def _shard(part: int, number: int, before: int, keys: list, blobs: list[bytes], width: int) -> dict:
    counts = np.asarray([len(b) // width for b in blobs], np.int64)
    some = np.asarray([k is not None for k in keys], bool)
    ids = np.asarray([0 if k is None else k for k in keys], np.int64)
    at = np.cumsum(counts) - counts
    distinct, first = np.unique(ids[some], return_index=True)
    levels, bits, ranks = build_index(distinct)
    slots = find_slots(distinct, levels, bits, ranks)
    prints, positions, lengths = np.zeros(len(distinct), np.uint32), np.zeros(len(distinct), np.int64), np.zeros(len(distinct), np.int64)
    prints[slots] = _fingerprint(distinct)
    positions[slots] = at[some][first]
    lengths[slots] = np.add.reduceat(counts[some], first) if len(first) else 0
    return {
        "part": part, "shard": number, "first_key": keys[0], "last_key": keys[-1], "n_docs": len(keys), "before": before, "n_ids": int(counts.sum()), "width": width,
        "doc_ids": ids.tobytes(), "counts": counts.tobytes(), "payload": b"".join(blobs), "levels": levels.tobytes(), "bits": bits.tobytes(), "ranks": ranks.tobytes(),
        "fingerprints": prints.tobytes(), "positions": positions.tobytes(), "lengths": lengths.tobytes(),
    }


@dataclass
class Deal:
    """Places of keys in ascending order: nulls first, then ranges between edges; a key that several edges share has places of its own."""

    edges: np.ndarray  # distinct
    times: np.ndarray  # places of the edge's own key, 0 where the range after it holds it
    nulls: int

    @classmethod
    def of(cls, edges: list[int], nulls: int) -> Deal:
        distinct, times = np.unique(np.asarray(edges, np.int64), return_counts=True)
        return cls(distinct, np.where(times > 1, times, 0), nulls)

    @property
    def places(self) -> int:
        return self.nulls + 1 + len(self.edges) + int(self.times.sum())

    def __call__(self, keys: pa.Array, blobs: list[bytes]) -> np.ndarray:
        null = np.asarray(keys.is_null())
        values = keys.cast(pa.int64()).fill_null(0).to_numpy()
        before = np.searchsorted(self.edges, values, "right")
        own = np.concatenate([[0], np.cumsum(self.times)])
        place = self.nulls + before + own[before]
        edge = np.maximum(before - 1, 0)
        same = (before > 0) & (self.edges[edge] == values) & (self.times[edge] > 0) if len(self.edges) else np.zeros(len(values), bool)
        for i in np.flatnonzero(same | null).tolist():
            mark = zlib.crc32(blobs[i])
            place[i] = mark % self.nulls if null[i] else place[i] - self.times[edge[i]] + mark % self.times[edge[i]]
        return place.astype(np.int32)


def deal_of(docs: DataFrame, parts: int) -> Deal:
    """About `parts` places of equally many rows, from approximate percentiles of the key."""
    grid = [i / parts for i in range(1, parts)] or [0.5]
    edges, nulls, rows = docs.select(F.col("doc_id").cast("long").alias("doc_id")).agg(F.percentile_approx("doc_id", grid, 20_000), F.count_if(F.col("doc_id").isNull()), F.count("*")).first()
    return Deal.of(edges or [], -(-nulls * parts // rows) if nulls else 0)


def write_store(docs: DataFrame, tokenizer: str, end_id: int = 1, shard_bytes: int = SHARD_BYTES, parts: int | None = None, path: str | None = None) -> TokenStore:
    """Encode all texts, deal them out by ranges of the key and write the shards in ascending key order."""
    spark = docs.sparkSession
    path = path or new_folder(spark, "token-store")
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    deal = deal_of(docs, parts)
    coded = encode_table(docs, tokenizer, end_id, place=deal).select("place", F.col("doc_id").cast("long").alias("doc_id"), "ids", "size")
    sorted_ = coded.repartitionById(deal.places, F.col("place")).sortWithinPartitions("place", F.asc_nulls_first("doc_id"))

    def run(batches):
        state: dict = {"part": None}

        def close():
            made = _shard(state["part"], state["shard"], state["before"], state["keys"], state["blobs"], state["width"])
            state["shard"] += 1
            state["before"] += made["n_ids"]
            state["keys"], state["blobs"], state["bytes"] = [], [], 0
            return pa.RecordBatch.from_pylist([made], schema=out)

        kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
        out = pa.schema([(name, kinds[kind]) for name, kind in map(str.split, _SCHEMA.split(", "))])
        for batch in batches:
            for part, key, ids, size in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if state["part"] != part:
                    if state["part"] is not None and state["keys"]:
                        yield close()
                    state |= {"part": part, "shard": 0, "before": 0, "keys": [], "blobs": [], "bytes": 0, "width": size}
                elif state["bytes"] >= shard_bytes:
                    yield close()
                state["keys"].append(key)
                state["blobs"].append(ids)
                state["bytes"] += len(ids)
        if state["part"] is not None and state["keys"]:
            yield close()

    sorted_.mapInArrow(run, _SCHEMA).write.option("parquet.block.size", shard_bytes).parquet(path)
    return TokenStore(spark, path)
