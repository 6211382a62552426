"""SimHash near-duplicates by multi-index hashing.

A fingerprint's bit is 1 where over half of the XXH64 values of its word shingles have it. Fingerprints are
cut into three segments. Two fingerprints within 4 bits differ by at most one bit in one of the first two
segments, or agree in the third; so each enumerates the radius-1 balls of the first two segments (flipping
only bits that are 0: the partner of a single flip finds it from the other side) and the third segment
itself, fetches what the tables hold there, and complete distances are verified. Only a spanning forest of
each bucket's links is passed on, so a bucket's output is linear in its members and no link is lost. A hot bucket is
divided by the other bits: cut into five parts, of which two members within 4 bits agree in one; what stays hot is dealt to
several tasks by its probes. Components are found by alternating star contraction.

Null texts and texts without a word have fingerprint zero and are linked like any other. Repeated rows share
their component. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations


import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import MapType, VariantType

from .common import broadcast_if_small, discard, materialise, slices, unused

SHINGLE = 4
RADIUS = 4
#: First bit and width of each segment; the first two are probed with one flip, the third exactly.
SEGMENTS = ((0, 22), (22, 22), (44, 20))
#: Table rows of one bucket above which it is divided.
HOT_ROWS = 4_000
#: Parts of the bits beside a segment: one more than the radius.
PARTS = RADIUS + 1


def fingerprint(text: bytes, size: int = SHINGLE, buffer: int = 1 << 16) -> int:
    """64-bit SimHash of a text's word shingles (bit-wise majority of XXH64, seed 42)."""
    import xxhash

    digest = xxhash.xxh64_intdigest
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    n = max(1, len(words) - size + 1)
    if n == 1:
        return digest(joined, 42)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    begins = np.concatenate([[0], ends[:-1] + 1])[:n].tolist()
    stops = ends[size - 1 :].tolist()
    total = np.zeros(64, np.int64)
    for k in range(0, n, buffer):
        values = np.fromiter([digest(joined[a:b], 42) for a, b in zip(begins[k : k + buffer], stops[k : k + buffer], strict=True)], np.uint64)
        total += _bit_counts(values)
    bits = (2 * total > n).astype(np.uint8)
    return int(np.packbits(bits[::-1]).view(">u8")[0])


def _bit_counts(values: np.ndarray) -> np.ndarray:
    """How many values have each bit, lowest first."""
    bits = np.unpackbits(values.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    whole = len(bits) // 255 * 255
    out = bits[whole:].sum(axis=0, dtype=np.int64)
    if whole:  # sums of up to 255 bits fit a byte
        out += np.add.reduce(bits[:whole].reshape(-1, 255, 64), axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
    return out


def fingerprints(docs: DataFrame, text: str = "text", size: int = SHINGLE) -> DataFrame:
    """doc_id and fp (signed 64-bit) of every document."""

    def run(batches):
        for batch in (part for whole in batches for part in slices(whole, 1)):
            column = batch.column(1).cast(pa.large_binary())
            values = np.fromiter((fingerprint(t or b"", size) for t in column.to_pylist()), np.uint64, len(column))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values.view(np.int64))], names=["doc_id", "fp"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, fp long")


def _forest(table: np.ndarray, probes: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges of a spanning forest of the links between probes and table rows of one bucket."""
    nodes, where = np.unique(np.concatenate([table, probes]), return_inverse=True)
    t, p = where[: len(table)], where[len(table) :]
    label = np.arange(len(nodes))
    left, right = [], []
    for k in range(len(p)):
        near = np.bitwise_count(table ^ probes[k]) <= radius
        if not near.any():
            continue
        met = np.unique(label[t[near]])
        own = label[p[k]]
        join = met[met != own]
        if len(join):
            left += [nodes[own]] * len(join)
            right += nodes[join].tolist()  # a label is the number of its first member
            low = min(int(own), int(join[0]))
            label[np.isin(label, np.append(join, own))] = low
    return np.asarray(left, np.uint64), np.asarray(right, np.uint64)


def _keys(fp: str) -> tuple[list[str], list[str]]:
    """SQL structs (segment, key, probe) of a fingerprint column: its table places and its probes."""
    tables, probes = [], []
    for s, (first, width) in enumerate(SEGMENTS):
        part = f"(shiftrightunsigned({fp}, {first}) & {(1 << width) - 1}L)"
        tables.append(f"struct({s} as seg, {part} as key, false as probe)")
        probes.append(f"struct({s} as seg, {part} as key, true as probe)")
        if s < 2:
            probes += [f"if(({part} & {1 << b}L) = 0, struct({s} as seg, {part} | {1 << b}L as key, true as probe), null)" for b in range(width)]
    return tables, probes


def _parts(fp: str, seg: str) -> str:
    """SQL array of (sub, bits): the value of each part of the bits beside a segment."""
    cases = []
    for s, (first, width) in enumerate(SEGMENTS):
        turn = (first + width) % 64
        rest = f"(shiftrightunsigned({fp}, {turn}) | shiftleft({fp}, {64 - turn}))" if turn else fp
        cuts = [k * (64 - width) // PARTS for k in range(PARTS + 1)]
        each = [f"struct({k} as sub, shiftrightunsigned({rest}, {cuts[k]}) & {(1 << cuts[k + 1] - cuts[k]) - 1}L as bits)" for k in range(PARTS)]
        cases.append(f"when {seg} = {s} then array({', '.join(each)})")
    return f"case {' '.join(cases)} end"


def links(distinct: DataFrame, radius: int = RADIUS, hot_rows: int = HOT_ROWS) -> DataFrame:
    """Edges (a, b), a > b, of a graph with the components of all pairs of distinct `fp` within the radius (up to RADIUS)."""
    if radius > RADIUS:
        raise ValueError(f"radius over {RADIUS}")
    tables, probes = _keys("fp")

    def at(places: list[str]) -> DataFrame:
        return distinct.selectExpr("fp", f"explode(array({', '.join(places)})) as at").where("at is not null").select("fp", "at.*")

    def divided(rows: DataFrame) -> DataFrame:
        """Rows of hot buckets once for each part, others as they are (sub -1)."""
        return rows.join(hot, ["seg", "key"], "left").selectExpr("fp", "seg", "key", "probe", f"explode(case when hot then {_parts('fp', 'seg')} else array(struct(-1 as sub, 0L as bits)) end) as p").select("fp", "seg", "key", "probe", "p.*")

    hot = broadcast_if_small(materialise(at(tables).groupBy("seg", "key").agg(F.count("*").alias("n")).where(F.col("n") > hot_rows).select("seg", "key", F.lit(True).alias("hot")), "hot-buckets"))
    still = divided(at(tables).join(hot, ["seg", "key"], "left_semi")).groupBy("seg", "key", "sub", "bits").agg(F.count("*").alias("n")).where(F.col("n") > hot_rows)
    still = broadcast_if_small(materialise(still.select("seg", "key", "sub", "bits", F.ceil(F.col("n") / hot_rows).cast("int").alias("parts")), "hot-parts"))
    # one number for a bucket, or a part of one, and a deal of its probes
    number = "shiftleft(cast(seg * 8 + sub + 1 as bigint), 56) | shiftleft(cast(key as bigint), 32) | shiftleft(bits, 20)"
    deals = "explode(case when parts is null then array(0) when probe then array(cast(pmod(xxhash64(fp), parts) as int)) else sequence(0, parts - 1) end)"
    dealt = divided(at(tables + probes)).join(still, ["seg", "key", "sub", "bits"], "left").selectExpr(f"{number} as place", "fp", "probe", f"{deals} as deal").selectExpr("place | deal as place", "fp", "probe")
    spread = dealt.repartition("place").sortWithinPartitions("place", "probe")

    def run(batches):
        kept: dict = {"key": None}

        def close(found):
            if kept["key"] is not None and kept["probes"]:
                t, p = np.concatenate(kept["table"] or [np.zeros(0, np.uint64)]), np.concatenate(kept["probes"])
                if len(t) and (len(t) > 1 or len(p) > 1 or t[0] != p[0]):
                    a, b = _forest(t, p, radius)
                    found.append((np.maximum(a, b), np.minimum(a, b)))

        def emit(found):
            a, b = (np.concatenate(x).view(np.int64) for x in zip(*found, strict=True))
            keep = a != b
            return pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(b[keep])], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            place, fp, probe = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            fp = fp.astype(np.int64).view(np.uint64)
            probe = probe.astype(bool)
            new = np.ones(len(place), bool)
            new[1:] = place[1:] != place[:-1]
            heads = np.flatnonzero(new)
            tails = np.append(heads[1:], len(place))
            inside = np.add.reduceat(probe.astype(np.int64), heads)
            found: list = []
            for i, (h, e, q) in enumerate(zip(heads.tolist(), tails.tolist(), inside.tolist(), strict=True)):
                if 0 < i < len(heads) - 1:  # a whole bucket
                    n = e - h - q
                    if n and q and (n > 1 or q > 1 or fp[h] != fp[h + 1]):
                        a, b = _forest(fp[h : h + n], fp[h + n : e], radius)
                        found.append((np.maximum(a, b), np.minimum(a, b)))
                    continue
                if int(place[h]) != kept["key"]:
                    close(found)
                    kept.update(key=int(place[h]), table=[], probes=[])
                kept["table"].append(fp[h : e - q])
                kept["probes"].append(fp[e - q : e])
            if found:
                yield emit(found)
        found = []
        close(found)
        if found:
            yield emit(found)

    return spread.select("place", "fp", "probe").mapInArrow(run, "a long, b long").distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """node, root (smallest node of its component) for all nodes of edges (a, b), by alternating star contraction.

    Large stars hang a node's greater neighbours on its least one, small stars its lesser ones. Every step is
    written to the shared folder; so both sides of each join are plain tables, and Spark can split the rows of
    a star's centre among tasks. Ends when a round changes nothing, or raises after `rounds`.
    """
    now = materialise(edges.selectExpr("greatest(a, b) as a", "least(a, b) as b").where("a <> b").distinct(), "edges")
    before = None
    for _ in range(rounds):
        both = now.select("a", "b").union(now.selectExpr("b as a", "a as b"))
        least = materialise(both.groupBy("a").agg(F.min("b").alias("m")).selectExpr("a", "least(a, m) as m"), "stars")
        large = materialise(both.where("b > a").join(least, "a").selectExpr("b as a", "m as b"), "large-stars")
        low = materialise(large.groupBy("a").agg(F.min("b").alias("m")), "lows")
        small = large.join(low, "a").selectExpr("b as a", "m as b").where("a <> b").union(low.selectExpr("a", "m as b")).distinct()
        after = materialise(small, "edges")
        state = after.agg(F.count("*"), F.expr("sum(cast(xxhash64(a, b) as decimal(38, 0)))")).first()
        for table in (now, least, large, low):
            discard(table)
        now = after
        if tuple(state) == before:
            return now.selectExpr("a as node", "b as root")
        before = tuple(state)
    raise RuntimeError(f"components not settled after {rounds} rounds")


def classes(marks: DataFrame, radius: int = RADIUS, hot_rows: int = HOT_ROWS) -> DataFrame:
    """fp and root (the least fp of its component) of every distinct `fp`."""
    distinct = materialise(marks.select("fp").distinct(), "distinct-fingerprints")
    roots = components(links(distinct, radius, hot_rows))
    made = materialise(distinct.join(roots, distinct.fp == roots.node, "left").select("fp", F.coalesce("root", "fp").alias("root")), "classes")
    discard(distinct)
    discard(roots)
    return made


def cluster(docs: DataFrame, text: str = "text", size: int = SHINGLE, radius: int = RADIUS, hot_rows: int = HOT_ROWS) -> DataFrame:
    """doc_id, fingerprint (hexadecimal) and component_id (least doc_id within reach) of every document."""
    marks = materialise(fingerprints(docs, text, size), "fingerprints")
    by_fp = classes(marks, radius, hot_rows)
    first = marks.groupBy("fp").agg(F.min("doc_id").alias("first_id"))
    named = by_fp.join(first, "fp").groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = materialise(by_fp.join(named, "root").select("fp", "component_id"), "named")
    discard(by_fp)
    return marks.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each group of near copies: that with the least id (rows without one last), then the least hash of its text.

    Rows are told apart by id and text, so rows that share an id but not their text are documents of their own. Of rows with equal id and
    text that one stays whose columns have the least hash.
    """
    id_, text = key = [unused(docs, "id"), unused(docs, "text_hash")]
    keyed = docs.withColumn(id_, F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).withColumn(text, F.xxhash64("text"))
    marks = keyed.select(F.struct(F.col("doc_id").isNull().alias("last"), F.col("doc_id").alias("id"), F.col(id_).alias("key"), F.col(text).alias("hash")).alias("doc_id"), "text")
    marks = materialise(fingerprints(marks), "fingerprints")
    # the least row of each fingerprint, then of each group; neither step brings a group's rows together
    first = marks.groupBy("fp").agg(F.min("doc_id").alias("row")).join(classes(marks), "fp").groupBy("root").agg(F.min("row").alias("row"))
    names = [F.col("row.last").alias("last"), F.col("row.key").alias(id_), F.col("row.hash").alias(text)]
    rows = marks.select(F.col("doc_id").alias("row")).select(*names).groupBy("last", *key).count()
    rows = materialise(rows, "rows")
    lost = materialise(rows.join(first.select(*names), ["last", *key], "left_anti").select(*key), "lost")
    twice = materialise(rows.where("count > 1").select(*key), "twice")
    discard(marks)
    discard(rows)
    kept = keyed.join(broadcast_if_small(lost), key, "left_anti")
    whole = [F.col(f"`{c}`") for c in docs.columns]
    if twice.isEmpty():
        return kept.select(*whole)
    some = broadcast_if_small(twice)
    plain = [c for c, f in zip(whole, docs.schema.fields, strict=True) if not isinstance(f.dataType, (MapType, VariantType))]
    one = kept.join(some, key, "left_semi").groupBy(*key).agg(F.min_by(F.struct(*whole), F.xxhash64(*plain)).alias("row")).select("row.*")
    return kept.join(some, key, "left_anti").select(*whole).unionAll(one)
