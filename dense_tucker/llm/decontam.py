"""Benchmark decontamination with a distributed positional inverted index of the training texts.

The index holds every word of every text and knows nothing of a test set: it is built once (build_index, write_index) and searched for any
number of test sets. It is split by documents: each row is a shard, a run of documents whose words are numbered through
(with a gap between documents), and holds its distinct words with their sorted positions. A test set is read in slices of about
SLICE_BYTES. Frequencies of a slice's terms are summed over all shards; a window is looked up by its rarest term,
whose positions, shifted by the term's place in the window, are intersected with the shifted lists of the
other terms in order of rarity. Words are found by hash and then compared byte by byte. Shards answer alone, so nothing but the answers is shuffled
and a frequent passage costs each shard its own matches only. Proximity matches are windows all of whose terms stand, in any
order, within `reach` words of an occurrence of the rarest one in the same document.

Words are runs of ASCII digits, letters (lower-cased) and non-ASCII characters. Null and empty texts have no
words and no hits; an item without words is in nothing; repeated rows are answered one by one, items that share an id are one item; empty tables
are allowed; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import lexing
from .common import broadcast_if_small, materialise, passes, texts_of

WINDOW = 10
#: Words to either side of a rarest term in which a proximity match has the other terms.
REACH = 15
#: Bytes of test texts that a search takes at a time; each worker holds a few dozen times as much.
SLICE_BYTES = 4 << 20
_GAP = 1
_INDEX = "shard long, doc_ids array<{}>, n_words binary, terms binary, ends binary, positions binary, spelled binary, spelled_ends binary"


@dataclass
class Phrases:
    """Distinct terms of the test items with their spelling, and the items' distinct windows as rows of term numbers."""

    terms: np.ndarray  # sorted hashes
    spelled: np.ndarray  # bytes of all terms
    spelled_ends: np.ndarray
    items: list[str]
    windows: np.ndarray  # (w, size), -1 after a short item's end
    lengths: np.ndarray
    owner: np.ndarray  # item of each window

    @classmethod
    def of(cls, rows: list[tuple[object, str | None]], size: int = WINDOW) -> Phrases:
        names = sorted({str(k) for k, _ in rows})
        data, starts, ends = texts_of(pa.array([t for _, t in rows], pa.string()))
        data = lexing.LOWER[data]
        h, a, b, row = lexing.words(data, starts, ends, lexing.ALNUM)
        terms, first, number = np.unique(h, return_index=True, return_inverse=True)
        if not lexing.same_spans(data, a, data, a[first[number]], np.minimum(b - a, (b - a)[first[number]])).all() or ((b - a) != (b - a)[first[number]]).any():
            raise ValueError("two test words with one hash; search the items that hold them apart")
        counts = np.bincount(row, minlength=len(rows)) if len(row) else np.zeros(len(rows), np.int64)
        begin = np.cumsum(counts) - counts
        place = {k: i for i, k in enumerate(names)}
        windows, owner = [np.zeros((0, size), np.int32)], [np.zeros(0, np.int64)]
        for (key, _), n, at in zip(rows, counts.tolist(), begin.tolist(), strict=True):
            if n:
                k = min(n, size)
                made = np.full((n - k + 1, size), -1, np.int32)
                made[:, :k] = np.lib.stride_tricks.sliding_window_view(number[at : at + n], k)
                windows.append(made)
                owner.append(np.full(len(made), place[str(key)]))
        table, who = np.concatenate(windows), np.concatenate(owner)
        if len(table):
            both = np.unique(np.concatenate([table, who[:, None].astype(np.int32)], 1), axis=0)
            table, who = np.ascontiguousarray(both[:, :-1]), both[:, -1].astype(np.int64)
        spelled, spelled_ends = _spelled(data, a[first], b[first])
        return cls(terms, spelled, spelled_ends, names, table, (table >= 0).sum(1), who)


def _spelled(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of these spans one after the other, and their ends."""
    size = ends - starts
    stops = np.cumsum(size)
    total = int(stops[-1]) if len(stops) else 0
    return data[np.arange(total) + np.repeat(starts - (stops - size), size)], stops


def build_index(docs: DataFrame, text: str = "text") -> DataFrame:
    """Shards: doc_ids, n_words (of each), terms (sorted hashes), ends (of each term's list), positions, spelled words and their ends."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        part, shard = TaskContext.get().partitionId(), 0
        for batch in batches:
            data, starts, ends = texts_of(batch.column(1))
            for i, j in passes(starts, ends):
                low = int(starts[i])
                own = lexing.LOWER[data[low : int(ends[j - 1])]]
                h, a, b, row = lexing.words(own, starts[i:j] - low, ends[i:j] - low, lexing.ALNUM)
                n = np.bincount(row, minlength=j - i)
                position = (np.arange(len(h)) + row * _GAP).astype(np.int32)
                order = np.argsort(h, kind="stable")
                sorted_ = h[order]
                lead = np.ones(len(h), bool)
                lead[1:] = sorted_[1:] != sorted_[:-1]
                head = np.flatnonzero(lead)
                lists = np.append(head[1:], len(h)) if len(h) else head
                # words whose hashes alone meet keep their places under lists of their own, with the same hash
                first = np.repeat(order[head], np.diff(np.append(head, len(h)))) if len(h) else order
                odd = np.flatnonzero((b - a)[order] != (b - a)[first])
                same = lexing.same_spans(own, a[order], own, a[first], np.minimum((b - a)[order], (b - a)[first]))
                if len(odd) or not same.all():
                    order = np.asarray(sorted(order.tolist(), key=lambda k: (h[k], own[a[k] : b[k]].tobytes(), k)), np.int64)
                    names = [(h[k], own[a[k] : b[k]].tobytes()) for k in order.tolist()]
                    head = np.asarray([k for k in range(len(names)) if not k or names[k] != names[k - 1]], np.int64)
                    lists, sorted_ = np.append(head[1:], len(h)), h[order]
                spelled, stops = _spelled(own, a[order[head]], b[order[head]])
                yield pa.RecordBatch.from_arrays(
                    [pa.array([part << 32 | shard], pa.int64()), pa.ListArray.from_arrays(pa.array([0, j - i], pa.int32()), batch.column(0).slice(i, j - i))]
                    + [pa.array([x.tobytes()], pa.binary()) for x in (n.astype(np.int32), sorted_[head], lists.astype(np.int32), position[order], spelled, stops.astype(np.int32))],
                    names=["shard", "doc_ids", "n_words", "terms", "ends", "positions", "spelled", "spelled_ends"],
                )
                shard += 1

    return docs.select("doc_id", F.col(text).alias("text")).mapInArrow(run, _INDEX.format(kind))


def write_index(docs: DataFrame, path: str, text: str = "text") -> DataFrame:
    """Build the index once, for any number of searches."""
    build_index(docs, text).write.option("compression", "zstd").parquet(path)
    return read_index(docs.sparkSession, path)


def read_index(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def _known(row: dict, phrases: Phrases) -> tuple[np.ndarray, np.ndarray]:
    """Terms of the test set that a shard has, and the numbers of their lists: hashes meet and bytes are equal."""
    terms = np.frombuffer(row["terms"], np.uint64)
    if not len(terms) or not len(phrases.terms):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.searchsorted(phrases.terms, terms)
    at[at == len(phrases.terms)] = 0
    mine = np.flatnonzero(phrases.terms[at] == terms)
    at = at[mine]
    stops = np.frombuffer(row["spelled_ends"], np.int32).astype(np.int64)
    begin = np.concatenate([[0], stops[:-1]])
    size, begin = (stops - begin)[mine], begin[mine]
    theirs = phrases.spelled_ends[at] - np.concatenate([[0], phrases.spelled_ends[:-1]])[at]
    good = (size == theirs) & lexing.same_spans(np.frombuffer(row["spelled"], np.uint8), begin, phrases.spelled, phrases.spelled_ends[at] - theirs, np.minimum(size, theirs))
    return at[good], mine[good]


_WORDS_OF = ["terms", "ends", "spelled", "spelled_ends"]


def frequencies(index: DataFrame, phrases: Phrases) -> np.ndarray:
    """Occurrences of every term of the test set in the whole corpus (one number for each term)."""
    n_terms = len(phrases.terms)

    def run(batches):
        total = np.zeros(n_terms, np.int64)
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1).to_pylist()[0]
                at, lists = _known(row, phrases)
                np.add.at(total, at, np.diff(np.frombuffer(row["ends"], np.int32), prepend=0)[lists])
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], names=["term", "n"])

    out = np.zeros(n_terms, np.int64)
    for r in index.select(*_WORDS_OF).mapInArrow(run, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).collect():
        out[r["term"]] = r["n"]
    return out


def _shard(row: dict, phrases: Phrases) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """n_words and first position of each document; keys (term << 32 | position) of the test set's terms, in order."""
    n = np.frombuffer(row["n_words"], np.int32).astype(np.int64)
    base = np.cumsum(n) - n + np.arange(len(n)) * _GAP
    at, lists = _known(row, phrases)
    ends = np.frombuffer(row["ends"], np.int32).astype(np.int64)
    begin = np.concatenate([[0], ends[:-1]])[lists]
    size = ends[lists] - begin
    stops = np.cumsum(size)
    total = int(stops[-1]) if len(stops) else 0
    where = np.frombuffer(row["positions"], np.int32)[np.arange(total) + np.repeat(begin - (stops - size), size)].astype(np.int64)
    return n, base, np.sort((np.repeat(at, size) << 32) | where)


def _has(keys: np.ndarray, term: np.ndarray, position: np.ndarray) -> np.ndarray:
    wanted = (term.astype(np.int64) << 32) | position
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return (keys[at] == wanted) & (position >= 0)


def _rarest(keys: np.ndarray, windows: np.ndarray, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Window and position of every occurrence of the windows' rarest terms."""
    rows = np.arange(len(windows))
    rarest = windows[rows, order[:, 0]].astype(np.int64)
    low, high = np.searchsorted(keys, rarest << 32), np.searchsorted(keys, (rarest + 1) << 32)
    n = high - low
    w = np.repeat(rows, n)
    at = np.arange(len(w)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low, n)
    return w, keys[at] & 0xFFFFFFFF


def match_windows(keys: np.ndarray, windows: np.ndarray, order: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Window and first position of every occurrence; `order` has each window's places from the rarest term on."""
    if not len(keys) or not len(windows):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    w, s = _rarest(keys, windows, order)
    s = s - order[w, 0]
    for k in range(1, windows.shape[1]):
        place = order[w, k]
        fits = (k >= lengths[w]) | _has(keys, windows[w, place], s + place)
        w, s = w[fits], s[fits]
        if not len(w):
            break
    return w, s


def near_windows(keys: np.ndarray, windows: np.ndarray, order: np.ndarray, lengths: np.ndarray, base: np.ndarray, n: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray]:
    """Window and document of every proximity match."""
    if not len(keys) or not len(windows):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    w, s = _rarest(keys, windows, order)
    doc = np.searchsorted(base, s, "right") - 1
    low, high = np.maximum(s - reach, base[doc]), np.minimum(s + reach, (base + n)[doc] - 1)
    for k in range(1, windows.shape[1]):
        term = windows[w, order[w, k]].astype(np.int64) << 32
        at = np.minimum(np.searchsorted(keys, term | low), len(keys) - 1)
        fits = (k >= lengths[w]) | ((keys[at] >= term | low) & (keys[at] <= term | high))
        w, doc, low, high = w[fits], doc[fits], low[fits], high[fits]
        if not len(w):
            break
    return w, doc


def _joined(intervals: np.ndarray) -> np.ndarray:
    """Disjoint ascending (start, end) rows that cover the same."""
    if not len(intervals):
        return intervals.reshape(0, 2)
    intervals = intervals[np.argsort(intervals[:, 0], kind="stable")]
    reach = np.maximum.accumulate(intervals[:, 1])
    new = np.ones(len(intervals), bool)
    new[1:] = intervals[1:, 0] > reach[:-1]
    heads = np.flatnonzero(new)
    return np.stack([intervals[heads, 0], reach[np.append(heads[1:], len(intervals)) - 1]], 1)


def matches(index: DataFrame, phrases: Phrases, reach: int = REACH) -> DataFrame:
    """shard, at (number of the document in it), doc_id, n_words, hits (start, end of hit words, by twos), item_ids and near_ids of every document."""
    kind = index.schema["doc_ids"].dataType.elementType.simpleString()
    seen = frequencies(index, phrases)
    rank = np.where(phrases.windows >= 0, seen[phrases.windows] if len(seen) else 0, np.iinfo(np.int64).max)
    order = np.argsort(rank, axis=1, kind="stable").astype(np.int32)
    alive = (rank > 0).all(1)
    windows, order, lengths, owner = phrases.windows[alive], order[alive], phrases.lengths[alive], phrases.owner[alive]
    names = phrases.items

    def items(n: int, doc: np.ndarray, w: np.ndarray) -> pa.Array:
        lists: list[list[str]] = [[] for _ in range(n)]
        for d, item in np.unique(np.stack([doc, owner[w]], 1), axis=0).tolist():
            lists[d].append(names[item])
        return pa.array(lists, pa.list_(pa.string()))

    def run(batches):
        for batch in batches:
            for k in range(batch.num_rows):
                ids, shard = batch.column(1)[k].values, batch.column(0)[k].as_py()
                row = batch.select(["n_words", "positions", *_WORDS_OF]).slice(k, 1).to_pylist()[0]
                n, base, keys = _shard(row, phrases)
                w, s = match_windows(keys, windows, order, lengths)
                doc = np.searchsorted(base, s, "right") - 1
                cover = _joined(np.stack([s, s + lengths[w]], 1))
                where = np.searchsorted(base, cover[:, 0], "right") - 1
                cuts = np.searchsorted(where, np.arange(len(n) + 1))
                near_w, near_doc = near_windows(keys, windows, order, lengths, base, n, reach)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.full(len(n), shard)),
                        pa.array(np.arange(len(n), dtype=np.int32)),
                        ids,
                        pa.array(n),
                        pa.ListArray.from_arrays(pa.array(2 * cuts, pa.int32()), pa.array((cover - base[where][:, None]).ravel(), pa.int64())),
                        items(len(n), doc, w),
                        items(len(n), near_doc, near_w),
                    ],
                    names=["shard", "at", "doc_id", "n_words", "hits", "item_ids", "near_ids"],
                )

    return index.mapInArrow(run, f"shard long, at int, doc_id {kind}, n_words long, hits array<long>, item_ids array<string>, near_ids array<string>")


def search(index: DataFrame, slices: Iterator[Phrases] | list[Phrases], reach: int = REACH) -> DataFrame:
    """One row for each document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, item_ids, near_ids and n_near (items with a proximity match)."""
    found = [matches(index, phrases, reach) for phrases in slices] or [matches(index, Phrases.of([]), reach)]
    every = found[0]
    if len(found) > 1:  # a document's answers from all slices together
        for more in found[1:]:
            every = every.unionAll(more)
        lists = [F.flatten(F.collect_list(c)).alias(c) for c in ("hits", "item_ids", "near_ids")]
        every = every.groupBy("shard", "at").agg(F.first("doc_id").alias("doc_id"), F.first("n_words").alias("n_words"), *lists)
    pairs = "transform(sequence(0, size(hits) div 2 - 1), i -> struct(hits[2 * i] as a, hits[2 * i + 1] as b))"
    cover = f"if(size(hits) = 0, 0L, aggregate(array_sort({pairs}), struct(0L as n, -1L as reach), (s, x) -> struct(s.n + greatest(0L, x.b - greatest(x.a, s.reach)) as n, greatest(s.reach, x.b) as reach)).n)"
    made = every.withColumn("n_hit", F.expr(cover)).withColumn("item_ids", F.array_sort(F.array_distinct("item_ids"))).withColumn("near_ids", F.array_sort(F.array_distinct("near_ids")))
    return made.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"), "item_ids", "near_ids", F.size("near_ids").cast("long").alias("n_near"))


def phrases_of(benchmark: DataFrame, size: int = WINDOW, slice_bytes: int = SLICE_BYTES) -> Iterator[Phrases]:
    """The test set in slices by a hash of its items, of about `slice_bytes` each; one is on the driver at a time."""
    rows = benchmark.where("text is not null").select("item_id", F.col("text").cast("string").alias("text"))
    count = 1 + (rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // slice_bytes
    for k in range(count):
        part = rows if count == 1 else rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(count)) == k)
        yield Phrases.of([(r[0], r[1]) for r in part.collect()], size)


def apply(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW, slice_bytes: int = SLICE_BYTES) -> DataFrame:
    return search(materialise(build_index(docs), "positions"), phrases_of(benchmark, size, slice_bytes))


def keep_clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Documents in which no window of the benchmark occurs; rows without an id are told apart by their text."""
    key = F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("#"), F.sha2(F.coalesce("text", F.lit("")), 256)))
    keyed = docs.select(F.struct(*docs.columns).alias("row"), key.alias("key"))
    foul = apply(keyed.select(F.col("key").alias("doc_id"), F.col("row.text").alias("text")), benchmark).where("contaminated").select(F.col("doc_id").alias("key"))
    foul = materialise(foul.distinct(), "contaminated")
    return keyed.join(broadcast_if_small(foul), "key", "left_anti").select("row.*")
