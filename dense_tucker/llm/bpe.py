"""Exact BPE ids of whole texts, fast on repetitive vocabulary.

No id of either public tokenizer spans a border of these kinds: before a lone space between two visible
characters, around another lone white-space character between two such, or between an ASCII letter or digit
and closing punctuation. A text's ids are therefore those of its pieces between such borders. Pieces are
looked up by hash in an open-addressed numpy table kept by each worker, which compares their bytes; only new ones go to the tokenizers
library. A text that holds the opening of a special token is one piece. The borders hold for tokenizers whose pre-tokenizer
is one of those known here; with any other one, every text is one piece.
"""

from __future__ import annotations

import json
import os

import numpy as np

from . import lexing

#: Distinct pieces (up to about 50 bytes each) and their ids that a worker keeps before it starts anew.
CACHE_PIECES = 1_500_000
CACHE_IDS = 16_000_000
CACHE_BYTES = 64_000_000
_CLOSING = np.zeros(256, bool)
_CLOSING[list(b".,!?;:|#$%&*)]")] = True
_ALNUM = np.zeros(256, bool)
_ALNUM[list(b"0123456789abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ")] = True
_CONTROL = np.zeros(256, bool)
_CONTROL[0x09:0x0E] = True
#: First bytes of characters that are surely no white space; two-byte ones from U+00C0 on.
_VISIBLE = np.zeros(256, bool)
_VISIBLE[0x21:0x7F] = True
_VISIBLE[0xC3:0xE0] = True
#: Normalizers and split patterns for which the borders hold (fixed values of the two public tokenizers).
_KNOWN = (
    ([], ["ByteLevel with its own pattern"]),
    (["NFC", "Replace", "Lowercase"], [r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+", "ByteLevel"]),
)
_encoders: dict[str, Encoder] = {}


def borders(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Positions where texts may be cut, with every text's start and the end of all; strictly ascending."""
    n = len(data)
    cut = np.zeros(n + 1, bool)
    if n > 2:
        after = np.zeros(n, bool)
        after[:-1] = _VISIBLE[data[1:]]
        before = np.zeros(n, bool)
        before[1:] = (_VISIBLE & (np.arange(256) < 0x80))[data[:-1]]
        before[2:] |= ((data[1:-1] & 0xC0) == 0x80) & (data[:-2] >= 0xC3) & (data[:-2] < 0xE0)
        lone = before & after
        space = lone & (data == 0x20)
        control = lone & _CONTROL[data]
        cut[:n] |= space | control
        cut[1:] |= control
        cut[1:n] |= _CLOSING[data[1:]] & _ALNUM[data[:-1]]
        special = np.flatnonzero((data[:-1] == 0x3C) & (data[1:] == 0x7C))
        for row in np.unique(lexing.owners(special, starts, ends)) if len(special) else ():
            cut[starts[row] : ends[row]] = False
    cut[starts] = True
    cut[n] = True
    return np.flatnonzero(cut)


def _with_room(held: np.ndarray, used: int, more: int) -> np.ndarray:
    return held if used + more <= len(held) else np.concatenate([held[:used], np.zeros(max(len(held), more), held.dtype)])


def _cuttable(path: str) -> bool:
    """Whether borders() was derived for this kind of tokenizer."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    splits = spec.get("pre_tokenizer") or {}
    patterns = [str(x.get("pattern", {}).get("Regex")) if x["type"] == "Split" else x["type"] for x in splits.get("pretokenizers", [splits] if splits else [])]
    if splits.get("type") == "ByteLevel" and splits.get("use_regex"):
        patterns = ["ByteLevel with its own pattern"]
    special = all(t["content"].startswith("<|") for t in spec.get("added_tokens", []))
    return spec["model"]["type"] == "BPE" and special and ([n.get("type") for n in (spec.get("normalizer") or {}).get("normalizers", [])], patterns) in _KNOWN


class Encoder:
    def __init__(self, path: str, cache: int = CACHE_PIECES):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.known = _cuttable(path)
        self.width = np.dtype("<u2") if self.library.get_vocab_size() <= 1 << 16 else np.dtype("<u4")
        self.limit = cache
        self._clear(1 << 16)

    def _clear(self, slots: int) -> None:
        self.keys = np.zeros(slots, np.uint64)
        self.values = np.zeros(slots, np.int32)  # the entry's number
        self.count, self.used = 0, 0
        self.begin = np.zeros(slots // 2, np.int64)  # at most half of the slots are filled
        self.length = np.zeros(slots // 2, np.int32)
        self.pool = np.zeros(slots * 4, self.width)
        self.text = np.zeros(slots * 4, np.uint8)  # bytes of all pieces, with eight spare ones
        self.origin = np.zeros(slots // 2, np.int64)
        self.size = np.zeros(slots // 2, np.int64)
        self.written = 0
        self.odd: dict[bytes, int] = {}  # entries of pieces whose hash another piece has

    def _find(self, keys: np.ndarray) -> np.ndarray:
        """Entry of each key, -1 where new."""
        mask = np.uint64(len(self.keys) - 1)
        at = (keys & mask).astype(np.int64)
        found = np.where(self.keys[at] == keys, self.values[at], -1)
        open_ = np.flatnonzero((found < 0) & (self.keys[at] != 0))
        while len(open_):
            at[open_] = (at[open_] + 1) & int(mask)
            here = self.keys[at[open_]]
            hit = here == keys[open_]
            found[open_[hit]] = self.values[at[open_[hit]]]
            open_ = open_[~hit & (here != 0)]
        return found

    def _place(self, keys: np.ndarray, values: np.ndarray) -> None:
        """Insert distinct new keys."""
        mask = len(self.keys) - 1
        at = (keys & np.uint64(mask)).astype(np.int64)
        todo = np.arange(len(keys))
        while len(todo):
            free = todo[self.keys[at[todo]] == 0]
            self.keys[at[free]] = keys[free]  # of those that meet here, the last stays
            self.values[at[free]] = values[free]
            todo = todo[self.keys[at[todo]] != keys[todo]]
            at[todo] = (at[todo] + 1) & mask

    def _learn(self, keys: np.ndarray, pieces: list[bytes]) -> None:
        if 2 * (self.count + len(keys)) > len(self.keys):
            held, entries = self.keys[self.keys != 0], self.values[self.keys != 0]
            slots = len(self.keys)
            while 2 * (self.count + len(keys)) > slots:
                slots *= 2
            self.keys, self.values = np.zeros(slots, np.uint64), np.zeros(slots, np.int32)
            self._place(held, entries)
        self._place(keys, self._append(pieces))

    def _append(self, pieces: list[bytes]) -> np.ndarray:
        """Numbers of new entries for these pieces."""
        batch = getattr(self.library, "encode_batch_fast", self.library.encode_batch)
        texts = [p.decode("utf-8", "replace") for p in pieces]
        made = [e.ids for i in range(0, len(texts), 5_000) for e in batch(texts[i : i + 5_000], add_special_tokens=False)]
        lengths = np.fromiter(map(len, made), np.int64, len(made))
        flat = np.fromiter((x for ids in made for x in ids), self.width, int(lengths.sum()))
        raw, sizes = np.frombuffer(b"".join(pieces), np.uint8), np.fromiter(map(len, pieces), np.int64, len(pieces))
        entries = np.arange(self.count, self.count + len(pieces))
        if self.count + len(pieces) > len(self.begin):
            room = max(2 * len(self.begin), self.count + len(pieces))
            self.begin, self.length, self.origin, self.size = (np.resize(x, room) for x in (self.begin, self.length, self.origin, self.size))
        self.pool, self.text = _with_room(self.pool, self.used, len(flat)), _with_room(self.text, self.written, len(raw) + 8)
        self.pool[self.used : self.used + len(flat)] = flat
        self.text[self.written : self.written + len(raw)] = raw
        self.begin[entries], self.length[entries] = self.used + np.cumsum(lengths) - lengths, lengths
        self.origin[entries], self.size[entries] = self.written + np.cumsum(sizes) - sizes, sizes
        self.used, self.written, self.count = self.used + len(flat), self.written + len(raw), self.count + len(pieces)
        return entries

    def _entries(self, data: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Entry of every piece, by hash and bytes."""
        keys = lexing.span_hashes(data, a, b)
        keys[keys == 0] = 1
        entry = self._find(keys)
        new = np.flatnonzero(entry < 0)
        raw = memoryview(np.ascontiguousarray(data))
        if len(new):
            fresh, first = np.unique(keys[new], return_index=True)
            self._learn(fresh, [bytes(raw[a[i] : b[i]]) for i in new[first]])
            entry[new] = self._find(keys[new])
        size = b - a
        held = self.size[entry]
        same = (held == size) & lexing.same_spans(data, a, self.text, self.origin[entry], np.minimum(size, held), padded=True)
        for i in np.flatnonzero(~same).tolist():
            piece = bytes(raw[a[i] : b[i]])
            if piece not in self.odd:
                self.odd[piece] = int(self._append([piece])[0])
            entry[i] = self.odd[piece]
        return entry

    def encode_bytes(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids of these texts in a row, and each text's number of ids."""
        if not len(data):
            return np.zeros(0, self.width), np.zeros(len(starts), np.int64)
        if self.count > self.limit or self.used > CACHE_IDS or self.written > CACHE_BYTES:
            self._clear(1 << 16)
        at = borders(data, starts, ends) if self.known else np.unique(np.append(starts, len(data)))
        at = at[: int(np.searchsorted(at, len(data))) + 1]
        a, b = at[:-1], at[1:]
        entry = self._entries(data, a, b)
        lengths = self.length[entry]
        done = np.cumsum(lengths)
        total = int(done[-1])
        ids = self.pool[np.arange(total) + np.repeat(self.begin[entry] - (done - lengths), lengths)]
        done = np.concatenate([[0], done])
        return ids, done[np.searchsorted(a, ends)] - done[np.searchsorted(a, starts)]


def encoder(path: str) -> Encoder:
    """One encoder for each worker process, kept between tasks."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]
