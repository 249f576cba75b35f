"""Byte-pair encoding of many words at once, from a public tokenizer's file.

The file's own library encodes a word in several microseconds; a corpus has too many distinct words for
that. Here the plain words of a batch (runs of Latin letters, of signs, and single digits, whose splitting and
lower-casing follow simple rules) are merged together in numpy: every round each word takes its best-ranked
pair, leftmost first, as the library does one by one. Words that the simple rules don't cover go to the library.
"""

from __future__ import annotations

import json

import numpy as np

from .common import IS_SPACE, span_hashes

#: Classes of bytes (fixed values): letters, signs, digits; everything else is left to the library.
SPACE, LETTER, SIGN, DIGIT, OTHER = range(5)
_CLASS = np.full(256, OTHER, np.uint8)
_CLASS[IS_SPACE] = SPACE
_CLASS[[*range(0x41, 0x5B), *range(0x61, 0x7B)]] = LETTER
_CLASS[list(b'!"#$%&()*+,-./:;=>?@[\\]^_`{|}~')] = SIGN
_CLASS[list(b"0123456789")] = DIGIT
EMPTY = np.uint64(0xFFFFFFFFFFFFFFFF)


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    shifted = iter(range(0x100, 0x200))
    return [chr(b) if b in set(plain) else chr(next(shifted)) for b in range(256)]


class WordMerger:
    """Merge table and symbols of a byte-level vocabulary with word ends."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as file:
            model = json.load(file)["model"]
        vocab, end = model["vocab"], model["end_of_word_suffix"]
        symbols = byte_symbols()
        self.inner = np.array([vocab[s] for s in symbols], np.int64)
        self.final = np.array([vocab[s + end] for s in symbols], np.int64)
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        keys = np.array([vocab[a] << 20 | vocab[b] for a, b in pairs], np.uint64)
        merged = np.array([vocab[a + b] for a, b in pairs], np.int64)
        self.bits = 18
        while (1 << self.bits) < 4 * len(keys):
            self.bits += 1
        size = 1 << self.bits
        self.keys, self.rank, self.merged = np.full(size, EMPTY), np.full(size, 1 << 30, np.int64), np.zeros(size, np.int64)
        left = np.arange(len(keys))
        slot = self._slot(keys)
        while len(left):  # open addressing: of those that meet in a free slot the first takes it
            free = self.keys[slot] == EMPTY
            winners = np.full(size, -1, np.int64)
            winners[slot[free][::-1]] = left[free][::-1]
            won = winners[slot] == left
            at, who = slot[won], left[won]
            self.keys[at], self.rank[at], self.merged[at] = keys[who], who, merged[who]
            left, slot = left[~won], (slot[~won] + 1) % size

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def look_up(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank and slot of pairs, rank high where there is no merge; packed as rank << 24 | slot."""
        keys = left.astype(np.uint64) << np.uint64(20) | right.astype(np.uint64)
        slot = self._slot(keys)
        out = np.full(len(keys), np.int64(1) << 54)
        open_ = np.arange(len(keys))
        while len(open_):
            found = self.keys[slot]
            hit = found == keys[open_]
            out[open_[hit]] = (self.rank[slot[hit]] << 24) | slot[hit]
            going = ~hit & (found != EMPTY)
            open_, slot = open_[going], (slot[going] + 1) & ((1 << self.bits) - 1)
        return out

    def encode(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all spans, one after another, and the number of ids of each."""
        lengths = ends - starts
        counts = np.zeros(len(starts), np.int64)
        pieces: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for length in np.unique(lengths).tolist():
            who = np.flatnonzero(lengths == length)
            for at in range(0, len(who), max(1, (1 << 18) // length)):
                part = who[at : at + max(1, (1 << 18) // length)]
                ids, left = self._merge(data[starts[part, None] + np.arange(length)])
                counts[part] = left
                pieces[len(pieces)] = (part, ids)
        ends_ = np.cumsum(counts)
        out = np.zeros(int(ends_[-1]) if len(ends_) else 0, np.int64)
        for part, ids in pieces.values():
            left = counts[part]
            target = np.repeat(ends_[part] - left - (np.cumsum(left) - left), left) + np.arange(int(left.sum()))
            out[target] = ids[np.arange(ids.shape[1]) < left[:, None]]
        return out, counts

    def _merge(self, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n, width = raw.shape
        ids = self.inner[raw]
        ids[:, -1] = self.final[raw[:, -1]]
        left = np.full(n, width)
        if width == 1:
            return ids, left
        none = np.int64(1) << 54
        ranks = self.look_up(ids[:, :-1].ravel(), ids[:, 1:].ravel()).reshape(n, width - 1)
        active = np.arange(n)
        columns = np.arange(width)
        out, counts = ids, left
        while len(active):
            place = (ranks >> 24).argmin(1)
            best = ranks[np.arange(len(active)), place]
            going = best < none
            if not going.all():
                done = ~going
                out[active[done], : ids.shape[1]] = ids[done]
                counts[active[done]] = left[done]
                active, ids, ranks, left, place, best = active[going], ids[going], ranks[going], left[going], place[going], best[going]
                if not len(active):
                    break
            row = np.arange(len(active))
            size = int(left.max())
            ids, ranks = ids[:, :size], ranks[:, : size - 1]
            # The pair becomes one symbol; what follows moves up by one place.
            shift = columns[:size] + (columns[:size] > place[:, None])
            shift[:, -1] = np.minimum(shift[:, -1], size - 1)
            ids = np.take_along_axis(ids, shift, 1)
            ids[row, place] = self.merged[best & ((1 << 24) - 1)]
            left = left - 1
            moved = shift[:, : size - 1]
            moved = np.minimum(moved, size - 2)
            ranks = np.take_along_axis(ranks, moved, 1)
            ranks[columns[: size - 1] >= (left - 1)[:, None]] = none
            before = np.flatnonzero(place > 0)
            ranks[before, place[before] - 1] = self.look_up(ids[before, place[before] - 1], ids[before, place[before]])
            after = np.flatnonzero(place < left - 1)
            ranks[after, place[after]] = self.look_up(ids[after, place[after]], ids[after, place[after] + 1])
        return out, counts


def simple_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Lower-cased bytes; starts and ends of the tokenizer's words; whether each is for the library; its row.

    A stretch between white space with anything but Latin letters, signs and digits is one span for the library.
    """
    kind = _CLASS[data]
    low = data | (((data >= 0x41) & (data <= 0x5A)) * np.uint8(0x20))
    lead = np.flatnonzero(data[:-1] == 0xC3) if len(data) > 1 else np.zeros(0, np.int64)
    next_ = data[lead + 1]
    letter = (next_ >= 0x80) & (next_ <= 0xBF) & (next_ != 0x97) & (next_ != 0xB7)
    lead, next_ = lead[letter], next_[letter]
    kind[lead] = kind[lead + 1] = LETTER
    upper = next_ <= 0x9E
    low[lead[upper] + 1] = next_[upper] + 0x20
    n = len(data)
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    solid = kind != SPACE
    # Stretches without white space, and which of them hold other bytes.
    opens = solid & (edge[:n] | np.concatenate([[True], ~solid[:-1]]))
    number = np.cumsum(opens) - 1
    odd = np.zeros(int(opens.sum()), bool)
    odd[number[solid & (kind == OTHER)]] = True
    whole = np.zeros(n, bool)
    whole[solid] = odd[number[solid]]
    begins = solid & ~whole & (edge[:n] | np.concatenate([[True], kind[1:] != kind[:-1]]) | (kind == DIGIT))
    begins |= opens
    starts = np.flatnonzero(begins)
    stop = np.concatenate([(begins | ~solid | edge[:n])[1:], [True]]) & solid
    ends = np.flatnonzero(stop) + 1
    return low, starts, ends, whole[starts], np.searchsorted(offsets, starts, "right") - 1


def distinct_spans(low: np.ndarray, data: np.ndarray, starts: np.ndarray, ends: np.ndarray, library: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of one span of each kind, and the kind of every span; library spans are told apart by their own bytes."""
    mixed = low.copy()
    for a, b in zip(starts[library].tolist(), ends[library].tolist(), strict=True):
        mixed[a:b] = data[a:b]
    codes = span_hashes(mixed, starts, ends) ^ (library.astype(np.uint64) * np.uint64(0xA0761D6478BD642F))
    _, first, kind = np.unique(codes, return_index=True, return_inverse=True)
    return first, kind
