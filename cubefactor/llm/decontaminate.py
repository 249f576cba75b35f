"""Benchmark decontamination by template canonicalisation.

Texts and benchmark items become sequences of canonical words: numbers, names and units of measure turn
into typed placeholders, other words into lower case without outer signs. A word in upper
case that opens a sentence may be a name or not and is read in both ways. Windows of `window` canonical
words with enough ordinary words (openers count as such) are joined by hash. A document holds an item where the windows found cover
`containment` of the item's windows and its placeholders are filled consistently: one filling of the item
always meets the same filling in the document, so a question asked anew with other numbers or names is
caught, and a chance meeting of common templates is not. Where the fillings of all hits together disagree,
each place of the document is tested by itself, and the figures are those of its best occurrence.

Benchmark windows are matched in blocks of at most `block_windows` (readings of openers aside), each sent to all tasks, so what is sent
has a fixed bound whatever the benchmark's size; all documents are read for every block.

Defined cases: null or empty texts and items match nothing; an item of fewer words than a window is one
window; items without a usable window, of numbers, names and units mostly, are matched by windows of their
own words, so only where they are copied; texts of any length are read whole; repeated items and
documents are reported for each row; a null doc_id is reported as null, a null item_id too; empty tables
give no rows; extra columns are ignored or, in `drop_contaminated`, kept.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, mix64, ship_package, span_hashes, text_or_empty

WINDOW, CONTAINMENT, CONSISTENCY, LEAST_ORDINARY = 5, 0.5, 0.8, 3
#: Units of measure and number words that become placeholders (fixed values).
UNITS = frozenset("mm cm m km in ft yd mi inch inches foot feet yard yards mile miles meter meters metre metres kilometer kilometers mg g kg lb lbs oz ton tons gram grams kilogram kilograms pound pounds ounce ounces ml l liter liters litre litres gallon gallons s sec secs second seconds min mins minute minutes h hr hrs hour hours day days week weeks month months year years dollar dollars cent cents euro euros usd eur percent mph kmh hz khz mhz ghz kb mb gb tb w kw v volt volts watt watts".split())
NUMBER_WORDS = frozenset("zero one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty thirty forty fifty sixty seventy eighty ninety hundred thousand million billion".split())
_BREAK = r"[\x20\x09-\x0D]+"
_NUMBER = re.compile(r"[+-]?[$€£]?\d[\d.,:/]*(st|nd|rd|th)?%?")
_OUTER = re.compile(r"^[^\w$€£+-]+|[^\w%]+$")
#: Kinds of canonical words.
ORDINARY, NUMBER, UNIT, NAME = range(4)
_PLACEHOLDER = mix64(np.arange(1, 5, dtype=np.uint64) * np.uint64(0xA24BAED4963EE407))


def describe(word: str) -> tuple[str, int, bool, bool]:
    """Canonical form, kind, whether it could be a name, and whether it ends a sentence."""
    core = _OUTER.sub("", word)
    ends = word.rstrip("\"')]}*#$%&").endswith((".", "!", "?", ":"))
    low = core.lower()
    if core and (_NUMBER.fullmatch(core) or low in NUMBER_WORDS):
        return low, NUMBER, False, ends
    if low in UNITS:
        return low, UNIT, False, ends
    return low, ORDINARY, len(core) > 1 and core[0].isupper() and not core.isupper(), ends


@dataclass
class Canonical:
    """Canonical words of several texts, one after another."""

    code: np.ndarray  # of the canonical word or its placeholder
    kind: np.ndarray
    filling: np.ndarray  # code of the word itself
    opener: np.ndarray  # whether it is ordinary but opens a sentence in upper case, so that it may be a name
    bounds: np.ndarray


def canonical_words(texts: pa.Array, seen: dict[str, tuple] | None = None) -> Canonical:
    split = pc.split_pattern_regex(texts.fill_null(""), _BREAK)
    flat = split.flatten()
    bounds = np.asarray(split.offsets).astype(np.int64)
    bounds = bounds - bounds[0]
    words = flat.dictionary_encode()
    seen = {} if seen is None else seen
    facts = []
    for w in words.dictionary.to_pylist():
        found = seen.get(w)
        if found is None:
            found = describe(w)
            if len(seen) < 50_000:  # the most common words come early; the bound keeps workers small
                seen[w] = found
        facts.append(found)
    index = np.asarray(words.indices).astype(np.int64)
    cores = pa.array([f[0] for f in facts], pa.string())
    raw = np.frombuffer(cores.buffers()[2] or b"", np.uint8) if len(facts) else np.zeros(0, np.uint8)
    offsets = np.frombuffer(cores.buffers()[1], np.int32)[: len(facts) + 1].astype(np.int64) if len(facts) else np.zeros(1, np.int64)
    own = span_hashes(raw, offsets[:-1], offsets[1:])
    kind_of = np.array([f[1] for f in facts], np.int8)
    nameable, closing = (np.array([f[k] for f in facts], bool) for k in (2, 3))
    empty_word = np.diff(offsets) == 0
    keep = ~empty_word[index]
    owner = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    opens = np.ones(len(index), bool)
    opens[1:] = closing[index[:-1]]
    opens[bounds[:-1][bounds[:-1] < len(index)]] = True
    index, owner, opens = index[keep], owner[keep], opens[keep]
    kind = kind_of[index].copy()
    kind[nameable[index] & ~opens] = NAME
    filling = own[index]
    code = np.where(kind == ORDINARY, filling, _PLACEHOLDER[kind])
    return Canonical(code, kind, filling, nameable[index] & opens, np.searchsorted(owner, np.arange(len(bounds))))


def _places(words: Canonical, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First word, end of the text and text number of every window; a text shorter than a window is one window."""
    sizes = np.diff(words.bounds)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    last = words.bounds[1:][owner]
    place = np.arange(len(words.code))
    at = np.flatnonzero((place + window <= last) | ((sizes < window)[owner] & (place == words.bounds[:-1][owner])))
    return at, last[at], owner[at]


def _hashed(code: np.ndarray, at: np.ndarray, last: np.ndarray, window: int, names: int = 0) -> np.ndarray:
    """Hashes of the windows' codes (padded by a window); the words at the bits of `names` are read as names."""
    value = np.zeros(len(at), np.uint64)
    for k in range(window):
        read = _PLACEHOLDER[NAME] if names >> k & 1 else code[at + k]
        value = (value ^ np.where(at + k < last, read, np.uint64(k + 1))) * np.uint64(0x9E3779B97F4A7C15)
        value ^= value >> np.uint64(32)
    return mix64(value)


def template_windows(words: Canonical, window: int = WINDOW, least: int = LEAST_ORDINARY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first word and text number of every usable window; a text shorter than a window is one window.

    A window over sentence openers has a hash for each choice of openers that are read as names. Whether it
    is usable is judged with openers as ordinary words.
    """
    at, last, owner = _places(words, window)
    if least:
        ordinary = np.concatenate([words.kind == ORDINARY, np.zeros(window, bool)])
        count = sum(((at + k < last) & ordinary[at + k] for k in range(window)), np.zeros(len(at), np.int64))
        usable = count >= np.minimum(least, np.maximum(np.diff(words.bounds)[owner] - 1, 1))
        at, last, owner = at[usable], last[usable], owner[usable]
    code = np.concatenate([words.code, np.zeros(window, np.uint64)])
    opener = np.concatenate([words.opener, np.zeros(window, bool)])
    openers = sum(((at + k < last) & opener[at + k]).astype(np.int64) << k for k in range(window)) if len(at) else np.zeros(0, np.int64)
    parts = [(_hashed(code, at, last, window), at, owner)]
    some = np.flatnonzero(openers)
    for names in range(1, 1 << window):
        mine = some[openers[some] & names == names]
        if len(mine):
            parts.append((_hashed(code, at[mine], last[mine], window, names), at[mine], owner[mine]))
    return tuple(np.concatenate(c) for c in zip(*parts, strict=True))


def exact_windows(words: Canonical, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first word and text number of every window of the words themselves."""
    at, last, owner = _places(words, window)
    return mix64(_hashed(np.concatenate([words.filling, np.zeros(window, np.uint64)]), at, last, window) ^ _PLACEHOLDER[ORDINARY]), at, owner


@dataclass
class Block:
    """Some benchmark items: their windows sorted by hash, and what fills their words."""

    items: list
    words: Canonical
    hashes: np.ndarray
    at: np.ndarray
    item: np.ndarray
    totals: np.ndarray
    filter: np.ndarray
    exact: bool  # whether some items are matched by exact windows, as they have no usable one


def make_blocks(items: list[tuple], *, window: int = WINDOW, block_windows: int = 1_000_000) -> list[Block]:
    """Blocks of consecutive items with at most `block_windows` windows each, or one item."""
    blocks, start = [], 0
    sizes = [max(len((t or "").split()), 1) for _, t in items]
    while start < len(items):
        stop, held = start, 0
        while stop < len(items) and (stop == start or held + sizes[stop] <= block_windows):
            held += sizes[stop]
            stop += 1
        part = items[start:stop]
        words = canonical_words(pa.array([t or "" for _, t in part], pa.string()))
        hashes, at, item = template_windows(words, window)
        bare = np.ones(len(part), bool)
        bare[item] = False
        plain = exact_windows(words, window)
        mine = bare[plain[2]]
        hashes, at, item = (np.concatenate([c, e[mine]]) for c, e in zip((hashes, at, item), plain, strict=True))
        owner = np.repeat(np.arange(len(part)), np.diff(words.bounds))
        totals = np.bincount(owner[np.unique(at)], minlength=len(part))
        order = np.argsort(hashes, kind="stable")
        seen = np.zeros(1 << 22, bool)
        seen[(hashes >> np.uint64(42)).astype(np.int64)] = True
        blocks.append(Block([i for i, _ in part], words, hashes[order], at[order], item[order], totals, seen, bool(mine.any())))
        start = stop
    return blocks


def slot_counts(hits: list[tuple[int, int]], item: int, words: Canonical, block: Block, window: int) -> tuple[int, int, int]:
    """Slots that the hits (word of the document, word of the item) cover, those filled consistently, those changed."""
    fillings: dict[int, dict[int, int]] = defaultdict(lambda: defaultdict(int))
    opening: dict[int, dict[int, int]] = defaultdict(lambda: defaultdict(int))
    last = int(block.words.bounds[item + 1])
    for a, b in {(a + k, b + k) for a, b in hits for k in range(min(window, last - b))}:
        if block.words.kind[b] != ORDINARY:
            fillings[int(block.words.filling[b])][int(words.filling[a])] += 1
        elif block.words.opener[b] or words.opener[a]:
            opening[int(block.words.filling[b])][int(words.filling[a])] += 1
    for own, v in opening.items():
        if own in fillings or len(v) > 1 or own not in v:  # a name, as it was changed or is one elsewhere in the item
            for other, n in v.items():
                fillings[own][other] += n
    slots = sum(sum(v.values()) for v in fillings.values())
    steady = sum(max(v.values()) for v in fillings.values())
    return slots, steady, sum(n for own, v in fillings.items() for other, n in v.items() if other != own)


def occurrences(hits: list[tuple[int, int]], least: float, length: int, window: int) -> Iterator[list[tuple[int, int]]]:
    """Groups of hits that lie in one place: whose offsets differ by nothing, a window, half an item or an item at most."""
    hits = sorted(hits, key=lambda h: (h[0] - h[1], h))
    offsets = [a - b for a, b in hits]
    for slack in sorted({0, min(window, length), length // 2, length}):
        stop, held = 0, defaultdict(int)
        for start in range(len(hits)):
            grown = False
            while stop < len(hits) and offsets[stop] <= offsets[start] + slack:
                held[hits[stop][1]] += 1
                stop += 1
                grown = True
            if grown and len(held) >= least:
                yield hits[start:stop]
            b = hits[start][1]
            held[b] -= 1
            if not held[b]:
                del held[b]


def find_items(texts: pa.Array, block: Block, *, window: int = WINDOW, containment: float = CONTAINMENT, consistency: float = CONSISTENCY, seen: dict | None = None) -> list[tuple]:
    """(text number, item number, windows found, windows of the item, slots, consistent slots, changed slots)."""
    words = canonical_words(texts, seen)
    hashes, at, text = template_windows(words, window, 0)  # the items' windows decide which are usable
    if block.exact:
        hashes, at, text = (np.concatenate(c) for c in zip((hashes, at, text), exact_windows(words, window), strict=True))
    likely = np.flatnonzero(block.filter[(hashes >> np.uint64(42)).astype(np.int64)])
    left = np.searchsorted(block.hashes, hashes[likely], "left")
    count = np.searchsorted(block.hashes, hashes[likely], "right") - left
    likely, left, count = likely[count > 0], left[count > 0], count[count > 0]
    pairs: dict[tuple[int, int], list[tuple[int, int]]] = defaultdict(list)
    for w, first, n in zip(likely.tolist(), left.tolist(), count.tolist(), strict=True):
        for k in range(first, first + n):
            pairs[int(text[w]), int(block.item[k])].append((int(at[w]), int(block.at[k])))
    out = []
    for (number, item), hits in sorted(pairs.items()):
        total = int(block.totals[item])
        found = len({b for _, b in hits})
        if found < containment * total:
            continue
        slots, steady, changed = slot_counts(hits, item, words, block, window)
        if steady < consistency * slots:  # perhaps several occurrences whose fillings differ
            best = None
            for own in occurrences(hits, containment * total, int(np.diff(block.words.bounds)[item]), window):
                slots, steady, changed = slot_counts(own, item, words, block, window)
                found = len({b for _, b in own})
                if steady >= consistency * slots and (best is None or (found, -changed) > (best[0], -best[3])):
                    best = (found, slots, steady, changed)
            if best is None:
                continue
            found, slots, steady, changed = best
        out.append((number, item, found, total, slots, steady, changed))
    return out


def _items(benchmark: DataFrame) -> list[tuple]:
    """The benchmark's rows; it is the stated query set, and is worked through in blocks of bounded size."""
    return [(r["item_id"], r["text"]) for r in benchmark.select("item_id", "text").orderBy("item_id", "text").toLocalIterator()]


def contamination(docs: DataFrame, benchmark: DataFrame, *, block_windows: int = 1_000_000, **options) -> DataFrame:
    """One row for each document and benchmark item that it holds."""
    schema = "doc_id long, item_id long, windows_found long, item_windows long, slots long, consistent_slots long, changed_slots long"

    def search(block: Block):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen: dict = {}
            for part in chunks(batches, limit=1 << 20):
                rows = find_items(part.column(1), block, seen=seen, **options)
                if rows:
                    ids = part.column(0).take(pa.array([r[0] for r in rows]))
                    yield pa.RecordBatch.from_arrays([ids, pa.array([block.items[r[1]] for r in rows], pa.int64()), *(pa.array([r[k] for r in rows], pa.int64()) for k in range(2, 7))], [x.split()[0] for x in schema.split(", ")])

        return run

    ship_package(docs.sparkSession)
    own = docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text"))
    found = [own.mapInArrow(search(block), schema) for block in make_blocks(_items(benchmark), block_windows=block_windows)]
    if not found:
        return docs.sparkSession.createDataFrame([], schema)
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, *, block_windows: int = 1_000_000, **options) -> DataFrame:
    """The rows of `docs`, all columns, that hold no benchmark item."""

    def clean(block: Block):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen: dict = {}
            for part in chunks(batches, limit=1 << 20):
                keep = np.ones(part.num_rows, bool)
                keep[[r[0] for r in find_items(part.column(part.schema.get_field_index("text")), block, seen=seen, **options)]] = False
                yield part.filter(pa.array(keep))

        return run

    ship_package(docs.sparkSession)
    for block in make_blocks(_items(benchmark), block_windows=block_windows):
        docs = docs.mapInArrow(clean(block), docs.schema)
    return docs
