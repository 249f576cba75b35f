import hashlib
import random

import numpy as np
from cubefactor.llm import block_repeats, suffix_repeats
from hypothesis import given, settings
from hypothesis import strategies as st


def brute_bytes(rows, window):
    seen, out = set(), {}
    for doc, text in sorted({(i, t or "") for i, t in rows if i is not None}):
        data = text.encode()
        gone = np.zeros(len(data), bool)
        for s in range(len(data) - window + 1):
            part = data[s : s + window]
            if part in seen:
                gone[s : s + window] = True
            seen.add(part)
        kept = np.frombuffer(data, np.uint8)[~gone].tobytes()
        spans = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out[doc] = (len(data), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest())
    return out


def brute_words(rows, window):
    first, out = {}, {}
    for doc, text in sorted({(i, t or "") for i, t in rows if i is not None}):
        words = text.encode().split()
        gone = np.zeros(len(words), bool)
        for s in range(len(words) - window + 1):
            if first.setdefault(tuple(words[s : s + window]), doc) < doc:
                gone[s : s + window] = True
        out[doc] = (len(words), int(gone.sum()), hashlib.sha256(b" ".join(w for w, g in zip(words, gone) if not g)).hexdigest())
    return out


def test_byte_repeats_equal_brute_force(docs_of, odd_rows):
    got = suffix_repeats.byte_repeats(docs_of(odd_rows)).collect()
    assert len(got) == len(odd_rows)
    expected = brute_bytes(odd_rows, 100)
    for r in got:
        if r["doc_id"] is None:
            assert r["n_removed"] == 0
        else:
            assert (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) == expected[r["doc_id"]]
    assert sum(v[1] for v in expected.values()) > 0


def test_word_repeats_equal_brute_force(docs_of, odd_rows):
    got = block_repeats.word_repeats(docs_of(odd_rows)).collect()
    assert len(got) == len(odd_rows)
    expected = brute_words(odd_rows, 50)
    for r in got:
        if r["doc_id"] is None:
            assert r["n_removed"] == 0
        else:
            assert (r["n_words"], r["n_removed"], r["kept_sha256"]) == expected[r["doc_id"]]


def test_repeated_bytes_are_cut_and_other_columns_stay(docs_of):
    text = "".join(map(chr, np.random.default_rng(4).integers(97, 123, 300)))
    docs = docs_of([(1, text), (2, "start " + text + " end"), (3, None)])
    got = {r["doc_id"]: r for r in suffix_repeats.remove_repeats(docs).collect()}
    assert got[1]["text"] == text and got[2]["text"] == "start  end" and got[3]["text"] is None and got[2]["_at"] == "x"


def test_empty_table(docs_of):
    assert suffix_repeats.byte_repeats(docs_of([])).count() == 0
    assert block_repeats.word_repeats(docs_of([])).count() == 0


@settings(max_examples=40, deadline=None)
@given(st.lists(st.text("ab", min_size=0, max_size=60), min_size=1, max_size=6), st.integers(4, 9))
def test_maximal_repeats_cover_what_brute_force_covers(pieces, least):
    data = np.frombuffer("".join(pieces).encode(), np.uint8)
    bounds = np.concatenate([[0], np.cumsum([len(p) for p in pieces])])
    covered = np.zeros(len(data), bool)
    for length, places in suffix_repeats.maximal_repeats(data, bounds, least):
        strings = {data[p : p + length].tobytes() for p in places.tolist()}
        assert len(strings) == 1 and len(places) > 1
        for p in sorted(places.tolist())[1:]:
            covered[p : p + length] = True
    expected, seen = np.zeros(len(data), bool), set()
    for a, b in zip(bounds, bounds[1:]):
        for s in range(a, b - least + 1):
            part = data[s : s + least].tobytes()
            if part in seen:
                expected[s : s + least] = True
            seen.add(part)
    assert (covered == expected).all()


def test_interval_tree_of_a_small_array():
    # Suffixes of banana in order: a, ana, anana, banana, na, nana.
    assert sorted(suffix_repeats.interval_tree([1, 3, 0, 0, 2], 1)) == [(1, 0, 2), (2, 4, 5), (3, 1, 2)]


def test_every_phase_of_a_repeat_meets_a_block():
    for window, block in ((50, 7), (50, 10), (23, 5)):
        row, places = block_repeats.block_places(np.array([400]), window, block)
        count = (window + 1) // block - 1
        aligned = {p for p in places.tolist() if p % block == 0}
        probes = {p for p in places.tolist() if p % (block * count) < block}
        for shift in range(block * count):
            for start in range(0, 400 - window - block * count):
                met = any(p in aligned and p + shift in probes for p in range(start, start + window - block + 1) if p + shift < 390)
                assert met or start + shift + window > 390


def test_equal_windows_share_their_anchor():
    rng = np.random.default_rng(1)
    shared = rng.integers(97, 123, 150).astype(np.uint8)
    a, b = (np.concatenate([rng.integers(97, 123, n).astype(np.uint8), shared, rng.integers(97, 123, 80).astype(np.uint8)]) for n in (37, 214))

    def owners(data):
        pos, start, last = suffix_repeats.anchor_places(data, np.array([0, len(data)]))
        return {s: p - s for p, x, y in zip(pos, start, last) for s in range(x, y + 1)}

    one, two = owners(a), owners(b)
    assert len(one) == len(a) - 99
    assert all(one[37 + k] == two[214 + k] for k in range(51))


def test_repeated_rows_keep_what_has_no_earlier_copy(docs_of):
    rng = random.Random(8)
    t, u = ("".join(rng.choice("abcdefgh ") for _ in range(600)) for _ in range(2))
    rows = [(9, t), (9, t), (10, u), (11, t + u)]
    got = [(r["doc_id"], r["n_removed"], r["n_spans"]) for r in suffix_repeats.byte_repeats(docs_of(rows)).orderBy("doc_id").collect()]
    assert got == [(9, 0, 0), (9, 0, 0), (10, 0, 0), (11, 1200, 1)]
    words = " ".join(f"w{k}" for k in range(120))
    other = [(r["doc_id"], r["n_removed"]) for r in block_repeats.word_repeats(docs_of([(9, words), (9, words), (10, words)])).orderBy("doc_id").collect()]
    assert other == [(9, 0), (9, 0), (10, 120)]


def test_texts_that_share_a_doc_id_are_documents_of_their_own(docs_of):
    rng = random.Random(9)
    t, u, v = (" ".join(f"{rng.choice('abcdefgh')}{rng.randrange(99)}" for _ in range(150)) for _ in range(3))
    rows = [(7, t), (7, u + " " + t), (7, u), (7, u), (3, v), (12, v + " " + u), (None, t), (8, None), (8, "")]
    sha = lambda text: hashlib.sha256((text or "").encode()).hexdigest()
    order = sorted({(i, sha(text)) for i, text in rows if i is not None})
    numbered = [(None if i is None else order.index((i, sha(text))), text) for i, text in rows]
    for run, brute, size in ((suffix_repeats.byte_repeats, brute_bytes, 100), (block_repeats.word_repeats, brute_words, 50)):
        expected = brute(numbered, size)
        got = sorted((r["doc_id"], r["n_removed"], r["kept_sha256"]) for r in run(docs_of(rows)).where("doc_id IS NOT NULL").collect())
        assert got == sorted((i, expected[n][1], expected[n][-1]) for (i, _), (n, _) in zip(rows, numbered, strict=True) if i is not None)
        assert run(docs_of(rows)).where("doc_id IS NULL AND n_removed = 0").count() == 1
    kept = suffix_repeats.remove_repeats(docs_of(rows))
    assert kept.columns == docs_of([]).columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 3, 7, 7, 7, 7, 8, 8, 12]
    bytes_kept = {n: e[-1] for n, e in brute_bytes(numbered, 100).items()}
    assert sorted(sha(r["text"]) for r in kept.where("doc_id IS NOT NULL").collect()) == sorted(bytes_kept[n] for n, _ in numbered if n is not None)
