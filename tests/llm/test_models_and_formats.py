import hashlib
import zlib

import numpy as np
import pyarrow as pa
import pytest
from cubefactor.llm import bpe, decontaminate, media, packing, quality, toxicity, warc
from hypothesis import given, settings
from hypothesis import strategies as st


# -- quality and toxicity ----------------------------------------------------------------------------


def test_trees_learn_a_threshold_and_flatten():
    rng = np.random.default_rng(0)
    x = rng.random((600, 3))
    y = ((x[:, 0] > 0.4) & (x[:, 2] < 0.7)).astype(float)
    model = quality.fit_trees(x, y, trees=30)
    fresh = rng.random((400, 3))
    assert ((model.score(fresh) > 0.5) == ((fresh[:, 0] > 0.4) & (fresh[:, 2] < 0.7))).mean() > 0.95
    assert np.allclose(quality.fit_trees(x[:0], y[:0]).score(fresh), 0.5)
    assert (quality.fit_trees(x, np.ones(600)).score(fresh) > 0.99).all()


def held_out_accuracy(rows, column):
    held = [r for r in rows if r["held_out"]]
    return sum(r["predicted"] == r[column] for r in held) / len(held)


@pytest.mark.parametrize(("run", "column", "least"), [(quality.classify_quality, "quality", 0.97), (toxicity.classify_toxicity, "toxic", 0.95)])
def test_held_out_accuracy(spark, run, column, least):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    got = run(docs, labels)
    assert got.count() == docs.count()
    rows = got.join(labels, "doc_id").collect()
    assert held_out_accuracy(rows, column) >= least
    assert all(0 <= r["score"] <= 1 for r in rows)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % (5 if column == "quality" else 3) == (0 if column == "quality" else 1)) for r in rows)


@pytest.mark.parametrize("run", [quality.classify_quality, toxicity.classify_toxicity])
def test_odd_rows_and_absent_labels(docs_of, spark, odd_rows, run):
    labels = spark.createDataFrame([(None, None, None), (4, 1, 0), (4, 1, 0)], "doc_id long, quality int, toxic int")
    assert run(docs_of(odd_rows), labels).count() == len(odd_rows)
    assert run(docs_of([]), labels).count() == 0
    assert run(docs_of(odd_rows), labels.limit(0)).count() == len(odd_rows)


def test_quality_stage_keeps_rows_whole(docs_of, spark, odd_rows):
    labels = spark.createDataFrame([(4, 1, 0)], "doc_id long, quality int, toxic int")
    kept = quality.keep_quality(docs_of(odd_rows), labels)
    assert kept.columns == docs_of([]).columns and kept.count() == len(odd_rows)


def test_kernel_tolerates_gaps_and_inserted_letters():
    same, gapped, other = toxicity.kernel(["moron"], ["moron", "morxon", "table"])[0]
    assert same == pytest.approx(1) and same > gapped > 0.4 > other
    clean = ["the weather is fine today"] * 40
    machine = toxicity.fit_machine(clean + [f"you are a moron number {k}" for k in range(30)], [0] * 40 + [1] * 30)
    score = lambda t: machine.score(toxicity.text_evidence(pa.array([t]), machine, {}))[0]
    assert score("what a m-o.r*on") > 0.7 > score("the weather is fine") and 0 <= score("") <= 1


# -- packing -----------------------------------------------------------------------------------------


def tokens(texts):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(packing.tokenizer_path())
    return [np.array([*e.ids, packing.END_ID], np.uint32) for e in tokenizer.encode_batch(texts, add_special_tokens=False)]


def test_packing_is_an_exact_partition(docs_of, odd_rows):
    got = packing.pack(docs_of(odd_rows)).collect()
    ids = dict(zip([i for i, _ in odd_rows], tokens([t or "" for _, t in odd_rows])))
    total = sum(len(x) for x in tokens([t or "" for _, t in odd_rows]))
    assert sum(r["length"] for r in got) == total
    sequences = {}
    for r in got:
        own = ids[r["doc_id"]]
        assert r["doc_tokens"] == len(own)
        assert zlib.crc32(own[r["start"] : r["start"] + r["length"]].astype("<u4").tobytes()) == r["ids_crc32"]
        sequences.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert sorted(sequences) == list(range(len(sequences)))
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= packing.CAPACITY
    assert packing.pack(docs_of([])).count() == 0


def test_column_generation_reaches_the_bound():
    rng = np.random.default_rng(2)
    histogram = {int(k): int(v) for k, v in zip(*np.unique(rng.integers(1, 128, 5000), return_counts=True))}
    runs = packing.plan_patterns(histogram, 128)
    used = {}
    for times, stems in runs:
        assert sum(s * n for s, n in stems) <= 128
        for s, n in stems:
            used[s] = used.get(s, 0) + times * n
    assert used == histogram
    assert sum(t for t, _ in runs) <= -(-sum(k * v for k, v in histogram.items()) // 128) * 1.03 + 1


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(st.one_of(st.sampled_from("abcDEFéÜß.,!?'<|>09 \n\t%"), st.characters(blacklist_categories=["Cs"])), max_size=40), min_size=1, max_size=5))
def test_ids_equal_the_library(texts):
    ids, offsets = packing.token_ids(pa.array(texts, pa.string()), packing.tokenizer_path())
    for got, expected in zip((ids[a:b] for a, b in zip(offsets, offsets[1:])), tokens(texts), strict=True):
        assert got.tolist() == expected.tolist()


def test_special_strings_go_to_the_library():
    data = np.frombuffer(b"plain <|endoftext|> it's", np.uint8)
    _, starts, ends, library, _ = bpe.simple_spans(data, np.array([0, len(data)]))
    assert [bytes(data[a:b]) for a, b, x in zip(starts, ends, library) if x] == [b"<|endoftext|>", b"it's"]


# -- decontamination ---------------------------------------------------------------------------------

QUESTION = "Anna buys 12 apples and 7 pears at the old market near the river. How many pieces of fruit does Anna carry home?"


def test_reparameterised_questions_are_found(docs_of, spark):
    changed = QUESTION.replace("12", "35").replace("7", "4").replace("Anna", "Lena")
    mixed = QUESTION.replace("12", "35", 1).replace("does Anna", "does Lena")
    rows = [(1, "Some words before. " + QUESTION + " And more."), (2, "intro text here. " + changed), (3, "nothing of the kind is written in this one"), (4, None), (5, ""), (6, "so " + mixed)]
    benchmark = spark.createDataFrame([(7, QUESTION), (8, None), (9, ""), (None, "tiny")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r for r in decontaminate.contamination(docs_of(rows), benchmark).collect()}
    assert {(1, 7), (2, 7)} <= set(got) and not any(k[0] in (3, 4, 5) for k in got)
    assert got[2, 7]["changed_slots"] > 0 and got[1, 7]["changed_slots"] == 0
    kept = decontaminate.drop_contaminated(docs_of(rows), benchmark)
    assert {3, 4, 5} <= {r["doc_id"] for r in kept.collect()} and kept.columns == docs_of([]).columns
    assert decontaminate.contamination(docs_of(rows), benchmark.limit(0)).count() == 0


def test_blocks_give_the_same(spark):
    docs, benchmark = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "benchmark"))
    whole, parts = (sorted(map(tuple, decontaminate.contamination(docs, benchmark, block_windows=n).collect())) for n in (10**6, 300))
    assert whole == parts and whole
    texts = {r["doc_id"]: " ".join(r["text"].split()) for r in docs.collect()}
    planted = {(d, b["item_id"]) for b in benchmark.collect() for d, t in texts.items() if " ".join(b["text"].split()) in t}
    assert planted <= {r[:2] for r in whole}


# -- media -------------------------------------------------------------------------------------------


@pytest.mark.parametrize("container", ["pgm", "bmp"])
def test_media_round_trip(docs_of, odd_rows, container):
    got = media.media_features(media.media_table(docs_of(odd_rows), container)).collect()
    assert len(got) == len(odd_rows)
    expected = sorted((i is None, i, len((t or "").encode())) for i, t in odd_rows)
    assert sorted((r["doc_id"] is None, r["doc_id"], r["n_bytes"]) for r in got) == expected
    texts = {i: (t or "").encode() for i, t in odd_rows}
    for r in got:
        raw = texts[r["doc_id"]]
        padded = raw + b"\xff" * (max(-(-len(raw) // 576), 1) * 576 - len(raw))
        assert r["payload_sha256"] == hashlib.sha256(padded).hexdigest() and r["tail_crc32"] == zlib.crc32(padded[-32:]) and r["payload_bytes"] == len(padded)


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 9), st.integers(1, 9), st.integers(0, 2**32 - 1))
def test_image_codecs_and_resize(height, width, seed):
    rng = np.random.default_rng(seed)
    grey, colour = rng.integers(0, 256, (height, width), np.uint8), rng.integers(0, 256, (height, width, 3), np.uint8)
    for image in (grey, colour):
        for data in (media.encode_pnm(image), media.encode_pnm(image, plain=True), media.encode_bmp(image)):
            assert (media.decode(data) == image).all()
    big = media.area_resize(grey, 4, 5)
    fine = np.repeat(np.repeat(grey.astype(float), 4, 0), 5, 1).reshape(4, height, 5, width).mean((1, 3))
    assert np.allclose(big, fine)


def test_netpbm_bits_and_comments():
    assert (media.decode_pnm(b"P1\n# c\n3 1\n1 0 1") == [[0, 255, 0]]).all()
    assert (media.decode_pnm(b"P4\n3 1\n\xa0") == [[0, 255, 0]]).all()
    assert (media.decode_pnm(b"P5\n1 1\n65535\n\x01\x02") == [[258]]).all()


# -- archives ----------------------------------------------------------------------------------------


def test_archives_round_trip(spark):
    rows = [(1, "http://a/1", "x" * 9000 + "\r\n\r\nWARC/1.1\r\n\r\n"), (2, None, None), (3, "http://a/3", ""), (4, "http://a/4", "same é"), (5, "http://a/5", "same é"), (5, "http://a/5b", "same é"), (None, "u", "alone")]
    pages = spark.createDataFrame([(*r, "extra") for r in rows], "page_id long, url string, html string, digest string")
    got = warc.archive_round_trip(pages, segment_bytes=1000).collect()
    assert len(got) == len(rows) and all(r["complete"] for r in got)
    for r in got:
        payloads = [(h or "").encode() for i, _, h in rows if i == r["page_id"]]
        assert r["payload_digest"] in {warc.digest_of(p) for p in payloads} and r["payload_bytes"] in {len(p) for p in payloads}
        if r["record_type"] == "response":
            assert r["payload"] in payloads
    kinds = sorted((r["page_id"] or 0, r["record_type"], r["refers_to"]) for r in got if r["record_type"] == "revisit")
    assert kinds[0] == (2, "revisit", 3) and (4, "revisit", 5) in kinds and len(kinds) == 3
    assert warc.archive_round_trip(pages.limit(0)).count() == 0


def test_broken_segments_are_told(spark):
    parts = [("o1", 1, None, "response", 1, None, None, "d", b"ab"), ("o1", 2, 4, "continuation", None, None, None, "", b"cd"), ("o2", 1, None, "response", 2, None, None, "d", b"ab"), ("o2", 3, 4, "continuation", None, None, None, "", b"cd"), ("o3", 1, None, "response", 3, None, None, "d", b"ab"), ("o3", 2, 5, "continuation", None, None, None, "", b"cd")]
    got = {r["page_id"]: (bytes(r["block"]), r["complete"]) for r in warc.reassemble(spark.createDataFrame(parts, warc.PART)).collect()}
    assert got == {1: (b"abcd", True), 2: (b"abcd", False), 3: (b"abcd", False)}


@settings(max_examples=50, deadline=None)
@given(st.binary(max_size=400), st.integers(1, 50))
def test_chunked_framing(payload, size):
    assert warc.chunk_unframe(warc.chunk_frame(payload, size)) == payload
    assert warc.chunk_unframe(warc.chunk_frame(payload, size)[:-6] + b"zz") is None
