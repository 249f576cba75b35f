"""Cases in which an operator once did less than the whole job."""

import corpus_pipeline
import pytest
from cubefactor.llm import decontaminate, document_dedup, line_dedup, simhash, warc

LINE = "the old miller carried seven heavy sacks of grain across the wooden bridge before the rain came"


def test_short_lines_that_differ_in_a_word_are_linked(docs_of):
    changed = LINE.replace("seven", "eight")
    assert len(LINE) == 95
    got = {r["doc_id"]: r["removed_lines"] for r in line_dedup.line_decisions(docs_of([(1, LINE), (2, changed)])).collect()}
    assert got == {1: [], 2: [0]}


def shingle_set(text):
    words = (text or "").lower().split()
    return {tuple(words[k : k + 5]) for k in range(max(len(words) - 4, 1))}


def similar(a, b):
    return min(len(a), len(b)) >= 0.8 * max(len(a), len(b)) and len(a & b) >= 0.8 * len(a | b)


def test_pipeline_drops_near_copies_at_the_stated_similarity(spark, docs_of):
    words = [f"w{k}" for k in range(200)]
    near, far = list(words), list(words)
    for k in (20, 60, 100):
        near[k] = "x"
    for k in range(10, 190, 20):
        far[k] = "x"
    rows = [(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(far)), (None, " ".join(words)), (4, None), (5, " ")]
    assert similar(shingle_set(rows[0][1]), shingle_set(rows[1][1])) and not similar(shingle_set(rows[0][1]), shingle_set(rows[2][1]))
    kept = corpus_pipeline.near_duplicates(spark, docs_of(rows), "")
    assert sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 1, 3, 4] and kept.columns == docs_of([]).columns


def test_groups_equal_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    sets = {r["doc_id"]: shingle_set(r["text"]) for r in docs.collect()}
    ids = sorted(sets)
    root = {i: i for i in ids}
    pairs = 0
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            if similar(sets[a], sets[b]):
                pairs += 1
                old, new = max(root[a], root[b]), min(root[a], root[b])
                root = {i: new if r == old else r for i, r in root.items()}
    assert pairs > 20
    kept = document_dedup.keep_one(docs)
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(set(root.values()))


def found_in(docs_of, spark, texts, items):
    benchmark = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    return {(r["doc_id"], r["item_id"]): r for r in decontaminate.contamination(docs_of(list(enumerate(texts))), benchmark).collect()}


QUESTION = "At noon Anna buys 12 apples and 7 pears at the old market near the river. How many pieces of fruit does Anna carry home?"


def test_occurrences_with_different_fillings_are_found(docs_of, spark):
    asked = [QUESTION.replace("12", str(20 + k)).replace("7", str(40 + k)).replace("Anna", name) for k, name in enumerate(["Lena", "Olga", "Rita"])]
    chance = " ".join(f"he buys {k} apples and {k + 1} pears at the shop." for k in range(9))
    got = found_in(docs_of, spark, [f"{QUESTION} {asked[0]}", " so ".join(asked), f"{chance} {QUESTION} {chance}", chance], [QUESTION])
    assert set(got) == {(0, 0), (1, 0), (2, 0)}
    assert got[0, 0]["changed_slots"] == got[2, 0]["changed_slots"] == 0 < got[1, 0]["changed_slots"]


def test_names_that_open_sentences_may_change(docs_of, spark):
    item = "Tom has 3 apples. Ann has 5 pears. Joe has 2 figs."
    texts = [item, "so " + item.replace("Tom", "Eva").replace("Ann", "Ida").replace("Joe", "Leo").replace("3", "8"), "some Eva has 8 apples. They run away."]
    got = found_in(docs_of, spark, texts, [item])
    assert set(got) == {(0, 0), (1, 0)}
    assert got[0, 0]["changed_slots"] == 0 and got[1, 0]["changed_slots"] == 4


def test_items_without_ordinary_words_are_found_where_copied(docs_of, spark):
    item = "12 kg 7 lb 30 cm 4 ft 9 min"
    got = found_in(docs_of, spark, [f"it says {item} here and goes on", "it says 1 kg 2 lb 3 cm 5 ft 6 min here", "12 kg"], [item, QUESTION])
    assert set(got) == {(0, 0)}


def test_repeated_pages_stay_separate_records(spark):
    long = "x" * 9000
    rows = [(1, "http://a/1", long), (1, "http://a/1", long), (1, "http://a/1", long), (2, "http://a/2", "y"), (None, "u", "z" * 5000), (None, "u", "z" * 5000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for least_bytes, responses in ((0, 3), (1 << 20, 6)):
        got = warc.archive_round_trip(pages, segment_bytes=1000, least_bytes=least_bytes).collect()
        assert sorted((r["page_id"] or 0, r["payload_bytes"]) for r in got) == sorted((i or 0, len(h)) for i, _, h in rows)
        assert all(r["complete"] for r in got) and sum(r["record_type"] == "response" for r in got) == responses
    keys = [r["key"] for r in warc.assign_responses(pages).collect()]
    assert len(set(keys)) == len(rows)


@pytest.mark.parametrize("keep", [simhash.keep_first, document_dedup.keep_one])
def test_one_row_of_each_group_stays(docs_of, keep):
    text, other = " ".join(f"w{k}" for k in range(60)), " ".join(f"v{k}" for k in range(60))
    rows = [(1, text), (1, text), (1, text.upper()), (2, text), (3, other), (3, other), (2, other + " x"), (None, text), (None, text)]
    kept = keep(docs_of(rows)).collect()
    assert sorted((r["doc_id"] or 0) for r in kept) == [0, 0, 1, 2] and {r["text"] for r in kept if r["doc_id"] == 2} == {other + " x"}
