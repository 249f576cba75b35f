"""Decontamination of a given table against nested loops over all documents and items."""

from collections import Counter, defaultdict
from itertools import product

from cubefactor.llm import decontaminate
from cubefactor.llm.decontaminate import NAME, ORDINARY, describe


def readings(text):
    """For each canonical word: itself, what it may be read as, whether it is ordinary."""
    out, opens = [], True
    for w in (text or "").split():
        low, kind, nameable, ends = describe(w)
        if low:
            if kind == ORDINARY and nameable:
                kinds = [low, NAME] if opens else [NAME]
            else:
                kinds = [low] if kind == ORDINARY else [kind]
            out.append((low, kinds, low in kinds))
        opens = ends
    return out


def windows(words, size=5):
    for at in range(max(len(words) - size + 1, 1 if words else 0)):
        part = words[at : at + size]
        yield at, part, set(product(*(k for _, k, _ in part)))


def brute(texts, items):
    found = set()
    places = {}
    for doc, text in texts.items():
        held = defaultdict(list)
        words = readings(text)
        for at, _, codes in windows(words):
            for c in codes:
                held[c].append(at)
        places[doc] = (words, held)
    for item, text in items.items():
        words = readings(text)
        least = min(3, max(min(len(words), 5) - 1, 1)) if len(words) < 5 else 3
        usable = [(at, part, codes) for at, part, codes in windows(words) if sum(o for _, _, o in part) >= least]
        for doc, (own, held) in places.items():
            hits = {(a, at) for at, _, codes in usable for c in codes for a in held.get(c, [])}
            if not usable or len({b for _, b in hits}) < 0.5 * len(usable):
                continue
            fillings = defaultdict(Counter)
            for a, b in {(a + k, b + k) for a, b in hits for k in range(min(5, len(words) - b))}:
                if not words[b][2]:
                    fillings[words[b][0]][own[a][0]] += 1
            slots = sum(sum(v.values()) for v in fillings.values())
            if sum(max(v.values()) for v in fillings.values()) >= 0.8 * slots:
                found.add((doc, item))
    return found


def test_pairs_equal_nested_loops(spark, sf_dir):
    docs, benchmark = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    expected = brute({r["doc_id"]: r["text"] for r in docs.collect()}, {r["item_id"]: r["text"] for r in benchmark.collect()})
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contamination(docs, benchmark).collect()}
    assert expected and got == expected
    kept = {r["doc_id"] for r in decontaminate.drop_contaminated(docs, benchmark).collect()}
    assert kept == {r["doc_id"] for r in docs.collect()} - {d for d, _ in expected}
