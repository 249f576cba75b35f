import numpy as np
import xxhash
import pytest
from cubefactor.llm import components, document_dedup, line_dedup, simhash
from hypothesis import given, settings
from hypothesis import strategies as st


def find_all(n, links):
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        parent[max(find(a), find(b))] = min(find(a), find(b))
    return [find(x) for x in range(n)]


def jaccard(a, b):
    return len(a & b) / max(len(a | b), 1)


def plain_fingerprint(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    n = max(len(words) - 3, 1)
    hashes = [xxhash.xxh64_intdigest(b" ".join(words[k : k + 4]), 42) for k in range(n)]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > n)


def test_fingerprints_and_components(docs_of, odd_rows):
    got = simhash.near_duplicates(docs_of(odd_rows)).collect()
    assert len(got) == len(odd_rows)
    prints = [plain_fingerprint(t) for _, t in odd_rows]
    assert sorted(r["fingerprint"] for r in got) == sorted(f"{p:016x}" for p in prints)
    n = len(odd_rows)
    roots = find_all(n, [(a, b) for a in range(n) for b in range(a) if (prints[a] ^ prints[b]).bit_count() <= 4])
    least = {}
    for (i, _), root in zip(odd_rows, roots):
        if i is not None:
            least[root] = min(least.get(root, i), i)
    expected = sorted((i, least[r]) for (i, _), r in zip(odd_rows, roots) if i is not None)
    assert sorted((r["doc_id"], r["component_id"]) for r in got if r["doc_id"] is not None) == expected


def test_one_document_of_each_group_stays(docs_of, odd_rows):
    rows = [r for r in odd_rows if r[0] is not None]
    docs = docs_of(rows)
    groups = simhash.near_duplicates(docs)
    kept = simhash.keep_first(docs)
    assert kept.columns == docs.columns
    assert {r["doc_id"] for r in kept.collect()} == {r["component_id"] for r in groups.collect()}
    assert simhash.keep_first(docs_of([])).count() == 0


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 2**64 - 1), min_size=2, max_size=12), st.lists(st.integers(0, 63), max_size=120))
def test_pigeonring_loses_no_link(seeds, flips):
    values = list(seeds)
    for k, bit in enumerate(flips):
        values.append(values[k % len(values)] ^ (1 << bit))
    fp = np.unique(np.array(values, np.uint64))
    import pyarrow as pa

    entries = list(simhash._entries(4)(iter([pa.RecordBatch.from_arrays([pa.array(fp.view(np.int64))], ["fp"])])))
    key, who, probe = (np.concatenate([e.column(k).to_numpy(zero_copy_only=False) for e in entries]) for k in range(3))
    low, high = simhash.link_entries(key, who, probe, 4)
    at = {v: k for k, v in enumerate(fp.view(np.int64).tolist())}
    near = [(a, b) for a in range(len(fp)) for b in range(a) if (int(fp[a]) ^ int(fp[b])).bit_count() <= 4]
    assert find_all(len(fp), near) == find_all(len(fp), [(at[a], at[b]) for a, b in zip(low.tolist(), high.tolist())])


def test_components_of_chains_and_hubs(spark):
    links = [(k, k + 1) for k in range(40)] + [(100, 100 + k) for k in range(1, 30)] + [(7, 7), (200, 199)]
    frame = spark.createDataFrame(links, "lo long, hi long").repartition(7)
    got = {r["node"]: r["root"] for r in components.connected_components(frame).collect()}
    assert got == {k: 0 for k in range(1, 41)} | {100 + k: 100 for k in range(1, 30)} | {200: 199}


def test_lines_equal_brute_force(docs_of):
    line = "the quick brown fox jumps over the lazy dog and runs far away into the deep dark forest tonight"
    other = "completely different words are written here so that nothing at all can be taken for the same line"
    rows = [(1, f"{line}\n{other}\n\nshort"), (2, f"{line.replace('tonight', 'tonite')}\nShort \nnew text"), (3, None), (4, ""), (5, f"{other}\n{other.upper()}"), (6, "\n\n"), (None, line)]
    docs = docs_of(rows)
    got = {r["doc_id"]: (r["n_lines"], r["removed_lines"]) for r in line_dedup.line_decisions(docs).collect()}
    assert got[1] == (4, []) and got[2] == (3, [0, 1]) and got[3] == (0, []) and got[4] == (0, []) and got[5] == (2, [0, 1]) and got[6] == (3, []) and got[None] == (1, [])
    texts = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(docs).collect()}
    assert texts[2] == "new text" and texts[3] is None and texts[5] == "" and texts[6] == "\n\n" and texts[1] == rows[0][1]
    assert line_dedup.dedup_lines(docs_of([])).count() == 0


def test_bands_find_pairs_at_the_threshold():
    rng = np.random.default_rng(5)
    alphabet = list("abcdefghijklmnopqrstuvwxyz ")
    found = total = 0
    for _ in range(150):
        line = "".join(rng.choice(alphabet, 300))
        at = int(rng.integers(0, 280))
        edited = line[:at] + "".join(rng.choice(alphabet, 20)) + line[at + 20 :]
        code, bounds = line_dedup.shingle_codes([line, edited])
        if jaccard(set(code[: bounds[1]].tolist()), set(code[bounds[1] :].tolist())) >= 0.8:
            total += 1
            keys = line_dedup.band_keys([line, edited])
            found += bool((keys[0] == keys[1]).any())
    assert total > 50 and found >= 0.95 * total


def test_a_dense_key_is_linked_as_a_whole():
    import pyarrow as pa

    rng = np.random.default_rng(4)
    bits = np.uint64(1) << rng.integers(0, 64, (3000, 3)).astype(np.uint64)
    fp = np.unique(np.uint64(0x0123456789ABCDEF) ^ np.bitwise_xor.reduce(bits, axis=1))
    entries = list(simhash._entries(4)(iter([pa.RecordBatch.from_arrays([pa.array(fp.view(np.int64))], ["fp"])])))
    key, who, probe = (np.concatenate([e.column(k).to_numpy(zero_copy_only=False) for e in entries]) for k in range(3))
    low, high = simhash.link_entries(key, who, probe, 4)
    at = {v: k for k, v in enumerate(fp.view(np.int64).tolist())}
    near = [(a, b) for a in range(len(fp)) for b in np.flatnonzero(np.bitwise_count(fp[:a] ^ fp[a]) <= 4).tolist()]
    assert len(low) < len(fp) and find_all(len(fp), near) == find_all(len(fp), [(at[a], at[b]) for a, b in zip(low.tolist(), high.tolist())])


@settings(max_examples=25, deadline=None)
@given(st.integers(2, 40), st.integers(1, 4), st.integers(0, 2**32 - 1))
def test_buckets_verify_as_brute_force(count, buckets, seed):
    rng = np.random.default_rng(seed)
    base = [rng.integers(0, 2**63, 30) for _ in range(4)]
    codes = []
    for k in range(count):
        own = base[k % 4].copy()
        own[: int(rng.integers(0, 5))] = rng.integers(0, 2**63)
        codes.append(own.astype(np.uint64))
    sets = [set(c.tolist()) for c in codes]
    bucket = np.sort(rng.integers(0, buckets, count))
    near = [(a, b) for a in range(count) for b in range(a) if bucket[a] == bucket[b] and jaccard(sets[a], sets[b]) >= 0.8]
    bounds = np.concatenate([[0], np.cumsum([len(c) for c in codes])])
    got = line_dedup.set_links(bucket, np.arange(count), np.concatenate(codes), bounds, 0.8)
    assert find_all(count, near) == find_all(count, got) and len(got) < count


def test_a_bucket_of_many_lines_stays_within_its_memory():
    """20,000 similar lines meet in blocks; each bucket holds at most `BUCKET_LINES`, every pair shares one."""
    n = 20_000
    line, key = np.arange(1, n + 1).astype(np.uint64), np.full(n, 7, np.uint64)
    bucket, member = line_dedup.verification_buckets(*line_dedup.shared(key, line), np.full(n, 100, np.uint32))
    sizes = np.unique(bucket, return_counts=True)[1]
    assert sizes.max() <= line_dedup.BUCKET_LINES and len(member) <= 10 * n
    together = np.zeros((n // 100, n // 100), bool)
    for b in np.unique(bucket):
        mine = np.unique((member[bucket == b] - 1) // 100).astype(int)
        together[np.ix_(mine, mine)] = True
    assert together.all()


def test_large_bucket_of_similar_lines_is_one_component():
    import tracemalloc

    rng = np.random.default_rng(3)
    base = "it is said that the old house by the river was built for a captain who never came home again"
    lines = [base.replace("captain", "".join(rng.choice(list("abcdefgh"), 7))) for _ in range(4000)]
    code, bounds = line_dedup.shingle_codes(lines)
    tracemalloc.start()
    links = line_dedup.set_links(np.zeros(4000, np.int64), np.arange(4000), code, bounds, 0.8)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(links) == 3999 and peak < 120 << 20


def test_lines_of_a_table_equal_all_pairs(spark):
    """Components over sf0.001 against the exact similarity of all pairs of its distinct lines."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    places, first = {}, {}
    for r in docs.collect():
        for number, line in enumerate((r["text"] or "").split("\n")):
            plain = line_dedup.canonical(line)
            if plain:
                places.setdefault(plain, []).append((r["doc_id"], number))
    lines = sorted(places)
    sets = [{x[k : k + 5] for k in range(max(len(x) - 4, 1))} for x in lines]
    order = sorted(range(len(lines)), key=lambda k: len(sets[k]))
    near = []
    for n, a in enumerate(order):
        for b in order[n + 1 :]:
            if len(sets[b]) * 0.8 > len(sets[a]):
                break
            if jaccard(sets[a], sets[b]) >= 0.8:
                near.append((a, b))
    roots = find_all(len(lines), near)
    for k, line in enumerate(lines):
        first[roots[k]] = min(first.get(roots[k], (1 << 60, 0)), min(places[line]))
    gone = {p for k, line in enumerate(lines) for p in places[line] if p != first[roots[k]]}
    got = {(r["doc_id"], n) for r in line_dedup.line_decisions(docs).collect() for n in r["removed_lines"]}
    assert len(near) > 5 and got <= gone and len(got) >= 0.99 * len(gone)


def test_repeated_rows_and_shared_ids(docs_of):
    text = "a line that stands in two equal rows and nowhere else in this table"
    rows = [(9, text), (9, text), (10, "x y z\n" + text), (9, "another text of the same number\nsecond line"), (9, "second line")]
    got = sorted((r["doc_id"], r["n_lines"], tuple(r["removed_lines"])) for r in line_dedup.line_decisions(docs_of(rows)).collect())
    assert got.count((9, 1, ())) >= 2 and (10, 2, (1,)) in got
    assert sum(len(r[2]) for r in got) == 2


@pytest.mark.parametrize(("common", "one", "two"), [(80, 10, 10), (80, 0, 20), (8, 1, 1), (4, 0, 1)])
def test_similar_documents_meet_by_their_fingerprints(common, one, two):
    rng, n = np.random.default_rng(5), 1000
    sets = []
    for _ in range(n):
        c = rng.integers(0, 2**44, common + one + two).astype(np.uint64)
        sets += [c[: common + one], np.concatenate([c[:common], c[common + one :]])]
    bounds = np.concatenate([[0], np.cumsum([len(s) for s in sets])])
    prints = document_dedup.document_prints(np.concatenate(sets), bounds)
    hashes = document_dedup.mix64(sets[0] * document_dedup._ODD + np.uint64(3))
    assert int(prints[0, 2]) == sum(1 << b for b in range(64) if 2 * sum(int(h) >> b & 1 for h in hashes) > len(hashes))
    turned = np.roll(prints.view(np.uint8), -1, axis=1).view("<u8")
    met = np.zeros((2, n), bool)
    for form in [prints, turned] if common + max(one, two) <= document_dedup.FEW else [prints]:
        key, chain = (c.reshape(2 * n, document_dedup.SEGMENTS, -1) for c in document_dedup.segment_entries(form))
        for k, other in enumerate((key[1::2], np.roll(key[1::2], 1, axis=0))):
            far = np.roll(chain[1::2], k, axis=0)
            near = document_dedup.chains_within((chain[::2] ^ far).reshape(-1, 2)).reshape(n, -1)
            met[k] |= ((key[::2] == other)[:, :, 0] & near).any(1)
    assert met[0].sum() >= 0.998 * n and met[1].sum() <= 0.002 * n


def test_all_candidates_of_the_pipeline_come_from_fingerprints(docs_of):
    rows = [(k, " ".join(f"w{j}" for j in range(100) if j != 50 + k)) for k in range(2)]
    assert document_dedup.keep_one(docs_of(rows)).count() == 1
    assert not {"signature", "meeting"} & set(vars(document_dedup))
