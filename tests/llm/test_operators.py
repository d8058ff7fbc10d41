"""Small tests of the operators against brute force, round trips and held-out accuracy."""

import hashlib
import random
import struct
import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from packflow.llm import bm25, classify, gbdt, pii, quality, records, sentencepiece_bpe, simhash, suffix, tiff, toxicity, warc
from packflow.llm.common import shared_dir

SCHEMA = "doc_id long, text string, score double, batch long"
SENTENCES = ["The quick brown fox jumps over the lazy dog near the old river bank today.", "Another line of text that is long enough to be shared between documents, surely it is.", "Short."]


def odd_rows():
    """Nulls, empties, ties, repeated rows, very long texts, and extra columns with clashing names."""
    r = random.Random(5)
    words = ["alpha", "beta", "gamma", "delta", "é", "日本", "you", "idiot", "!!!", "x1", "and"]
    made = [(k, " ".join(r.choice(words) for _ in range(r.randint(0, 80))), 0.5, k) for k in range(40)]
    made += [(100 + k, SENTENCES[k % 3] * (k % 4), None, None) for k in range(12)]
    made += [(200, None, None, None), (201, "", None, 1), (202, "   \n\t ", 1.0, 1), (None, "no id here " * 9, None, None), (None, None, None, None)]
    made += [(203, "tie " * 30, 1.0, 1), (204, "tie " * 30, 1.0, 1), (204, "tie " * 30, 1.0, 1), (205, "long " * 20_000, None, None), (206, "a" * 50_000, None, None)]
    return made


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(odd_rows(), SCHEMA).repartition(4)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# -- TIFF ---------------------------------------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(st.binary(min_size=1, max_size=700), st.sampled_from([None, 1, 5, 8, 32773]), st.sampled_from([1, 2]), st.sampled_from([0, 16]), st.integers(1, 9))
def test_tiff_round_trip(data, compression, predictor, tile, page_rows):
    payload = tiff.padded_payload(data)
    media = tiff.encode_tiff(payload, compression=compression, predictor=predictor, tile=tile, strip_rows=3, page_rows=page_rows)
    assert b"".join(p.samples.tobytes() for p in tiff.read_pages(media)) == payload


def test_damaged_tiff_gives_error_rows_and_never_a_crash(spark):
    """Every kind of damage to pages of every compression: a row with samples or one with an error."""
    r = random.Random(11)
    whole = [tiff.encode_tiff(tiff.padded_payload(bytes(r.choices(b"abcz", k=900))), compression=c, page_rows=6, strip_rows=3, tile=t) for c in (1, 5, 8, 32773) for t in (0, 16)]
    rows = [(0, None), (1, b""), (2, b"II*\0"), (3, b"II*\0" + b"\xff" * 40)]
    for n in range(600):
        bad = bytearray(r.choice(whole))
        for _ in range(r.randint(1, 6)):
            bad[r.randrange(len(bad))] = r.choice((0, 255, r.randrange(256)))
        rows.append((10 + n, bytes(bad[: r.choice((len(bad), len(bad), r.randrange(8, len(bad))))])))
    first_code = bytearray(tiff.encode_tiff(bytes(64), compression=5))
    first_code[9] = 0xFF  # the first LZW code is past the table
    no_width = bytearray(tiff.encode_tiff(bytes(64), compression=1))
    at = no_width.index(struct.pack("<HHI", 256, 4, 1)) + 8
    huge = bytearray(no_width)
    no_width[at : at + 4], huge[at : at + 4] = bytes(4), b"\xff\xff\xff\x7f"
    rows += [(5000, bytes(first_code)), (5001, bytes(no_width)), (5002, bytes(huge))]
    df = spark.createDataFrame(rows, "id long, media binary").repartition(4)
    got = tiff.tiff_pages(df, "id", "media").collect()
    assert {x.id for x in got} == {k for k, m in rows if m is not None}
    assert all((x.error is None) == (x.samples is not None) for x in got)
    assert all(x.error for x in got if x.id in (1, 2, 3, 5000, 5001, 5002))
    media = spark.createDataFrame([(1, None, None), (2, 3, whole[0])], "doc_id long, n_bytes long, media binary")
    digests = {x.doc_id: x for x in tiff.media_digest(media).collect()}
    assert digests[1].payload_sha256 is None and digests[2].payload_bytes == 960


def test_lzw_and_packbits_on_long_input():
    data = bytes(random.Random(1).choices(b"abc ", k=60_000)) + b"z" * 5000
    assert tiff.lzw_decode(tiff.lzw_encode(data)) == data
    assert tiff.packbits_decode(tiff.packbits_encode(data), len(data)) == data


def test_tiff_big_endian_and_errors(spark):
    body = bytes(range(64))
    ifd = struct.pack(">H", 8) + b"".join(struct.pack(">HHI", *f) for f in ((256, 4, 1), (257, 4, 1), (258, 3, 1), (259, 3, 1), (273, 4, 1), (277, 3, 1), (278, 4, 1), (279, 4, 1)))
    vals = [64, 1, 8 << 16, 1 << 16, 8, 1 << 16, 1, 64]
    ifd = struct.pack(">H", 8) + b"".join(struct.pack(">HHII", t, k, 1, v) for (t, k), v in zip(((256, 4), (257, 4), (258, 3), (259, 3), (273, 4), (277, 3), (278, 4), (279, 4)), vals, strict=True))
    media = b"MM\0*" + struct.pack(">I", 72) + body + ifd + b"\0\0\0\0"
    assert next(tiff.read_pages(media)).samples.tobytes() == body
    df = spark.createDataFrame([(1, bytearray(media)), (2, bytearray(b"rubbish")), (3, None), (4, bytearray(media[:-30]))], "id long, m binary")
    got = {r.id: (r.page, r.error is None) for r in tiff.tiff_pages(df, "id", "m").collect()}
    assert got[1] == (0, True) and got[2] == (-1, False) and 3 not in got and not got[4][1]


def test_tiff_digest(docs, empty):
    rows = tiff.media_digest(tiff.texts_to_tiff(docs)).collect()
    assert len(rows) == len(odd_rows())
    want = sorted((str(k), hashlib.sha256(tiff.padded_payload((t or "").encode())).hexdigest(), len((t or "").encode())) for k, t, *_ in odd_rows())
    assert sorted((str(r.doc_id), r.payload_sha256, r.n_bytes) for r in rows) == want
    assert all(r.payload_bytes % 64 == 0 and r.payload_bytes >= 64 for r in rows)
    assert tiff.media_digest(tiff.texts_to_tiff(empty)).count() == 0


# -- repeated substrings -------------------------------------------------------------------------------------


def brute_repeats(rows, length=50):
    key = lambda k: 2**63 - 1 if k is None else k
    first, out = {}, []
    texts = [(key(k), (t or "").encode()) for k, t in rows]
    for d, t in sorted(texts):
        for i in range(len(t) - length + 1):
            first.setdefault(t[i : i + length], d)
    for d, t in texts:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - length + 1):
            if first[t[i : i + length]] < d:
                gone[i : i + length] = True
        runs = int((gone & ~np.append(False, gone[:-1])).sum()) if len(t) else 0
        kept = bytes(np.frombuffer(t, np.uint8)[~gone])
        out.append((str(None if d == 2**63 - 1 else d), len(t), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def test_repeats_on_odd_rows(docs, empty):
    got = sorted((str(r[0]), *r[1:]) for r in suffix.remove_repeats(docs).collect())
    assert got == brute_repeats([(k, t) for k, t, *_ in odd_rows()])
    assert suffix.remove_repeats(empty).count() == 0


def test_repeats_on_random_texts(spark):
    r = random.Random(9)
    pieces = ["".join(r.choices("ab", k=r.randint(20, 90))) for _ in range(12)] + ["ab" * 60, "c" * 130]
    rows = [(r.randint(0, 30), "".join(r.choice(pieces) for _ in range(r.randint(0, 6)))) for _ in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert sorted((str(x[0]), *x[1:]) for x in suffix.remove_repeats(df).collect()) == brute_repeats(rows)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.sampled_from([b"ab", b"abc", b"b" * 9, b"a" * 17, b"c"]), min_size=1, max_size=30), st.integers(1, 60), st.sampled_from([0, 8, 24, 40]))
def test_deep_shallow_sort(parts, depth, shallow):
    data = b"".join(parts)
    buf = np.frombuffer(data + b"\0" * 64, np.uint8)
    order, group = suffix.deep_shallow_sort(buf, np.arange(len(data)), depth, shallow)
    keys = [bytes(buf[k : k + depth]) for k in order.tolist()]
    assert keys == sorted(keys)
    assert [a == b for a, b in zip(keys, keys[1:], strict=False)] == [a == b for a, b in zip(group.tolist(), group[1:].tolist(), strict=False)]


# -- SimHash -------------------------------------------------------------------------------------------------


def brute_components(rows, bits=2):
    f = [simhash.fingerprint((t or "").encode()) & (2**64 - 1) for _, t in rows]
    ids = [2**63 - 1 if k is None else k for k, _ in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if bin(f[i] ^ f[j]).count("1") <= bits:
                root[find(i)] = find(j)
    least = {}
    for i in range(len(rows)):
        least[find(i)] = min(least.get(find(i), 2**63 - 1), ids[i])
    none = lambda k: None if k == 2**63 - 1 else k
    return sorted((str(rows[i][0]), f[i], str(none(least[find(i)]))) for i in range(len(rows)))


def test_simhash_components(docs, empty):
    rows = [(k, t) for k, t, *_ in odd_rows()]
    got = sorted((str(r.doc_id), r.fingerprint & (2**64 - 1), str(r.component_id)) for r in simhash.near_duplicates(docs).collect())
    assert got == brute_components(rows)
    assert simhash.near_duplicates(empty).count() == 0


def test_large_groups_are_linked_without_pairs(spark, monkeypatch):
    r = random.Random(3)
    base = r.getrandbits(63)
    fps = {base}
    for _ in range(400):
        f = r.choice(sorted(fps))
        for _ in range(r.randint(1, 2)):
            f ^= 1 << r.randrange(63)
        fps.add(f)
    fps |= {r.getrandbits(63) for _ in range(50)}
    fps = sorted(fps)
    root = {f: f for f in fps}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(fps):
        for b in fps[:i]:
            if (a ^ b).bit_count() <= 2:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    nodes = spark.createDataFrame([(f,) for f in fps], "fp long")
    shared_dir(spark, "t")
    for limit in (4, 64):
        monkeypatch.setattr(simhash, "PAIR_GROUP", limit)
        got = {r.node: r.root for r in simhash.components(simhash.links(nodes)).collect()}
        assert {f: got.get(f, f) for f in fps} == {f: find(f) for f in fps}


def test_long_chains_become_one_component(spark):
    shared_dir(spark, "t")
    edges = spark.createDataFrame([(k, k + 1) for k in range(300)] + [(1000, 1001)], "a long, b long")
    got = {r.node: r.root for r in simhash.components(edges).collect()}
    assert got == {k: 0 for k in range(301)} | {1000: 1000, 1001: 1000}


def test_keep_one(docs):
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    ids = [r.doc_id for r in kept.collect()]
    want = {c for _, _, c in brute_components([(k, t) for k, t, *_ in odd_rows()])}
    assert sorted(map(str, ids)) == sorted(want)


@pytest.mark.parametrize("bits", [0, 1, 2, 3])
def test_links_join_what_all_pairs_join(spark, monkeypatch, bits):
    """Few and many fingerprints of a variant, by every number of bits, against all pairs."""
    r = random.Random(bits)
    fps = {r.getrandbits(63) for _ in range(30)}
    for _ in range(160):
        f = r.choice(sorted(fps))
        for _ in range(r.randint(1, 4)):
            f ^= 1 << r.randrange(63)
        fps.add(f)
    root = {f: f for f in fps}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in fps:
        for b in fps:
            if (a ^ b).bit_count() <= bits:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    nodes = spark.createDataFrame([(f,) for f in fps], "fp long")
    shared_dir(spark, "t")
    for limit in (3, 64):
        monkeypatch.setattr(simhash, "PAIR_GROUP", limit)
        made = simhash.links(nodes, bits)
        assert all((x.a ^ x.b).bit_count() <= bits and x.a < x.b for x in made.collect())
        got = {x.node: x.root for x in simhash.components(made).collect()}
        assert {f: got.get(f, f) for f in fps} == {f: find(f) for f in fps}


def test_keep_one_leaves_clashing_columns(spark):
    rows = [(1, "a b c d", "mine", 1), (2, "a b c d", "yours", 2), (None, "other words here now", "kept", 3)]
    df = spark.createDataFrame(rows, "doc_id long, text string, __key string, node long")
    assert sorted(map(tuple, simhash.keep_one(df).collect()), key=str) == sorted([rows[0], rows[2]], key=str)


# -- BM25 ----------------------------------------------------------------------------------------------------

ITEMS = [(k, f"What is the {w} of {v}? It is the {w} number {k} that everyone in {v} should know by heart.") for k, (w, v) in enumerate([("capital", "France"), ("height", "Everest"), ("colour", "copper"), ("speed", "light")])]


def test_leaks_are_found_and_clean_texts_left(spark, empty):
    noise = "lorem ipsum dolor sit amet consectetur adipiscing elit sed do eiusmod tempor " * 20
    rows = [(1, noise + ITEMS[0][1] + noise), (2, noise), (3, ITEMS[1][1].upper()), (4, "What is the capital of Spain? " + noise), (None, ITEMS[2][1]), (5, None), (6, ""), (7, ITEMS[3][1] + " " + ITEMS[0][1])]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    items = spark.createDataFrame([*ITEMS, (9, None), (10, "")], "item_id long, text string")
    got = sorted(((r.doc_id, r.item_id) for r in bm25.leaked_items(df, items).collect()), key=str)
    assert got == sorted([(1, 0), (3, 1), (None, 2), (7, 3), (7, 0)], key=str)
    assert bm25.leaked_items(empty, items).count() == 0 and bm25.leaked_items(df, items.limit(0)).count() == 0
    kept = bm25.drop_leaking(df.withColumnRenamed("text", "text"), items)
    assert sorted(str(r.doc_id) for r in kept.collect()) == ["2", "4", "5", "6"]


def test_items_in_blocks_give_the_same_scores(spark, monkeypatch):
    """Scores and overlaps are those of the whole test set however it is cut into blocks."""
    r = random.Random(9)
    words = "river stone cloud window silver garden market bridge winter letter north seven".split()
    more = [(k, f"How many {' '.join(r.choices(words, k=r.randint(4, 40)))} are there? There are {r.choice(words)} {k} of them.") for k in range(20, 50)]
    edited = [(k, "intro words here " + t.replace("many", "often").replace("by heart", "at once")) for k, t in [*ITEMS, *more]]
    df = spark.createDataFrame(edited, "doc_id long, text string")
    items = spark.createDataFrame([*ITEMS, *more], "item_id long, text string")
    assert len(list(bm25.indexes(items, block_bytes=500))) > 3
    whole = sorted(map(tuple, bm25.leaked_items(df, items).collect()))
    original = bm25.indexes
    monkeypatch.setattr(bm25, "indexes", lambda i: original(i, block_bytes=500))
    assert sorted(map(tuple, bm25.leaked_items(df, items).collect())) == whole and len(whole) >= 30


def slow_leaks(items, text):
    """Every passage against every piece by sums over all words, then the three verifications by definition."""
    bags = [p for _, t in items for p in bm25.pieces(t)]
    n, mean, longest = len(bags), sum(len(p[0]) for p in bags) / len(bags), max(len(p[0]) for p in bags)
    n_with = {w: sum(w in p[0] for p in bags) for p in bags for w in p[0]}
    step, words, found = max(8, longest), bm25.words_of(text.lower()), {}
    number = {}
    code = lambda w: number.setdefault(w, len(number))
    for start in range(0, max(1, len(words) - step), step):
        passage = words[start : start + 2 * step]
        held, spaced = bm25.shingles(passage), " " + " ".join(passage) + " "
        for key, t in items:
            for piece, parts, question in bm25.pieces(t):
                for bag, alone in ((piece, False), (question, True)):
                    if bag is None:
                        continue
                    impact = {w: np.log(1 + (n - n_with[w] + 0.5) / (n_with[w] + 0.5)) * bag.count(w) * 2.2 / (bag.count(w) + 1.2 * (0.25 + 0.75 * len(bag) / mean)) for w in set(bag)}
                    score = sum(v for w, v in impact.items() if w in passage) / sum(impact.values())
                    if score < bm25.THRESHOLD - 1e-9:
                        continue
                    share = [sum(s in held or (len(s) < 5 and f" {' '.join(s)} " in spaced) for s in part) / len(part) if part else 1.0 for part in parts]
                    allowed = int(0.2 * len(bag) + 1e-9)
                    near = not alone and allowed > 0 and bm25.edits([code(w) for w in bag], [code(w) for w in passage]) <= allowed
                    if share[0] >= 0.8 and (alone or share[1] >= 0.8) or near:
                        found[key] = max(found.get(key, 0.0), score)
    return found


def test_search_from_end_to_end_equals_brute_force():
    """The first look at essential words, block-max WAND and verification together lose and add nothing."""
    r = random.Random(21)
    words = [f"w{k}" for k in range(60)]
    items = [(k, f"{' '.join(r.choices(words, k=r.randint(3, 30)))}? {' '.join(r.choices(words, k=r.randint(0, 8)))}") for k in range(25)]
    index, hits = bm25.Index(items), 0
    for _ in range(60):
        text = r.choices(words, k=r.randint(0, 120))
        for _, t in r.sample(items, 2):
            copy = [w if r.random() > 0.08 else "other" for w in t.replace("?", "").split()]
            at = r.randint(0, len(text))
            text[at:at] = copy[: r.choice((len(copy), len(copy), len(copy) * 3 // 4))]
        want = slow_leaks(items, " ".join(text))
        got = {k: v[0] for k, v in index.leaks(" ".join(text)).items()}
        assert set(got) == set(want) and all(abs(got[k] - want[k]) < 1e-9 for k in got)
        hits += len(got)
    assert hits > 40


def test_one_edited_word_hides_no_item():
    """In the question or the answer, replaced, dropped or with a word put in before it."""
    index = bm25.Index([*ITEMS, (7, "A river of the north has its long and winding course through seven lands. Name it: Onega.")])
    for key, text in [*ITEMS, (7, "A river of the north has its long and winding course through seven lands. Name it: Onega.")]:
        words = text.split()
        for k in range(len(words)):
            for put in (["other"], [], ["other", words[k]]):
                assert key in index.leaks("before it " + " ".join(words[:k] + put + words[k + 1 :]) + " and after it"), (key, k, put)


def test_a_whole_question_without_its_answer_is_a_leak():
    question = "A river of the north has its long and winding course through seven lands."
    index = bm25.Index([(7, question + " Name it: Onega."), (8, "Who sings here? The old bird in the tall green tree by the lake sings.")])
    noise = "lorem ipsum dolor sit amet consectetur adipiscing elit " * 9
    assert set(index.leaks(noise + question + " " + noise)) == {7}
    assert not index.leaks(noise + question.replace("north", "south").replace("long", "short") + " " + noise)
    assert not index.leaks(noise + "Who sings here? " + noise)  # too few words to stand for an item


@given(st.lists(st.integers(0, 3), min_size=1, max_size=12), st.lists(st.integers(0, 3), max_size=25))
def test_edits_equal_the_table_of_distances(item, passage):
    row = [0] * (len(passage) + 1)
    for i, x in enumerate(item, 1):
        last, row = row, [i]
        for j, y in enumerate(passage, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    assert bm25.edits(item, passage) == min(row)


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 10**6), st.floats(0.01, 0.9))
def test_wand_equals_exhaustive_search(seed, threshold):
    r = random.Random(seed)
    vocabulary = [f"w{k}" for k in range(40)]
    index = bm25.Index([(k, " ".join(r.choices(vocabulary, k=r.randint(1, 30)))) for k in range(60)])
    terms = set(r.sample(range(len(index.term)), r.randint(1, min(25, len(index.term)))))
    got, want = sorted(index.search(terms, threshold)), index.exhaustive(terms, threshold)
    assert [d for d, _ in got] == [d for d, _ in want] and np.allclose([s for _, s in got], [s for _, s in want])
    ids = np.array(r.choices([*terms, len(index.term)], k=r.randint(1, 90)))
    for start in range(0, len(ids), 10):
        if index.exhaustive(set(ids[start : start + 20].tolist()) - {len(index.term)}, threshold):
            last = max(0, -(-len(ids) // 10) - 2) * 10
            assert min(start, last) // 10 in index.promising(ids, 10, threshold) or start > last


# -- classifiers -----------------------------------------------------------------------------------------------


def test_trees_learn_and_flatten():
    r = np.random.default_rng(0)
    x = r.normal(size=(3000, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.5)).astype(float)
    m = gbdt.fit(x[:2000], y[:2000], trees=60, depth=3)
    assert gbdt.auc(m.probability(x[2000:]), y[2000:]) > 0.97
    one = np.array([m.base + sum(m.leaf[t, walk(m, t, row)] for t in range(60)) for row in x[:20]])
    assert np.allclose(one, m.margin(x[:20]))
    assert gbdt.fit(x[:0], y[:0]).probability(x[:2]).tolist() == [0.5, 0.5]
    assert len(gbdt.fit(x[:9], np.ones(9)).feature) == 0


def walk(m, t, row):
    node = 0
    while node < m.feature.shape[1]:
        node = 2 * node + 1 + int(row[m.feature[t, node]] > m.threshold[t, node])
    return node - m.feature.shape[1]


def test_isotonic_rises():
    s = np.linspace(0, 1, 200)
    y = (np.random.default_rng(1).random(200) < s).astype(float)
    f = gbdt.fit_isotonic(s, y)
    assert (np.diff(f(s)) >= 0).all() and abs(f(s).mean() - y.mean()) < 0.05
    assert gbdt.fit_isotonic(s, np.zeros(200))(0.3) == 0.3


@pytest.mark.parametrize(("module", "label", "query"), [(quality, "quality", "quality_scores"), (toxicity, "toxic", "toxicity_scores")])
def test_held_out_accuracy(spark, docs, empty, module, label, query):
    d = "/root/testdata/sf0.1"
    table, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    got = getattr(module, query)(table, labels).join(labels, "doc_id").where("held_out").toPandas()
    assert gbdt.auc(got["score"].to_numpy(), got[label].to_numpy()) > 0.95 and len(got) > 500
    folds = {zlib.crc32(str(k).encode()) % module.PARTS == module.HELD for k in got["doc_id"]}
    assert folds == {True}
    odd = getattr(module, query)(docs, labels).collect()
    assert len(odd) == len(odd_rows()) and all(0 <= r.score <= 1 for r in odd)
    assert getattr(module, query)(empty, labels.limit(0)).count() == 0
    assert classify.labelled_sample(table, labels, label, module.PARTS, module.HELD, 50).count() <= 50


# -- personal data -----------------------------------------------------------------------------------------------

BASE = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"),
]


def luhn(d):
    total = 0
    for k, c in enumerate(reversed(d)):
        x = int(c) * (1 + k % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def brute_pii(text):
    import re

    out = []
    for rank, (kind, pattern) in enumerate(BASE):
        for m in re.finditer(pattern, text, re.ASCII):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else True, "card": 12 <= len(digits) <= 19 and luhn(digits), "phone": 9 <= len(digits) <= 15}[kind]
            if ok:
                out.append((m.start(), rank, f"{kind}:{m.start()}:{m.end()}"))
    return ",".join(x[2] for x in sorted(out))


def test_pii_on_random_strings(spark):
    r = random.Random(11)
    bits = ["a@b.c", "@", ".", "x.y@z-1.co.uk", "1", "12", "255", "256", "1.2.3.4", "+1 (415) 555-2671", "4111 1111 1111 1111", "4111-1111-1111-1111", " ", "-", "+", "é", "😀", "%", "_", "\n", "5500005555555559", "0", "999"]
    texts = ["".join(r.choice(bits) for _ in range(r.randint(0, 14))) for _ in range(3000)] + ["9" * 30_000, "a" * 30_000 + "@", "1 " * 20_000, "+" * 500, "1." * 5000]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    got = {x.doc_id: x for x in pii.pii_digest(df).collect()}
    for k, t in enumerate(texts):
        want = brute_pii(t)
        assert ",".join(s for s in got[k].spans.split(",") if not s.startswith("iban")) == want, repr(t[:200])
        assert got[k].base_sha256 == hashlib.sha256(want.encode()).hexdigest()


def test_pii_iban_context_and_redaction(spark, docs, empty):
    rows = [(1, "My bank account: GB82 WEST 1234 5698 7654 32 ok"), (2, "GB82 WEST 1234 5698 7654 33"), (3, "write to me at a@b.cd please"), (4, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in pii.pii_digest(df).collect()}
    assert got[1].spans.startswith("iban:17:44") and got[1].top_score == 1.0 and got[2].n_iban == 0 and got[4].spans == ""
    clean = {r.doc_id: r.text for r in pii.redact(df).collect()}
    assert clean == {1: "My bank account: [IBAN] ok", 2: rows[1][1], 3: "write to me at [EMAIL] please", 4: None}
    assert pii.redact(docs).columns == docs.columns and pii.redact(docs).count() == len(odd_rows())
    assert pii.redact(empty).count() == 0 and pii.pii_digest(empty).count() == 0


def test_pii_has_no_python(docs):
    for df in (pii.pii_digest(docs), pii.redact(docs)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not any(x in plan for x in ("Python", "Pandas", "Arrow"))


# -- tokens ------------------------------------------------------------------------------------------------------

public_tokenizers = pytest.importorskip("public_tokenizers")


def nasty_texts():
    r = random.Random(4)
    made = ["", " ", "  a  b ", "a\n\nb", "ﬁ １", "▁x ▁", "a\xa0b\t c", "é é\0z", "=" * 3000, "a" * 2000, "<s> </s> <0x0A> <|endoftext|>", "😀😀 ‍", " \n x\n", "\x85 b \x1c c"]
    return made + ["".join(r.choice("aabtheino ▁ \n0é日😀.'") for _ in range(r.randint(1, 80))) for _ in range(1500)] + ["".join(r.choice(["th", "ing", "er", "ation", "s", "e", "##", " ", "\n"]) for _ in range(r.randint(1, 60))) for _ in range(1500)]


def test_sentencepiece_equals_the_library(spark, docs, empty):
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = nasty_texts()
    m = sentencepiece_bpe.model(path)
    for _ in range(2):  # with a cold and a warm cache
        ids, cuts = m.encode(pa.array(texts))
        for k, t in enumerate(texts):
            own = ids[cuts[k] : cuts[k + 1]].tolist()
            assert own == sp.encode(t, add_eos=True), repr(t)
            assert m.decode(own) == sp.decode(own)
    got = sorted((str(r.doc_id), r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in sentencepiece_bpe.piece_digest(docs, path).collect())
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = [(str(k), len(i := sp.encode(t or "", add_eos=True)), sha(" ".join(map(str, i))), sha(sp.decode(i))) for k, t, *_ in odd_rows()]
    assert got == sorted(want)
    back = sentencepiece_bpe.decode_pieces(sentencepiece_bpe.encode_pieces(docs.where("doc_id < 40"), path), path)
    assert sorted(map(tuple, back.collect())) == sorted((k, sp.decode(sp.encode(t))) for k, t, *_ in odd_rows() if k is not None and k < 40)
    assert sentencepiece_bpe.piece_digest(empty, path).count() == 0


def test_records_equal_the_library(spark, docs, empty):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    t = Tokenizer.from_file(path)
    end = "<|endoftext|>"
    texts = [*nasty_texts(), end, f"a {end} b", f"x{end}\n{end}y", "<|endof text|>", "<|endof", "text|>"]
    assert t.encode(end, add_special_tokens=False).ids == [50256]
    m = records.WordEncoder(path)
    for _ in range(2):
        ids, cuts = m.encode(pa.array(texts), 2)
        for k, e in enumerate(t.encode_batch(texts, add_special_tokens=False)):
            assert ids[cuts[k] : cuts[k + 1]].tolist() == [*e.ids, 2], repr(texts[k])
    folder = shared_dir(spark, "t")
    files = records.write_records(docs, path, folder)
    got = [tuple(r) for r in records.read_digest(spark, files).collect()]
    rows = sorted(odd_rows(), key=lambda r: (r[0] is None, r[0], r[1] is not None, (r[1] or "").encode()))
    start, want = 0, []
    for k, text, *_ in rows:
        i = np.array([*t.encode(text or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((k, start, len(i), zlib.crc32(i.tobytes())))
        start += len(i)
    assert sorted(got, key=str) == sorted(want, key=str)
    index = records.read_index(files[0].path)
    doc, ids = records.read_record(files[0].path, index[len(index) // 2])
    assert doc == index["doc"][len(index) // 2] and ids[-1] == 2
    assert records.record_digest(empty, path).count() == 0


def test_rows_of_one_id_fill_many_files(spark):
    """A third of all rows have no id, and many of these one text: no file has much more than its share."""
    rows = [(k, f"text {k}") for k in range(600)] + [(None, "the same" if k % 2 else f"other {k}") for k in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.shuffle.partitions", "9")
    try:
        files = records.write_records(df, public_tokenizers.path("byte_bpe_50k.json"), shared_dir(spark, "t"))
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert len(files) == 9 and sum(f.n_docs for f in files) == 900 and max(f.n_docs for f in files) <= 200
    got = records.read_digest(spark, files).orderBy("start").collect()
    ids = [r.doc_id for r in got]
    assert ids == [*range(600), *[None] * 300]


def test_damaged_records_are_noticed():
    whole = records.frame(records.pack_body(7, np.array([1, 2, 3]), 2))
    doc, ids = records.unpack_body(records.unframe(memoryview(whole), 0)[0])
    assert doc == 7 and ids.tolist() == [1, 2, 3]
    for k in range(len(whole)):
        bad = bytearray(whole)
        bad[k] ^= 1
        with pytest.raises((records.RecordError, struct.error)):
            records.unframe(memoryview(bytes(bad)), 0)


def test_warc_has_no_python_dependency_on_pages_columns(spark):
    pages = spark.createDataFrame([(1, "u", "x" * 120, "clash"), (2, "u", "x" * 120, "clash")], "page_id long, url string, html string, digest string")
    assert sorted((r.page_id, r.record_type, r.refers_to) for r in warc.page_records(pages).collect()) == [(1, "response", None), (2, "revisit", 1)]


def slow_trees(x, y, trees, depth, bins, rate=0.1, l2=1.0, least=1.0):
    """Margins by boosting one node at a time, every split of every feature tried by sums over its rows."""
    share = (y.sum() + 0.5) / (len(y) + 1)
    margin = np.full(len(y), np.log(share / (1 - share)))
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for c in x.T]
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h, step = p - y, p * (1 - p), np.zeros(len(y))

        def grow(rows, left, g=g, h=h, step=step):
            if not left:
                step[rows] = -rate * g[rows].sum() / (h[rows].sum() + l2)
                return
            score = lambda r: g[r].sum() ** 2 / (h[r].sum() + l2)
            best, chosen = 1e-6, None
            for f in range(x.shape[1]):
                for e in edges[f]:
                    low, high = rows[x[rows, f] <= e], rows[x[rows, f] > e]
                    if h[low].sum() < least or h[high].sum() < least:
                        continue
                    gain = score(low) + score(high) - score(rows)
                    if gain > best + 1e-12:
                        best, chosen = gain, (low, high)
            for part in chosen or (rows,):
                grow(part, left - 1)

        grow(np.arange(len(y)), depth)
        margin = margin + step
    return margin


def test_histogram_splits_equal_splits_tried_one_by_one():
    r = np.random.default_rng(4)
    x = np.column_stack([r.normal(size=150), r.integers(0, 5, 150), r.random(150), np.zeros(150)])
    y = (x[:, 0] + 0.7 * x[:, 1] + r.normal(size=150) > 1.5).astype(float)
    model = gbdt.fit(x, y, trees=4, depth=3, bins=8)
    assert np.allclose(model.margin(x), slow_trees(x, y, 4, 3, 8))


def test_the_labelled_sample_is_the_same_in_every_run(spark):
    """Rows of one id, contradicting labels, and the bounds of rows and bytes."""
    rows = [(k % 40, f"text {k} " * (k % 7 + 1)) for k in range(120)] + [(3, None), (None, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(k, k % 2) for k in range(40)] + [(3, 0), (None, 1), (7, None)], "doc_id long, toxic int")
    shared_dir(spark, "t")
    seen = [[tuple(r) for r in classify.labelled_sample(docs.repartition(n), labels.repartition(n), "toxic", 5, 0, 20).collect()] for n in (1, 3, 7)]
    assert seen[0] == seen[1] == seen[2] and len(seen[0]) == 20
    few = classify.labelled_sample(docs, labels, "toxic", 5, 0, 20, most_bytes=100).collect()
    assert [tuple(r) for r in few] == seen[0][: len(few)] and 0 < sum(len(r.text or "") for r in few) <= 100
