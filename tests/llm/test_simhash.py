import math
import random

import numpy as np
import xxhash

from blendgraph.llm import simhash


def plain_fingerprint(text, width=4):
    words = [w for w in "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ") if w]
    shingles = [" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_words(text):
    return [w for w in "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ") if w]


def plain_copy_fingerprints(text, width=5):
    """(bits of the words, bits of the shingles) as whole numbers."""
    words = plain_words(text)
    if not words:
        return 0, 0
    weight = {w: round(16 * (1 + math.log(words.count(w)))) for w in words}
    hashed = {w: xxhash.xxh64_intdigest(w.encode(), 42) for w in weight}
    first = sum(1 << b for b in range(64) if 2 * sum(weight[w] for w in weight if hashed[w] >> b & 1) > sum(weight.values()))
    wide = []
    for s in [" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]:
        h = xxhash.xxh64_intdigest(s.encode(), 42)
        x = 0
        for k in range(4):
            z = (h + (k + 1) * 0x9E3779B97F4A7C15) % 2**64
            z = (z ^ z >> 30) * 0xBF58476D1CE4E5B9 % 2**64
            z = (z ^ z >> 27) * 0x94D049BB133111EB % 2**64
            x |= (z ^ z >> 31) << 64 * k
        wide.append(x)
    return first, sum(1 << b for b in range(256) if 2 * sum(x >> b & 1 for x in wide) > len(wide))


def plain_copies(ids, texts, max_bits=7, check_bits=46):
    """The smallest id of each component of texts that link."""
    values = [plain_copy_fingerprints(t) for t in texts]
    return plain_components(ids, values, lambda a, b: (a[0] ^ b[0]).bit_count() <= max_bits and (a[1] ^ b[1]).bit_count() <= check_bits)


def plain_components(ids, values, max_bits):
    linked = max_bits if callable(max_bits) else lambda a, b: (a ^ b).bit_count() <= max_bits
    root = list(range(len(ids)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(ids)):
        for j in range(i):
            if linked(values[i], values[j]):
                root[find(i)] = find(j)
    least = {}
    for i, d in enumerate(ids):
        least[find(i)] = min(d, least.get(find(i), d))
    return {d: least[find(i)] for i, d in enumerate(ids)}


def corpus(n=220, seed=3):
    r = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(300)] + ["Äpfel", "日本"]
    base = [[r.choice(vocabulary) for _ in range(r.randint(30, 120))] for _ in range(n // 4)]
    out = [None, "", "  \n\t ", "one", "One", "a b c"]
    while len(out) < n:
        words = list(r.choice(base))
        for _ in range(r.choice([0, 0, 1, 2])):
            words[r.randrange(len(words))] = r.choice(vocabulary)
        out.append(" ".join(words))
    return out


def test_fingerprint_against_plain():
    for text in corpus():
        assert simhash.fingerprint((text or "").encode()) == simhash.signed(plain_fingerprint(text))


def test_components_against_all_pairs(spark):
    texts = corpus()
    rows = [(i * 7 % 1000, t, "x") for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp string")
    want = plain_components([r[0] for r in rows], [plain_fingerprint(r[1]) for r in rows], 4)
    for largest in (20_000, 3):
        got = {r.doc_id: r.component_id for r in simhash.near_duplicates(docs, largest_block=largest).collect()}
        assert got == want


def test_large_blocks_against_all_pairs(spark):
    """One centre with many values around it: blocks above SMALL, by forest, and by midpoints."""
    r = random.Random(11)
    centres = [r.getrandbits(64) for _ in range(3)]
    values = list({simhash.signed(c ^ sum(1 << b for b in r.sample(range(64), r.randint(0, 5)))) for c in centres for _ in range(70)})
    df = spark.createDataFrame([(v,) for v in values], "fp long")
    want = plain_components(values, [v & (2**64 - 1) for v in values], 4)
    for largest in (20_000, 40):
        edges = simhash.hamming_edges(df, 4, largest)
        roots = {x.node: x.root for x in simhash.connected_components(edges).collect()}
        assert {v: roots.get(v, v) for v in values} == want


def test_midpoints_for_odd_limits(spark):
    r = np.random.default_rng(1)
    centre = int(r.integers(-(1 << 62), 1 << 62))
    values = sorted({centre ^ simhash.signed(sum(1 << int(b) for b in r.choice(64, 3, replace=False))) for _ in range(40)})
    df = spark.createDataFrame([(v,) for v in values], "fp long")
    for bits in (2, 3):
        edges = [(e.a, e.b) for e in simhash.midpoint_edges(df, bits).collect()]
        assert all(((a ^ b) & (2**64 - 1)).bit_count() <= bits for a, b in edges)
        root = {v: v for v in values}
        for _ in values:
            for a, b in edges:
                root[a] = root[b] = min(root[a], root[b])
        want = plain_components(values, [v & (2**64 - 1) for v in values], bits)
        assert root == want


def test_masks_cover_all_pairs():
    r = random.Random(5)
    for max_bits, masks in ((4, simhash.block_masks(4, 10)), (4, simhash.block_masks(4, 10**6)), (7, simhash.piece_masks(7, 2)), (7, simhash.piece_masks(7, 3))):
        for _ in range(300):
            flips = sum(1 << b for b in r.sample(range(64), max_bits))
            assert any(flips & m == 0 for m in masks)


def test_empty_table_and_repeats(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert simhash.near_duplicates(docs).collect() == []
    docs = spark.createDataFrame([(5, "a b"), (5, "a b"), (None, "a b")], "doc_id long, text string")
    assert [r.component_id for r in simhash.near_duplicates(docs).collect()] == [5, 5, 5]


def edited(r, words, share, vocabulary):
    """The words with a share of them replaced, deleted or doubled."""
    out = list(words)
    for _ in range(max(1, round(share * len(out)))):
        i = r.randrange(len(out))
        out[i : i + 1] = r.choice([[r.choice(vocabulary)], [], [out[i], r.choice(vocabulary)]])
    return out


def test_near_copies_against_all_pairs(spark):
    texts = corpus(160, 9)
    ids = [i * 7 % 1000 for i in range(len(texts))]
    docs = spark.createDataFrame([(i, t, "x") for i, t in zip(ids, texts)], "doc_id long, text string, node string")
    want = plain_copies(ids, texts)
    assert len(set(want.values())) < len(ids) - 20
    for largest, pieces in ((20_000, 2), (6, 2), (20_000, 1)):
        got = {r.doc_id: r.component_id for r in simhash.near_copies(docs, largest_block=largest, pieces=pieces).collect()}
        assert got == want


def test_recall_of_near_copies(spark):
    """Pairs whose five-word shingles are similar to 0.8 or more: at least nine in ten are linked, and no unrelated text."""
    r = random.Random(21)
    vocabulary = [f"word{i}" for i in range(2000)]
    zipf = [1 / (i + 1) for i in range(2000)]
    rows = []
    for i in range(400):
        words = r.choices(vocabulary, zipf, k=r.randint(40, 400))
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(edited(r, words, r.choice([0.005, 0.01, 0.015, 0.02]), vocabulary)))]
    text = dict(rows)
    shingles = {d: {tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for d, t in rows}
    similar = {d for d in text if d % 2 and len(shingles[d] & shingles[d - 1]) >= 0.8 * len(shingles[d] | shingles[d - 1])}
    got = {x.doc_id: x.component_id for x in simhash.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    caught = {d for d in similar if got[d] == got[d - 1]}
    assert len(similar) > 200 and len(caught) >= 0.95 * len(similar), (len(caught), len(similar))
    assert all(got[d] in (d, d - d % 2) for d in text)


def test_keep_one_each_edges(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, x int")
    assert simhash.keep_one_each(docs).collect() == []
    docs = spark.createDataFrame([(5, "a b", 1), (5, "a b", 2), (None, "a b", 3), (7, "a b", 4), (9, None, 5), (8, "", 6)], "doc_id long, text string, x int")
    got = simhash.keep_one_each(docs)
    assert got.columns == docs.columns and sorted(r.x for r in got.collect()) == [1, 2, 3, 6]
