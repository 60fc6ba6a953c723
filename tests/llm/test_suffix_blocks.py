import hashlib
import random
from collections import Counter

import numpy as np

from blendgraph.llm import suffix_blocks


def plain(texts, length):
    often = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - length + 1):
            if often[t[i : i + length]] > 1:
                gone[i : i + length] = True
        kept = bytes(b for b, g in zip(t, gone) if not g)
        out.append((len(t), int(gone.sum()), int((np.diff(np.concatenate([[0], gone])) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return out


def corpus(seed, n=40):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefé日") for _ in range(r.randint(1, 7)))
    text = lambda k: " ".join(word() for _ in range(k))
    shared = [text(r.randint(20, 90)) for _ in range(6)]
    line = text(25)
    out = [None, "", "x" * 199, "x" * 900, "ab" * 300, text(3)]
    for _ in range(n):
        parts = [text(r.randint(1, 80))]
        for _ in range(r.randint(0, 3)):
            s = r.choice([*shared, line])
            a = r.randrange(len(s) // 2)
            parts += [s[a:] if r.random() < 0.5 else s, text(r.randint(0, 30))]
        out.append("".join(parts))
    out += [out[10], out[11], out[11][3:]]
    return out


def test_against_all_strings(spark):
    for seed, length, gram, largest in ((1, 200, 64, 4000), (2, 200, 64, 2), (3, 50, 12, 4000), (4, 96, 40, 3)):
        texts = corpus(seed)
        docs = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, sb_doc string")
        got = {r.doc_id: tuple(r)[1:5] for r in suffix_blocks.remove_repeats(docs, length, gram, largest).collect()}
        want = plain([(t or "").encode() for t in texts], length)
        assert [got[i] for i in range(len(texts))] == want


def test_long_text_is_cut_without_loss(monkeypatch, spark):
    r = random.Random(9)
    text = "".join(r.choice("abcd ") for _ in range(6000))
    docs = [text, text[1000:2500] + "z" + text[:400]]
    monkeypatch.setattr(suffix_blocks, "PIECE", 700)
    import pyarrow as pa

    batch = pa.RecordBatch.from_arrays([pa.array([0, 1]), pa.array([0, 1]), pa.array(docs)], ["a", "b", "c"])
    starts = Counter()
    for x, cuts, row, offset in suffix_blocks._pieces(batch, 200):
        start, count, which, *_ = suffix_blocks.suffix_runs(x, cuts, 200, 64)
        for s, c, w in zip(start, count, which):
            for i in range(c):
                at = int(s - cuts[w] + offset[w] + i)
                assert bytes(x[s + i : s + i + 200]) == docs[row[w]].encode()[at : at + 200]
                starts[int(row[w]), at] += 1
    assert starts == Counter({(d, i): 1 for d, t in enumerate(docs) for i in range(len(t) - 199)})


def test_ranks_order_cover_suffixes():
    r = np.random.default_rng(0)
    x = r.integers(97, 99, 400).astype(np.uint8)
    starts = np.arange(0, 200)
    for length in (64, 96, 150, 200):
        got = suffix_blocks.repeated_in_bucket(np.concatenate([x, x[50:300]]), np.concatenate([starts, [400, 410]]), length)
        y = np.concatenate([x, x[50:300]]).tobytes()
        all_starts = [*starts.tolist(), 400, 410]
        often = Counter(y[i : i + length] for i in all_starts)
        assert got.tolist() == [often[y[i : i + length]] > 1 for i in all_starts]


def test_empty_table_null_ids_and_repeats(spark):
    assert suffix_blocks.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).collect() == []
    t = "".join(chr(97 + i * i % 26) for i in range(300))
    rows = suffix_blocks.remove_repeats(spark.createDataFrame([(None, t + "q"), (1, t), (1, t), (2, "a")], "doc_id long, text string")).collect()
    assert sorted((r.doc_id or 0, r.n_removed) for r in rows) == [(0, 300), (1, 300), (1, 300), (2, 0)]


def test_ids_of_other_types(spark):
    text = "".join(chr(97 + i * i * 7 % 26) for i in range(300))
    docs = spark.createDataFrame([("abc", text), (None, text), ("", "x"), (None, None)], "doc_id string, text string")
    got = sorted((r.doc_id or "-", r.n_bytes, r.n_removed) for r in suffix_blocks.remove_repeats(docs).collect())
    assert got == [("-", 0, 0), ("-", 1, 0), ("-", 300, 300), ("abc", 300, 300)]
