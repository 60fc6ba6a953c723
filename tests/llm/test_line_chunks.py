import random

import xxhash

from blendgraph.llm import line_chunks


def signed(x):
    x &= 2**64 - 1
    return x - 2**64 if x >> 63 else x


def plain_chunks(text):
    lines = (text or "").split("\n")
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in lines]
    ends = [i for i in range(len(lines)) if i == len(lines) - 1 or i > 0 and (signed(h[i - 1] << 1) ^ signed(h[i])) >> 7 & 3 == 0]
    return [lines[a:b] for a, b in zip([0, *(e + 1 for e in ends)], [e + 1 for e in ends])]


def plain(rows):
    """rows: distinct (doc_id, text), none null."""
    first = {}
    for d, t in sorted(rows, key=lambda r: (r[0], signed(xxhash.xxh64_intdigest((r[1] or "").encode(), 42)))):
        for c in plain_chunks(t):
            if len(c) > 1 and "".join(c).strip(" "):
                first.setdefault("\n".join(c), (d, t, None))
    out = {}
    seen = set()
    for d, t in sorted(rows, key=lambda r: (r[0], signed(xxhash.xxh64_intdigest((r[1] or "").encode(), 42)))):
        kept, removed, lines = [], 0, 0
        for c in plain_chunks(t):
            text = "\n".join(c)
            if text in first and text in seen:
                removed, lines = removed + 1, lines + len(c)
            else:
                kept += c
            seen.add(text)
        out[d, t] = ("\n".join(kept) if removed else t, removed, lines)
    return out


def corpus(seed, n=60):
    r = random.Random(seed)
    pool = [f"line {i} é" for i in range(40)]
    blocks = [[r.choice(pool) + str(k) for k in range(r.randint(3, 12))] for _ in range(8)]
    out = [None, "", "\n\n\n\n\n\n", " \n \n ", "one"]
    while len(out) < n:
        lines = []
        for _ in range(r.randint(1, 4)):
            lines += r.choice(blocks) if r.random() < 0.6 else [r.choice(pool) for _ in range(r.randint(1, 5))]
        out.append("\n".join(lines))
    return out


def test_against_plain(spark):
    for seed in (1, 2):
        texts = corpus(seed)
        rows = [(i * 37 % 101, t) for i, t in enumerate(texts)]
        docs = spark.createDataFrame([(*r, 5, "x") for r in rows], "doc_id long, text string, lc_no int, source string")
        got = {(r.doc_id, t): (r.text, r.lc_removed_chunks, r.lc_removed_lines) for r in line_chunks.drop_repeated_chunks(docs).collect() for t in [dict(rows)[r.doc_id]]}
        want = plain(rows)
        assert {k: v for k, v in got.items() if k[1] is not None} == {k: v for k, v in want.items() if k[1] is not None}
        assert got[[k for k in got if k[1] is None][0]] == (None, 0, 0)
        assert sum(v[1] for v in got.values()) > 10


def test_shift_moves_no_far_boundary():
    lines = [f"row {i}" for i in range(60)]
    a, b = plain_chunks("\n".join(lines)), plain_chunks("\n".join(["new", *lines]))
    assert len([c for c in b if c in a]) >= len(a) - 1


def test_repeated_rows_null_ids_and_empty(spark):
    text = "\n".join(f"row {i}" for i in range(30))
    docs = spark.createDataFrame([(3, text), (3, text), (None, text), (4, text), (2, "a")], "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.lc_removed_lines) for r in line_chunks.drop_repeated_chunks(docs).collect())
    multi = sum(len(c) for c in plain_chunks(text) if len(c) > 1)
    assert got == [(0, 0), (2, 0), (3, 0), (3, 0), (4, multi)]
    assert line_chunks.drop_repeated_chunks(docs.limit(0)).collect() == []


def test_no_python_in_the_plan(spark, tmp_path):
    docs = spark.createDataFrame([(1, "a")], "doc_id long, text string")
    docs.write.parquet(str(tmp_path / "d"))
    plan = line_chunks.drop_repeated_chunks(spark.read.parquet(str(tmp_path / "d")))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan
