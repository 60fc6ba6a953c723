import random

import xxhash

from blendgraph.llm import line_chunks

from .test_line_chunks import plain_chunks, signed


def plain_pieces(text):
    """(first line, number of lines) of the chunks, of each two neighbouring lines with words, and of the whole text."""
    lines = (text or "").split("\n")
    full = [i for i, x in enumerate(lines) if x.strip(" ")]
    out, at = {(a, b - a + 1) for a, b in zip(full, full[1:])}, 0
    for c in plain_chunks(text):
        out.add((at, len(c)))
        at += len(c)
    out.add((0, len(lines)))
    return {(a, n) for a, n in out if n > 1 and "".join(lines[a : a + n]).strip(" ")}


def plain_runs(rows):
    """rows: distinct (doc_id, text) -> text, chunks and lines removed of each; by a set of all pieces read so far."""
    seen, out = set(), {}
    for d, t in sorted(rows, key=lambda r: (r[0], signed(xxhash.xxh64_intdigest((r[1] or "").encode(), 42)))):
        lines, gone = (t or "").split("\n"), set()
        for a, n in sorted(plain_pieces(t)):
            piece = "\n".join(lines[a : a + n])
            if piece in seen:
                gone |= set(range(a, a + n))
            seen.add(piece)
        chunks, at = 0, 0
        for c in plain_chunks(t):
            chunks += gone.issuperset(range(at, at + len(c)))
            at += len(c)
        out[d, t] = ("\n".join(x for i, x in enumerate(lines) if i not in gone) if gone else t, chunks, len(gone))
    return out


def planted(seed, n=50):
    """Texts of lines of their own, some with a passage of 2 to 4 lines that others hold too."""
    r = random.Random(seed)
    passages = [[f"shared {k} {i}" for i in range(2 + k % 3)] for k in range(9)]
    out = []
    for i in range(n):
        lines = [f"own {i} {j}" for j in range(r.randint(2, 9))]
        at = r.randint(0, len(lines))
        lines[at:at] = r.choice(passages)
        if i % 5 == 0:
            lines.insert(r.randint(0, len(lines)), "")
        out.append("\n".join(lines))
    return [*out, out[3], out[7], "\n\n", "\nTitle\n", "\nTitle\n", "a\na\na\na", "one", "one", "", None]


def removed(spark, texts):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return {(r.doc_id, texts[r.doc_id]): (r.text, r.lc_removed_chunks, r.lc_removed_lines) for r in line_chunks.drop_repeated_chunks(docs, runs=True).collect()}


def test_runs_against_plain(spark):
    for seed in (1, 2):
        texts = planted(seed)
        assert removed(spark, texts) == plain_runs(list(enumerate(texts)))


def test_every_repeated_run_of_two_lines_goes(spark):
    """Brute force: a line that with the next one stood before, in whatever context, is not kept; no line is lost."""
    texts = planted(3)
    got = removed(spark, texts)
    seen = set()
    for i, t in enumerate(texts):
        lines = (t or "").split("\n")
        kept = (got[i, t][0] or "").split("\n")
        twos = [(a, b) for a, b in zip(lines, lines[1:]) if a.strip() and b.strip()]
        if not seen.intersection(twos):
            assert got[i, t][2] == 0 or "Title" in t or "a\na" in t
        for two in twos:
            assert two not in seen or not {*two} & {*kept}
        seen |= {*twos} - {("a", "a")}
    assert {x for t, *_ in got.values() for x in (t or "").split("\n") if x.strip()} == {x for t in texts for x in (t or "").split("\n") if x.strip()}


def test_copies_of_whole_texts_leave_nothing(spark):
    texts = ["\n\nfirst line\nsecond\n\n\nthird\n"] * 3 + ["\nTitle\n\n", "\nTitle\n\n"]
    got = removed(spark, texts)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows = sorted((r.doc_id, r.text) for r in line_chunks.drop_repeated_chunks(docs, runs=True).collect())
    assert [t for _, t in rows] == [texts[0], "", "", texts[3], ""] and len(got) == 5
