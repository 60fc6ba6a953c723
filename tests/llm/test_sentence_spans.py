import random
import re

from blendgraph.llm import sentence_spans

SPLIT = re.compile(r"(?<=[.!?…])(?=[ \t\n\r\x0b\x0c])|(?<=[。！？])(?!$)|(?<=[^.!?…。！？ \t\n\r\x0b\x0c]\n)")


def plain_pieces(text):
    return [x for x in SPLIT.split(text) if x]


def plain(rows, width, min_words):
    seen, out = set(), {}
    for d, t in sorted(rows):
        p = plain_pieces(t)
        at = [i for i, x in enumerate(p) if x.strip(" \t\n\r\x0b\x0c")]
        s = [re.sub("[A-Z]", lambda m: m[0].lower(), p[i].strip(" \t\n\r\x0b\x0c")) for i in at]
        gone = set()
        for j in range(max(1, len(s) - width + 1) if s else 0):
            run = tuple(s[j : j + width])
            if sum(len(x.encode().split()) for x in run) >= min_words:
                if run in seen:
                    gone |= set(at[j : j + width])
                seen.add(run)
        out[d] = "".join(x for i, x in enumerate(p) if i not in gone), len(gone)
    return out


def test_pieces():
    for t in ("", "a", "A b. C d! E\nF\n\nG…\nH。I！J？", "Version 2.0. x@y.de?! Yes", "..\n.", "\n\n", "a \nb\n", "。"):
        got = [t.encode()[a:b].decode() for a, b in sentence_spans.pieces(t.encode())]
        assert got == plain_pieces(t) and "".join(got) == t


def test_against_plain(spark):
    r = random.Random(4)
    word = lambda: "".join(r.choice("abcdeé") for _ in range(r.randint(1, 6)))
    sentence = lambda: " ".join(word() for _ in range(r.randint(1, 12))).capitalize() + r.choice([".", "!", "?", "\n", ".\n", "。"])
    passages = [" ".join(sentence() for _ in range(r.randint(2, 7))) for _ in range(8)]
    texts = ["", "Short.", "Version 2.0. a.b@c.de\n\nNext"]
    for _ in range(60):
        texts.append(" ".join(r.choice(passages) if r.random() < 0.4 else sentence() for _ in range(r.randint(1, 8))))
    rows = [(i * 11 % 67, t) for i, t in enumerate(texts)]
    docs = spark.createDataFrame([(*x, 1) for x in rows], "doc_id long, text string, ss_no int")
    for width, min_words in ((2, 12), (3, 4)):
        got = {x.doc_id: (x.text, x.ss_removed) for x in sentence_spans.drop_repeated_spans(docs, width, min_words).collect()}
        assert got == plain(rows, width, min_words)
        assert sum(v[1] for v in got.values()) > 20


def test_nulls_repeats_empty(spark):
    t = "One two three four five six. Seven eight nine ten eleven twelve. Thirteen."
    docs = spark.createDataFrame([(None, t), (1, None), (2, t), (2, t), (3, t)], "doc_id long, text string")
    got = sorted((x.doc_id or 0, x.ss_removed, x.text) for x in sentence_spans.drop_repeated_spans(docs, 2, 8).collect() if x.text)
    assert got == [(0, 0, t), (2, 0, t), (2, 0, t), (3, 2, " Thirteen.")]
    assert sentence_spans.drop_repeated_spans(docs.limit(0)).collect() == []
