"""The whole pipeline against plain Python on a small fixture."""

import hashlib
import math
import random

import pytest

from blendgraph.llm import line_quality

from . import test_line_runs as runs
from . import test_scans as scans
from . import test_simhash as sim

pipeline = pytest.importorskip("corpus_pipeline")


def corpus(seed=6):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7)))
    sentence = lambda: (" ".join(word() for _ in range(r.randint(6, 16))) + ".").capitalize()
    shared = ["\n".join(sentence() for _ in range(14)) for _ in range(3)]
    items = [(i, " ".join(word() for _ in range(18))) for i in range(4)]
    rows, long = [], []
    for i in range(140):
        lines = [sentence() for _ in range(r.randint(2, 9))]
        kind = r.random()
        if kind < 0.15:
            lines.insert(1, r.choice(shared))
        elif kind < 0.25:
            lines.append(r.choice(items)[1] + ".")
        elif kind < 0.35:
            lines += ["home | about | news | contact"] * r.randint(1, 9)
        elif kind < 0.6 and long:
            lines = [" ".join(word() if k == at else w for k, w in enumerate(x.split(" "))) for x in r.choice(long) for at in [r.randrange(60)]]
        elif kind < 0.65:
            lines = [" ".join(word() for _ in range(r.randint(80, 110))) + "." for _ in range(3)]
            long.append(lines)
        elif kind < 0.75 and rows:
            words = (r.choice(rows)[1] or "").split(" ")
            if len(words) > 60:
                words[r.randrange(len(words))] = word()
            lines = [" ".join(words)]
        rows.append((i * 13 % 149, "\n".join(lines), "en", r.choice(["a", "b", "c", None])))
    rows += [(500, None, "en", "a"), (501, "", None, "b"), (502, rows[3][1], "en", "c")]
    return items, [(*x, len(x[1] or "")) for x in rows]


def plain_quality(rows):
    out = []
    for d, t, lang, source, _ in rows:
        t = t or ""
        words = t.split()
        kept = [x for x in t.split("\n") if not line_quality.line_failure(x)]
        windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
        repeated = {j for i, w in enumerate(windows) if windows.count(w) > 1 for j in range(i, i + 5)}
        if len(words) >= 10 and 100 * len(repeated) <= 20 * len(words) and sum(len(x.split()) for x in kept) >= 0.5 * len(words):
            out.append((d, "\n".join(kept), lang, source, len("\n".join(kept))))
    return out


def plain_lines(rows):
    cleaned = runs.plain_runs([(d, t) for d, t, *_ in rows])
    out = []
    for d, t, lang, source, n in rows:
        text, _, removed = cleaned[d, t]
        if not removed or text.strip(" "):
            out.append((d, text, lang, source, len(text) if removed else n))
    return out


def plain_near(rows):
    kept = sim.plain_copies([r[0] for r in rows], [r[1] for r in rows])
    return [r for r in rows if kept[r[0]] == r[0]]


def plain_clean(rows, items):
    windows = {tuple(w[i : i + 10]) for _, t in items for w in [scans.plain_words(t)] for i in range(len(w) - 9)}
    return [r for r in rows if not any(tuple(w[i : i + 10]) in windows for w in [scans.plain_words(r[1])] for i in range(len(w) - 9))]


def plain_mix(rows):
    size = {r[0]: len(r[1].split()) for r in rows}
    sizes = {}
    for r in rows:
        sizes[r[3]] = sizes.get(r[3], 0) + size[r[0]]
    target = scans.mixture_plain(sizes)
    out = {}
    for s in sizes:
        bits = lambda n: max(1, n.bit_length())
        h = lambda d: hashlib.md5(str(d).encode()).hexdigest()
        own = sorted((bits(n) * 16 + (n >> max(bits(n) - 4, 0)), int(h(d)[:2], 16) % 64, n, h(d), d) for d, n in ((r[0], size[r[0]]) for r in rows if r[3] == s))
        u, rate = int(hashlib.md5(f"{s or ''}|17".encode()).hexdigest()[:8], 16) / 2**32, target[s] / sizes[s]
        for i, x in enumerate(own, 1):
            out[x[-1]] = math.floor(u + rate * i) - math.floor(u + rate * (i - 1))
    return sorted((*r, k) for r in rows for k in range(1, out[r[0]] + 1))


def test_pipeline_against_plain(spark, tmp_path):
    items, rows = corpus()
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(items, "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    stages = [plain_quality, plain_lines, plain_near, lambda r: plain_clean(r, items)]
    want = rows
    sizes = []
    for f in stages:
        want = f(want)
        sizes.append(len(want))
    assert len(rows) > sizes[0] > sizes[1] - 1 and sizes[1] > sizes[2] > sizes[3] > 40
    got = pipeline.run(spark, str(tmp_path))
    assert got.columns == [*docs.columns, "mx_copy"]
    key = lambda x: tuple(str(v) for v in x)
    assert sorted(map(tuple, got.collect()), key=key) == sorted(plain_mix(want), key=key)


def test_stages_on_an_empty_table(spark, tmp_path):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    spark.createDataFrame([(1, "a")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    for _, stage in pipeline.STAGES:
        out = stage(spark, docs, str(tmp_path))
        assert out.collect() == [] and out.columns[:5] == docs.columns


def test_tables_without_some_columns(spark, tmp_path):
    """n_chars is no input of any stage but is kept right where it is there; nulls stay what they are."""
    rows = [(i, "\n".join(f"This is line {j} of text {i}, which ends well and is long." for j in range(4)), "a" if i else None) for i in range(6)]
    docs = spark.createDataFrame([*rows, (None, None, None), (None, rows[1][1], "a")], "doc_id long, text string, source string")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, "a")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert set(pipeline.run(spark, str(tmp_path)).columns) == {*docs.columns, "mx_copy"}
