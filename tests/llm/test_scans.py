"""Quality rules, decontamination, mixing, licenses and URL trust against plain Python, and their edge cases."""

import hashlib
import math
import random
import re
import textwrap
from collections import Counter

import duckdb
import pandas as pd

from blendgraph.llm import decontamination, licenses, line_quality, mixing, sql, url_trust

ODD = [None, "", " \t\n", "x", "ZERO\x00BYTE", "a\x0bb\x1cc d\r\n", "É ß İ", "\n\n", "cc by cc by", "word " * 3000]


def rows(df, *cols):
    return sorted((tuple(r) for r in df.select(*cols).collect()), key=str)


def plain_words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def corpus(n=80, seed=2):
    r = random.Random(seed)
    items = [" ".join(r.choice(["alpha", "beta", "Gamma", "dé", "e2"]) + str(r.randrange(30)) for _ in range(k)) for k in (4, 12, 25, 25)]
    lines = ["Licensed under the Apache License, Version 2.0.", "Released under the MIT License.", "home | about | news | contact", "We use cookies.", "plain words end here.", "no end"]
    out = list(ODD)
    while len(out) < n:
        parts = []
        for _ in range(r.randint(1, 8)):
            item = r.choice(items).split()
            a = r.randrange(len(item))
            parts.append(r.choice([" ".join(item[a:]), ", ".join(item), r.choice(lines), "filler " * r.randint(0, 9) + "done.", "#*$ %& <>"]))
        out.append(r.choice(["\n", " "]).join(parts))
    return items, out


def test_decontamination_against_plain(spark):
    items, texts = corpus()
    bench = [(1, items[0]), (2, items[1]), (30, items[2]), (4, items[3]), (4, items[3]), (5, None), (6, " . ")]
    docs = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id long, text string, n_hit int")
    found = decontamination.find_contamination(docs, spark.createDataFrame(bench, "item_id long, text string"), max_item_mb=0.0001)
    got = {r.doc_id: r for r in found.collect()}
    bad = 0
    for d, t in enumerate(texts):
        w, hit, ids = plain_words(t), set(), set()
        for item_id, item in set(bench):
            x = plain_words(item)
            n = min(10, len(x))
            windows = {tuple(x[i : i + n]) for i in range(len(x) - n + 1)} if x else set()
            for i in range(len(w) - n + 1):
                if n and tuple(w[i : i + n]) in windows:
                    hit |= set(range(i, i + n))
                    ids.add(str(item_id))
        want = len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit)
        r = got[d]
        assert (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) == want
        bad += bool(hit)
        assert [x for a, b in r.hit_spans for x in plain_words(t[a:b])] == [w[i] for i in sorted(hit)]
    assert bad > 20
    kept = decontamination.drop_contaminated(docs, spark.createDataFrame(bench, "item_id long, text string"))
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {d for d, r in got.items() if not r.contaminated}


def test_decontamination_limits_and_empty(spark):
    docs = spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    none = spark.createDataFrame([], "item_id long, text string")
    assert [r.contaminated for r in decontamination.find_contamination(docs, none).collect()] == [False]
    assert decontamination.find_contamination(docs.limit(0), none).collect() == []


def test_more_items_than_a_worker_holds(spark):
    """Groups of items, each a pass of its own, give what one pass gives."""
    items, texts = corpus(60, 5)
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    docs = spark.createDataFrame([(None if i == 3 else i // 2, t) for i, t in enumerate(texts)], "doc_id long, text string")
    cols = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "hit_spans"]
    one, many = (rows(decontamination.find_contamination(docs, bench, max_item_mb=mb), *cols) for mb in (16, 2e-6))
    assert one == many and len(decontamination._item_groups(bench, 2e-6)) > 2
    kept = [rows(decontamination.drop_contaminated(docs, bench, max_item_mb=mb), "doc_id", "text") for mb in (16, 2e-6)]
    assert kept[0] == kept[1] and 0 < len(kept[0]) < len(texts)


def test_base_counts_against_plain():
    for t in corpus()[1]:
        t = t or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        windows = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        often = Counter(windows)
        covered = {j for i, x in enumerate(windows) if often[x] > 1 for j in range(i, i + 5)}
        want = len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered)
        assert line_quality.base_counts(t.encode()) == want


def test_line_rules_and_cleaning(spark):
    fails = {"home | about | news": "navigation", "We use cookies to help.": "boilerplate", "### word": "symbols", "no end here": "punctuation", "A fine line.": None, "He said “yes.”": None, " ": None}
    for line, want in fails.items():
        assert line_quality.line_failure(line) == want
    good = "This is a fine line that ends well and is long enough to stay."
    docs = spark.createDataFrame([(1, f"{good}\nhome | about | news\nOnce more.", "en", 99), (2, "a | b | c | d\n" * 20, "en", 5), (3, None, None, None)], "doc_id long, text string, kept string, n_chars long")
    got = line_quality.clean_documents(docs)
    assert got.columns == docs.columns
    assert [tuple(r) for r in got.collect()] == [(1, f"{good}\nOnce more.", "en", len(good) + 11)]
    assert line_quality.score_quality(docs.limit(0)).collect() == []
    assert rows(line_quality.score_quality(docs), "doc_id", "base_failed", "kept") == [(1, False, True), (2, True, False), (3, True, False)]


def mixture_plain(sizes):
    total, weights, cap = 1.5 * sum(sizes.values()), {}, {}
    for i, s in enumerate(sorted(sizes, key=lambda x: (x is None, x))):
        weights[s], cap[s] = (5, 2, 1)[i % 3], 2 * sizes[s]
    fixed = set()
    while True:
        left = total - sum(cap[s] for s in fixed)
        w = sum(weights[s] for s in sizes if s not in fixed)
        target = {s: cap[s] if s in fixed else left * weights[s] / w for s in sizes}
        over = {s for s in sizes if s not in fixed and target[s] > cap[s] * (1 + 1e-12)}
        if not over:
            return target
        fixed |= over


def test_mixture_targets_and_counts(spark):
    r = random.Random(8)
    docs = []
    for s, n in (("a", 900), ("b", 20), (None, 40), ("ä", 5), ("c", 300), ("empty", 0)):
        docs += [(len(docs) + i, "w " * r.choice([1, 7, 7, 30, 90]), s, "k") for i in range(n)]
    docs += [(9000, None, "empty", "k"), (None, "w w", "a", "k"), (9001, "same same", "c", "k"), (9001, "same same", "c", "k")]
    df = spark.createDataFrame(docs, "doc_id long, text string, source string, mx_rate string")
    got = mixing.plan_mixture(df).collect()
    assert len(got) == len(docs)
    sizes = Counter()
    for d in docs:
        sizes[d[2]] += len((d[1] or "").split())
    target = mixture_plain(sizes)
    taken = Counter()
    for x in got:
        assert x.mx_source_size == sizes[x.source] and abs(x.mx_target - target[x.source]) < 1e-6 * max(1, target[x.source])
        assert 0 <= x.mx_copies <= 2
        taken[x.source] += x.mx_copies * x.mx_size
    for s in sizes:
        assert abs(taken[s] - target[s]) <= max(2 * 90, 0.02 * target[s])
    assert rows(mixing.plan_mixture(df), "doc_id", "mx_copies") == rows(mixing.plan_mixture(df.repartition(5)), "doc_id", "mx_copies")
    mixed = mixing.mix(df.drop("mx_rate"))
    assert mixed.columns == ["doc_id", "text", "source", "mx_copy"] and mixed.count() == sum(x.mx_copies for x in got)
    assert mixing.plan_mixture(df.limit(0)).collect() == []


def test_license_join_against_plain(spark):
    texts = [*corpus()[1], *licenses.NOTICES.values(), "MIT License mit-license, MIT license\nGNU general public LICENSE"]
    r = random.Random(1)
    for t in licenses.NOTICES.values():
        w = t.split()
        texts += [" ".join(x for x in w if r.random() > 0.15) for _ in range(4)]
    docs = spark.createDataFrame([(i, t, "z") for i, t in enumerate(texts)], "doc_id long, text string, labels string")
    sets = {k: set(plain_words(v)) for k, v in licenses.NOTICES.items()}
    for x in licenses.scan_licenses(docs).collect():
        w = plain_words(texts[x.doc_id])
        at = {label: [i for i in range(len(w)) if w[i : i + len(p.split())] == p.split()] for p, label in licenses.PHRASES.items()}
        base = sorted(k for k, v in at.items() if v)
        starts = sorted(i for v in at.values() for i in v)
        share = {}
        for k, s in sets.items():
            width = math.ceil(1.25 * len(plain_words(licenses.NOTICES[k])))
            c = max((len(s & set(w[i : i + width])) / len(s) for i in range(len(w))), default=0)
            if c >= 0.8 - 1e-9:
                share[k] = c
        want = len(w), len(starts), starts[0] if starts else None, starts[-1] if starts else None, ",".join(base), ",".join(sorted({*base, *share})), 1.0 if base else max(share.values(), default=0.0)
        assert (x.n_words, x.n_base, x.first_word, x.last_word, x.base_labels, x.labels, x.score) == want
    assert licenses.scan_licenses(docs.limit(0)).collect() == []


def test_wrapped_and_commented_headers(spark):
    wrapped = {k: textwrap.fill(t, 78) for k, t in licenses.NOTICES.items()}
    rest = "some words of code before\nand after " * 40
    texts = [f"{rest}\n{t}\n{rest}" for t in wrapped.values()]
    texts += [rest + "".join(f"\n{mark} {line}" for line in t.split("\n")) + "\n" + rest for mark, t in zip(["#", "//", " *"] * 9, wrapped.values())]
    texts += [" ".join(x + " odd" * 9 for x in licenses.NOTICES["mit-header"].split()), None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in licenses.scan_licenses(docs).collect()}
    names = list(wrapped)
    for i in range(2 * len(names)):
        assert names[i % len(names)] in got[i].labels.split(","), names[i % len(names)]
        a, b = next(x for x in got[i].blocks if x.endswith(":" + names[i % len(names)])).split(":")[0].split("-")
        assert set(plain_words(texts[i])[int(a) : int(b) + 1]) >= set(plain_words(licenses.NOTICES[names[i % len(names)]]))
    assert got[len(texts) - 2].labels == got[len(texts) - 1].labels == ""


def test_long_texts_are_read_in_pieces(spark, monkeypatch):
    text = "word " * 50 + licenses.NOTICES["gpl-header"] + " word" * 30 + licenses.NOTICES["mit"]
    whole = licenses.NoticeIndex(licenses.NOTICES, {}, 0.8)
    normal = licenses.normal_words(text.encode())
    want = {x[0] for x in whole.matches(normal.split())}
    monkeypatch.setattr(licenses, "PIECE", 64)
    cut = list(licenses.pieces(normal, whole.widest))
    assert len(cut) > 5 and {x[0] for _, words in cut for x in whole.matches(words)} == want >= {"gpl-header", "mit"}
    assert all(normal.split()[n : n + len(w)] == w for n, w in cut)


def test_url_trust_against_sql(spark):
    link = lambda *hosts: " ".join(f'<a class=x href="{h}">y</a>' for h in hosts)
    pages = [
        (1, "http://a.example.net/en/1", link("//b.com/x", "https://C.org", "/own", "http://b.com?q")),
        (2, "https://www.B.com/x?y#z", link("http://c.org/1", "http://spam.net/")),
        (3, "http://spam.net/a", link("http://d.io/")),
        (4, "http://d.io", link("http://spam.net/", "http://other.net/x")),
        (5, "http://x.example.com/de/1", None), (6, "http://y.org/fr/2", link("http://d.io/")), (7, None, "<a href='http://d.io/'>"), (8, "no scheme", ""), (8, "no scheme", ""),
        (9, "http://net", ""), (10, "http://notnet/", ""), (11, "http://e.io/p://q/r?s", link("http://spam.net/", "http://f.io")), (12, "http://f.io#x", ""),
    ]
    df = spark.createDataFrame([(*p, "k") for p in pages], "page_id long, url string, html string, kind string")
    got = url_trust.judge_urls(df)
    con = duckdb.connect()
    con.register("pages", pd.DataFrame(pages, columns=["page_id", "url", "html"]))
    want = sorted(con.execute(sql.url_trust()).fetchall(), key=str)
    names = ["page_id", "host", "path", "rule", "verdict", "trust", "distrust"]
    assert rows(got, *names) == want
    by = {r.page_id: r for r in got.collect()}
    assert (by[1].rule, by[3].rule, by[5].rule, by[6].rule, by[9].rule) == ("example.net/en/", "net/", "example.com/de/", "org/fr/", None)
    assert by[11].verdict == "block" and by[11].path == "/p://q/r" and by[12].verdict == "allow" and by[7].host == ""
    assert url_trust.judge_urls(df.limit(0)).collect() == []


def plain_trust(pages, rules, rounds=10):
    """Verdicts by dictionaries: rules, links of hosts, and both walks in whole numbers."""
    lower = lambda x: re.sub("[A-Z]", lambda m: m[0].lower(), x)
    parts = {}
    for i, url, _ in pages:
        rest = (url or "").partition("://")[2]
        h = re.match("[^/?#]*", rest)[0]
        parts[i] = lower(h), re.match("[^?#]*", rest[len(h) :])[0]

    def rule_of(host, path):
        fits = [(len(r), r, what) for what, r in rules for own, _, p in [r.partition("/")] if (host == own or host.endswith("." + own)) and path.startswith("/" + p)]
        return max(fits)[1:] if fits else (None, None)

    edges = set()
    for i, _, html in pages:
        for m in re.finditer(r"""<a\s[^>]*?href\s*=\s*["']?\s*((?:https?:)?//[^"'\s>]+)""", html or "", re.I):
            edges.add((parts[i][0], lower(re.match("[^/?#]*", m[1].partition("//")[2])[0])))
    edges = {(a, b) for a, b in edges if a and b and a != b}
    for h in {p[0] for p in parts.values()} | {b for _, b in edges}:
        up = re.fullmatch(r"[^.]+\.([^.]+\.[^.]+\..+)", h)
        if up:
            edges |= {(h, up[1]), (up[1], h)}
    found = []
    for what, way in (("allow", edges), ("block", {(b, a) for a, b in edges})):
        seeds = {parts[i][0] for i in parts if rule_of(*parts[i])[1] == what} - {""}
        out = Counter(a for a, _ in way)
        score = {s: url_trust.UNIT for s in seeds}
        for _ in range(rounds):
            new = Counter({s: url_trust.UNIT * 15 // 100 for s in seeds})
            for a, b in way:
                new[b] += score.get(a, 0) * 85 // (100 * out[a])
            score = new
        found.append(score)
    rows = []
    for i in parts:
        trust, distrust = (s.get(parts[i][0], 0) for s in found)
        rule, what = rule_of(*parts[i])
        rows.append((i, *parts[i], rule, what or ("block" if distrust * 100 > (trust + distrust) * 50 else "allow")))
    return sorted(rows)


def test_url_trust_against_plain(spark):
    r = random.Random(4)
    hosts = ["a.net", "x.a.net", "www.x.a.net", "b.example.net", "example.com", "c.org", "d.io", "e.io", "f.io", "g.h.io", "k.g.h.io", "z.example.com"]
    pages = []
    for i in range(60):
        links = "".join(f"<A class=q HREF='{r.choice(['http:', 'https:', ''])}//{r.choice(hosts).upper()}/p{r.randrange(9)}'>t</a>" for _ in range(r.randrange(4)))
        pages.append((i, r.choice([None, "none"] + [f"http://{h}{p}" for h in hosts for p in ("", "/en/1", "/de/?x", "/fr/#y", "/")]), r.choice([links, None, ""]) if i % 7 else links))
    got = url_trust.judge_urls(spark.createDataFrame(pages, "page_id long, url string, html string"))
    assert rows(got, "page_id", "host", "path", "rule", "verdict") == sorted(plain_trust(pages, url_trust.RULES), key=str)


def test_long_texts_count_alike(monkeypatch):
    r = random.Random(3)
    texts = [" ".join(r.choice(["a", "b", "cc", "d\n", "é"]) for _ in range(n)) for n in (0, 3, 5, 40, 900, 3000)] + [t or "" for t in ODD]
    want = [line_quality.base_counts(t.encode()) for t in texts]
    monkeypatch.setattr(line_quality, "PIECE", 16)
    assert [line_quality.base_counts(t.encode()) for t in texts] == want


def test_items_without_an_id_are_none(spark):
    docs = spark.createDataFrame([(1, "one two three four")], "doc_id long, text string")
    items = spark.createDataFrame([(None, "one two"), (5, "three four")], "item_id long, text string")
    r = decontamination.find_contamination(docs, items).first()
    assert (r.n_items, r.n_hit) == (1, 2)
