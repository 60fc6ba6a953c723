"""DuckDB SQL for the rows of the queries that SQL can express."""

from __future__ import annotations

from .licenses import NOTICES, PHRASES, SLACK
from .line_quality import BOILERPLATE, LineRules
from .url_trust import LOWERED, RULES, UNIT, UPPER

SPACED = r"[^\x20\x09-\x0D]+"
PLAIN = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words(text: str) -> str:
    return f"coalesce(regexp_extract_all(translate({text}, '{UPPER}', '{LOWERED}'), '{PLAIN}'), [])"


def url_trust(rounds: int = 10, damping: int = 85) -> str:
    href = r"""(?i)<a\s[^>]*?href\s*=\s*["'']?\s*((?:https?:)?//[^"''\s>]+)"""
    when = [(w, r, *r.partition("/")[::2]) for w, r in sorted(RULES, key=lambda r: (-len(r[1]), r[1]))]
    fits = lambda h, p: f"(host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '/{p}')"
    rule = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{r}'" for _, r, h, p in when) + " END"
    ruled = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{w}'" for w, _, h, p in when) + " END"
    steps = "".join(
        f""", r{i} AS MATERIALIZED (SELECT kind, host, CAST(sum(score) AS BIGINT) AS score FROM (
            SELECT e.kind, e.dst AS host, (r.score * {damping}) // (100 * e.n) AS score FROM r{i - 1} r JOIN paths e ON e.kind = r.kind AND e.src = r.host
            UNION ALL SELECT kind, host, {UNIT * (100 - damping) // 100} FROM seeds) GROUP BY ALL)"""
        for i in range(1, rounds + 1)
    )
    return f"""WITH p AS (SELECT page_id, html, translate(coalesce(regexp_extract(url, '://([^/?#]*)', 1), ''), '{UPPER}', '{LOWERED}') AS host,
            coalesce(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
        j AS (SELECT page_id, host, path, {rule} AS rule, {ruled} AS ruled FROM p),
        l AS (SELECT DISTINCT host AS src, translate(regexp_extract(u, '//([^/?#]*)', 1), '{UPPER}', '{LOWERED}') AS dst
            FROM (SELECT host, unnest(regexp_extract_all(html, '{href}', 1)) AS u FROM p)),
        links AS (SELECT * FROM l WHERE src <> dst AND src <> '' AND dst <> ''),
        nodes AS (SELECT host FROM p UNION SELECT dst FROM links),
        site AS (SELECT host AS src, regexp_extract(host, '^[^.]+\\.([^.]+\\.[^.]+\\..+)$', 1) AS dst FROM nodes WHERE regexp_matches(host, '^[^.]+\\.([^.]+\\.[^.]+\\..+)$')),
        e AS (SELECT * FROM links UNION SELECT * FROM site UNION SELECT dst, src FROM site),
        k AS (SELECT 0 AS kind, src, dst FROM e UNION ALL SELECT 1, dst, src FROM e),
        paths AS MATERIALIZED (SELECT *, count(*) OVER (PARTITION BY kind, src) AS n FROM k),
        seeds AS MATERIALIZED (SELECT DISTINCT CASE ruled WHEN 'allow' THEN 0 ELSE 1 END AS kind, host FROM j WHERE ruled IS NOT NULL AND host <> ''),
        r0 AS (SELECT kind, host, CAST({UNIT} AS BIGINT) AS score FROM seeds){steps},
        t AS (SELECT host, sum(CASE WHEN kind = 0 THEN score ELSE 0 END) AS trust, sum(CASE WHEN kind = 1 THEN score ELSE 0 END) AS distrust FROM r{rounds} GROUP BY host),
        o AS (SELECT j.*, CAST(coalesce(trust, 0) AS BIGINT) AS trust, CAST(coalesce(distrust, 0) AS BIGINT) AS distrust FROM j LEFT JOIN t USING (host))
        SELECT page_id, host, path, rule, coalesce(ruled, CASE WHEN distrust * 100 > (trust + distrust) * 50 THEN 'block' ELSE 'allow' END) AS verdict, trust, distrust FROM o"""


DECONTAMINATE = f"""WITH it AS (SELECT DISTINCT item_id, {words('text')} AS w FROM benchmark),
    iw AS (SELECT DISTINCT item_id, len(x) AS n, array_to_string(x, ' ') AS k
        FROM (SELECT item_id, unnest(list_transform(range(1, greatest(len(w) - 9, 1) + 1), lambda i: w[i:i + 9])) AS x FROM it WHERE len(w) > 0)),
    lens AS (SELECT DISTINCT n FROM iw),
    d AS (SELECT row_number() OVER () AS rid, doc_id, {words('text')} AS w FROM documents),
    dw AS (SELECT rid, i, n, array_to_string(w[i:i + n - 1], ' ') AS k FROM (SELECT rid, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, lens WHERE len(w) >= n)),
    hit AS MATERIALIZED (SELECT rid, i, dw.n, item_id FROM dw JOIN iw USING (k)),
    hw AS (SELECT rid, count(DISTINCT p) AS n_hit FROM (SELECT rid, unnest(range(i, i + n)) AS p FROM hit) GROUP BY rid),
    ids AS (SELECT rid, count(*) AS n_items, sha256(string_agg(s, ',' ORDER BY s)) AS h FROM (SELECT DISTINCT rid, item_id::VARCHAR AS s FROM hit) GROUP BY rid)
    SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
        coalesce(h, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated FROM d LEFT JOIN hw USING (rid) LEFT JOIN ids USING (rid)"""


def line_quality() -> str:
    r = LineRules()
    quoted = BOILERPLATE.pattern.replace("'", "''")
    seps = r"len(regexp_extract_all(line, '[|»›•·]|\s[>/]\s'))"
    marks = "length(regexp_replace(line, '[^#*$%&|<>]', '', 'g'))"
    ends = r"""regexp_matches(line, '[.!?…。！？؟।:;]["''”’»)\]*_]*[ \t\n\r\x0B\x0C]*$')"""
    fails = f"""({seps} >= 2 AND n <= 6 * (1 + {seps})) OR {marks} > {r.max_symbols_per_word} * n
        OR (n <= {r.boilerplate_words} AND regexp_matches(line, '(?i){quoted}')) OR (n < {r.short_line} AND NOT {ends})"""
    return f"""WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{SPACED}') AS w FROM documents),
        l AS (SELECT rid, line, len(regexp_extract_all(line, '{SPACED}')) AS n FROM (SELECT rid, unnest(string_split(text, chr(10))) AS line FROM d)),
        s AS (SELECT rid, count(*) - count(DISTINCT line) AS dup, sum(CASE WHEN {fails} THEN 0 ELSE n END) AS stay FROM l WHERE n > 0 GROUP BY rid),
        win AS (SELECT rid, i, array_to_string(w[i:i + 4], ' ') AS k FROM (SELECT rid, w, unnest(range(1, len(w) - 3)) AS i FROM d)),
        rep AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, unnest(range(i, i + 5)) AS p FROM (SELECT rid, i FROM win QUALIFY count(*) OVER (PARTITION BY rid, k) > 1)) GROUP BY rid),
        m AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars,
            CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(dup, 0) AS BIGINT) AS n_dup_lines,
            CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words, coalesce(stay, 0) AS stay FROM d LEFT JOIN s USING (rid) LEFT JOIN rep USING (rid)),
        b AS (SELECT *, n_words < {r.min_words} OR 100 * n_repeat_words > {r.max_repeat_percent} * n_words AS base_failed FROM m)
        SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND stay >= {r.min_kept} * n_words AS kept FROM b"""


MIXTURE = f"""WITH d AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '{SPACED}')), 0) AS BIGINT) AS size FROM documents),
    s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
    r AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS rk, sum(source_size) OVER () * CAST(1.5 AS DOUBLE) AS total FROM s),
    w AS (SELECT *, CAST([5, 2, 1][CAST(rk % 3 AS INT) + 1] AS DOUBLE) AS wt, source_size * CAST(2 AS DOUBLE) AS cap FROM r),
    l AS (SELECT *, (total - coalesce(sum(cap) OVER (ORDER BY cap / wt, rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
        / sum(wt) OVER (ORDER BY cap / wt, rk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w),
    t AS (SELECT *, max(CASE WHEN level * wt <= cap THEN level END) OVER () AS best FROM l),
    g AS (SELECT source, source_size, coalesce(least(best * wt, cap), cap) AS target FROM t),
    h AS (SELECT *, length(bin(size)) AS bits, md5(coalesce(doc_id::VARCHAR, '')) AS hash FROM d),
    o AS (SELECT *, row_number() OVER (PARTITION BY source ORDER BY bits * 16 + (size >> greatest(bits - 4, 0)), ('0x' || substr(hash, 1, 2))::BIGINT % 64, size, hash, doc_id) AS pos FROM h),
    x AS (SELECT doc_id, size, source_size, target, pos, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS rate,
        ('0x' || substr(md5(coalesce(o.source, '') || '|17'), 1, 8))::BIGINT / CAST(4294967296 AS DOUBLE) AS u FROM o JOIN g ON o.source IS NOT DISTINCT FROM g.source)
    SELECT doc_id, size, source_size, target, CAST(floor(u + rate * pos) - floor(u + rate * (pos - 1)) AS BIGINT) * size AS taken FROM x"""


def license_scan(threshold: float = 0.8) -> str:
    notices = ", ".join(f"('{label}', '{text}')" for label, text in NOTICES.items())
    phrases = ", ".join(f"('{label}', ['{phrase.replace(' ', chr(39) + ', ' + chr(39))}'])" for phrase, label in PHRASES.items())
    return f"""WITH t AS (SELECT label, list_distinct({words('text')}) AS s, CAST(ceil(len({words('text')}) * {SLACK}) AS BIGINT) AS width FROM (VALUES {notices}) v(label, text)),
        f AS (SELECT * FROM (VALUES {phrases}) v(label, p)),
        d AS (SELECT row_number() OVER () AS rid, doc_id, text, {words('text')} AS w FROM documents),
        b AS (SELECT rid, label, i - 1 AS pos FROM (SELECT rid, w, label, p, unnest(range(1, len(w) - len(p) + 2)) AS i FROM d, f WHERE list_has_all(w, p)) WHERE w[i:i + len(p) - 1] = p),
        base AS (SELECT rid, count(*) AS n, min(pos) AS a, max(pos) AS z FROM b GROUP BY rid),
        x AS (SELECT rid, w, t.* FROM (SELECT rid, w, list_distinct(w) AS u FROM d) q, t WHERE len(list_intersect(u, s)) >= ceil({threshold} * len(s) - 1e-9)),
        p AS MATERIALIZED (SELECT rid, label, len(s) AS n, width, i, w[i] AS token FROM (SELECT *, unnest(range(1, len(w) + 1)) AS i FROM x) WHERE list_contains(s, w[i])),
        m AS (SELECT a.rid, a.label, a.n, a.i, count(DISTINCT z.token) AS shared FROM p a JOIN p z ON a.rid = z.rid AND a.label = z.label AND z.i BETWEEN a.i AND a.i + a.width - 1 GROUP BY ALL),
        c AS (SELECT rid, label, shared / n AS share FROM m WHERE shared >= ceil({threshold} * n - 1e-9)),
        best AS (SELECT rid, max(share) AS share FROM c GROUP BY rid),
        bl AS (SELECT rid, string_agg(label, ',' ORDER BY label) AS labels FROM (SELECT DISTINCT rid, label FROM b) GROUP BY rid),
        al AS (SELECT rid, string_agg(label, ',' ORDER BY label) AS labels FROM (SELECT rid, label FROM b UNION SELECT rid, label FROM c) GROUP BY rid)
        SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(base.n, 0) AS BIGINT) AS n_base, CAST(base.a AS BIGINT) AS first_word, CAST(base.z AS BIGINT) AS last_word,
            coalesce(bl.labels, '') AS base_labels, coalesce(al.labels, '') AS labels, CASE WHEN base.n > 0 THEN CAST(1 AS DOUBLE) ELSE CAST(coalesce(share, 0) AS DOUBLE) END AS score
        FROM d LEFT JOIN base USING (rid) LEFT JOIN bl USING (rid) LEFT JOIN al USING (rid) LEFT JOIN best USING (rid)"""


def oracle_sql() -> dict[str, str]:
    return {"op1_url_trust": url_trust(), "op4_decontaminate": DECONTAMINATE, "op6_line_quality": line_quality(), "op9_mixture": MIXTURE, "op10_license_scan": license_scan()}
