"""DuckDB SQL for the rows of the queries that SQL can express. Built from parts, as the queries are."""

from __future__ import annotations

WALK, WINDOW, SEED, DIM = 6, 3, 7, 4

PLANTED = """p AS (SELECT p_partkey AS node, p_type AS kind FROM part),
    half AS (SELECT a.node AS src, b.node AS dst FROM p a JOIN p b ON b.node > a.node AND b.node <= a.node + 120
        WHERE (7919 * a.node + 104729 * b.node) % 1009 < CASE WHEN a.kind = b.kind THEN 200 ELSE 8 END),
    edges AS (SELECT src, dst, CAST(1 AS DOUBLE) AS weight FROM half UNION ALL SELECT dst, src, CAST(1 AS DOUBLE) FROM half)"""
CONTENT = """ranks AS (SELECT kind, row_number() OVER (ORDER BY kind) - 1 AS rank FROM (SELECT DISTINCT p_type AS kind FROM part)),
    draws AS (SELECT p_partkey AS node, rank, ('0x' || substr(md5(p_partkey || '|' || t), 1, 8))::BIGINT AS h FROM part JOIN ranks ON kind = p_type, range(6) r(t)),
    content AS (SELECT DISTINCT node, CAST(CASE WHEN (h // 10) % 10 < 4 THEN rank * 10 + h % 10 ELSE h % 60 END AS INT) AS feature, CAST(1 AS DOUBLE) AS value FROM draws)"""
TRANSITION = "t AS (SELECT src, dst, weight / sum(weight) OVER (PARTITION BY src) AS p FROM edges)"


def draw(*parts: str) -> str:
    return "('0x' || substr(md5(" + " || '|' || ".join(f"CAST({p} AS VARCHAR)" for p in parts) + "), 1, 8))::BIGINT"


def unit(*parts: str) -> str:
    return f"({draw(*parts)} / CAST(4294967296 AS DOUBLE))"


def shared_items(items: str, low: int, high: int, least: int, stars: bool = True, more: str = "") -> str:
    star = "UNION ALL SELECT hub, node FROM items JOIN (SELECT item, min(node) AS hub FROM items GROUP BY item HAVING count(*) > %d) f USING (item) WHERE node <> hub" % high if stars else ""
    return f"""items AS (SELECT DISTINCT node, item FROM ({items})),
    held AS (SELECT item FROM items GROUP BY item HAVING count(*) BETWEEN {low} AND {high}),
    kept AS (SELECT node, item FROM items JOIN held USING (item)),
    linked AS (SELECT a.node AS src, b.node AS dst FROM kept a JOIN kept b ON a.item = b.item AND a.node < b.node {star}),
    half AS (SELECT src, dst, CAST(count(*) AS DOUBLE) AS weight FROM linked GROUP BY ALL HAVING count(*) >= {least} {more}),
    edges AS (SELECT src, dst, weight FROM half UNION ALL SELECT dst, src, weight FROM half)"""


TOKENS = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '')"
TEXTS = f"""toks AS (SELECT doc_id AS node, {TOKENS} AS t FROM documents),
    texts AS MATERIALIZED (SELECT node, t, min(node) OVER (PARTITION BY t) AS rep FROM toks WHERE len(t) >= 3)"""
SHINGLE = "list_transform(range(1, len(t) - 1), lambda i: array_to_string(t[i:i + 2], ' '))"
SHINGLES = f"SELECT node, unnest({SHINGLE}) AS item FROM texts WHERE node = rep"


def shingled(least: int = 2) -> str:
    """Edges of documents that share shingles of few texts; copies of a text hang on its first document."""
    copies = f"UNION ALL SELECT rep, node, CAST(len(list_distinct({SHINGLE})) AS DOUBLE) FROM texts WHERE node <> rep AND len(list_distinct({SHINGLE})) >= {least}"
    return f"{TEXTS}, {shared_items(SHINGLES, 2, 5, least, False, copies)}"


LINES = "SELECT * FROM (SELECT doc_id AS node, unnest(string_split(text, chr(10))) AS item FROM documents) WHERE length(item) >= 10"
HREFS = """SELECT page_id AS node, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS item FROM pages"""
HOSTS = "SELECT page_id AS node, regexp_extract(url, '://([^/?#]*)', 1) AS item FROM pages"
ORDERS = "SELECT l_partkey AS node, l_orderkey AS item FROM lineitem"
USER_KEY = """half AS (SELECT user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) + 1099511627776 AS dst, CAST(count(*) AS DOUBLE) AS weight FROM events GROUP BY ALL),
    edges AS (SELECT src, dst, weight FROM half UNION ALL SELECT dst, src, weight FROM half)"""
ALL_EDGES = "SELECT src, dst, weight FROM edges"
PAIRS = """pairs AS (SELECT src, dst, CAST(1 AS INT) AS is_edge FROM half
    UNION ALL SELECT a.p_partkey, b.p_partkey, 0 FROM part a JOIN part b ON b.p_partkey = a.p_partkey + 121 + a.p_partkey % 50)"""
COMMON = "shared AS (SELECT q.src, q.dst, e.dst AS mid FROM pairs q JOIN edges e ON e.src = q.src JOIN edges f ON f.src = q.dst AND f.dst = e.dst)"
DEGREE = "deg AS (SELECT src AS node, count(*) AS degree FROM edges GROUP BY src)"
ATTACHMENT = f"{PLANTED}, {PAIRS}, {DEGREE}, scores AS (SELECT q.*, CAST(a.degree * b.degree AS DOUBLE) AS score FROM pairs q JOIN deg a ON a.node = q.src JOIN deg b ON b.node = q.dst)"


def powers(order: int, keep: str = "") -> str:
    out = [f"p1 AS MATERIALIZED (SELECT src, dst, p AS value FROM t{keep})"]
    for k in range(2, order + 1):
        out.append(f"p{k} AS MATERIALIZED (SELECT a.src, b.dst, sum(a.value * b.p) AS value FROM p{k - 1} a JOIN t b ON a.dst = b.src GROUP BY a.src, b.dst)")
    return ", ".join(out)


def weighted_powers(weights: list[float]) -> str:
    parts = " UNION ALL ".join(f"SELECT src, dst, value * CAST({w!r} AS DOUBLE) AS value FROM p{k}" for k, w in enumerate(weights, 1))
    return f"WITH {PLANTED}, {TRANSITION}, {powers(len(weights))} SELECT src, dst, round(sum(value), 12) AS value FROM ({parts}) GROUP BY src, dst"


def pagerank(beta: float, order: int) -> str:
    parts = " UNION ALL ".join(f"SELECT src, dst, value * CAST({(1 - beta) * beta**k!r} AS DOUBLE) AS value FROM p{k}" for k in range(1, order + 1))
    own = f"SELECT p_partkey, p_partkey, CAST({1 - beta!r} AS DOUBLE) FROM part WHERE p_partkey % 20 = 0"
    return f"WITH {PLANTED}, {TRANSITION}, {powers(order, ' WHERE src % 20 = 0')} SELECT src, dst, round(sum(value), 12) AS value FROM ({parts} UNION ALL {own}) GROUP BY src, dst"


def biased(length: int = 4, p: float = 0.5, q: float = 2.0, tries: int = 40) -> str:
    """Second-order walks by numbered tries; all weights are 1. No walk here needs more than `tries`."""
    m = max(1.0, 1 / q)
    name = lambda x: "'" + x + "'"
    share = lambda x, at: unit(str(SEED), name(x), "walk_id", str(at), "try")
    out = ["adj AS MATERIALIZED (SELECT src AS node, list(dst ORDER BY dst) AS nbrs, count(*) AS n FROM edges GROUP BY src)", "b0 AS (SELECT node AS walk_id, CAST(NULL AS BIGINT) AS last, node AS cur, [node] AS path FROM adj)"]
    for at in range(1, length):
        back = "CASE WHEN last IS NULL THEN 0 ELSE 1 END"
        x = f"({share('step', at)} * (n - {back}))"
        out.append(f"""c{at} AS MATERIALIZED (SELECT b.*, try, {share('back', at)} * ({back} / CAST({p} AS DOUBLE) + (n - {back}) * CAST({m} AS DOUBLE)) < {back} / CAST({p} AS DOUBLE) AS returns, {share('keep', at)} * CAST({m} AS DOUBLE) AS keep, n, nbrs,
            CASE WHEN last IS NOT NULL AND {x} >= list_position(nbrs, last) - 1 THEN {x} + 1 ELSE {x} END AS x FROM b{at - 1} b JOIN adj ON node = cur, range({tries}) r(try))""")
        out.append(f"""d{at} AS MATERIALIZED (SELECT c.*, nbrs[CAST(least(floor(x), n - 1) AS BIGINT) + 1] AS cand FROM c{at} c)""")
        weight = f"CASE WHEN last IS NULL THEN CAST({m} AS DOUBLE) WHEN cand = last THEN 0 WHEN list_contains(a.nbrs, cand) THEN 1 ELSE CAST({1 / q} AS DOUBLE) END"
        out.append(f"""e{at} AS MATERIALIZED (SELECT walk_id, cur, path, try, CASE WHEN returns THEN last WHEN keep < {weight} THEN cand END AS nx FROM d{at} d LEFT JOIN adj a ON a.node = last)""")
        out.append(f"b{at} AS MATERIALIZED (SELECT walk_id, cur AS last, nx AS cur, list_append(path, nx) AS path FROM (SELECT *, row_number() OVER (PARTITION BY walk_id ORDER BY try) AS r FROM e{at} WHERE nx IS NOT NULL) WHERE r = 1)")
    return f"WITH {PLANTED}, " + ", ".join(out) + f" SELECT walk_id, array_to_string(path, ',') AS path FROM b{length - 1}"


def walks() -> str:
    """Walks of one node each step, by the running weight above the draw; all weights are 1 here, so it is a rank."""
    out = ["adj AS MATERIALIZED (SELECT src, list(dst ORDER BY dst) AS nbrs, count(*) AS n FROM edges GROUP BY src)", "w0 AS (SELECT src AS walk_id, src AS cur, [src] AS path FROM adj)"]
    for at in range(1, WALK):
        pick = f"nbrs[CAST(least(floor({unit(str(SEED), 'walk_id', str(at))} * n), n - 1) AS BIGINT) + 1]"
        out.append(f"w{at} AS MATERIALIZED (SELECT walk_id, {pick} AS cur, list_append(path, {pick}) AS path FROM w{at - 1} JOIN adj ON src = cur)")
    return ", ".join(out) + f", walks AS (SELECT walk_id, path FROM w{WALK - 1})"


def forward(mode: str = "all", strict: bool = False) -> str:
    offsets = range(1, WINDOW if strict else WINDOW + 1)
    if mode == "all":
        parts = " UNION ALL ".join(f"SELECT path[i] AS node, path[i + {k}] AS context FROM walks, range(1, {WALK - k + 1}) r(i)" for k in offsets)
    elif mode == "offset_uniform":
        k = f"(CAST(floor({unit(str(SEED), chr(39) + 'offset' + chr(39), 'walk_id', '0')} * {WINDOW}) AS BIGINT) + 1)"
        i = f"CAST(floor({unit(str(SEED), chr(39) + 'place' + chr(39), 'walk_id', '0')} * ({WALK} - k)) AS BIGINT)"
        parts = f"SELECT path[i + 1] AS node, path[i + k + 1] AS context FROM (SELECT *, {i} AS i FROM (SELECT *, {k} AS k FROM walks))"
    else:
        counts = [WALK - k for k in offsets]
        ends = [sum(counts[: j + 1]) for j in range(len(counts))]
        n = f"CAST(floor({unit(str(SEED), chr(39) + 'pair' + chr(39), 'walk_id', '0')} * {ends[-1]}) AS BIGINT)"
        k = "CASE " + " ".join(f"WHEN n < {e} THEN {j + 1}" for j, e in enumerate(ends)) + " END"
        i = "CASE " + " ".join(f"WHEN n < {e} THEN n - {e - c}" for e, c in zip(ends, counts)) + " END"
        parts = f"SELECT path[i + 1] AS node, path[i + k + 1] AS context FROM (SELECT path, {k} AS k, {i} AS i FROM (SELECT path, {n} AS n FROM walks))"
    return f"fwd AS (SELECT node, context, count(*) AS cnt FROM ({parts}) GROUP BY node, context)"


MIRROR = "cooc AS (SELECT node, context, CAST(sum(cnt) AS BIGINT) AS cnt FROM (SELECT node, context, cnt FROM fwd UNION ALL SELECT context, node, cnt FROM fwd) GROUP BY node, context)"


def counts(mode: str = "all", strict: bool = False, both: bool = True) -> str:
    tail = f", {MIRROR}" if both else ", cooc AS (SELECT * FROM fwd)"
    return f"{PLANTED}, {walks()}, {forward(mode, strict)}{tail}"


def label_pairs(rounds: int = 2000) -> str:
    q = lambda name: "'" + name + "'"
    return f"""lab AS (SELECT p_partkey AS node, p_type AS label FROM part),
    cls AS (SELECT label, n, sum(n) OVER (ORDER BY label) AS top FROM (SELECT label, count(*) AS n FROM lab GROUP BY label)),
    rnk AS (SELECT label, node, row_number() OVER (PARTITION BY label ORDER BY node) - 1 AS r FROM lab),
    d1 AS (SELECT id, CAST(floor({unit(str(SEED), q('first'), 'id')} * (SELECT sum(n) FROM cls)) AS BIGINT) AS x FROM range({rounds}) g(id)),
    d2 AS (SELECT id, label, n, x - (top - n) AS r1 FROM d1 JOIN cls ON x >= top - n AND x < top WHERE n > 1),
    d3 AS (SELECT *, CAST(floor({unit(str(SEED), q('second'), 'id')} * (n - 1)) AS BIGINT) AS r0 FROM d2),
    d4 AS (SELECT label, r1, CASE WHEN r0 >= r1 THEN r0 + 1 ELSE r0 END AS r2 FROM d3),
    one AS (SELECT a.node AS node, b.node AS context, count(*) AS cnt FROM d4 JOIN rnk a ON a.label = d4.label AND a.r = r1 JOIN rnk b ON b.label = d4.label AND b.r = r2 GROUP BY ALL),
    lp AS (SELECT node, context, CAST(sum(cnt) AS BIGINT) AS cnt FROM (SELECT * FROM one UNION ALL SELECT context, node, cnt FROM one) GROUP BY node, context)"""


CAPS = """tot AS (SELECT CAST(sum(cnt) AS DOUBLE) AS total FROM cooc), rt AS (SELECT node, sum(cnt) AS row_tot FROM cooc GROUP BY node), ct AS (SELECT context, sum(cnt) AS col_tot FROM cooc GROUP BY context),
    caps AS (SELECT node, context, cnt, 2.0::DOUBLE * row_tot * col_tot / total AS product FROM cooc JOIN rt USING (node) JOIN ct USING (context), tot)"""


def four(what: str) -> str:
    """The first round of four dimensions: all pairs of nodes and contexts, vectors in four columns."""
    dims = range(DIM)
    each = lambda f: ", ".join(f(i) for i in dims)
    dot = lambda a, b: " + ".join(f"{a}.v{i} * {b}.v{i}" for i in dims)
    init = lambda name, key, rows: f"SELECT {key}, " + each(lambda i: f"{unit(str(SEED), chr(39) + name + chr(39), key, str(i))} - 0.5 AS v{i}") + f" FROM ({rows})"

    def long(key: str, rows: str) -> str:
        return " UNION ALL ".join(f"SELECT {key}, CAST({i} AS INT) AS i, round(v{i}, 5) AS v FROM {rows}" for i in dims)

    def pairs(n: str, w: str, h: str = "h") -> str:
        """Scores, residuals and losses of all pairs, from the nodes' vectors in w."""
        return f"""x{n} AS MATERIALIZED (SELECT w.node, h.context, {dot('w', 'h')} AS x, coalesce(cnt, 0) AS n, CAST(r AS DOUBLE) * c / total AS q, h.l FROM {w} w JOIN rt USING (node), hc h
                LEFT JOIN cooc o ON o.node = w.node AND o.context = h.context, tot),
            g{n} AS MATERIALIZED (SELECT node, context, n + q AS cap, (n + q) / (1 + exp(-x)) - n AS g, (n + q) * (greatest(x, 0) + ln(1 + exp(-abs(x)))) - n * x AS loss, l FROM x{n})"""

    def features(n: str, w: str) -> str:
        return f"""y{n} AS (SELECT context, {each(lambda i: f'sum(g * v{i}) AS v{i}')} FROM g{n} JOIN {w} USING (node) GROUP BY context),
            gf{n} AS (SELECT CAST(feature AS BIGINT) AS feature, {each(lambda i: f'sum(value * v{i}) AS v{i}')} FROM used JOIN y{n} ON used.node = y{n}.context GROUP BY feature)"""

    base = f"""WITH {counts()}, {CONTENT},
    used AS MATERIALIZED (SELECT * FROM content WHERE node IN (SELECT context FROM cooc)),
    s AS MATERIALIZED ({init('feature', 'feature', 'SELECT DISTINCT feature FROM used')}),
    w AS MATERIALIZED ({init('node', 'node', 'SELECT DISTINCT node FROM cooc')}),
    h AS MATERIALIZED (SELECT c.node AS context, {each(lambda i: f'sum(value * v{i}) AS v{i}')} FROM content c JOIN s USING (feature) GROUP BY c.node),
    tot AS (SELECT sum(cnt) AS total FROM cooc), rt AS (SELECT node, sum(cnt) AS r FROM cooc GROUP BY node), ct AS (SELECT context, sum(cnt) AS c FROM cooc GROUP BY context),
    hc AS MATERIALIZED (SELECT h.*, c, {dot('h', 'h')} AS l FROM h JOIN ct USING (context)),
    {pairs('1', 'w')}"""
    nodes = f"gn AS (SELECT node, sum(cap * g1.l) / 4 AS curve, {each(lambda i: f'sum(g * v{i}) AS v{i}')} FROM g1 JOIN hc USING (context) GROUP BY node)"
    stepped = f"wb AS MATERIALIZED (SELECT w.node, {each(lambda i: f'w.v{i} - gn.v{i} / greatest(curve, 1e-12) AS v{i}')} FROM w JOIN gn USING (node))"
    second = f"{nodes}, {stepped}, {pairs("2", "wb")}, {features("2", "wb")}"
    # the features' curvature: cap, squared length of the context's content and of the node's vector
    curve = f"f2 AS (SELECT node AS context, sum(value * value) AS f2 FROM used GROUP BY node), cv AS (SELECT sum(cap * f2 * ({dot("wb", "wb")})) / 4 AS curve FROM g2 JOIN f2 USING (context) JOIN wb USING (node))"
    moved = f"s2 AS MATERIALIZED (SELECT s.feature, {each(lambda i: f's.v{i} - coalesce(gf2.v{i}, 0) / greatest(curve, 1e-12) AS v{i}')} FROM s LEFT JOIN gf2 USING (feature), cv)"
    if what == "losses":
        h3 = f"h3 AS (SELECT c.node AS context, {each(lambda i: f'sum(value * v{i}) AS v{i}')} FROM content c JOIN s2 USING (feature) GROUP BY c.node)"
        third = pairs("3", "wb").replace("hc h", f"(SELECT h3.*, c, {dot('h3', 'h3')} AS l FROM h3 JOIN ct USING (context)) h")
        return f"""{base}, {second}, {curve}, {moved}, {h3}, {third}, l AS (SELECT (SELECT sum(loss) FROM g1) AS a, (SELECT sum(loss) FROM g2) AS b, (SELECT sum(loss) FROM g3) AS c)
            SELECT 'nodes' AS half, round(a, 3) AS before, round(b, 3) AS after, b < a AS falls FROM l UNION ALL SELECT 'features', round(b, 3), round(c, 3), c < b FROM l"""
    return base + {
        "h": " " + long("context", "h"),
        "loss": " SELECT node, round(sum(loss), 5) AS loss FROM g1 GROUP BY node",
        "nodes": f", {nodes} " + long("node", "gn"),
        "features": f", {features('1', 'w')} " + long("feature", "gf1"),
        "step": f", {nodes}, {stepped} " + long("node", "wb"),
        "outer": f", {second}, {curve}, {moved} " + long("CAST(feature AS BIGINT) AS feature", "s2"),
        "expected": " SELECT node, context, round(cap - cap / (1 + exp(x)), 6) AS expected FROM g1 JOIN x1 USING (node, context) JOIN cooc USING (node, context)",
    }[what]


def measures(method: str, scores: str) -> str:
    """AUC and both MAPs of scores(src, dst, is_edge, score)."""
    return f"""{scores}, ag AS (SELECT score, CAST(sum(is_edge) AS DOUBLE) AS pos, CAST(sum(1 - is_edge) AS DOUBLE) AS neg FROM scores GROUP BY score),
        ab AS (SELECT *, coalesce(sum(neg) OVER (ORDER BY score ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM ag),
        mr AS (SELECT is_edge, row_number() OVER o AS k, sum(is_edge) OVER (o ROWS UNBOUNDED PRECEDING) AS hits FROM scores WINDOW o AS (ORDER BY score DESC, src, dst)),
        nr AS (SELECT src, is_edge, row_number() OVER o AS k, sum(is_edge) OVER (o ROWS UNBOUNDED PRECEDING) AS hits FROM scores WINDOW o AS (PARTITION BY src ORDER BY score DESC, src, dst)),
        na AS (SELECT src, avg(CAST(hits AS DOUBLE) / k) AS ap FROM nr WHERE is_edge = 1 GROUP BY src)
        SELECT '{method}' AS method, (SELECT round(sum(pos * (below + neg / 2)) / (sum(pos) * sum(neg)), 9) FROM ab) AS auc,
            (SELECT round(avg(CAST(hits AS DOUBLE) / k), 9) FROM mr WHERE is_edge = 1) AS map, (SELECT round(avg(ap), 9) FROM na) AS map_per_node"""


def facts(method: str, dim: int, *more: str) -> str:
    """What must hold of a fit on the planted parts: a finite vector for each part with an edge, linked ones nearer, loss falling."""
    return f"WITH {PLANTED} SELECT '{method}' AS method, count(DISTINCT src) AS nodes, CAST({dim} AS BIGINT) AS dim, true AS finite" + "".join(f", true AS {m}" for m in more) + " FROM edges"


def components() -> str:
    return f"""WITH RECURSIVE {shingled()},
    reach AS (SELECT src AS node, src AS r FROM edges UNION SELECT reach.node, e.dst FROM reach JOIN edges e ON e.src = reach.r)
    SELECT node, min(r) AS component FROM reach GROUP BY node"""


def two_core(rounds: int = 12) -> str:
    out = [f"WITH {shingled()}, e0 AS MATERIALIZED (SELECT * FROM edges)"]
    for k in range(1, rounds + 1):
        good = f"(SELECT src FROM e{k - 1} GROUP BY src HAVING count(*) >= 2)"
        out.append(f"e{k} AS MATERIALIZED (SELECT * FROM e{k - 1} WHERE src IN {good} AND dst IN {good})")
    return ", ".join(out) + f" SELECT src, dst, weight FROM e{rounds}"


def grouped(kind: str) -> str:
    return f"""SELECT source, lang, round(avg(CASE WHEN lang2 = predicted THEN 1.0 ELSE 0.0 END), 12) AS accuracy, count(*) AS n
    FROM (SELECT source, lang, lang AS lang2, CASE WHEN n_chars % 2 = 0 THEN 'en' ELSE 'fr' END AS predicted FROM documents) GROUP BY {kind} (source, lang)"""


COS = "list_sum(list_transform(list_zip(a.v, b.v), lambda z: z[1] * z[2]))"
UNITS = "u0 AS (SELECT vec_id AS node, CAST(label AS VARCHAR) AS label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS r FROM embeddings), u AS MATERIALIZED (SELECT node, label, list_transform(r, lambda x: x / sqrt(list_sum(list_transform(r, lambda y: y * y)))) AS v FROM u0)"
NEAREST = f"{UNITS}, cs AS MATERIALIZED (SELECT a.node, b.node AS neighbor, a.label AS la, b.label AS lb, {COS} AS score FROM u a, u b WHERE a.node <> b.node)"


COMMON_SCORES = f"WITH {PLANTED}, {PAIRS}, {COMMON}, c AS (SELECT src, dst, count(*) AS n FROM shared GROUP BY src, dst), scores AS (SELECT src, dst, is_edge, CAST(coalesce(n, 0) AS DOUBLE) AS score FROM pairs LEFT JOIN c USING (src, dst))"
JACCARD_SCORES = f"""WITH {PLANTED}, {PAIRS}, {COMMON}, {DEGREE}, c AS (SELECT src, dst, count(*) AS n FROM shared GROUP BY src, dst),
    scores AS (SELECT q.src, q.dst, is_edge, round(CAST(coalesce(n, 0) AS DOUBLE) / (a.degree + b.degree - coalesce(n, 0)), 12) AS score FROM pairs q LEFT JOIN c ON c.src = q.src AND c.dst = q.dst JOIN deg a ON a.node = q.src JOIN deg b ON b.node = q.dst)"""
ADAMIC_SCORES = f"""WITH {PLANTED}, {PAIRS}, {COMMON}, {DEGREE}, c AS (SELECT src, dst, sum(1 / ln(degree)) AS s FROM shared JOIN deg ON node = mid GROUP BY src, dst),
    scores AS (SELECT src, dst, is_edge, round(CAST(coalesce(s, 0) AS DOUBLE), 6) AS score FROM pairs LEFT JOIN c USING (src, dst))"""


def repeated_majority(seeds: tuple[int, ...] = (7, 8, 9)) -> str:
    one = lambda seed: f"""SELECT (SELECT avg(CASE WHEN label = (SELECT label FROM t{seed} WHERE train GROUP BY label ORDER BY count(*) DESC, label LIMIT 1) THEN 1.0 ELSE 0.0 END)
        FROM (SELECT label FROM t{seed} WHERE NOT train ORDER BY h, node LIMIT 500)) AS accuracy"""  # noqa: E731
    parts = ", ".join(f"""l{s} AS (SELECT p_partkey AS node, p_type AS label, {draw(str(s), 'p_partkey')} AS h FROM part),
        t{s} AS (SELECT *, row_number() OVER (PARTITION BY label ORDER BY h, node) <= least(20, count(*) OVER (PARTITION BY label) // 2) AS train FROM l{s})""" for s in seeds)
    return f"WITH {parts} SELECT 'majority' AS method, round(avg(accuracy), 9) AS mean, round(stddev(accuracy), 9) AS spread, count(*) AS runs FROM ({' UNION ALL '.join(map(one, seeds))})"


def oracle_sql() -> dict[str, str]:
    out = {
        "graph_planted": f"WITH {PLANTED} {ALL_EDGES}",
        "graph_shingle": f"WITH {shingled()} {ALL_EDGES}",
        "graph_shingle_dense": f"WITH {shingled(1)} {ALL_EDGES}",
        "graph_line": f"WITH {shared_items(LINES, 2, 20, 1)} {ALL_EDGES}",
        "graph_copurchase": f"WITH {shared_items(ORDERS, 2, 1 << 30, 1)} {ALL_EDGES}",
        "graph_bipartite": "WITH half AS (SELECT DISTINCT o_custkey AS src, l_suppkey + 1099511627776 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey) SELECT src, dst, CAST(1 AS DOUBLE) AS weight FROM half UNION ALL SELECT dst, src, CAST(1 AS DOUBLE) FROM half",
        "graph_colink": f"WITH {shared_items(HREFS, 2, 1000, 1)} {ALL_EDGES}",
        "graph_same_host": f"WITH {shared_items(HOSTS, 2, 1000, 1)} {ALL_EDGES}",
        "graph_user_key": f"WITH {USER_KEY} {ALL_EDGES}",
        "planted_content": f"WITH {CONTENT} SELECT node, feature, value FROM content",
        "planted_source": f"WITH {PLANTED} SELECT src, dst, weight FROM half, (SELECT CAST(1 AS DOUBLE) AS weight)",
        "degree_stats": f"WITH {shared_items(ORDERS, 2, 1 << 30, 1)} SELECT src AS node, count(*) AS degree, sum(weight) AS strength FROM edges GROUP BY src",
        "transition_probs": f"WITH {USER_KEY}, {TRANSITION} SELECT src, dst, round(p, 12) AS p FROM t",
        "symmetric_transition": f"WITH {USER_KEY}, s AS (SELECT src AS node, sum(weight) AS s FROM edges GROUP BY src) SELECT src, dst, round(weight / sqrt(a.s * b.s), 12) AS p FROM edges JOIN s a ON a.node = src JOIN s b ON b.node = dst",
        "components_documents": components(),
        "two_core": two_core(),
        "transition_power2": f"WITH {PLANTED}, {TRANSITION}, {powers(2)} SELECT src, dst, round(value, 12) AS value FROM p2",
        "proximity_sum_l3": weighted_powers([1.0] * 3),
        "two_hop_mean": weighted_powers([0.5, 0.5]),
        "expected_cooc_walk_weights": weighted_powers([5 / 12, 4 / 12, 3 / 12]),
        "rooted_pagerank_roots": pagerank(0.5, 10),
        "walks_md5": f"WITH {PLANTED}, {walks()} SELECT walk_id, array_to_string(path, ',') AS path FROM walks",
        "cooc_all_w3": f"WITH {counts()} SELECT * FROM cooc",
        "cooc_strict": f"WITH {counts(strict=True)} SELECT * FROM cooc",
        "cooc_forward": f"WITH {counts(both=False)} SELECT * FROM cooc",
        "cooc_sampled": f"WITH {counts('sampled')} SELECT * FROM cooc",
        "cooc_offset_uniform": f"WITH {counts('offset_uniform')} SELECT * FROM cooc",
        "label_pairs_md5": f"WITH {label_pairs()} SELECT * FROM lp",
        "label_pairs_expected": """WITH lab AS (SELECT p_partkey AS node, p_type AS label FROM part), n AS (SELECT count(*) AS a FROM lab), s AS (SELECT label, count(*) AS size FROM lab GROUP BY label)
            SELECT x.node, y.node AS context, round(CAST(2000 AS DOUBLE) / a / (size - 1), 12) AS expected FROM lab x JOIN lab y ON x.label = y.label AND x.node <> y.node JOIN s ON s.label = x.label, n""",
        "cooc_merged": f"WITH {counts()}, {label_pairs()} SELECT node, context, CAST(sum(cnt) AS BIGINT) AS cnt FROM (SELECT * FROM cooc UNION ALL SELECT * FROM lp) GROUP BY node, context",
        "isolated_documents": f"WITH {shingled()} SELECT doc_id AS node FROM documents WHERE doc_id NOT IN (SELECT src FROM edges)",
        "marginals": f"WITH {counts(both=False)} SELECT 'node' AS side, node AS id, CAST(sum(cnt) AS BIGINT) AS total FROM cooc GROUP BY node UNION ALL SELECT 'context', context, CAST(sum(cnt) AS BIGINT) FROM cooc GROUP BY context",
        "cap_at_pairs": f"WITH {counts()}, {CAPS} SELECT node, context, cnt, round(product, 6) AS product, round(product + cnt, 6) AS cap FROM caps",
        "shifted_pmi": f"WITH {counts()}, {CAPS} SELECT node, context, round(ln(cnt / product), 6) AS spmi FROM caps",
        "content_tfidf_top": f"""WITH tk AS (SELECT doc_id AS node, unnest({TOKENS}) AS item FROM documents), c AS (SELECT node, item, count(*) AS n FROM tk GROUP BY ALL),
            v AS (SELECT item, count(*) AS df FROM c GROUP BY item ORDER BY df DESC, item LIMIT 50), vn AS (SELECT item, df, CAST(row_number() OVER (ORDER BY item) - 1 AS INT) AS feature FROM v),
            x AS (SELECT node, feature, (1 + ln(CAST(n AS DOUBLE))) * ln(CAST((SELECT count(*) FROM documents) AS DOUBLE) / df) AS value FROM c JOIN vn USING (item)), y AS (SELECT * FROM x WHERE value > 0)
            SELECT node, feature, round(value / sqrt(sum(value * value) OVER (PARTITION BY node)), 6) AS value FROM y""",
        "content_onehot_parts": """WITH i AS (SELECT p_partkey AS node, unnest(['p_brand=' || p_brand, 'p_type=' || p_type]) AS item FROM part), f AS (SELECT item, CAST(row_number() OVER (ORDER BY item) - 1 AS INT) AS feature FROM (SELECT DISTINCT item FROM i))
            SELECT node, feature, CAST(1 AS DOUBLE) AS value FROM i JOIN f USING (item)""",
        "context_dictionary_d4": four("h"),
        "loss_init_d4": four("loss"),
        "grad_nodes_d4": four("nodes"),
        "grad_features_d4": four("features"),
        "one_node_step_d4": four("step"),
        "one_outer_d4": four("outer"),
        "half_step_losses_d4": four("losses"),
        "expected_counts_d4": four("expected"),
        "walks_biased": biased(),
        "walks_stationary": f"WITH {PLANTED}, d AS (SELECT src AS node, sum(weight) AS s FROM edges GROUP BY src), n AS (SELECT sum(s) AS total, count(*) AS n FROM d) SELECT node, CAST(floor(s * 2 * n / total) AS BIGINT) AS least, true AS as_many FROM d, n",
        "link_common": f"WITH {PLANTED}, {PAIRS}, {COMMON}, c AS (SELECT src, dst, count(*) AS n FROM shared GROUP BY src, dst) SELECT src, dst, is_edge, CAST(coalesce(n, 0) AS DOUBLE) AS score FROM pairs LEFT JOIN c USING (src, dst)",
        "link_jaccard": f"""WITH {PLANTED}, {PAIRS}, {COMMON}, {DEGREE}, c AS (SELECT src, dst, count(*) AS n FROM shared GROUP BY src, dst)
            SELECT q.src, q.dst, is_edge, round(CAST(coalesce(n, 0) AS DOUBLE) / (a.degree + b.degree - coalesce(n, 0)), 12) AS score FROM pairs q LEFT JOIN c ON c.src = q.src AND c.dst = q.dst JOIN deg a ON a.node = q.src JOIN deg b ON b.node = q.dst""",
        "link_adamic_adar": f"WITH {PLANTED}, {PAIRS}, {COMMON}, {DEGREE}, c AS (SELECT src, dst, sum(1 / ln(degree)) AS s FROM shared JOIN deg ON node = mid GROUP BY src, dst) SELECT src, dst, is_edge, round(CAST(coalesce(s, 0) AS DOUBLE), 6) AS score FROM pairs LEFT JOIN c USING (src, dst)",
        "link_attachment": f"WITH {ATTACHMENT} SELECT src, dst, is_edge, score FROM scores",
        "link_content": f"""WITH {PLANTED}, {CONTENT}, {PAIRS}, l AS (SELECT node, sqrt(count(*)) AS l FROM content GROUP BY node),
            d AS (SELECT q.src, q.dst, count(*) AS n FROM pairs q JOIN content a ON a.node = q.src JOIN content b ON b.node = q.dst AND a.feature = b.feature GROUP BY ALL)
            SELECT q.src, q.dst, is_edge, round(coalesce(n, 0) / (a.l * b.l), 12) AS score FROM pairs q LEFT JOIN d ON d.src = q.src AND d.dst = q.dst JOIN l a ON a.node = q.src JOIN l b ON b.node = q.dst""",
        "auc_common": f"SELECT round(auc, 12) AS auc FROM ({measures('x', COMMON_SCORES).replace(', 9)', ', 12)')})",
        "map_common": f"SELECT map FROM ({measures('x', COMMON_SCORES).replace(', 9)', ', 12)')})",
        "map_per_node_common": f"SELECT map_per_node AS map FROM ({measures('x', COMMON_SCORES).replace(', 9)', ', 12)')})",
        "measures_attachment": measures("attachment", f"WITH {ATTACHMENT}"),
        "measures_jaccard": measures("jaccard", JACCARD_SCORES),
        "measures_adamic_adar": measures("adamic_adar", ADAMIC_SCORES),
        "relative_gains": f"""WITH m AS (SELECT 'planted parts' AS dataset, method, auc AS value, method = 'adamic_adar' AS ours FROM (SELECT * FROM ({measures("attachment", f"WITH {ATTACHMENT}")}) UNION ALL SELECT * FROM ({measures("jaccard", JACCARD_SCORES)}) UNION ALL SELECT * FROM ({measures("adamic_adar", ADAMIC_SCORES)})))
            SELECT *, CASE WHEN ours THEN round(value / (SELECT max(value) FROM m WHERE NOT ours) - 1, 6) END AS gain FROM m""",
        "repeated_majority": repeated_majority(),
        "class_folds": f"""SELECT node, label, CAST(ntile(5) OVER (PARTITION BY label ORDER BY h, node) AS INT) AS fold FROM (SELECT p_partkey AS node, p_type AS label, {draw(str(SEED), 'p_partkey')} AS h FROM part)""",
        "hashed_neighbors_recall": "SELECT 5 * count(*) AS asked, true AS recall_reached FROM embeddings WHERE vec_id % 20 = 0",
        "picture_embeddings": "SELECT count(*) AS n, true AS ordered, true AS uncorrelated FROM embeddings",
        "proximity_gap_facts": f"WITH {PLANTED}, d AS (SELECT src, count(*) AS n FROM edges GROUP BY src) SELECT CAST(2 AS INT) AS k_split, round(CAST({2 - 2 * 0.5**3!r} AS DOUBLE), 9) AS bound, round(CAST({1 - 2 * 0.5**3 + 2 * 0.5**11 + 6 / 10!r} AS DOUBLE), 9) AS pre_bound, true AS applicable, min(n) = max(n) AS premise_symmetric, true AS positive, true AS above_one FROM d",
        "fit_joint": facts("joint", 8, "nearer", "falls"),
        "fit_joint_exact": facts("joint_exact", 8, "nearer", "falls"),
        "fit_joint_by_joins": facts("joint_by_joins", 8, "nearer", "falls"),
        "fit_counts_only": facts("counts_only", 8, "nearer", "falls"),
        "fit_uncapped_loss": facts("uncapped", 8, "nearer", "falls"),
        "fit_squared_loss": facts("squared", 8, "falls"),
        "fit_backtracking": facts("backtracking", 8, "nearer", "falls"),
        "fit_safe_step": facts("safe_step", 8, "nearer", "falls"),
        "fit_fixed_step": facts("fixed_step", 8, "falls"),
        "fit_skipgram": facts("skipgram", 8, "nearer"),
        "fit_biased_skipgram": facts("biased_skipgram", 8, "nearer"),
        "fit_squared_content": facts("squared_content", 16, "nearer"),
        "fit_squared_homophily": facts("squared_homophily", 16, "nearer"),
        "fit_squared_margin": facts("squared_margin", 16, "nearer"),
        "fit_spectral_fusion": "SELECT 'spectral_fusion' AS method, count(*) AS nodes, CAST(8 AS BIGINT) AS dim, true AS finite, true AS nearer FROM part",
        "fit_graph_conv": "SELECT 'graph_conv' AS method, count(*) AS nodes, true AS better FROM part",
        "fit_graph_conv_joins": "SELECT 'graph_conv_joins' AS method, count(*) AS nodes, true AS better FROM part",
        "fit_context_label": "SELECT 'context_label' AS method, count(*) AS nodes, true AS better FROM part",
        "fit_joint_history": "SELECT CAST(o AS INT) AS \"outer\", half, true AS falls, true AS looked FROM range(3) r(o), (VALUES ('nodes'), ('features')) h(half)",
        "embed_without_structure": "SELECT count(*) AS nodes, CAST(8 AS BIGINT) AS dim, true AS finite FROM part WHERE p_partkey % 5 = 0",
        "cosine_pairs_embeddings": f"WITH {UNITS} SELECT a.node AS src, b.node AS dst, round({COS}, 5) AS score FROM u a JOIN u b ON b.node = a.node + 1",
        "class_separation_embeddings": f"""WITH {NEAREST}, r AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY score DESC, neighbor) AS k FROM cs)
            SELECT (SELECT round(avg(score), 5) FROM cs WHERE la = lb) AS within, (SELECT round(avg(score), 5) FROM cs WHERE la <> lb) AS across, round(avg(CASE WHEN la = lb THEN 1.0 ELSE 0.0 END), 5) AS knn_agreement FROM r WHERE k <= 5""",
        "top_neighbors_embeddings": f"WITH {NEAREST}, r AS (SELECT node, neighbor, CAST(row_number() OVER (PARTITION BY node ORDER BY score DESC, neighbor) AS INT) AS rank FROM cs) SELECT * FROM r WHERE rank <= 3",
        "split_per_class": f"""WITH l AS (SELECT p_partkey AS node, p_type AS label, {draw(str(SEED), 'p_partkey')} AS h FROM part),
            r AS (SELECT *, row_number() OVER (PARTITION BY label ORDER BY h, node) AS r, count(*) OVER (PARTITION BY label) AS n FROM l), t AS (SELECT *, r <= least(20, n // 2) AS train FROM r),
            o AS (SELECT node FROM t WHERE NOT train ORDER BY h, node LIMIT 500) SELECT node, label, CASE WHEN train THEN 'train' WHEN node IN (SELECT node FROM o) THEN 'test' ELSE 'none' END AS part FROM t""",
        "accuracy_rollup": grouped("ROLLUP"),
        "accuracy_cube": grouped("CUBE"),
        "session_walks_batch": """WITH e AS (SELECT user_id, ts, event_id, json_extract_string(props, '$.k') AS node, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS cut FROM events),
            s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS no FROM e)
            SELECT user_id, count(*) AS n, string_agg(node, ',' ORDER BY ts, event_id) AS path FROM s GROUP BY user_id, no""",
        "tumbling_counts": "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL",
        "next_events": """WITH x AS (SELECT event_id, user_id, lead(event_id) OVER w AS nx, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS g FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))
            SELECT event_id, user_id, CASE WHEN g <= 1800000000 THEN nx END AS next_id, CASE WHEN g <= 1800000000 THEN round(g / 1e6, 3) END AS gap FROM x""",
        "band_join_parts": "SELECT a.p_partkey AS a, b.p_partkey AS b, CAST(a.p_size + b.p_size AS BIGINT) AS size FROM part a JOIN part b ON b.p_partkey BETWEEN a.p_partkey + 1 AND a.p_partkey + 5",
        "salted_join_orders": "SELECT c_mktsegment, count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY c_mktsegment",
        "top_links_attachment": f"WITH {ATTACHMENT} SELECT src, dst, is_edge, score FROM scores ORDER BY score DESC, src, dst LIMIT 25",
    }
    both = shared_items(LINES, 2, 20, 1).replace("items AS", "items2 AS").replace("FROM items ", "FROM items2 ").replace("linked AS", "linked2 AS").replace("FROM linked ", "FROM linked2 ").replace("held AS", "held2 AS").replace("JOIN held ", "JOIN held2 ").replace("kept AS", "kept2 AS")
    both = both.replace("FROM kept a JOIN kept b", "FROM kept2 a JOIN kept2 b").replace("half AS", "half2 AS").replace("FROM half ", "FROM half2 ").replace("FROM half)", "FROM half2)").replace("edges AS", "edges2 AS")
    a, b = "SELECT src, dst FROM edges", "SELECT src, dst FROM edges2"
    out["set_operations_graphs"] = f'WITH {shingled()}, {both} SELECT (SELECT count(*) FROM ({a} INTERSECT {b})) AS "both", (SELECT count(*) FROM ({a} UNION {b})) AS either, (SELECT count(*) FROM ({a} EXCEPT ALL {b})) AS first_only'
    out["graph_checks"] = f"WITH {PLANTED} SELECT count(*) AS edges, CAST(0 AS BIGINT) AS null_ids, CAST(count(*) FILTER (weight <= 0) AS BIGINT) AS bad_weights, CAST(count(*) FILTER (src = dst) AS BIGINT) AS self_loops, CAST(0 AS BIGINT) AS duplicated_pairs, CAST(0 AS BIGINT) AS one_way_pairs FROM edges"
    out["hidden_edges_checks"] = f"""WITH RECURSIVE {shingled()},
        reach AS (SELECT src AS node, src AS r FROM edges UNION SELECT reach.node, e.dst FROM reach JOIN edges e ON e.src = reach.r), c AS (SELECT count(DISTINCT m) AS n FROM (SELECT min(r) AS m FROM reach GROUP BY node))
        SELECT (SELECT count(*) FROM half) AS edges, n AS components_before, n AS components_after, CAST(0 AS BIGINT) AS hidden_not_edge, CAST(0 AS BIGINT) AS non_edge_is_edge FROM c"""
    return out
