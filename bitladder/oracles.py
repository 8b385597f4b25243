"""SQL (DuckDB) for the registered queries, by routes that share no code with them.

Codes are rebuilt as lists of ±1 with Hadamard rows and compared by list products:
no popcount, no bit packing.
"""

from __future__ import annotations

import math

SCALE = math.sqrt(2.0 / (math.pi * 64)) / 8.0
N, LANE, WIDTH = 10, 8, 16


def planes(weighted: bool = True) -> str:
    """CTEs to ``p2``: vec_id, v and the sign lists s0, s1, s2 of every vector."""
    w1, w2 = (0.5, 0.25) if weighted else (1.0, 1.0)
    sign = "list(CASE WHEN list_dot_product({x}, r) > 0 THEN 1.0 ELSE -1.0 END ORDER BY i)"
    left = f"list(v[i + 1] - tanh({SCALE!r} * list_dot_product({{b}}, r)) ORDER BY i)"
    return f"""
h AS (SELECT i, list(CASE WHEN bit_count(CAST(i & j AS BIGINT)) % 2 = 0 THEN CAST(1 AS DOUBLE) ELSE CAST(-1 AS DOUBLE) END ORDER BY j) AS r FROM range(64) a(i), range(64) b(j) GROUP BY i),
e AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings WHERE embedding IS NOT NULL),
p0 AS (SELECT vec_id, any_value(v) AS v, {sign.format(x='v')} AS s0 FROM e, h GROUP BY vec_id),
l1 AS (SELECT vec_id, any_value(v) AS v, any_value(s0) AS s0, {left.format(b='s0')} AS x FROM p0, h GROUP BY vec_id),
p1 AS (SELECT vec_id, any_value(v) AS v, any_value(s0) AS s0, {sign.format(x='x')} AS s1 FROM l1, h GROUP BY vec_id),
c1 AS (SELECT vec_id, v, s0, s1, list_transform(list_zip(s0, s1), lambda z: z[1] + {w1} * z[2]) AS b FROM p1),
l2 AS (SELECT vec_id, any_value(v) AS v, any_value(s0) AS s0, any_value(s1) AS s1, {left.format(b='b')} AS x FROM c1, h GROUP BY vec_id),
p2 AS (SELECT vec_id, any_value(v) AS v, any_value(s0) AS s0, any_value(s1) AS s1, {sign.format(x='x')} AS s2 FROM l2, h GROUP BY vec_id)"""


def dense(depth: int, weighted: bool = True) -> str:
    """The scaled whole-number code of ``depth`` residual planes."""
    w = [2 ** (depth - t) if weighted else 1 for t in range(3)]
    if depth == 0:
        return "s0"
    if depth == 1:
        return f"list_transform(list_zip(s0, s1), lambda z: {w[0]} * z[1] + {w[1]} * z[2])"
    return f"list_transform(list_zip(s0, s1, s2), lambda z: {w[0]} * z[1] + {w[1]} * z[2] + {w[2]} * z[3])"


def shift(depth: int, weighted: bool = True) -> int:
    total = sum(2 ** (depth - t) if weighted else 1 for t in range(depth + 1))
    return 2 * math.ceil(math.log2(64 * total * total + 1))


def pairs(u: int = 2, v: int = 1, weighted: bool = True, self_too: bool = False) -> str:
    """CTEs to ``scored``: q, k, s (dot), qn, kn and key of all pairs."""
    return f"""WITH {planes(weighted)},
code AS (SELECT vec_id, {dense(u, weighted)} AS dq, {dense(v, weighted)} AS dk FROM p2),
raw AS (SELECT q.vec_id AS q, k.vec_id AS k, CAST(list_dot_product(q.dq, k.dk) AS BIGINT) AS s, list_dot_product(q.dq, q.dq) AS qn, CAST(list_dot_product(k.dk, k.dk) AS BIGINT) AS kn
  FROM code q, code k{'' if self_too else ' WHERE q.vec_id <> k.vec_id'}),
scored AS (SELECT *, CASE WHEN kn > 0 THEN CASE WHEN s < 0 THEN -1 ELSE 1 END * ((s * s * {2 ** shift(v, weighted)}) // kn) END AS key, CASE WHEN qn * kn > 0 THEN s / sqrt(qn * CAST(kn AS DOUBLE)) END AS cos FROM raw)"""


TOP = "SELECT q AS query_id, CAST(rn AS INTEGER) AS rank, k AS keyword_id, key AS rank_key FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY key DESC, k) AS rn FROM {source}) WHERE rn <= {n}"
EXACT = f"{pairs()} {TOP.format(source='scored', n=N)}"


def lane(r: int = 1, size: int = LANE) -> str:
    return f"""(SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY q, k // {size * WIDTH} * {WIDTH} + k % {WIDTH} ORDER BY key DESC, k) AS lr FROM scored) WHERE lr <= {r})"""


def lane_top(r: int = 1) -> str:
    return f"{pairs()} {TOP.format(source=lane(r), n=N)}"


def code_dots(u: int, v: int, weighted: bool = True) -> str:
    return f"""{pairs(u, v, weighted, True)} SELECT q AS query_id, count(*) AS pairs, CAST(sum(s) AS BIGINT) AS dots, CAST(0 AS BIGINT) AS order_gap, max(key) AS best_key,
round(sum(cos), 6) AS cosines, round(max(CASE WHEN q <> k THEN cos END), 9) AS nearest FROM scored GROUP BY q"""


FLOAT = """fl AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings WHERE embedding IS NOT NULL),
fp AS (SELECT a.vec_id AS q, b.vec_id AS k, list_dot_product(list_transform(a.v, lambda x: x / sqrt(list_dot_product(a.v, a.v))), list_transform(b.v, lambda x: x / sqrt(list_dot_product(b.v, b.v)))) AS c FROM fl a, fl b WHERE a.vec_id <> b.vec_id),
near AS (SELECT * FROM (SELECT q, k, c, row_number() OVER (PARTITION BY q ORDER BY c DESC, k) AS rn FROM fp) WHERE rn <= 10)"""


def auc(select: str, by: str) -> str:
    """Area by rank sums over ``select`` (columns: by, s, pos)."""
    return f"""SELECT {by}, (sum(CASE WHEN pos THEN r END) - count_if(pos) * (count_if(pos) + 1) / 2.0) / (count_if(pos) * CAST(count_if(NOT pos) AS DOUBLE)) AS auc
FROM (SELECT {by}, pos, avg(n) OVER (PARTITION BY {by}, s) AS r FROM (SELECT {by}, pos, s, row_number() OVER (PARTITION BY {by} ORDER BY s) AS n FROM ({select}))) GROUP BY {by}"""


def depth_scores(depths, weighted: bool = True, p: str = "p2") -> str:
    parts = []
    for u, v in depths:
        a, b = (f"(SELECT vec_id, {dense(d, weighted)} AS d FROM {p})" for d in (u, v))
        parts.append(f"SELECT 'code({u},{v})' AS model, q.vec_id AS q, k.vec_id AS k, list_dot_product(q.d, k.d) / sqrt(nullif(list_dot_product(q.d, q.d) * list_dot_product(k.d, k.d), 0)) AS s FROM {a} q, {b} k WHERE q.vec_id <> k.vec_id")
    return " UNION ALL ".join(parts)


def bits() -> str:
    rows = f"SELECT x.model, x.s, n.q IS NOT NULL AS pos FROM ({depth_scores(((0, 0), (1, 1), (2, 1), (2, 2)))}) x LEFT JOIN near n ON n.q = x.q AND n.k = x.k"
    return f"WITH {planes()}, {FLOAT} SELECT model, round(auc, 9) AS auc FROM ({auc(rows, 'model')})"


def weights() -> str:
    def side(weighted: bool) -> str:
        rows = f"SELECT x.model, x.s, n.q IS NOT NULL AS pos FROM ({depth_scores(((1, 1), (2, 1), (2, 2)), weighted)}) x LEFT JOIN near n ON n.q = x.q AND n.k = x.k WHERE x.s IS NOT NULL"
        return f"(WITH {planes(weighted)}, {FLOAT} {auc(rows, 'model')})"

    return f"SELECT a.model, round(a.auc, 9) AS auc_weighted, round(b.auc, 9) AS auc_plain FROM {side(True)} a JOIN {side(False)} b ON a.model = b.model"


GROUPS = """best AS (SELECT q AS g, k FROM near WHERE rn = 1),
members AS (SELECT g, k, true AS pos FROM best UNION ALL SELECT g, k, false FROM (SELECT vec_id AS g, (vec_id + d) % (SELECT count(*) FROM embeddings) AS k FROM embeddings, range(1, 11) t(d)) o WHERE NOT EXISTS (SELECT 1 FROM best b WHERE b.g = o.g AND b.k = o.k)),
gs AS (SELECT m.g, m.pos, s.cos FROM members m JOIN scored s ON s.q = m.g AND s.k = m.k)"""


def log_loss(gammas, both: bool) -> str:
    grid = ", ".join(f"({g})" for g in gammas)
    head = f"{pairs(self_too=True)}, {FLOAT}, {GROUPS}, probs AS (SELECT gamma, g, pos, exp(gamma * cos) / sum(exp(gamma * cos)) OVER (PARTITION BY gamma, g) AS p FROM gs, (VALUES {grid}) t(gamma))"
    if both:
        return f"{head} SELECT CAST(gamma AS DOUBLE) AS gamma, round(sum(CASE WHEN pos THEN -ln(p) END) / count_if(pos), 9) AS per_group, round(sum(CASE WHEN pos THEN -ln(p) END) / count(*), 9) AS per_sample FROM probs GROUP BY gamma"
    return f"{head} SELECT CAST(gamma AS DOUBLE) AS gamma, round(avg(CASE WHEN pos THEN -ln(p) END), 9) AS log_loss FROM probs GROUP BY gamma"


WORDS = "list_filter(string_split(regexp_replace(lower(coalesce({t}, '')), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'), ' '), lambda w: length(w) > 0)"


def words(t: str = "text") -> str:
    return WORDS.format(t=t)


POSTINGS = f"""kp AS (SELECT doc_id AS k, term, count(*) AS tf FROM (SELECT doc_id, unnest({words()}) AS term FROM documents) GROUP BY ALL),
qp AS (SELECT item_id AS q, term, count(*) AS qtf FROM (SELECT item_id, unnest({words()}) AS term FROM benchmark) GROUP BY ALL),
n AS (SELECT CAST(count(*) AS DOUBLE) AS c FROM documents), df AS (SELECT term, count(*) AS df FROM kp GROUP BY term)"""
RANK5 = "SELECT q AS query_id, CAST(rn AS INTEGER) AS rank, k AS keyword_id, score FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY score DESC, k) AS rn FROM (SELECT q, k, round(score, 6) AS score FROM {source})) WHERE rn <= 5"
BM25 = f"""{POSTINGS}, ln AS (SELECT k, sum(tf) AS len FROM kp GROUP BY k), mean AS (SELECT sum(len) / (SELECT c FROM n) AS m FROM ln),
bm AS (SELECT qp.q, kp.k, sum(ln((c - df + 0.5) / (df + 0.5) + 1.0) * tf * 2.2 / (tf + 1.2 * (1.0 - 0.75 + 0.75 * len / m))) AS score FROM qp JOIN kp USING (term) JOIN df USING (term) JOIN ln ON ln.k = kp.k, n, mean GROUP BY qp.q, kp.k)"""
TFIDF = """kw AS (SELECT k, kp.term, tf * ln(c / df) AS w FROM kp JOIN df ON df.term = kp.term, n), qw AS (SELECT q, qp.term, qtf * ln(c / df) AS w FROM qp JOIN df ON df.term = qp.term, n),
tn AS (SELECT k, sqrt(sum(w * w)) AS kn FROM kw GROUP BY k), qnorm AS (SELECT q, sqrt(sum(w * w)) AS qn FROM qw GROUP BY q),
ti AS (SELECT d.q, d.k, d.dot / (kn * qn) AS score FROM (SELECT qw.q, kw.k, sum(qw.w * kw.w) AS dot FROM qw JOIN kw ON kw.term = qw.term GROUP BY ALL) d JOIN tn ON tn.k = d.k JOIN qnorm ON qnorm.q = d.q WHERE kn > 0 AND qn > 0)"""


def triples(table: str, key: str) -> str:
    return f"SELECT DISTINCT {key}, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT {key}, w, unnest(range(1, len(w) - 1)) AS i FROM (SELECT {key}, {words()} AS w FROM {table}) WHERE len(w) >= 3)"


JUDGED = f"""ta AS ({triples('benchmark', 'item_id')}), tb AS ({triples('documents', 'doc_id')}), sz AS (SELECT item_id, count(*) AS size FROM ta GROUP BY item_id),
jg AS (SELECT query_id, keyword_id, CASE WHEN c >= 0.3 THEN 'excellent' WHEN c >= 0.05 THEN 'good' ELSE 'fair' END AS grade FROM (SELECT item_id AS query_id, doc_id AS keyword_id, count(*) / any_value(size) AS c FROM ta JOIN tb USING (g) JOIN sz USING (item_id) GROUP BY ALL)),
dr AS (SELECT DISTINCT item_id AS query_id, (item_id * 7919 + j * 104729) % (SELECT count(*) FROM documents) AS keyword_id FROM benchmark, range(1, 21) t(j)),
jd AS (SELECT *, true AS is_pos FROM jg UNION ALL SELECT query_id, keyword_id, 'bad', false FROM dr WHERE keyword_id IN (SELECT doc_id FROM documents) AND NOT EXISTS (SELECT 1 FROM jg WHERE jg.query_id = dr.query_id AND jg.keyword_id = dr.keyword_id))"""
CLICKS = "SELECT DISTINCT user_id AS query_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS keyword_id FROM events WHERE event_type = 'click'"
VIEWS = """FROM (SELECT *, json_extract_string(props, '$.k') AS item FROM events WHERE event_type = 'click') c JOIN (SELECT *, json_extract_string(props, '$.k') AS item FROM events WHERE event_type = 'view') v
ON c.user_id = v.user_id AND c.item = v.item AND v.ts <= c.ts AND v.ts >= c.ts - INTERVAL 5 DAY"""



def vector_planes(name: str, source: str) -> str:
    """CTEs {name}0 to {name}2: planes of the vectors (vec_id, v) of ``source``; rows h must be known."""
    sign = "list(CASE WHEN list_dot_product({x}, r) > 0 THEN 1.0 ELSE -1.0 END ORDER BY i)"
    left = f"list(v[i + 1] - tanh({SCALE!r} * list_dot_product({{b}}, r)) ORDER BY i)"
    return f"""{name}0 AS (SELECT vec_id, any_value(v) AS v, {sign.format(x='v')} AS s0 FROM {source}, h GROUP BY vec_id),
{name}x AS (SELECT vec_id, any_value(v) AS v, any_value(s0) AS s0, {left.format(b='s0')} AS x FROM {name}0, h GROUP BY vec_id),
{name}1 AS (SELECT vec_id, any_value(v) AS v, any_value(s0) AS s0, {sign.format(x='x')} AS s1 FROM {name}x, h GROUP BY vec_id),
{name}c AS (SELECT vec_id, v, s0, s1, list_transform(list_zip(s0, s1), lambda z: z[1] + 0.5 * z[2]) AS b FROM {name}1),
{name}y AS (SELECT vec_id, any_value(s0) AS s0, any_value(s1) AS s1, {left.format(b='b')} AS x FROM {name}c, h GROUP BY vec_id),
{name}2 AS (SELECT vec_id, any_value(s0) AS s0, any_value(s1) AS s1, {sign.format(x='x')} AS s2 FROM {name}y, h GROUP BY vec_id)"""


def hashed_sum(table: str, key: str) -> str:
    """vec_id, v: the sum of the words' MD5 sign vectors, scaled to length one."""
    half = "CAST('0x' || substr(md5(x), {at}, 8) AS BIGINT)"
    bit = f"CASE WHEN i >= 32 THEN ({half.format(at=1)} >> (i - 32)) & 1 ELSE ({half.format(at=9)} >> i) & 1 END"
    return f"""SELECT vec_id, list_transform(v, lambda x: x / norm) AS v FROM (SELECT vec_id, v, sqrt(list_sum(list_transform(v, lambda x: x * x))) AS norm FROM (SELECT vec_id, list(CAST(s AS DOUBLE) ORDER BY i) AS v
FROM (SELECT vec_id, i, sum(n * (2 * {bit} - 1)) AS s FROM (SELECT {key} AS vec_id, x, count(*) AS n FROM (SELECT {key}, unnest({words()}) AS x FROM {table}) GROUP BY ALL), range(64) t(i) GROUP BY vec_id, i) GROUP BY vec_id)) WHERE norm > 0"""


def bm25(name: str, where: str) -> str:
    """The five best by BM25 over the documents that ``where`` keeps."""
    return f"""{name}p AS (SELECT * FROM kp WHERE {where.format(k='k')}), {name}n AS (SELECT CAST(count(*) AS DOUBLE) AS c FROM documents WHERE {where.format(k='doc_id')}), {name}d AS (SELECT term, count(*) AS df FROM {name}p GROUP BY term), {name}l AS (SELECT k, sum(tf) AS len FROM {name}p GROUP BY k), {name}m AS (SELECT sum(len) / (SELECT c FROM {name}n) AS m FROM {name}l),
{name}s AS (SELECT qp.q, p.k, sum(ln((c - df + 0.5) / (df + 0.5) + 1.0) * tf * 2.2 / (tf + 1.2 * (1.0 - 0.75 + 0.75 * len / m))) AS score FROM qp JOIN {name}p p ON p.term = qp.term JOIN {name}d d ON d.term = qp.term JOIN {name}l l ON l.k = p.k, {name}n, {name}m GROUP BY qp.q, p.k),
{name} AS ({RANK5.format(source=f'{name}s')})"""


ROWS = "h AS (SELECT i, list(CASE WHEN bit_count(CAST(i & j AS BIGINT)) % 2 = 0 THEN CAST(1 AS DOUBLE) ELSE CAST(-1 AS DOUBLE) END ORDER BY j) AS r FROM range(64) a(i), range(64) b(j) GROUP BY i)"
SAMPLED = "CAST('0x' || substr(md5('0:' || CAST({k} AS VARCHAR)), 1, 7) AS BIGINT) % 1000 < (SELECT share FROM fits)"
#: our codes (``ours``) and both production settings (``th``) from text, and judged pairs (``jd``)
SYSTEMS = f"""WITH {ROWS}, {JUDGED}, {POSTINGS}, fits AS (SELECT 20 * (SELECT count(*) FROM documents) * 1000 // greatest(12 * (SELECT count(*) FROM kp), 1) AS share),
{bm25('pa', 'true')}, {bm25('pb', SAMPLED)}, th AS (SELECT 'equal keywords' AS baseline, query_id, keyword_id FROM pa UNION ALL SELECT 'equal memory', query_id, keyword_id FROM pb),
qe AS ({hashed_sum('benchmark', 'item_id')}), ke AS ({hashed_sum('documents', 'doc_id')}), {vector_planes('qa', 'qe')}, {vector_planes('ka', 'ke')},
code_q AS (SELECT vec_id AS q, {dense(2)} AS dq FROM qa2), code_k AS (SELECT vec_id AS k, {dense(1)} AS dk FROM ka2),
raw AS (SELECT q, k, CAST(list_dot_product(dq, dk) AS BIGINT) AS s, CAST(list_dot_product(dk, dk) AS BIGINT) AS kn FROM code_q, code_k),
scored AS (SELECT q, k, CASE WHEN s < 0 THEN -1 ELSE 1 END * ((s * s * {2 ** shift(1)}) // kn) AS key FROM raw WHERE kn > 0),
ours AS (SELECT q AS query_id, CAST(rn AS INTEGER) AS rank, k AS keyword_id, key AS rank_key FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY key DESC, k) AS rn FROM {lane()}) WHERE rn <= 5)"""

BENT = "list_transform(list_zip(r, range(64)), lambda z: z[1] * CASE WHEN bit_count(CAST(z[2] & (z[2] >> 1) AS BIGINT)) % 2 = 0 THEN 1 ELSE -1 END)"
ACCURACY = f"""WITH {planes()}, {FLOAT}, h2 AS (SELECT i, r FROM h UNION ALL SELECT i + 64, {BENT} FROM h),
w AS (SELECT vec_id, list(CASE WHEN list_dot_product(v, r) > 0 THEN 1.0 ELSE -1.0 END ORDER BY i) AS s FROM e, h2 GROUP BY vec_id),
tv AS (SELECT vec_id, list(list_dot_product(v, r) ORDER BY i) AS f FROM e, h GROUP BY vec_id), k1 AS (SELECT vec_id, {dense(1)} AS d FROM p2),
sc AS (SELECT 'float64d' AS model, q, k, c AS s FROM fp UNION ALL SELECT 'sign128', a.vec_id, b.vec_id, list_dot_product(a.s, b.s) / 128.0 FROM w a, w b WHERE a.vec_id <> b.vec_id
UNION ALL SELECT 'hybrid', a.vec_id, b.vec_id, list_dot_product(a.f, b.d) / sqrt(list_dot_product(a.f, a.f) * list_dot_product(b.d, b.d)) FROM tv a, k1 b WHERE a.vec_id <> b.vec_id UNION ALL {depth_scores(((0, 0), (2, 1)))}),
au AS ({auc("SELECT x.model, x.s, n.q IS NOT NULL AS pos FROM sc x LEFT JOIN near n ON n.q = x.q AND n.k = x.k", 'model')})
SELECT model, round(auc, 6) AS auc, round((auc - (SELECT auc FROM au WHERE model = 'sign128')) * 100.0 / ((SELECT auc FROM au WHERE model = 'float64d') - (SELECT auc FROM au WHERE model = 'sign128')), 2) AS auc_lift FROM au"""


def recall() -> str:
    parts = []
    for size in (4, 8, 16):
        for r in (1, 2):
            got = f"(SELECT q, k FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY key DESC, k) AS rn FROM {lane(r, size)}) WHERE rn <= {N})"
            # hypergeometric chances that a lane holds none, or one, of the N
            none = "exp(lgamma(c - {i} + 1) - lgamma(c - {i} - {n} + 1) - lgamma(c + 1) + lgamma(c - {n} + 1))".format(i=size, n=N)
            one = f"({size}.0 * {N} / (c - {size} - {N} + 1) * {none})"
            kept = f"(1 - {none})" if r == 1 else f"({one} + 2 * (1 - {none} - {one}))"
            parts.append(f"SELECT {size} AS lane_size, {r} AS r, count(DISTINCT e.q) AS queries, round(count(g.q) / (count(DISTINCT e.q) * {N}.0), 9) AS recall, round({N} - count(g.q) / CAST(count(DISTINCT e.q) AS DOUBLE), 9) AS mean_missed, round(any_value({N} - t.c // {size} * {kept}), 6) AS theory FROM ex e LEFT JOIN {got} g ON g.q = e.q AND g.k = e.k, (SELECT CAST(count(*) - count(*) % {size} AS DOUBLE) AS c FROM embeddings) t")
    return f"{pairs()}, ex AS (SELECT q, k FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY key DESC, k) AS rn FROM scored) WHERE rn <= {N}) " + " UNION ALL ".join(parts)


RECALL = recall()


def miss(count: str, n: int, size: int, most: int) -> str:
    """Misses by the lanes' overflow among ``count`` keywords: each way to share l among lanes, relative to no miss at all."""

    def ways(left: int, largest: int):
        if left == 0:
            yield ()
        for e in range(min(left, largest), 0, -1):
            for rest in ways(left - e, e):
                yield (e, *rest)

    terms = []
    for l in range(most + 1):  # noqa: E741
        for way in ways(l, l):
            factor = []
            for e in set(way):
                # lanes that hold 1 + e of the relevant, against lanes that hold one each
                share = " * ".join([*(f"({size - i}e0 / {i + 1})" for i in range(1 + e)), f"power({size}e0, -{1 + e})"])
                factor.append(f"power({share}, {way.count(e)}) / {math.factorial(way.count(e))}")
            down = " * ".join(f"{n - i}e0" for i in range(len(way) + l)) or "1e0"
            up = " * ".join(f"(lanes - {n - i})" for i in range(1, l + 1)) or "1e0"
            terms.append(f"SELECT {l} AS l, {' * '.join(factor) or '1e0'} * ({down}) / ({up}) AS x FROM t")
    none = f"(SELECT exp(sum(ln((c - i * {size}e0) / (c - i)))) FROM t, range({n}) k(i))"
    return f"WITH t AS (SELECT CAST(c - c % {size} AS DOUBLE) AS c, CAST(c // {size} AS DOUBLE) AS lanes FROM ({count})), p AS (SELECT l, sum(x) * {none} AS p FROM ({' UNION ALL '.join(terms)}) GROUP BY l) SELECT CAST(l AS INTEGER) AS l, round(p, 9) AS p, round(sum(p) OVER (ORDER BY l), 9) AS p_cum FROM p"


MISS = miss("SELECT count(l_orderkey) AS c FROM lineitem", 100, 16, 4)
USABLE = "embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL)) = 0"


def values(weighted: bool) -> str:
    """planes, values: distinct values of a dimension among codes of one to four planes."""
    w = [8, 4, 2, 1] if weighted else [1, 1, 1, 1]
    b = "list_transform(list_zip(s0, s1, s2), lambda z: " + ("z[1] + 0.5 * z[2] + 0.25 * z[3]" if weighted else "z[1] + z[2] + z[3]") + ")"
    parts = " UNION ALL ".join(f"SELECT {p} AS planes, count(DISTINCT {' + '.join(f'{w[t]} * z[{t + 1}]' for t in range(p))}) AS n FROM z" for p in range(1, 5))
    return f"""(WITH {planes(weighted)}, c2 AS (SELECT vec_id, v, s0, s1, s2, {b} AS b FROM p2), l3 AS (SELECT vec_id, any_value(s0) AS s0, any_value(s1) AS s1, any_value(s2) AS s2, list(v[i + 1] - tanh({SCALE!r} * list_dot_product(b, r)) ORDER BY i) AS x FROM c2, h GROUP BY vec_id),
p3 AS (SELECT vec_id, any_value(s0) AS s0, any_value(s1) AS s1, any_value(s2) AS s2, list(CASE WHEN list_dot_product(x, r) > 0 THEN 1.0 ELSE -1.0 END ORDER BY i) AS s3 FROM l3, h GROUP BY vec_id), z AS (SELECT unnest(list_zip(s0, s1, s2, s3)) AS z FROM p3) {parts})"""


WORD = "((CAST('0x' || substr({d}, 1, 8) AS HUGEINT) << 32) + CAST('0x' || substr({d}, 9, 8) AS HUGEINT))"


def generated() -> str:
    """Recall over MD5 codes: bits as HUGEINT, compared by xor."""
    def words_of(key: str, count: int, p: str) -> str:
        return ", ".join(f"{WORD.format(d=f'md5({key} || {chr(39)}:{i}{chr(39)})')} AS {p}{i}" for i in range(count))

    keys = "concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey)"
    dot = " + ".join(f"{2 ** (2 - i + 1 - j)} * (64 - 2 * CAST(bit_count(xor(q{i}, k{j})) AS INTEGER))" for i in range(3) for j in range(2))
    lane_of = "pos // 1024 * 16 + pos % 16"
    top = "SELECT q, pos FROM (SELECT q, pos, row_number() OVER (PARTITION BY q ORDER BY key DESC, pos) AS rn FROM {s}) WHERE rn <= 100"
    return f"""WITH a AS (SELECT s_suppkey AS q, {words_of("CAST(s_suppkey AS VARCHAR)", 3, 'q')} FROM supplier), b AS (SELECT row_number() OVER (ORDER BY md5({keys})) - 1 AS pos, {words_of(keys, 2, 'k')} FROM lineitem),
s AS (SELECT q, pos, CAST({dot} AS BIGINT) AS s, CAST(320 + 4 * (64 - 2 * CAST(bit_count(xor(k0, k1)) AS INTEGER)) AS BIGINT) AS n FROM a, b), t AS (SELECT q, pos, CASE WHEN s < 0 THEN -1 ELSE 1 END * ((s * s * {2 ** shift(1)}) // n) AS key FROM s),
ex AS ({top.format(s='t')}), ln AS (SELECT q, max(struct_pack(key := key, p := -pos)) AS m FROM t GROUP BY q, {lane_of}), la AS ({top.format(s='(SELECT q, m.key AS key, -m.p AS pos FROM ln)')}),
c AS (SELECT count(*) AS c FROM lineitem), x AS (SELECT c, CAST(c - c % 64 AS DOUBLE) AS d FROM c)
SELECT (SELECT c FROM c) AS keywords, count(DISTINCT ex.q) AS queries, round(count(la.q) / (count(DISTINCT ex.q) * 100.0), 9) AS recall, (SELECT CASE WHEN c >= 6400 THEN round(d / 64 * (1 - exp(lgamma(d - 63) - lgamma(d - 163) - lgamma(d + 1) + lgamma(d - 99))) / 100.0, 4) END FROM x) AS expected FROM ex LEFT JOIN la ON la.q = ex.q AND la.pos = ex.pos"""


GENERATED = generated()

ORACLES: dict[str, str] = {
    "lane_top_n": lane_top(),
    "lane_top_n_r2": lane_top(2),
    "lane_top_n_tree": lane_top(),
    "lane_top_n_block": lane_top(),
    "exact_top_n": EXACT,
    "exact_top_n_block": EXACT,
    "radix_top_n": EXACT,
    "index_top_n": f"""{pairs(self_too=True)}, best AS (SELECT *, min(key) OVER (PARTITION BY q) AS least FROM (SELECT q, k, key, row_number() OVER (PARTITION BY q ORDER BY key DESC, k) AS rn FROM scored) WHERE rn <= {N + 1})
SELECT q AS query_id, CAST(row_number() OVER (PARTITION BY q ORDER BY key DESC, k) AS INTEGER) AS rank, k AS keyword_id, key AS rank_key FROM best WHERE key > least""",
    "float_top_n": f"WITH {FLOAT} SELECT q AS query_id, CAST(rn AS INTEGER) AS rank, k AS keyword_id, round(c, 9) AS score FROM near",
    "ladder_planes": f"""WITH {planes()} SELECT vec_id, {', '.join(f"array_to_string(list_transform(s{p}, lambda x: CASE WHEN x > 0 THEN '+' ELSE '-' END), '') AS plane{p}" for p in range(3))},
CAST(list_dot_product({dense(1)}, {dense(1)}) AS INTEGER) AS norm1, CAST(list_dot_product({dense(2)}, {dense(2)}) AS INTEGER) AS norm2 FROM p2""",
    "code_dots_2_1": code_dots(2, 1),
    "code_dots_0_0": code_dots(0, 0),
    "code_dots_1_1": code_dots(1, 1),
    "code_dots_2_2": code_dots(2, 2),
    "code_dots_plain_2_1": code_dots(2, 1, False),
    "sql_functions": f"{pairs(self_too=True)}, base AS (SELECT a.vec_id AS q, sum(list_dot_product(a.s0, b.s0)) AS d FROM p2 a, p2 b GROUP BY a.vec_id) SELECT q AS query_id, CAST(sum(s) AS BIGINT) AS dots, CAST(any_value(base.d) AS BIGINT) AS base_dots, round(sum(cos), 6) AS cosines FROM scored JOIN base USING (q) GROUP BY q",
    "progressive": f"""{pairs(self_too=True)}, kept AS (SELECT *, min(base) OVER (PARTITION BY q) AS least FROM (SELECT a.vec_id AS q, b.vec_id AS k, list_dot_product(a.s0, b.s0) AS base, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_dot_product(a.s0, b.s0) DESC, b.vec_id) AS br FROM p2 a, p2 b) WHERE br <= 50)
SELECT q AS query_id, count(*) AS kept, max(key) AS best_key, CAST(min(br) AS INTEGER) AS first_rank, max(s / sqrt(CAST(kn AS DOUBLE))) > any_value(CASE WHEN 8 * least + 832 >= 0 THEN (8 * least + 832) / 8.0 ELSE (8 * least + 832) / 24.0 END) AS certified FROM kept JOIN scored USING (q, k) GROUP BY q""",
    "above_threshold": f"{pairs()} SELECT q AS query_id, count(*) AS keywords, round(max(cos), 9) AS best FROM scored WHERE cos >= 0.4 GROUP BY q",
    "bits_table": bits(),
    "weights_table": weights(),
    "log_loss_table": log_loss((1, 5, 10), True),
    "gamma_search": log_loss((1, 2, 5, 10, 20), False),
    "memory_table": f"SELECT CAST(p AS INTEGER) AS planes, n AS keywords, CAST(8 * p AS INTEGER) AS bytes_per_keyword, CAST(8 * p * n AS BIGINT) AS code_bytes, CAST(4 * d AS BIGINT) AS float_bytes FROM range(1, 4) t(p), (SELECT count(*) AS n, sum(len(embedding)) AS d FROM embeddings WHERE {USABLE})",
    "cost_table": f"SELECT CAST(u AS INTEGER) AS u, CAST(v AS INTEGER) AS v, CAST((u + 1) * (v + 1) * n * n AS BIGINT) AS popcounts, CAST((u + v) * n * n AS BIGINT) AS horner_shifts, CAST(((u + 1) * (v + 1) - 1) * n * n AS BIGINT) AS naive_shifts FROM (VALUES (0, 0), (1, 1), (2, 1), (2, 2)) t(u, v), (SELECT count(*) AS n FROM embeddings WHERE {USABLE})",
    "cardinality_table": f"SELECT CAST(a.planes AS INTEGER) AS planes, CAST(a.n AS INTEGER) AS weighted_values, CAST(b.n AS INTEGER) AS plain_values FROM {values(True)} a JOIN {values(False)} b ON a.planes = b.planes",
    "lane_geometry": f"SELECT pos // {LANE * WIDTH} * {WIDTH} + pos % {WIDTH} AS lane, count(*) AS keywords, min(pos) AS first, max(pos) AS last FROM (SELECT row_number() OVER () - 1 AS pos FROM lineitem) GROUP BY 1",
    "plane_stats": f"WITH {planes()} SELECT word, round(avg(list_sum(list_transform(s, lambda x: (x + 1) / 2)) / 64), 9) AS share FROM (SELECT 'p0_w0' AS word, s0 AS s FROM p2 UNION ALL SELECT 'p1_w0', s1 FROM p2 UNION ALL SELECT 'p2_w0', s2 FROM p2) GROUP BY word",
    "pairs_clicks": CLICKS,
    "pairs_turns": "SELECT conv_id * 16777216 + turn AS pair_id, text AS q_text, k_text FROM (SELECT *, lead(role) OVER w AS nr, lead(text) OVER w AS k_text FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND nr = 'assistant'",
    "pairs_lines": "SELECT doc_id AS pair_id, split_part(text, chr(10), 1) AS q_text, CAST(length(text) - length(split_part(text, chr(10), 1)) - 1 AS INTEGER) AS k_chars FROM documents WHERE contains(text, chr(10))",
    "training_samples": f"SELECT query_id, count(*) AS groups, count(*) AS positives, 10 * count(*) AS negatives FROM ({CLICKS}) GROUP BY query_id",
    "time_split": "SELECT CASE WHEN ts < TIMESTAMP '2024-01-24' THEN 'train' ELSE 'validation' END AS fold, count(*) AS clicks FROM events WHERE event_type = 'click' GROUP BY 1",
    "trigram_vocab": f"""SELECT trigram, df, CAST(row_number() OVER (ORDER BY df DESC, trigram COLLATE BINARY) - 1 AS INTEGER) AS idx FROM (SELECT trigram, count(DISTINCT doc_id) AS df FROM
(SELECT doc_id, substr(w, i, 3) AS trigram FROM (SELECT doc_id, '#' || w || '#' AS w, unnest(range(1, length(w) + 1)) AS i FROM (SELECT doc_id, unnest({words()}) AS w FROM documents))) GROUP BY trigram) ORDER BY df DESC, trigram LIMIT 49292""".replace(" COLLATE BINARY", ""),
    "window_counts": f"""SELECT conv_id, turn, CAST(len(w) AS INTEGER) AS windows, CAST(coalesce(list_sum(list_transform(range(1, len(w) + 1), lambda i: length(w[i]) + CASE WHEN i > 1 THEN length(w[i - 1]) ELSE 0 END + CASE WHEN i < len(w) THEN length(w[i + 1]) ELSE 0 END)), 0) AS DOUBLE) AS trigrams FROM (SELECT conv_id, turn, {words()} AS w FROM conversations)""",
    "judged_pairs": f"WITH {JUDGED} SELECT * FROM jd",
    "lexical_bm25": f"WITH {BM25} {RANK5.format(source='bm')}",
    "lexical_tfidf": f"WITH {POSTINGS}, {TFIDF} {RANK5.format(source='ti')}",
    "lexical_bim": f"WITH {POSTINGS}, bi AS (SELECT qp.q, kp.k, sum(ln((c - df + 0.5) / (df + 0.5))) AS score FROM qp JOIN kp USING (term) JOIN df USING (term), n GROUP BY qp.q, kp.k) {RANK5.format(source='bi')}",
    "quality_table": f"""{SYSTEMS}, names AS (SELECT DISTINCT baseline FROM th), ga AS (SELECT coalesce(grade, 'bad') AS grade, count(*) AS n FROM ours o LEFT JOIN jd ON jd.is_pos AND jd.query_id = o.query_id AND jd.keyword_id = o.keyword_id GROUP BY 1),
gb AS (SELECT baseline, coalesce(grade, 'bad') AS grade, count(*) AS n FROM th t LEFT JOIN jd ON jd.is_pos AND jd.query_id = t.query_id AND jd.keyword_id = t.keyword_id GROUP BY 1, 2)
SELECT baseline, grade, coalesce(a.n, 0) AS ours, coalesce(b.n, 0) AS theirs, round(CASE WHEN coalesce(b.n, 0) > 0 THEN (coalesce(a.n, 0) - b.n) * 100.0 / b.n END, 6) AS change FROM (SELECT baseline, grade, n FROM names, ga) a FULL JOIN gb b USING (baseline, grade)""",
    "overlap_table": f"""{SYSTEMS}, good AS (SELECT query_id, keyword_id FROM jd WHERE grade IN ('good', 'excellent')), a AS (SELECT query_id, keyword_id FROM ours JOIN good USING (query_id, keyword_id)), b AS (SELECT baseline, query_id, keyword_id FROM th JOIN good USING (query_id, keyword_id)),
m AS (SELECT baseline, (SELECT count(*) FROM a) AS na, (SELECT count(*) FROM b WHERE b.baseline = n.baseline) AS nb, (SELECT count(*) FROM a JOIN b USING (query_id, keyword_id) WHERE b.baseline = n.baseline) AS c FROM (VALUES ('equal keywords'), ('equal memory')) n(baseline))
SELECT baseline, c AS common, round(CASE WHEN na > 0 THEN c / na END, 9) AS of_ours, round(CASE WHEN nb > 0 THEN c / nb END, 9) AS of_theirs, round(CASE WHEN na + nb > c THEN c / (na + nb - c) END, 9) AS jaccard FROM m""",
    "text_top_n": f"{SYSTEMS} SELECT query_id, rank, keyword_id, rank_key FROM ours",
    "judge_agreement": f"WITH {JUDGED} SELECT grade, count(*) AS pairs, count(quality) AS labelled, count_if(quality = 1) AS good, count_if(toxic = 1) AS toxic FROM jd LEFT JOIN labels ON doc_id = keyword_id GROUP BY grade",
    "objective_table": f"""{pairs(self_too=True)}, {FLOAT}, {GROUPS}, probs AS (SELECT g, pos, exp(10 * cos) / sum(exp(10 * cos)) OVER (PARTITION BY g) AS p FROM gs) SELECT round(sum(CASE WHEN pos THEN -ln(p) END), 6) AS objective, round(sum(CASE WHEN pos THEN -ln(p) END) / count_if(pos), 9) AS log_loss FROM probs""",
    "accuracy_table": ACCURACY,
    "recall_table": RECALL,
    "miss_table": MISS,
    "pairs_pages": r"""SELECT page_id AS pair_id, regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1) AS q_text, CAST(length(trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<head[^>]*>.*?</head>', ' ', 'g'), '(?is)<script[^>]*>.*?</script>', ' ', 'g'), '(?is)<style[^>]*>.*?</style>', ' ', 'g'), '(?s)<[^>]+>', ' ', 'g'), '[ \t\n\x0B\f\r]+', ' ', 'g'))) AS INTEGER) AS k_chars FROM pages""",
    "generated_recall": GENERATED,
    "attributed_clicks": f"SELECT c.event_id AS click_id, count(*) AS views, max(v.event_id) AS last_view {VIEWS} GROUP BY 1",
    "stream_pairs": f"SELECT c.event_id AS click_id, count(*) AS views, max(v.event_id) AS last_view {VIEWS} GROUP BY 1",
    "stream_unique": CLICKS,
    "asof_views": """SELECT event_id AS click_id, user_id, lv AS view_id FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, CASE WHEN event_type = 'view' THEN 0 ELSE 1 END, CASE WHEN event_type = 'view' THEN event_id END ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS lv
FROM events WHERE event_type IN ('view', 'click')) WHERE event_type = 'click'""",
    "rolling_ctr": """SELECT event_id, user_id, CAST(c AS BIGINT) AS clicks, CAST(v AS BIGINT) AS views, round(CASE WHEN v > 0 THEN c / v END, 9) AS ctr FROM (SELECT event_id, user_id, sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) OVER w AS c, sum(CASE WHEN event_type = 'view' THEN 1 ELSE 0 END) OVER w AS v
FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS t FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY t RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW))""",
    "clicks_cube": "SELECT c_mktsegment, n_name, count(*) AS clicks FROM events JOIN customer ON c_custkey = user_id JOIN nation ON n_nationkey = c_nationkey WHERE event_type = 'click' GROUP BY CUBE (c_mktsegment, n_name)",
    "star_top": f"""WITH win AS ({EXACT}), rev AS (SELECT l_partkey AS keyword_id, sum(l_extendedprice * (1 - l_discount)) AS revenue FROM lineitem GROUP BY 1)
SELECT p_brand, count(*) AS winners, round(sum(coalesce(revenue, 0)), 2) AS revenue FROM win JOIN part ON p_partkey = keyword_id LEFT JOIN rev USING (keyword_id) GROUP BY p_brand""",
    "set_operations": f"""WITH a AS (SELECT query_id, keyword_id FROM ({EXACT})), b AS (SELECT query_id, keyword_id FROM ({lane_top()}))
SELECT * FROM (SELECT 'kept' AS kind, (SELECT count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b)) AS pairs UNION ALL SELECT 'lost', (SELECT count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)) UNION ALL SELECT 'instead', (SELECT count(*) FROM (SELECT * FROM b EXCEPT SELECT * FROM a))) WHERE pairs > 0""",
    "grade_pivot": f"WITH {JUDGED} SELECT query_id, CAST(count_if(grade = 'fair') AS BIGINT) AS fair, CAST(count_if(grade = 'good') AS BIGINT) AS good, CAST(count_if(grade = 'excellent') AS BIGINT) AS excellent FROM jd WHERE is_pos GROUP BY query_id",
    "event_profile": "SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS users, round(quantile_cont(value, 0.5), 6) AS median, round(stddev_samp(value), 6) AS spread FROM events GROUP BY event_type",
    "user_windows": """SELECT event_id, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS INTEGER) AS dr, lag(event_id) OVER w AS before, lead(event_type) OVER w AS after, CAST(ntile(4) OVER w AS INTEGER) AS quarter,
CAST(sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 6 PRECEDING AND CURRENT ROW) AS BIGINT) AS recent FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
    "lateral_top": "SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS rn FROM events) WHERE rn <= 2",
    "stream_answers": f"{pairs(self_too=True)} SELECT * FROM ({TOP.format(source='scored', n=N)}) WHERE query_id IN (SELECT user_id % (SELECT count(*) FROM embeddings) FROM events)",
}
