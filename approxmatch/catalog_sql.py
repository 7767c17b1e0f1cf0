"""SQL for DuckDB: the predicates and measures of the catalog, written independently of the Spark plans."""

from __future__ import annotations

#: Fixed: the noisy queries against part descriptions.
QS = [(1, "smal ring ECONOMY 2"), (2, "widget red SMALL 17"), (3, "bleu bolt ECONOMIC 4"), (4, "hot gear"), (5, "zzz qqq")]

PART_DESC = "SELECT p_partkey AS tid, p_name || ' ' || p_type || ' ' || substr(p_brand, 7) AS s FROM part"
PART_FULL = "SELECT p_partkey AS tid, p_name || ' ' || p_brand || ' ' || p_type AS s FROM part"


def values(rows=QS) -> str:
    return "SELECT * FROM (VALUES " + ", ".join(f"({i}, '{s}')" for i, s in rows) + ") v(qid, s)"


def norm(s: str = "s") -> str:
    return f"trim(regexp_replace({s}, '\\s+', ' ', 'g'))"


def grams(source: str, key: str, q: int = 2, s: str = "s") -> str:
    pads = "$" * (q - 1)
    padded = f"'{pads}' || replace({norm(s)}, ' ', '{pads}') || '{pads}'"
    return f"SELECT {key}, substr(p, i, {q}) AS token FROM (SELECT {key}, p, unnest(range(1, length(p) - {q - 2})) AS i FROM (SELECT {key}, {padded} AS p FROM ({source}) WHERE {norm(s)} <> ''))"


def words(source: str, key: str) -> str:
    return f"SELECT {key}, unnest(string_split({norm()}, ' ')) AS token FROM ({source}) WHERE {norm()} <> ''"


def tokens(source: str, key: str, kind: str, q: int) -> str:
    return words(source, key) if kind == "word" else grams(source, key, q)


def ctes(base: str = PART_DESC, queries: str | None = None, kind: str = "qgram", q: int = 2, prune: float | None = None) -> str:
    """base, qry, bag, sizes, stats, coll (n, cs, mean_idf), qbag, met: what every predicate needs."""
    first = f"""
base AS ({base}), qry AS ({queries or values()}),
bag0 AS (SELECT tid, token, count(*) AS tf FROM ({tokens('SELECT * FROM base', 'tid', kind, q)}) GROUP BY tid, token),
qbag0 AS (SELECT qid, token, count(*) AS tf FROM ({tokens('SELECT * FROM qry', 'qid', kind, q)}) GROUP BY qid, token),
n0 AS (SELECT count(*) AS n FROM base), """
    if prune is None:
        first += "bag AS (SELECT * FROM bag0), qbag AS (SELECT * FROM qbag0), "
    else:
        first += f"""
idf0 AS (SELECT token, ln(max(n)::DOUBLE) - ln(count(*)::DOUBLE) AS idf FROM bag0, n0 GROUP BY token),
low AS (SELECT token FROM idf0 WHERE idf < (SELECT min(idf) + {prune} * (max(idf) - min(idf)) FROM idf0) - 1e-12),
bag AS (SELECT * FROM bag0 WHERE token NOT IN (SELECT token FROM low)),
qbag AS (SELECT * FROM qbag0 WHERE token NOT IN (SELECT token FROM low)), """
    return first + """
sizes AS (SELECT tid, count(*) AS len, sum(tf) AS dl FROM bag GROUP BY tid),
stats AS (SELECT token, count(*) AS df, sum(tf) AS cf, sum(tf::DOUBLE / dl) AS sum_pml FROM bag JOIN sizes USING (tid) GROUP BY token),
coll AS (SELECT max(n)::DOUBLE AS n, (SELECT sum(dl) FROM sizes)::DOUBLE AS cs, (SELECT avg(ln(n::DOUBLE) - ln(df::DOUBLE)) FROM stats, n0) AS mean_idf FROM n0),
qsizes AS (SELECT qid, count(*) AS qlen FROM qbag GROUP BY qid),
met AS (SELECT q.qid, b.tid, b.token, q.tf AS qtf, b.tf, s.dl, s.len, t.df, t.cf, t.sum_pml, c.n, c.cs, qs.qlen
        FROM qbag q JOIN bag b USING (token) JOIN sizes s USING (tid) JOIN stats t USING (token) JOIN qsizes qs USING (qid) CROSS JOIN coll c)
"""


IDF = "(ln(n) - ln(df::DOUBLE))"
RS = "ln((n - df + 0.5::DOUBLE) / (df + 0.5::DOUBLE))"


def p_lm() -> str:
    mean = "(sum_pml / df)"
    f = f"({mean} * dl)"
    risk = f"(pow({f} / (1 + {f}), tf) / (1 + {f}))"
    return f"least(greatest(pow(tf::DOUBLE / dl, 1 - {risk}) * pow({mean}, {risk}), 1e-12), 1 - 1e-12)"


def scores(select: str, **options) -> str:
    return f"WITH {ctes(**options)} {select}"


def simple(expr: str, **options) -> str:
    """A sum over shared tokens."""
    return scores(f"SELECT qid, tid, round({expr}, 6) AS score FROM met GROUP BY qid, tid", **options)


def sql_bm25(k1: float = 1.5, k3: float = 8.0, b: float = 0.675) -> str:
    return f"sum({RS} * ({k1}::DOUBLE + 1) * tf / ({k1}::DOUBLE * ((1 - {b}::DOUBLE) + {b}::DOUBLE * dl / (cs / n)) + tf) * ({k3}::DOUBLE + 1) * qtf / ({k3}::DOUBLE + qtf))"


XECT = "count(*)::DOUBLE"
JACCARD = "count(*)::DOUBLE / (max(len) + max(qlen) - count(*))"


def sql_wj(kind: str, **options) -> str:
    w, new = (RS, "ln((n + 0.5::DOUBLE) / 0.5::DOUBLE)") if kind == "rs" else (IDF, "mean_idf")
    return scores(
        f"""
, wl AS (SELECT tid, sum({w}) AS wlen FROM bag JOIN stats USING (token) CROSS JOIN coll GROUP BY tid),
ql AS (SELECT qid, sum(CASE WHEN df IS NULL THEN {new} ELSE {w} END) AS qw FROM qbag LEFT JOIN stats USING (token) CROSS JOIN coll GROUP BY qid),
sh AS (SELECT qid, tid, sum({w}) AS w FROM met GROUP BY qid, tid)
SELECT qid, tid, round(CASE WHEN wlen + qw - w <> 0 THEN w / (wlen + qw - w) ELSE 0 END, 6) AS score FROM sh JOIN wl USING (tid) JOIN ql USING (qid)""",
        **options,
    )


def sql_cosine(**options) -> str:
    return scores(
        f"""
, dn AS (SELECT tid, sqrt(sum(pow(tf * {IDF}, 2))) AS dnorm FROM bag JOIN stats USING (token) CROSS JOIN coll GROUP BY tid),
qn AS (SELECT qid, sqrt(sum(pow(tf * {IDF}, 2))) AS qnorm FROM qbag JOIN stats USING (token) CROSS JOIN coll GROUP BY qid),
sh AS (SELECT qid, tid, sum(qtf * tf * pow({IDF}, 2)) AS w FROM met GROUP BY qid, tid)
SELECT qid, tid, round(CASE WHEN dnorm * qnorm > 0 THEN w / (dnorm * qnorm) ELSE 0 END, 6) AS score FROM sh JOIN dn USING (tid) JOIN qn USING (qid)""",
        **options,
    )


G = "least(cf / cs, 1 - 1e-12)"


def sql_lm(full: bool = False) -> str:
    p = p_lm()
    if not full:
        return scores(f"""
, own AS (SELECT tid, sum(ln(1 - p)) AS comp FROM (SELECT tid, {p} AS p FROM bag JOIN sizes USING (tid) JOIN stats USING (token)) GROUP BY tid),
sh AS (SELECT qid, tid, sum(ln(p) - ln(1 - p) - ln(g)) AS w FROM (SELECT qid, tid, {p} AS p, {G} AS g FROM met) GROUP BY qid, tid)
SELECT qid, tid, round(w + comp, 6) AS score FROM sh JOIN own USING (tid)""")
    return scores(f"""
, own AS (SELECT tid, sum(ln(1 - p) - ln(1 - g)) AS comp FROM (SELECT tid, {p} AS p, {G} AS g FROM bag JOIN sizes USING (tid) JOIN stats USING (token) CROSS JOIN coll) GROUP BY tid),
sh AS (SELECT qid, tid, sum(ln(p) - ln(g) - ln(1 - p) + ln(1 - g)) AS w FROM (SELECT qid, tid, {p} AS p, {G} AS g FROM met) GROUP BY qid, tid),
qc AS (SELECT qid, sum(ln({G}) - ln(1 - {G})) AS qc FROM qbag JOIN stats USING (token) CROSS JOIN coll GROUP BY qid),
al AS (SELECT sum(ln(1 - {G})) AS a FROM stats CROSS JOIN coll)
SELECT qid, tid, round(w + comp + qc + a, 6) AS score FROM sh JOIN own USING (tid) JOIN qc USING (qid) CROSS JOIN al""")


def hmm_term(a0: float = 0.2) -> str:
    return f"ln(1 + (1 - {a0}::DOUBLE) * (tf::DOUBLE / dl) / ({a0}::DOUBLE * (cf / cs)))"


def sql_hmm_full(a0: float = 0.2) -> str:
    return scores(f"""
, qc AS (SELECT qid, sum(ln({a0}::DOUBLE * cf / cs)) AS qc FROM qbag JOIN stats USING (token) CROSS JOIN coll GROUP BY qid),
sh AS (SELECT qid, tid, sum({hmm_term(a0)}) AS w FROM met GROUP BY qid, tid)
SELECT qid, tid, round(w + qc, 6) AS score FROM sh JOIN qc USING (qid)""")


def edit(theta: float | None = None, base: str = PART_DESC) -> str:
    bound = "" if theta is None else f" WHERE levenshtein(b.s, q.s) <= floor((1 - {theta}::DOUBLE) * greatest(length(b.s), length(q.s)) + 1e-9)"
    return f"WITH base AS ({base}), qry AS ({values()}) SELECT qid, tid, round(1 - levenshtein(b.s, q.s)::DOUBLE / greatest(length(b.s), length(q.s)), 6) AS score FROM base b CROSS JOIN qry q{bound}"


#: Words of queries with their idf (the mean for unknown ones), and different words of the base.
WORDS = """
, qw AS (SELECT qid, unnest(string_split(s, ' ')) AS word, unnest(range(len(string_split(s, ' ')))) AS pos FROM qry),
qi AS (SELECT qid, pos, word, coalesce(ln(n) - ln(df::DOUBLE), mean_idf) AS w FROM qw CROSS JOIN coll LEFT JOIN stats ON token = word),
qt AS (SELECT qid, sum(w) AS total FROM qi GROUP BY qid),
voc AS (SELECT token AS word FROM stats), asked AS (SELECT DISTINCT word FROM qi)
"""


def word_grams(source: str, q: int = 2) -> str:
    return f"SELECT DISTINCT word, token FROM ({grams(source, 'word', q, 'word')})"


def gram_sims(kind: str = "jaccard") -> str:
    value = "n::DOUBLE / (a + b - n)" if kind == "jaccard" else "n::DOUBLE"
    return f"""
, vg AS ({word_grams('SELECT word FROM voc')}), ag AS ({word_grams('SELECT word FROM asked')}),
vn AS (SELECT word, count(*) AS b FROM vg GROUP BY word), an AS (SELECT word, count(*) AS a FROM ag GROUP BY word),
common AS (SELECT ag.word AS qword, vg.word AS word, count(*) AS n FROM ag JOIN vg USING (token) GROUP BY ag.word, vg.word),
sims AS (SELECT qword, common.word AS word, {value} AS sim FROM common JOIN vn ON vn.word = common.word JOIN an ON an.word = qword)
"""


def minhash_sims(coefficients: list[tuple[int, int]]) -> str:
    prime = (1 << 31) - 1
    mins = ", ".join(f"min((h * {a} + {b}) % {prime})" for a, b in coefficients)
    signed = lambda source: f"SELECT word, [{mins}] AS sig FROM (SELECT word, ('0x' || substr(md5(token), 1, 8))::BIGINT % {prime} AS h FROM ({word_grams(source)})) GROUP BY word"
    return f"""
, vs AS ({signed('SELECT word FROM voc')}), sa AS ({signed('SELECT word FROM asked')}),
vp AS (SELECT word, unnest(sig) AS v, unnest(range({len(coefficients)})) AS f FROM vs), ap AS (SELECT word, unnest(sig) AS v, unnest(range({len(coefficients)})) AS f FROM sa),
sims AS (SELECT ap.word AS qword, vp.word AS word, count(*)::DOUBLE / {len(coefficients)} AS sim FROM ap JOIN vp USING (f, v) GROUP BY ap.word, vp.word)
"""


def ges_bound(sims: str, q: int = 2) -> str:
    return scores(
        WORDS + sims + f"""
, best AS (SELECT qi.qid, bag.tid, qi.pos, max(sim) AS sim, max(w) AS w FROM qi JOIN sims ON qword = qi.word JOIN bag ON bag.token = sims.word GROUP BY qi.qid, bag.tid, qi.pos)
SELECT qid, tid, round(sum(w * sim) * 2.0::DOUBLE / {q} / max(total) + 1 - 1.0::DOUBLE / {q}, 6) AS score FROM best JOIN qt USING (qid) GROUP BY qid, tid""",
        kind="word",
    )


def soft(sims: str, theta: float) -> str:
    return scores(
        WORDS + sims + f"""
, q1 AS (SELECT qid, word, count(*) * max(w) AS w FROM qi GROUP BY qid, word),
q2 AS (SELECT qid, word, w / sqrt(sum(w * w) OVER (PARTITION BY qid)) AS wq FROM q1),
d1 AS (SELECT tid, token, tf * {IDF} AS w FROM bag JOIN stats USING (token) CROSS JOIN coll),
d2 AS (SELECT tid, token, w / sqrt(sum(w * w) OVER (PARTITION BY tid)) AS wd FROM d1),
near AS (SELECT q2.qid, d2.tid, q2.word AS qword, wq, wd, sim, row_number() OVER (PARTITION BY q2.qid, d2.tid, q2.word ORDER BY sim DESC, d2.token) AS place
         FROM q2 JOIN sims ON sims.qword = q2.word AND sim > {theta} JOIN d2 ON d2.token = sims.word)
SELECT qid, tid, round(sum(wq * wd * sim), 6) AS score FROM near WHERE place = 1 GROUP BY qid, tid""",
        kind="word",
    )


JW_SIMS = ", sims AS (SELECT a.word AS qword, v.word AS word, jaro_winkler_similarity(a.word, v.word) AS sim FROM asked a CROSS JOIN voc v)"
EDIT_SIMS = ", sims AS (SELECT a.word AS qword, v.word AS word, 1 - levenshtein(a.word, v.word)::DOUBLE / greatest(length(a.word), length(v.word)) AS sim FROM asked a CROSS JOIN voc v)"

#: Word lists with idf, and the table of the alignment: one recursion step a query word, whose row is built cell by cell.
GES = """
, dw AS (SELECT tid, unnest(string_split(s, ' ')) AS word, unnest(range(len(string_split(s, ' ')))) AS pos FROM base),
dl AS (SELECT tid, list(word ORDER BY pos) AS dwords, list(ln(n) - ln(df::DOUBLE) ORDER BY pos) AS dws FROM dw JOIN stats ON token = word CROSS JOIN coll GROUP BY tid),
ql AS (SELECT qid, list(word ORDER BY pos) AS qwords, list(w ORDER BY pos) AS qws, sum(w) AS total FROM qi GROUP BY qid),
al(qid, tid, i, line) AS (
  SELECT qid, tid, 0, list_prepend(0.0::DOUBLE, list_transform(range(1, len(dws) + 1), lambda k: list_sum(dws[1:k]) * 0.5::DOUBLE)) FROM ql CROSS JOIN dl
  UNION ALL
  SELECT al.qid, al.tid, i + 1, list_reduce(list_prepend([line[1] + qws[i + 1]], list_transform(range(1, len(dwords) + 1), lambda j:
           [dws[j] * 0.5::DOUBLE, line[j + 1] + qws[i + 1], line[j] + levenshtein(qwords[i + 1], dwords[j])::DOUBLE / greatest(length(qwords[i + 1]), length(dwords[j])) * qws[i + 1]])),
         lambda done, x: list_append(done, least(done[len(done)] + x[1], x[2], x[3])))
  FROM al JOIN ql ON ql.qid = al.qid JOIN dl ON dl.tid = al.tid WHERE i < len(qwords)),
ges AS (SELECT al.qid, al.tid, 1 - least(line[len(line)] / total, 1.0::DOUBLE) AS score FROM al JOIN ql ON ql.qid = al.qid WHERE i = len(qwords))
"""


def recursive(sql: str) -> str:
    return sql.replace("WITH ", "WITH RECURSIVE ", 1)


def ges(theta: float | None = None, sims: str | None = None, q: int = 2) -> str:
    """Exact generalised edit similarity of all pairs; of those from theta on; of those whose bound reaches it too."""
    if sims is None:
        where = "" if theta is None else f" WHERE score >= {theta}::DOUBLE - 1e-12"
        return recursive(scores(WORDS + GES + f"SELECT qid, tid, round(score, 6) AS score FROM ges{where}", kind="word"))
    bound = f"""
, best AS (SELECT qi.qid, bag.tid, qi.pos, max(sim) AS sim, max(w) AS w FROM qi JOIN sims ON qword = qi.word JOIN bag ON bag.token = sims.word GROUP BY qi.qid, bag.tid, qi.pos),
bound AS (SELECT qid, tid, sum(w * sim) * 2.0::DOUBLE / {q} / max(total) + 1 - 1.0::DOUBLE / {q} AS b FROM best JOIN qt USING (qid) GROUP BY qid, tid)
SELECT ges.qid, ges.tid, round(score, 6) AS score FROM ges JOIN bound ON bound.qid = ges.qid AND bound.tid = ges.tid WHERE score >= {theta}::DOUBLE - 1e-12 AND b >= {theta}::DOUBLE - 1e-12"""
    return recursive(scores(WORDS + sims + GES + bound, kind="word"))


def edit_costs(insert: float, delete: float, substitute: float, swap: float) -> str:
    """Least cost between the query and the tuple by a table of characters: two rows are carried, for the exchange."""
    return f"""
WITH RECURSIVE base AS ({PART_DESC}), qry AS ({values()}),
p AS (SELECT qid, tid, q.s AS a, b.s AS b FROM base b CROSS JOIN qry q),
t(qid, tid, i, above, line) AS (
  SELECT qid, tid, 0, []::DOUBLE[], list_transform(range(0, length(b) + 1), lambda j: j * {insert}::DOUBLE) FROM p
  UNION ALL
  SELECT t.qid, t.tid, i + 1, line, list_reduce(list_prepend([(i + 1) * {delete}::DOUBLE], list_transform(range(1, length(b) + 1), lambda j:
           [line[j + 1] + {delete}::DOUBLE, line[j] + CASE WHEN a[i + 1] = b[j] THEN 0 ELSE {substitute}::DOUBLE END,
            CASE WHEN i > 0 AND j > 1 AND a[i + 1] = b[j - 1] AND a[i] = b[j] THEN above[j - 1] + {swap}::DOUBLE ELSE 1e9::DOUBLE END])),
         lambda done, x: list_append(done, least(done[len(done)] + {insert}::DOUBLE, x[1], x[2], x[3])))
  FROM t JOIN p ON p.qid = t.qid AND p.tid = t.tid WHERE i < length(a))
SELECT t.qid, t.tid, round(1 - line[len(line)] / greatest(length(a), length(b)), 6) AS score FROM t JOIN p ON p.qid = t.qid AND p.tid = t.tid WHERE i = length(a)"""


def filter_edit(theta: float, q: int = 2) -> str:
    """Pairs that the bag filter of end-padded grams leaves, their share, and results that it misses."""
    pads = "$" * (q - 1)
    bag = lambda source, key: f"SELECT {key}, g, count(*) AS tf FROM (SELECT {key}, substr(p, i, {q}) AS g FROM (SELECT {key}, p, unnest(range(1, length(p) - {q - 2})) AS i FROM (SELECT {key}, '{pads}' || s || '{pads}' AS p FROM {source}))) GROUP BY ALL"
    return f"""
WITH base AS ({PART_DESC}), qry AS ({values()}), bb AS ({bag('base', 'tid')}), qb AS ({bag('qry', 'qid')}),
sh AS (SELECT qid, tid, sum(least(bb.tf, qb.tf)) AS shared FROM bb JOIN qb USING (g) GROUP BY qid, tid),
k AS (SELECT qid, tid, b.s AS d, q.s AS a, greatest(length(b.s), length(q.s)) AS longer, floor(greatest(length(b.s), length(q.s)) * (1 - {theta}::DOUBLE) + 1e-9) AS k FROM base b CROSS JOIN qry q),
c AS (SELECT qid, tid FROM k JOIN sh USING (qid, tid) WHERE abs(length(d) - length(a)) <= k AND shared >= longer + {q - 1} - k * {q}),
x AS (SELECT qid, tid FROM k WHERE 1 - levenshtein(d, a)::DOUBLE / longer >= {theta}::DOUBLE)
SELECT (SELECT count(*) FROM c) AS candidates, round((SELECT count(*) FROM c)::DOUBLE / (SELECT count(*) FROM k), 9) AS share,
       (SELECT count(*) FROM x ANTI JOIN c USING (qid, tid)) AS missed"""



def ranked(inner: str) -> str:
    return f"SELECT qid, tid, score, row_number() OVER (PARTITION BY qid ORDER BY round(score, 9) DESC, tid) AS rank FROM ({inner})"


SAMPLED = f"SELECT tid AS qid, s FROM ({PART_DESC}) ORDER BY md5('42|' || tid), tid LIMIT 25"
TRUTH = "SELECT a.p_partkey AS qid, b.p_partkey AS tid FROM part a JOIN part b ON a.p_name = b.p_name AND a.p_type = b.p_type"
#: Ranks that the measures look at.
CUT = 50


def evaluated(final: str) -> str:
    inner = f"SELECT qid, tid, {sql_bm25()} AS score FROM met GROUP BY qid, tid"
    return f"""WITH {ctes(queries=f"SELECT tid AS qid, s FROM ({PART_DESC})")}
, rk AS (SELECT * FROM ({ranked(inner)}) WHERE rank <= {CUT}), tr AS ({TRUTH}), tot AS (SELECT qid, count(*) AS relevant FROM tr GROUP BY qid),
jd AS (SELECT rk.qid, rk.tid, rank, CASE WHEN tr.tid IS NULL THEN 0 ELSE 1 END AS rel FROM rk LEFT JOIN tr ON tr.qid = rk.qid AND tr.tid = rk.tid),
pr AS (SELECT qid, tid, rank, rel, sum(rel) OVER w::DOUBLE / rank AS precision, sum(rel) OVER w::DOUBLE / relevant AS recall, relevant
       FROM jd JOIN tot USING (qid) WINDOW w AS (PARTITION BY qid ORDER BY rank ROWS UNBOUNDED PRECEDING)),
ap AS (SELECT qid, sum(precision * rel) / max(relevant) AS ap, max(CASE WHEN precision + recall > 0 THEN 2 * precision * recall / (precision + recall) ELSE 0 END) AS f1 FROM pr GROUP BY qid)
{final}"""
