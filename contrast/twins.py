"""DuckDB SQL with the results of the workloads' queries, put together from common table expressions."""

from __future__ import annotations

from contrast.schema import SYMBOL, HybridSchema

FEATURES = {
    "documents": r"""
toks AS (SELECT d.doc_id, d.lang, d.source, CAST(l.toxic AS VARCHAR) AS toxic, CAST(l.quality AS VARCHAR) AS quality, d.text, regexp_extract_all(d.text, '\S+') AS tokens FROM documents d JOIN labels l ON d.doc_id = l.doc_id),
feat AS (SELECT doc_id, length(text) AS n_chars, len(tokens) AS n_words, len(regexp_extract_all(text, '\n')) + 1 AS n_lines,
  CAST(floor(100::DOUBLE * len(regexp_extract_all(text, '[A-Z]')) / length(text)) AS BIGINT) AS upper_pct,
  CAST(floor(100::DOUBLE * len(regexp_extract_all(text, '[!*$&%#@]')) / length(text)) AS BIGINT) AS junk_pct,
  CAST(floor(100::DOUBLE * len(regexp_extract_all(text, '[0-9]')) / length(text)) AS BIGINT) AS digit_pct,
  CAST(floor(100::DOUBLE * len(list_distinct(tokens)) / len(tokens)) AS BIGINT) AS uniq_pct,
  CAST(floor(10::DOUBLE * length(text) / len(tokens)) AS BIGINT) AS word_len10, lang, source, toxic, quality, tokens
  FROM toks WHERE length(text) > 0 AND len(tokens) > 0)""",
    "conversations": r"""
feat AS (SELECT conv_id, turn, length(text) AS n_chars, len(regexp_extract_all(text, '\S+')) AS n_words, len(regexp_extract_all(text, '[!*$&%#@]')) AS n_marks, role FROM conversations)""",
    "embeddings": """
feat AS (SELECT vec_id, CAST(embedding[1] AS DOUBLE) AS e0, CAST(embedding[2] AS DOUBLE) AS e1, CAST(embedding[3] AS DOUBLE) AS e2, CAST(embedding[4] AS DOUBLE) AS e3, CAST(label AS VARCHAR) AS label FROM embeddings)""",
    "orders": """
feat AS (SELECT o_orderkey, o_totalprice, c_acctbal, month(o_orderdate) AS month, o_orderpriority, c_mktsegment, r_name, o_orderstatus FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)""",
    "lineitem": """
feat AS (SELECT l_quantity, l_discount, l_tax, p_size, p_type, p_brand, l_linestatus, l_returnflag FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey)""",
    "part": """
feat AS (SELECT p_partkey, p_size, p_retailprice, p_type FROM part)""",
    "events": """
feat AS (SELECT event_id, ts, user_id, value, hour(ts) AS hour, CAST(json_extract_string(props, '$.k') AS INT) AS k, event_type FROM events)""",
}


def base(source: str, schema: HybridSchema, positive: str, merge: bool = True) -> str:
    """The WITH clause up to: rows, hist, pure, cuts, sym, codes, tx (tx_id, k0, k1, ..., n_pos, n_neg), tot (p, n), long, items, root."""
    numbers, symbols = schema.numbers(), schema.symbols()
    empty = "SELECT CAST(NULL AS INT) AS attr, CAST(NULL AS BIGINT) AS cell, CAST(NULL AS DOUBLE) AS v, CAST(NULL AS INT) AS pos WHERE false"
    vals = " UNION ALL ".join([f"SELECT {i} AS attr, CAST(floor(CAST({a.name} AS DOUBLE) / {a.delta!r}::DOUBLE) AS BIGINT) AS cell, CAST({a.name} AS DOUBLE) AS v, pos FROM rows WHERE {a.name} IS NOT NULL" for i, a in numbers] or [empty])
    syms = " UNION ALL ".join([f"SELECT {i} AS attr, {a.name} AS value, pos FROM rows WHERE {a.name} IS NOT NULL" for i, a in symbols] or ["SELECT CAST(NULL AS INT) AS attr, CAST(NULL AS VARCHAR) AS value, CAST(NULL AS INT) AS pos WHERE false"])
    joins = "".join(f" LEFT JOIN cuts c{i} ON c{i}.attr = {i} AND (c{i}.lo IS NULL OR r.{a.name} >= c{i}.lo) AND (c{i}.hi IS NULL OR r.{a.name} < c{i}.hi)" for i, a in numbers) + "".join(f" LEFT JOIN sym c{i} ON c{i}.attr = {i} AND c{i}.value = r.{a.name}" for i, a in symbols)
    ks = [f"k{i}" for i in range(len(schema.attributes))]
    same = "purity <> 'mixed' AND lag(purity) OVER (PARTITION BY attr ORDER BY cell) = purity" if merge else "false"
    long = " UNION ALL ".join(f"SELECT tx_id, {i} AS attr, k{i} AS code, n_pos, n_neg FROM tx WHERE k{i} >= 0" for i in range(len(ks)))
    return f"""WITH {FEATURES[source]},
rows AS (SELECT *, CASE WHEN {positive} THEN 1 ELSE 0 END AS pos FROM feat),
vals AS ({vals}),
hist AS (SELECT attr, cell, min(v) AS vmin, max(v) AS vmax, CAST(sum(pos) AS BIGINT) AS n_pos, CAST(sum(1 - pos) AS BIGINT) AS n_neg FROM vals GROUP BY attr, cell),
pure AS (SELECT *, CASE WHEN n_neg = 0 THEN 'pos' WHEN n_pos = 0 THEN 'neg' ELSE 'mixed' END AS purity FROM hist),
flag AS (SELECT *, CASE WHEN {same} THEN 0 ELSE 1 END AS begins FROM pure),
runs AS (SELECT *, CAST(sum(begins) OVER (PARTITION BY attr ORDER BY cell ROWS UNBOUNDED PRECEDING) - 1 AS INT) AS code FROM flag),
regions AS (SELECT attr, code, min(vmin) AS vmin, max(vmax) AS vmax, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg, any_value(purity) AS purity FROM runs GROUP BY attr, code),
cuts AS (SELECT attr, code, (lag(vmax) OVER w + vmin) / 2 AS lo, (vmax + lead(vmin) OVER w) / 2 AS hi, n_pos, n_neg, purity FROM regions WINDOW w AS (PARTITION BY attr ORDER BY code)),
symv AS ({syms}),
sym AS (SELECT attr, value, CAST(row_number() OVER (PARTITION BY attr ORDER BY value) - 1 AS INT) AS code, CAST(sum(pos) AS BIGINT) AS n_pos, CAST(sum(1 - pos) AS BIGINT) AS n_neg FROM symv GROUP BY attr, value),
codes AS (SELECT r.*, {', '.join(f'coalesce(c{i}.code, -1) AS k{i}' for i in range(len(ks)))} FROM rows r{joins}),
tx AS (SELECT {" || ',' || ".join(f'CAST({k} AS VARCHAR)' for k in ks)} AS tx_id, {', '.join(ks)}, CAST(sum(pos) AS BIGINT) AS n_pos, CAST(sum(1 - pos) AS BIGINT) AS n_neg FROM codes GROUP BY {', '.join(ks)}),
tot AS (SELECT CAST(sum(n_pos) AS BIGINT) AS p, CAST(sum(n_neg) AS BIGINT) AS n FROM tx),
long AS ({long}),
sizes AS (SELECT attr, max(code) + 1 AS size FROM cuts GROUP BY attr),
items AS (SELECT a.attr, a.code AS lo, b.code + 1 AS hi FROM cuts a JOIN cuts b ON a.attr = b.attr AND a.code <= b.code JOIN sizes s ON s.attr = a.attr WHERE NOT (a.code = 0 AND b.code + 1 = s.size)
  UNION ALL SELECT attr, code AS lo, code + 1 AS hi FROM sym),
root AS (SELECT i.attr, i.lo, i.hi, CAST(sum(l.n_pos) AS BIGINT) AS n_pos, CAST(sum(l.n_neg) AS BIGINT) AS n_neg FROM items i JOIN long l ON l.attr = i.attr AND l.code >= i.lo AND l.code < i.hi GROUP BY i.attr, i.lo, i.hi)"""


SCORES = {
    "fscore": "2::DOUBLE * n_pos / (p + n_pos + n_neg)",
    "suppdiff": "n_pos / p::DOUBLE - n_neg / n::DOUBLE",
    "confidence": "n_pos / (n_pos + n_neg)::DOUBLE",
    "chi2": "CASE WHEN n_pos + n_neg > 0 AND n_pos + n_neg < p + n THEN (n_pos::DOUBLE * n - n_neg::DOUBLE * p) * (n_pos::DOUBLE * n - n_neg::DOUBLE * p) / ((n_pos + n_neg)::DOUBLE * (p + n - n_pos - n_neg) * p * n) ELSE 0 END",
}


def _h(x: str, size: str) -> str:
    return f"(CASE WHEN {x} > 0 THEN -({x})::DOUBLE / ({size}) * log2(({x})::DOUBLE / ({size})) ELSE 0 END)"


_a, _b, _c, _r = "n_pos", "n_neg", "(n_pos + n_neg)", "(p + n - n_pos - n_neg)"
SCORES["infogain"] = f"{_h('p', '(p + n)')} + {_h('n', '(p + n)')} - ({_h(_a, _c)} + {_h(_b, _c)}) * {_c} / (p + n) - ({_h('(p - n_pos)', _r)} + {_h('(n - n_neg)', _r)}) * {_r} / (p + n)"


def item_id(attr: str = "attr", lo: str = "lo", hi: str = "hi") -> str:
    return f"CAST({attr} AS VARCHAR) || ':' || CAST({lo} AS VARCHAR) || ':' || CAST({hi} AS VARCHAR)"


def rules(where: str = "n_pos > 0 AND n_pos * n >= n_neg * p", score: str = SCORES["fscore"]) -> str:
    """rule (pattern_id, attr, lo, hi, n_pos, n_neg, score): admitted single items; met: each positive row with its rules."""
    return f""",
rule AS (SELECT {item_id()} AS pattern_id, attr, lo, hi, n_pos, n_neg, {score} AS score FROM root, tot WHERE {where}),
met AS (SELECT l.tx_id, r.pattern_id, r.score FROM long l JOIN rule r ON l.attr = r.attr AND l.code >= r.lo AND l.code < r.hi WHERE l.n_pos > 0)"""


def patterns(schema: HybridSchema, measure: str = "fscore") -> str:
    """All patterns over a schema of a few attributes, after base().

    pat (pattern_id, l0, h0, ..., n_pos, n_neg, score, admitted): those that cover a row; hit: each positive
    row with its admitted ones and their place; clid (pattern_id, closure).
    """
    every = range(len(schema.attributes))
    symbols = {i for i, _ in schema.symbols()}
    bounds = ", ".join(f"l{i}, h{i}" for i in every)
    ids = "concat_ws(';', " + ", ".join(f"CASE WHEN l{i} IS NOT NULL THEN '{i}:' || l{i} || ':' || h{i} END" for i in every) + ")"
    covers = " AND ".join(f"(l{i} IS NULL OR (k{i} >= l{i} AND k{i} < h{i}))" for i in every)
    ks = ", ".join(f"k{i}" for i in every)
    whole = lambda i: f"min(k{i}) < 0 OR " + (f"min(k{i}) <> max(k{i})" if i in symbols else f"(min(k{i}) = 0 AND max(k{i}) + 1 = (SELECT size FROM sizes WHERE attr = {i}))")
    spans = ", ".join(f"CASE WHEN {whole(i)} THEN NULL ELSE min(k{i}) END AS l{i}, CASE WHEN {whole(i)} THEN NULL ELSE max(k{i}) + 1 END AS h{i}" for i in every)
    ones = ",\n".join(f"one{i} AS (SELECT lo AS l{i}, hi AS h{i} FROM items WHERE attr = {i} UNION ALL SELECT NULL, NULL)" for i in every)
    return f""",
{ones},
cells AS (SELECT {ks}, sum(n_pos) AS n_pos, sum(n_neg) AS n_neg FROM tx GROUP BY {ks}),
sums AS (SELECT {bounds}, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg FROM cells, {', '.join(f'one{i}' for i in every)} WHERE {covers} AND NOT ({' AND '.join(f'l{i} IS NULL' for i in every)}) GROUP BY {bounds}),
pat AS (SELECT {ids} AS pattern_id, {bounds}, n_pos, n_neg, {SCORES[measure]} AS score, n_pos > 0 AND n_pos * n >= n_neg * p AS admitted FROM sums, tot),
hit AS (SELECT t.tx_id, {', '.join(f't.k{i}' for i in every)}, t.n_pos, q.pattern_id, q.score, rank() OVER (PARTITION BY t.tx_id ORDER BY q.score DESC) AS place FROM tx t JOIN pat q ON {covers} WHERE t.n_pos > 0 AND q.admitted),
clo AS (SELECT pattern_id, {spans} FROM hit GROUP BY pattern_id),
clid AS (SELECT pattern_id, {ids} AS closure FROM clo)"""


def covering() -> str:
    """The covering answer, after patterns(): closures of each row's best, and of these the best for some row."""
    return """,
closure AS (SELECT DISTINCT c.closure FROM hit h JOIN clid c USING (pattern_id) WHERE h.place = 1 AND c.closure <> ''),
again AS (SELECT h.tx_id, q.pattern_id, rank() OVER (PARTITION BY h.tx_id ORDER BY q.score DESC) AS place FROM closure c JOIN pat q ON q.pattern_id = c.closure AND q.admitted JOIN hit h ON h.pattern_id = q.pattern_id),
answer AS (SELECT * FROM pat WHERE pattern_id IN (SELECT pattern_id FROM again WHERE place = 1))"""
