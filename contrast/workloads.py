"""Named queries over the given tables: each method, variant, baseline, measure and workload, and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from contrast import twins
from contrast.functions.measures import CHI2, CONFIDENCE, FSCORE, INFOGAIN, MEASURES, SUPPDIFF, Measure, associated
from contrast.functions.patterns import PATTERN, item, pattern_id, render, subsumes
from contrast.operators import baselines, constraints, cuts, encode, lattice, rules
from contrast.plans import search
from contrast.plans.kernel import DENSE, Dense, Options
from contrast.schema import HybridSchema, number, symbol
from contrast.session import settled
from contrast.sources import tables
from contrast.streaming import histograms

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
SMALL, PAIR = tables.DOCUMENTS_SMALL, HybridSchema((number("uniq_pct"), number("upper_pct")))
BAD = "quality = '0'"


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


def _docs(spark, sf_dir, label="quality"):
    return tables.document_features(spark, sf_dir, label)


def _bad():
    return F.col("cls") == "0"


def _histogram(spark, sf_dir, schema=SMALL):
    return cuts.value_histogram(_docs(spark, sf_dir), schema, _bad())


def _prepared(spark, sf_dir, schema=SMALL, **options) -> search.Prepared:
    return search.prepare(_docs(spark, sf_dir), schema, _bad(), **options)


def _root(prep: search.Prepared, merge=True, closed=True, uppers=True) -> DataFrame:
    """attr, lo, hi, n_pos, n_neg, least of the root's items."""
    rows = prep.tx.select(F.lit("").alias("node"), F.lit(0).alias("first"), "codes", "n_pos", "n_neg", "best")
    return lattice.items(lattice.header(rows), prep.is_symbol(), prep.size_column(), merge, closed, uppers).drop("node")


def _rules(prep: search.Prepared, measure: Measure = FSCORE) -> DataFrame:
    """pattern_id, items, n_pos, n_neg, score of all admitted single items."""
    found = lattice.scored(_root(prep, merge=False, closed=False), measure, prep.p, prep.n).where("admitted and n_pos > 0")
    items = F.array(item(F.col("attr"), F.col("lo"), F.col("hi")))
    return found.select(pattern_id(items).alias("pattern_id"), items.alias("items"), "n_pos", "n_neg", "score")


def _all_pairs(prep: search.Prepared) -> DataFrame:
    return settled(baselines.brute_force(prep, FSCORE, (0, 1)), "pairs")


# Cut-points and encoding

_BASE = twins.base("documents", SMALL, BAD)
_PAIR = twins.base("documents", PAIR, BAD)
_PAIRS = _PAIR + twins.patterns(PAIR)


@query(_BASE + " SELECT * FROM hist")
def hist_doc(spark, sf_dir):
    return _histogram(spark, sf_dir)


@query(_BASE + " SELECT attr, cell, cut FROM (SELECT attr, cell, (vmax + lead(vmin) OVER (PARTITION BY attr ORDER BY cell)) / 2 AS cut FROM hist) WHERE cut IS NOT NULL")
def initial_cuts_doc(spark, sf_dir):
    return cuts.initial_cuts(_histogram(spark, sf_dir))


@query(_BASE + " SELECT attr, cell, n_pos, n_neg, purity FROM pure")
def purity_doc(spark, sf_dir):
    return cuts.purity(_histogram(spark, sf_dir)).select("attr", "cell", "n_pos", "n_neg", "purity")


@query(_BASE + " SELECT * FROM cuts")
def merged_cuts_doc(spark, sf_dir):
    return cuts.merged_cuts(_histogram(spark, sf_dir))


@query(twins.base("documents", SMALL, BAD, merge=False) + " SELECT attr, code, lo, hi, n_pos, n_neg FROM cuts")
def unmerged_cuts_doc(spark, sf_dir):
    return cuts.merged_cuts(_histogram(spark, sf_dir), False, False).select("attr", "code", "lo", "hi", "n_pos", "n_neg")


@query(
    _BASE.replace("floor(CAST(uniq_pct AS DOUBLE) / 1.0::DOUBLE)", "floor(CAST(uniq_pct AS DOUBLE) / 1.0::DOUBLE)")
    + """ SELECT attr, CAST(dense_rank() OVER (PARTITION BY attr ORDER BY place) - 1 AS INT) AS code, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg FROM
(SELECT *, CASE WHEN high = low THEN 0 ELSE least(5, CAST(floor(6 * (vmin - low) / (high - low)) AS BIGINT)) END AS place FROM (SELECT *, min(vmin) OVER (PARTITION BY attr) AS low, max(vmax) OVER (PARTITION BY attr) AS high FROM hist)) GROUP BY attr, place"""
)
def cuts_width(spark, sf_dir):
    return cuts.width_cuts(_histogram(spark, sf_dir), 6).select("attr", "code", "n_pos", "n_neg")


@query(
    _BASE
    + """ SELECT attr, CAST(dense_rank() OVER (PARTITION BY attr ORDER BY place) - 1 AS INT) AS code, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg FROM
(SELECT *, floor(6 * before / total::DOUBLE) AS place FROM (SELECT *, sum(n_pos + n_neg) OVER (PARTITION BY attr ORDER BY cell ROWS UNBOUNDED PRECEDING) - n_pos - n_neg AS before, sum(n_pos + n_neg) OVER (PARTITION BY attr) AS total FROM hist)) GROUP BY attr, place"""
)
def cuts_quantile(spark, sf_dir):
    return cuts.quantile_cuts(_histogram(spark, sf_dir), 6).select("attr", "code", "n_pos", "n_neg")


@query()
def cuts_entropy_mdl(spark, sf_dir):
    return cuts.entropy_cuts(_histogram(spark, sf_dir))


@query()
def cuts_optimal_histogram(spark, sf_dir):
    return cuts.optimal_cuts(_histogram(spark, sf_dir))


@query(_BASE + " SELECT attr, count(*) AS bases, count(*) * (count(*) + 1) // 2 - 1 AS items, CAST(sum(CASE WHEN n_pos > 0 THEN 1 ELSE 0 END) AS BIGINT) AS ends FROM cuts GROUP BY attr")
def base_intervals(spark, sf_dir):
    return cuts.base_counts_summary(cuts.merged_cuts(_histogram(spark, sf_dir))).select("attr", "bases", "items", "ends")


@query(_BASE + " SELECT doc_id, k0, k1, k2, pos = 1 AS is_pos FROM codes")
def encode_doc(spark, sf_dir):
    df = _docs(spark, sf_dir)
    book = encode.codebook(df, SMALL, _bad(), settled(cuts.merged_cuts(_histogram(spark, sf_dir)), "cuts"))
    return encode.encode(df, book, _bad(), ("doc_id",)).select("doc_id", *(F.col("codes")[i].alias(f"k{i}") for i in range(3)), "is_pos")


@query(_BASE + " SELECT tx_id, n_pos, n_neg FROM tx")
def compress_tx(spark, sf_dir):
    return _prepared(spark, sf_dir).tx.select("tx_id", "n_pos", "n_neg")


@query(_BASE + " SELECT p + n AS n, p AS n_pos, n AS n_neg, p / (p + n)::DOUBLE AS p_class, n / (p + n)::DOUBLE AS p_other FROM tot")
def class_totals(spark, sf_dir):
    return encode.probabilities(_prepared(spark, sf_dir).tx)


# Lattice counts

@query(_BASE + " SELECT attr, lo, hi, n_pos, n_neg FROM root WHERE n_pos > 0")
def lattice_counts(spark, sf_dir):
    return _root(_prepared(spark, sf_dir), merge=False, closed=False).select("attr", "lo", "hi", "n_pos", "n_neg")


@query(_BASE + " SELECT r.attr, r.lo, r.hi, r.n_pos, r.n_neg FROM root r WHERE r.attr = 2 AND n_pos > 0 OR (r.attr < 2 AND (SELECT n_pos FROM cuts c WHERE c.attr = r.attr AND c.code = r.lo) > 0 AND (SELECT n_pos FROM cuts c WHERE c.attr = r.attr AND c.code = r.hi - 1) > 0)")
def closed_ends(spark, sf_dir):
    return _root(_prepared(spark, sf_dir), merge=False).select("attr", "lo", "hi", "n_pos", "n_neg")


@query(_BASE + " SELECT attr, lo, hi, n_pos, n_neg FROM root WHERE hi = lo + 1 AND n_pos > 0")
def base_items_only(spark, sf_dir):
    return _root(_prepared(spark, sf_dir), merge=False, closed=False, uppers=False).select("attr", "lo", "hi", "n_pos", "n_neg")


def _header(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    return prep, lattice.header(prep.tx.select(F.lit("").alias("node"), F.lit(0).alias("first"), "codes", "n_pos", "n_neg", "best"))


_HEAD = ", head AS (SELECT attr, code, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg FROM long GROUP BY attr, code)"


@query(_BASE + _HEAD + " SELECT * FROM head WHERE attr < 2 OR n_pos >= 12")
def rare_symbols(spark, sf_dir):
    prep, head = _header(spark, sf_dir)
    return lattice.drop_rare_symbols(head, prep.is_symbol(), F.lit(12)).select("attr", "code", "n_pos", "n_neg")


@query(_BASE + _HEAD + " SELECT attr, code, n_pos, n_neg FROM (SELECT *, sum(n_pos) OVER (PARTITION BY attr) AS t FROM head) WHERE attr = 2 OR t >= 12")
def rare_attrs(spark, sf_dir):
    prep, head = _header(spark, sf_dir)
    return lattice.drop_rare_attributes(head, prep.is_symbol(), F.lit(12)).select("attr", "code", "n_pos", "n_neg")


@query(
    _BASE
    + """, given AS (SELECT attr, code, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg FROM long WHERE attr < 2 AND tx_id IN (SELECT tx_id FROM tx WHERE k2 = 0) GROUP BY attr, code),
kind AS (SELECT *, CASE WHEN n_neg = 0 THEN 'pos' WHEN n_pos = 0 THEN 'neg' ELSE 'mixed' END AS kind FROM given),
cut AS (SELECT *, CASE WHEN kind <> 'mixed' AND lag(kind) OVER (PARTITION BY attr ORDER BY code) = kind THEN 0 ELSE 1 END AS b FROM kind),
joined AS (SELECT *, sum(b) OVER (PARTITION BY attr ORDER BY code ROWS UNBOUNDED PRECEDING) AS run FROM cut)
SELECT attr, min(code) AS code, max(code) AS last, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg FROM joined GROUP BY attr, run"""
)
def remerge_given_lang(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    rows = prep.tx.where(F.col("codes")[2] == 0).select(F.lit("2:0:1").alias("node"), F.lit(0).alias("first"), "codes", "n_pos", "n_neg", "best")
    return lattice.remerge(lattice.header(rows).where("attr < 2")).select("attr", "code", "last", "n_pos", "n_neg")


@query(_PAIR + f" SELECT {twins.item_id('a.attr', 'a.lo', 'a.hi')} AS general, {twins.item_id('b.attr', 'b.lo', 'b.hi')} AS special FROM items a JOIN items b ON a.attr = b.attr AND a.lo <= b.lo AND b.hi <= a.hi AND NOT (a.lo = b.lo AND a.hi = b.hi) WHERE a.attr = 1")
def subsumption_pairs(spark, sf_dir):
    size = _prepared(spark, sf_dir, PAIR).sizes[1]
    every = spark.createDataFrame([(lo, hi) for lo in range(size) for hi in range(lo + 1, size + 1) if (lo, hi) != (0, size)], "lo int, hi int").select(F.array(item(1, F.col("lo"), F.col("hi"))).alias("p"))
    other = every.select(F.col("p").alias("q"))
    return every.join(other, subsumes(F.col("p"), F.col("q"), strict=True)).select(pattern_id(F.col("p")).alias("general"), pattern_id(F.col("q")).alias("special"))


_FIXED = [[(0, 0, 2)], [(0, 0, 3), (1, 1, 3)], [(1, 0, 1), (2, 0, 1)], [(0, 1, 4), (1, 0, 2), (2, 1, 2)], [(2, 3, 4)]]


def _fixed(spark):
    rows = [([{"attr": a, "lo": b, "hi": c} for a, b, c in p],) for p in _FIXED]
    return spark.createDataFrame(rows, f"items {PATTERN}").select(pattern_id(F.col("items")).alias("pattern_id"), "items")


@query(
    _BASE
    + ", one AS ("
    + " UNION ALL ".join(f"SELECT '{';'.join(f'{a}:{b}:{c}' for a, b, c in p)}' AS pattern_id, coalesce(sum(n_pos), 0) AS a, coalesce(sum(n_neg), 0) AS b FROM tx WHERE {' AND '.join(f'k{a} >= {b} AND k{a} < {c}' for a, b, c in p)}" for p in _FIXED)
    + ") SELECT pattern_id, CAST(a AS BIGINT) AS n_pos, CAST(b AS BIGINT) AS n_neg, a / (p + n)::DOUBLE AS p_joint, (a + b) / (p + n)::DOUBLE AS p_pattern, CASE WHEN a + b > 0 THEN a / (a + b)::DOUBLE END AS conf, a / p::DOUBLE AS pos_supp, b / n::DOUBLE AS neg_supp FROM one, tot"
)
def pattern_stats_fixed(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    return constraints.with_shares(constraints.pattern_stats(prep.tx, _fixed(spark)), prep.p, prep.n).drop("items")


_trim = lambda c: f"regexp_replace(regexp_replace(printf('%.6f', {c}), '0+$', ''), '\\.$', '')"


@query(_BASE + f" SELECT {twins.item_id('attr', 'code', 'code + 1')} AS pattern_id, CASE WHEN lo IS NULL THEN '' ELSE {_trim('lo')} || ' <= ' END || CASE attr WHEN 0 THEN 'uniq_pct' ELSE 'upper_pct' END || CASE WHEN hi IS NULL THEN '' ELSE ' < ' || {_trim('hi')} END AS text FROM cuts UNION ALL SELECT {twins.item_id('attr', 'code', 'code + 1')}, 'lang = ' || value FROM sym")
def render_items(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    sizes = [(i, k) for i, size in enumerate(prep.sizes) for k in range(size)]
    items = F.array(item(F.col("attr"), F.col("code"), F.col("code") + 1))
    return spark.createDataFrame(sizes, "attr int, code int").select(pattern_id(items).alias("pattern_id"), render(items, *prep.book.columns()).alias("text"))


# Measures

def _measured(measure: Measure):
    def f(spark, sf_dir):
        prep = _prepared(spark, sf_dir)
        found = lattice.scored(_root(prep, merge=False, closed=False), measure, prep.p, prep.n)
        return found.select("attr", "lo", "hi", "n_pos", "n_neg", F.round("score", 6).alias("score"), "admitted")

    return f


for _m in (FSCORE, CHI2, INFOGAIN, SUPPDIFF):
    QUERIES[f"measure_{_m.name}"] = _measured(_m)
    ORACLE_SQL[f"measure_{_m.name}"] = _BASE + f" SELECT attr, lo, hi, n_pos, n_neg, round({twins.SCORES[_m.name]}, 6) AS score, n_pos * n >= n_neg * p AS admitted FROM root, tot WHERE n_pos > 0"


@query(_BASE + " SELECT attr, lo, hi, n_pos, round(2::DOUBLE * n_pos / (p + n_pos), 6) AS bound, round(s / (2 - s), 6) AS floor FROM (SELECT *, 2::DOUBLE * n_pos / (p + n_pos + n_neg) AS s FROM root, tot WHERE n_pos > 0)")
def bound_and_floor(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    found = lattice.scored(_root(prep, merge=False, closed=False), FSCORE, prep.p, prep.n)
    return found.select("attr", "lo", "hi", "n_pos", F.round(FSCORE.bound(F.col("n_pos"), prep.p, prep.n), 6).alias("bound"), F.round(FSCORE.floor_column(F.col("score")), 6).alias("floor"))


@query(
    _BASE
    + ", ends AS (SELECT n_pos AS a, n_neg AS b, p, n FROM root, tot WHERE n_pos > 0 AND n_pos * n >= n_neg * p), "
    + "steps AS (SELECT * FROM (SELECT a, b, a + 1 AS a2, b AS b2, 1 AS up, p, n FROM ends WHERE a < p UNION ALL SELECT a, b, a, b + 1, -1, p, n FROM ends WHERE b < n AND a * n >= (b + 1) * p)), "
    + "moves AS ("
    + " UNION ALL ".join(
        f"SELECT '{name}' AS measure, up * ((SELECT {score} FROM (SELECT a2 AS n_pos, b2 AS n_neg)) - (SELECT {score} FROM (SELECT a AS n_pos, b AS n_neg))) AS rise FROM steps"
        for name, score in {**twins.SCORES, "recall": "n_pos / p::DOUBLE", "dice": twins.SCORES["fscore"]}.items()
    )
    + ") SELECT measure, min(rise) >= -1e-12 AS dual_monotone FROM moves GROUP BY measure"
)
def measures_monotone(spark, sf_dir):
    """Whether each measure rises with one more positive and falls with one more negative row, from the counts of every item of documents that may be an answer."""
    prep = _prepared(spark, sf_dir)
    p, n, a, b = prep.p, prep.n, F.col("n_pos"), F.col("n_neg")
    found = settled(_root(prep, merge=False, closed=False).where(associated(a, b, F.lit(p), F.lit(n)) & (a > 0)).select("n_pos", "n_neg").distinct(), "counts")
    out = None
    for name, m in MEASURES.items():
        here = m.column(a, b, F.lit(p), F.lit(n))
        up = F.when(a < p, m.column(a + 1, b, F.lit(p), F.lit(n)) - here)
        down = F.when((b < n) & associated(a, b + 1, F.lit(p), F.lit(n)), here - m.column(a, b + 1, F.lit(p), F.lit(n)))
        one = found.agg((F.least(F.min(up), F.min(down)) >= -1e-12).alias("dual_monotone")).select(F.lit(name).alias("measure"), "dual_monotone")
        out = one if out is None else out.unionByName(one)
    return out


# Searches and constraints

_ANSWER = " SELECT pattern_id, n_pos, n_neg, round(score, 6) AS score FROM answer"


def _told(patterns: DataFrame) -> DataFrame:
    return patterns.select("pattern_id", "n_pos", "n_neg", F.round("score", 6).alias("score"))


def _small(measure: Measure = FSCORE, positive: str = BAD) -> str:
    return twins.base("documents", SMALL, positive) + twins.patterns(SMALL, measure.name) + twins.covering()


@query(_BASE + twins.rules() + " SELECT pattern_id, n_pos, n_neg, round(score, 6) AS score FROM rule ORDER BY rule.score DESC, pattern_id LIMIT 10")
def top_items_doc(spark, sf_dir):
    best = _rules(_prepared(spark, sf_dir)).orderBy(F.col("score").desc(), "pattern_id").limit(10)
    return best.select("pattern_id", "n_pos", "n_neg", F.round("score", 6).alias("score"))


@query(_PAIRS + " SELECT place, round(score, 6) AS score FROM (SELECT row_number() OVER (ORDER BY score DESC, pattern_id) AS place, score FROM pat WHERE admitted) WHERE place <= 10")
def topk_pairs_doc(spark, sf_dir):
    from pyspark.sql import Window

    prep = _prepared(spark, sf_dir, PAIR)
    found = search.mine_topk(prep, 10, options=Options(merge=False, closed=False)).patterns
    return found.select(F.row_number().over(Window.orderBy(F.col("score").desc(), "pattern_id")).cast("long").alias("place"), F.round("score", 6).alias("score"))


@query(_PAIRS + " SELECT tx_id, round(max(score), 6) AS best FROM hit GROUP BY tx_id")
def cover_best_pairs(spark, sf_dir):
    """The best score of each positive row, as the whole search finds it, against all patterns of two attributes."""
    prep = _prepared(spark, sf_dir, PAIR)
    answer = search.mine_covering(prep).patterns
    return constraints.candidate_lists(prep.tx, answer).groupBy("tx_id").agg(F.round(F.max("score"), 6).alias("best"))


@query(
    _PAIRS
    + twins.covering()
    + _ANSWER
)
def mine_covering_pairs(spark, sf_dir):
    """The whole answer over two attributes, against the same by brute force."""
    answer = search.mine_covering(_prepared(spark, sf_dir, PAIR)).patterns
    return answer.select("pattern_id", "n_pos", "n_neg", F.round("score", 6).alias("score"))


@query(_BASE + twins.rules() + " SELECT tx_id, pattern_id, round(score, 6) AS score FROM (SELECT *, rank() OVER (PARTITION BY tx_id ORDER BY score DESC) AS place FROM met) WHERE place = 1")
def candidate_lists(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    return constraints.candidate_lists(prep.tx, _rules(prep)).select("tx_id", "pattern_id", F.round("score", 6).alias("score"))


@query(_BASE + twins.rules() + " SELECT pattern_id, round(min(best), 6) AS floor FROM met JOIN (SELECT tx_id, max(score) AS best FROM met GROUP BY tx_id) USING (tx_id) GROUP BY pattern_id")
def scoped_floor(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    found = settled(_rules(prep), "rules")
    floors = constraints.scoped_floors(constraints.offer(prep.tx, found), found)
    return floors.select("pattern_id", F.round("floor", 6).alias("floor"))


@query(_PAIRS + " SELECT pattern_id, round(score, 6) AS score FROM pat JOIN clid USING (pattern_id) WHERE closure = pattern_id")
def closed_on_positives(spark, sf_dir):
    prep = _prepared(spark, sf_dir, PAIR)
    found = _all_pairs(prep).where("admitted and n_pos > 0")
    return constraints.closed(prep.tx, found, prep.is_symbol(), prep.size_column()).select("pattern_id", F.round("score", 6).alias("score"))


@query(
    _PAIRS
    + """, spans AS (SELECT pattern_id, any_value(l0) AS l0, any_value(h0) AS h0, any_value(l1) AS l1, any_value(h1) AS h1, min(k0) AS a0, max(k0) + 1 AS b0, min(k1) AS a1, max(k1) + 1 AS b1 FROM tx JOIN pat ON (l0 IS NULL OR (k0 >= l0 AND k0 < h0)) AND (l1 IS NULL OR (k1 >= l1 AND k1 < h1)) WHERE admitted GROUP BY pattern_id)
SELECT pattern_id FROM spans WHERE (CASE WHEN a0 = 0 AND b0 = (SELECT size FROM sizes WHERE attr = 0) THEN l0 IS NULL ELSE l0 IS NOT DISTINCT FROM a0 AND h0 IS NOT DISTINCT FROM b0 END) AND (CASE WHEN a1 = 0 AND b1 = (SELECT size FROM sizes WHERE attr = 1) THEN l1 IS NULL ELSE l1 IS NOT DISTINCT FROM a1 AND h1 IS NOT DISTINCT FROM b1 END)"""
)
def closed_on_all(spark, sf_dir):
    prep = _prepared(spark, sf_dir, PAIR)
    found = _all_pairs(prep).where("admitted and n_pos > 0")
    return constraints.closed(prep.tx, found, prep.is_symbol(), prep.size_column(), on_all=True).select("pattern_id")


@query(_PAIRS + " SELECT DISTINCT pattern_id FROM hit WHERE place = 1")
def best_covering(spark, sf_dir):
    prep = _prepared(spark, sf_dir, PAIR)
    return constraints.best_covering(prep.tx, _all_pairs(prep).where("admitted and n_pos > 0")).select("pattern_id")


@query(
    _BASE
    + twins.rules()
    + " SELECT r.pattern_id FROM rule r WHERE NOT EXISTS (SELECT 1 FROM rule g WHERE g.attr = r.attr AND g.lo <= r.lo AND r.hi <= g.hi AND NOT (g.lo = r.lo AND g.hi = r.hi) AND g.score >= r.score)"
)
def productivity(spark, sf_dir):
    return constraints.productive(_rules(_prepared(spark, sf_dir))).select("pattern_id")


@query(
    _BASE
    + twins.rules()
    + """, ranked AS (SELECT *, row_number() OVER (ORDER BY n_pos / (n_pos + n_neg)::DOUBLE DESC, n_pos DESC, pattern_id) AS place FROM rule)
SELECT DISTINCT pattern_id, place FROM ranked WHERE place IN (SELECT min(place) FROM met JOIN ranked USING (pattern_id) GROUP BY tx_id)"""
)
def database_coverage(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    shares = constraints.with_shares(_rules(prep), prep.p, prep.n)
    return rules.database_coverage(prep.tx, shares).select("pattern_id", F.col("place").cast("long").alias("place"))


@query()
def sequential_cover(spark, sf_dir):
    return rules.sequential_cover(_prepared(spark, sf_dir), strategy="depth").select("place", "pattern_id", "score", "positives_left")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What tells documents of bad quality from the others: the covering answer over all narrow attributes."""
    answer = search.mine_covering(_prepared(spark, sf_dir, tables.DOCUMENTS))
    return answer.patterns.select("pattern_id", "n_pos", "n_neg", "conf", "pos_supp", "score", "text")


@query()
def mine_covering_doc(spark, sf_dir):
    return flagship(spark, sf_dir)


@query()
def mine_covering_good(spark, sf_dir):
    answer = search.mine_covering(search.prepare(_docs(spark, sf_dir), tables.DOCUMENTS, F.col("cls") == "1"))
    return answer.patterns.select("pattern_id", "n_pos", "n_neg", "conf", "pos_supp", "score", "text")


def _covering(name: str, measure: Measure = FSCORE, strategy: str = "hybrid", options: Options = Options(), good: bool = False) -> None:
    """The whole answer over two numbers and a symbol, against all patterns by brute force."""

    def f(spark, sf_dir):
        prep = search.prepare(_docs(spark, sf_dir), SMALL, F.col("cls") == "1") if good else _prepared(spark, sf_dir)
        return _told(search.mine_covering(prep, measure, options, strategy).patterns)

    QUERIES[name] = f
    ORACLE_SQL[name] = _small(measure, "quality = '1'" if good else BAD) + _ANSWER


for _name, _given in {
    "mine_covering_small": {},
    "mine_covering_good_small": {"good": True},
    "mine_covering_level": {"strategy": "level"},
    "mine_covering_depth": {"strategy": "depth"},
    "mine_covering_chi2": {"measure": CHI2},
    "mine_covering_infogain": {"measure": INFOGAIN},
    "mine_covering_suppdiff": {"measure": SUPPDIFF},
    "mine_covering_closure_jump": {"options": Options(closure=True)},
    "mine_covering_by_support": {"options": Options(prune="support")},
    "mine_covering_unpruned": {"options": Options(floor="none", merge=False, closed=False, pure_leaves=False), "strategy": "depth"},
}.items():
    _covering(_name, **_given)


@query(_PAIR + twins.patterns(PAIR, "confidence") + twins.covering() + _ANSWER)
def mine_covering_confidence(spark, sf_dir):
    """Highest-confidence covering: the same search by another measure.

    Without merging at nodes: by confidence a narrower interval of a pure run ties with the whole run.
    """
    return _told(search.mine_covering(_prepared(spark, sf_dir, PAIR), CONFIDENCE, Options(merge=False)).patterns)


@query(_small() + " SELECT count(*) AS patterns, min(k) AS shortest, max(k) AS longest, CAST(sum(k) AS BIGINT) AS items FROM (SELECT len(string_split(pattern_id, ';')) AS k FROM answer)")
def answer_lengths(spark, sf_dir):
    """How many patterns an answer has, and of how many items."""
    k = F.size("items").cast("long")
    return search.mine_covering(_prepared(spark, sf_dir)).patterns.agg(F.count(F.lit(1)).alias("patterns"), F.min(k).alias("shortest"), F.max(k).alias("longest"), F.sum(k).alias("items"))


@query(_small() + " SELECT CAST(sum(n_pos) AS BIGINT) AS covered, any_value(p) AS positives, sum(n_pos) / any_value(p)::DOUBLE AS share FROM tx, tot WHERE tx_id IN (SELECT tx_id FROM hit WHERE pattern_id IN (SELECT pattern_id FROM answer))")
def answer_coverage(spark, sf_dir):
    prep = _prepared(spark, sf_dir)
    return search.coverage(prep, search.mine_covering(prep).patterns)


@query(twins.base("documents", SMALL, BAD) + twins.patterns(SMALL) + " SELECT pattern_id, n_pos, n_neg, round(score, 6) AS score FROM pat WHERE admitted ORDER BY pat.score DESC, pattern_id LIMIT 20")
def mine_topk_small(spark, sf_dir):
    return _told(search.mine_topk(_prepared(spark, sf_dir), 20).patterns)


@query(_PAIRS + " SELECT pattern_id, n_pos, n_neg, round(score, 6) AS score FROM pat WHERE admitted ORDER BY pat.score DESC, pattern_id LIMIT 20")
def mine_topk_pairs(spark, sf_dir):
    return _told(search.mine_topk(_prepared(spark, sf_dir, PAIR), 20).patterns)


_INDEPENDENT = "(SELECT CAST(k * p AS BIGINT) AS n_pos, CAST(k * n AS BIGINT) AS n_neg FROM tot, range(1, 10) t(k)), (SELECT CAST(10 * p AS BIGINT) AS p, CAST(10 * n AS BIGINT) AS n FROM tot)"


@query(_BASE + " " + " UNION ALL ".join(f"SELECT '{m}' AS measure, n_pos, round({twins.SCORES[m]}, 6) + 0.0 AS score FROM {_INDEPENDENT}" for m in ("fscore", "chi2", "infogain", "suppdiff")))
def zero_at_independence(spark, sf_dir):
    """Measures of patterns that are independent of the class: all but the F-score are zero there.

    Each document of the table stands once for each of ten values of one more attribute, so the patterns
    of the first one to nine values are independent of its class.
    """
    dealt = _prepared(spark, sf_dir).tx.select("n_pos", "n_neg", F.explode(F.sequence(F.lit(0), F.lit(9))).alias("dealt"))
    values = dealt.groupBy("dealt").agg(F.sum("n_pos").alias("a"), F.sum("n_neg").alias("b"))
    whole = values.agg(F.sum("a").alias("p"), F.sum("b").alias("n"))
    covered = spark.range(1, 10).join(values, F.col("dealt") < F.col("id")).groupBy("id").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    counts = settled(covered.crossJoin(F.broadcast(whole)), "independent")
    out = None
    for m in (FSCORE, CHI2, INFOGAIN, SUPPDIFF):
        one = counts.select(F.lit(m.name).alias("measure"), F.col("a").alias("n_pos"), (F.round(m.column(F.col("a"), F.col("b"), F.col("p"), F.col("n")), 6) + 0.0).alias("score"))
        out = one if out is None else out.unionByName(one)
    return out


@query()
def mine_covering_toxic(spark, sf_dir):
    """The hard case, a rare class that these attributes hardly tell, to its end: patterns, with the visits it took."""
    schema = HybridSchema((*SMALL.attributes, number("digit_pct"), symbol("quality")))
    answer = search.mine_covering(search.prepare(_docs(spark, sf_dir, "toxic"), schema, F.col("cls") == "1"))
    return answer.patterns.select("pattern_id", "n_pos", "n_neg", "score", "text").join(answer.stats.select("visited", "complete"))


@query()
def mine_toxic_anytime(spark, sf_dir):
    """The same on more attributes, stopped after a number of visits: what it has by then, marked as incomplete."""
    schema = HybridSchema((*tables.DOCUMENTS.attributes[:6], symbol("quality")))
    answer = search.mine_covering(search.prepare(_docs(spark, sf_dir, "toxic"), schema, F.col("cls") == "1"), options=Options(visits=200_000))
    return answer.patterns.select("pattern_id", "n_pos", "n_neg", "score", "text").join(answer.stats.select("visited", "complete"))


@query()
def mine_topk_doc(spark, sf_dir):
    return search.mine_topk(_prepared(spark, sf_dir, tables.DOCUMENTS), 20).patterns.select("pattern_id", "n_pos", "n_neg", "score", "text")


@query()
def mine_stats_doc(spark, sf_dir):
    """Visits, prunes and time of the flagship search, and its coverage of positive rows."""
    prep = _prepared(spark, sf_dir, tables.DOCUMENTS)
    answer = search.mine_covering(prep)
    return answer.stats.join(search.coverage(prep, answer.patterns))


FIRST, CAPPED = SMALL.reordered("symbols_first"), SMALL.limited(1)
ABLATIONS = {
    "all": (Options(), SMALL, {}),
    "no merge of cuts": (Options(), SMALL, {"merge_pos": False, "merge_neg": False}),
    "no merge at nodes": (Options(merge=False), SMALL, {}),
    "no closed ends": (Options(closed=False), SMALL, {}),
    "given order": (Options(order="given"), SMALL, {}),
    "symbols first": (Options(order="given"), FIRST, {}),
    "one number": (Options(), CAPPED, {}),
    "closure in the search": (Options(closure=True), SMALL, {}),
    "raised support": (Options(prune="support"), SMALL, {}),
    "base items only": (Options(uppers=False), SMALL, {}),
    "fixed support": (Options(floor="none", support=5), SMALL, {}),
    "no floor": (Options(floor="none"), SMALL, {}),
}


@query()
def ablations(spark, sf_dir):
    """Visits with each part of the search left out or another in its place, in one task each, all to the end.

    visits_a_second is a time's measure and differs by machine; the others don't.
    """
    out, preps = None, {}
    for name, (options, schema, prepared) in ABLATIONS.items():
        if (key := str((schema, prepared))) not in preps:
            preps[key] = _prepared(spark, sf_dir, schema, **prepared)
        prep = preps[key]
        found, stats = search.search(prep, options=options, strategy="depth")
        best = found.agg(F.max("score").alias("best_score"), F.count(F.lit(1)).alias("candidates"))
        rate = (1000 * F.col("visited") / F.greatest("elapsed_ms", F.lit(1))).alias("visits_a_second")
        one = stats.select(F.lit(name).alias("left_out"), "visited", rate, "pruned_floor", "pruned_closed", "complete").join(best)
        out = one if out is None else out.unionByName(one)
    return out


@query()
def covering_contrast(spark, sf_dir):
    """Rules learnt one after the other, each from what is left, and all at once from all rows: how many, and their scores over all rows."""
    prep = _prepared(spark, sf_dir)
    strategy = "depth" if Dense.patterns(prep.sizes, prep.symbols) <= DENSE else "hybrid"
    one_by_one = rules.sequential_cover(prep, strategy="depth").select("pattern_id", "items")
    at_once = search.mine_covering(prep, strategy=strategy).patterns.select("pattern_id", "items")
    out = None
    for name, found in (("separate and conquer", one_by_one), ("all rows at once", at_once)):
        counted = constraints.pattern_stats(prep.tx, settled(found.distinct(), "contrast"))
        score = FSCORE.column(F.col("n_pos"), F.col("n_neg"), prep.p, prep.n)
        one = counted.agg(F.lit(name).alias("way"), F.count(F.lit(1)).alias("rules"), F.round(F.max(score), 6).alias("best"), F.round(F.min(score), 6).alias("lowest"), F.min(F.col("n_pos")).alias("least_support"))
        out = one if out is None else out.unionByName(one)
    return out


@query()
def discretisations(spark, sf_dir):
    """Best score and lowest best score of a positive row, by how numbers are cut."""
    ways = {"adaptive": None, "width": lambda h: cuts.width_cuts(h, 8), "quantile": lambda h: cuts.quantile_cuts(h, 8), "entropy": cuts.entropy_cuts, "optimal": cuts.optimal_cuts}
    out = None
    for name, way in ways.items():
        prep = _prepared(spark, sf_dir, SMALL, discretise=way)
        answer = search.mine_covering(prep, strategy="depth")
        best = constraints.candidate_lists(prep.tx, answer.patterns).groupBy("tx_id").agg(F.max("score").alias("score"))
        one = best.agg(F.max("score").alias("best"), F.min("score").alias("lowest")).select(F.lit(name).alias("cuts"), F.lit(sum(prep.sizes)).alias("codes"), "best", "lowest")
        out = one if out is None else out.unionByName(one)
    return out


@query()
def classify_rules(spark, sf_dir):
    """Accuracy of a rule list and a vote of both classes' answers, learnt on ids that 3 doesn't divide, tested on the others."""
    df = _docs(spark, sf_dir)
    train, test = df.where("doc_id % 3 <> 0"), df.where("doc_id % 3 = 0")
    out = None
    prep = search.prepare(train, SMALL, F.col("cls") == "0")
    other = search.Prepared(prep.book, prep.tx.select("tx_id", "codes", F.col("n_neg").alias("n_pos"), F.col("n_pos").alias("n_neg"), "best"), prep.n, prep.p)
    both = settled(search.mine_covering(prep).patterns.withColumn("cls", F.lit("0")).unionByName(search.mine_covering(other).patterns.withColumn("cls", F.lit("1"))), "rules")
    rows = encode.encode(test, prep.book, _bad(), ("doc_id", "cls"))
    for name, made in (("list", rules.classify_by_list(rows, both, "1")), ("vote", rules.classify_by_vote(rows, both, "0", "1"))):
        made = settled(made, "classified")
        auc = rules.area_under_curve(made.withColumn("margin", F.when(F.col("predicted") == "0", F.abs("margin")).otherwise(-F.abs("margin"))), "0")
        one = rules.accuracy(rules.confusion(made)).select(F.lit(name).alias("classifier"), "n", "right", "accuracy").join(auc)
        out = one if out is None else out.unionByName(one)
    return out


@query(
    f"WITH {twins.FEATURES['documents']}, pos AS (SELECT lang, source FROM feat WHERE quality = '0'), sets AS (SELECT 'lang=' || lang AS items FROM pos WHERE lang IS NOT NULL UNION ALL SELECT 'source=' || source FROM pos WHERE source IS NOT NULL UNION ALL SELECT 'lang=' || lang || ',source=' || source FROM pos WHERE lang IS NOT NULL AND source IS NOT NULL)"
    " SELECT items, count(*) AS freq FROM sets GROUP BY items HAVING count(*) >= ceil(0.05::DOUBLE * (SELECT count(*) FROM pos))"
)
def frequent_symbols(spark, sf_dir):
    schema = HybridSchema((symbol("lang"), symbol("source")))
    return baselines.frequent_symbols(_docs(spark, sf_dir), schema, _bad(), 0.05).select(F.array_join("items", ",").alias("items"), "freq")


@query(f"WITH {twins.FEATURES['documents']} SELECT lang, toxic, CAST(sum(CASE WHEN quality = '0' THEN 1 ELSE 0 END) AS BIGINT) AS n_pos, CAST(sum(CASE WHEN quality = '0' THEN 0 ELSE 1 END) AS BIGINT) AS n_neg FROM feat GROUP BY CUBE (lang, toxic) HAVING lang IS NOT NULL OR toxic IS NOT NULL")
def symbolic_cube(spark, sf_dir):
    return baselines.symbol_cube(_docs(spark, sf_dir), HybridSchema((symbol("lang"), symbol("toxic"))), _bad())


@query(f"WITH {twins.FEATURES['documents']}, each AS (SELECT CASE WHEN quality = '0' THEN 1 ELSE 0 END AS pos, unnest(list_distinct(tokens)) AS token FROM feat) SELECT token, CAST(sum(pos) AS BIGINT) AS n_pos, CAST(sum(1 - pos) AS BIGINT) AS n_neg FROM each GROUP BY token")
def basket_tokens(spark, sf_dir):
    docs = tables.table(spark, sf_dir, "documents").join(tables.table(spark, sf_dir, "labels"), "doc_id")
    rows = docs.select(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0)).alias("tokens"), (F.col("quality") == 0).alias("bad"))
    return baselines.basket_items(rows, "tokens", F.col("bad"))


# Other workloads: all items of each attribute, with counts and scores

def _items_of(name: str, read, schema: HybridSchema, column: str, positive: str):
    def f(spark, sf_dir):
        prep = search.prepare(read(spark, sf_dir), schema, F.col("cls") == positive)
        found = lattice.scored(_root(prep, merge=False), FSCORE, prep.p, prep.n)
        best = found.groupBy("attr").agg(F.count(F.lit(1)).alias("items"), F.sum("n_pos").alias("n_pos"), F.sum("n_neg").alias("n_neg"), F.round(F.max("score"), 6).alias("best"))
        return best

    source = {"conversations_roles": "conversations", "embeddings_items": "embeddings", "orders_null_control": "orders", "star_lineitem": "lineitem", "parts_null_control": "part"}[name]
    ends = "(r.attr IN (SELECT attr FROM sym) OR ((SELECT n_pos FROM cuts c WHERE c.attr = r.attr AND c.code = r.lo) > 0 AND (SELECT n_pos FROM cuts c WHERE c.attr = r.attr AND c.code = r.hi - 1) > 0))"
    QUERIES[name] = f
    ORACLE_SQL[name] = twins.base(source, schema, f"{column} = '{positive}'") + f" SELECT attr, count(*) AS items, CAST(sum(n_pos) AS BIGINT) AS n_pos, CAST(sum(n_neg) AS BIGINT) AS n_neg, round(max({twins.SCORES['fscore']}), 6) AS best FROM root r, tot WHERE n_pos > 0 AND {ends} GROUP BY attr"


_items_of("conversations_roles", tables.conversation_features, tables.CONVERSATIONS, "role", "user")
_items_of("embeddings_items", tables.embedding_features, tables.EMBEDDINGS, "label", "3")
_items_of("orders_null_control", tables.order_features, tables.ORDERS, "o_orderstatus", "F")
_items_of("star_lineitem", tables.lineitem_features, tables.LINEITEMS, "l_returnflag", "R")
_items_of("parts_null_control", tables.part_features, tables.PARTS, "p_type", "PROMO")


_LENGTH = HybridSchema((number("n_chars", 100.0),))


def _class_sql(cls: str) -> str:
    return f"SELECT '{cls}' AS cls, * FROM ({twins.base('conversations', _LENGTH, f"role = '{cls}'")}{twins.patterns(_LENGTH)}{twins.covering()}{_ANSWER})"


@query(" UNION ALL ".join(map(_class_sql, ("assistant", "system", "user"))))
def conversations_classes(spark, sf_dir):
    """One run for each role, each with cut-points of its own."""
    found = search.mine_all_classes(tables.conversation_features(spark, sf_dir), _LENGTH)
    return found.select("cls", "pattern_id", "n_pos", "n_neg", F.round("score", 6).alias("score"))


def _whole(name: str, read, schema: HybridSchema, positive: str) -> None:
    """The covering answer over all attributes of a workload, to its end."""

    def f(spark, sf_dir):
        answer = search.mine_covering(search.prepare(read(spark, sf_dir), schema, F.col("cls") == positive), options=Options(length=2))
        return answer.patterns.select("pattern_id", "n_pos", "n_neg", F.round("score", 6).alias("score"), "text").join(answer.stats.select("visited", "complete"))

    QUERIES[name] = f


_whole("conversations_covering", tables.conversation_features, tables.CONVERSATIONS, "assistant")
_whole("parts_covering", tables.part_features, tables.PARTS, "PROMO")
_whole("embeddings_covering", tables.embedding_features, tables.EMBEDDINGS, "3")
_whole("orders_two_items", tables.order_features, tables.ORDERS, "F")


@query()
def orders_covering(spark, sf_dir):
    schema = HybridSchema((number("month"), symbol("o_orderpriority"), symbol("r_name")))
    answer = search.mine_covering(search.prepare(tables.order_features(spark, sf_dir), schema, F.col("cls") == "F"))
    return answer.patterns.select("pattern_id", "n_pos", "n_neg", "score", "text")


@query()
def pages_flags(spark, sf_dir):
    schema = HybridSchema((symbol("top"), number("depth"), number("n_p")))
    answer = search.mine_covering(search.prepare(tables.page_features(spark, sf_dir), schema, F.col("cls") == "en"))
    return answer.patterns.select("pattern_id", "n_pos", "n_neg", "score", "text")


@query()
def planted_box(spark, sf_dir):
    """Rows with a known box and noise, searched to the end: the box has the best score."""
    answer = search.mine_covering(search.prepare(tables.planted(spark, 20_000), tables.PLANTED, F.col("cls") == "1"))
    return answer.patterns.select("pattern_id", "n_pos", "n_neg", F.round("score", 6).alias("score"), "text").join(answer.stats.select("visited", "complete"))


# Events: the batch side of the streams

def _epoch(name: str):
    """Seconds since 1970 of a time without a zone."""
    return F.expr(f"timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', {name})")


_EVENTS = HybridSchema((number("value", 10.0), number("hour"), number("k")))


@query(f"WITH {twins.FEATURES['events']}, each AS (" + " UNION ALL ".join(f"SELECT date_trunc('day', ts) AS day, {i} AS attr, CAST(floor(CAST({a.name} AS DOUBLE) / {a.delta!r}::DOUBLE) AS BIGINT) AS cell, CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END AS pos FROM feat WHERE {a.name} IS NOT NULL" for i, a in _EVENTS.numbers()) + ") SELECT CAST(epoch(day) AS BIGINT) AS day, attr, cell, CAST(sum(pos) AS BIGINT) AS n_pos, CAST(sum(1 - pos) AS BIGINT) AS n_neg FROM each GROUP BY day, attr, cell")
def events_window_hist(spark, sf_dir):
    rows = histograms.event_rows(tables.table(spark, sf_dir, "events"))
    found = histograms.window_histogram(rows, _EVENTS, histograms.tumbling())
    return found.select(_epoch("begin").alias("day"), "attr", "cell", "n_pos", "n_neg")


@query("""WITH o AS (SELECT user_id, ts, event_type, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o)
SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS begin, count(*) AS n, CAST(sum(CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END) AS BIGINT) AS n_pos FROM s GROUP BY user_id, k""")
def events_sessions(spark, sf_dir):
    found = histograms.sessions(histograms.event_rows(tables.table(spark, sf_dir, "events")))
    return found.select("user_id", _epoch("begin").alias("begin"), "n", "n_pos")


@query("SELECT event_id, CAST(CASE WHEN ts >= TIMESTAMP '2024-02-01' THEN 2 WHEN ts >= TIMESTAMP '2024-01-10' THEN 1 END AS INT) AS version FROM events")
def events_as_of(spark, sf_dir):
    versions = spark.sql("SELECT * FROM VALUES (1, TIMESTAMP '2024-01-10 00:00:00'), (2, TIMESTAMP '2024-02-01 00:00:00') AS v(version, since)")
    return histograms.latest_version(tables.table(spark, sf_dir, "events").select("event_id", "ts"), versions).select("event_id", "version")
