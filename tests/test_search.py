"""Whole searches: routes agree, answers are closed, productive and cover all positives; edges of encoding."""

import pytest
from pyspark.sql import functions as F

from contrast import workloads
from contrast.functions.measures import CHI2, FSCORE, MEASURES
from contrast.functions.patterns import PATTERN
from contrast.functions.sql import as_predicate, contrast_mine, register_all
from contrast.operators import constraints, cuts, encode, lattice, rules
from contrast.plans import search
from contrast.schema import HybridSchema, infer_schema, number, symbol
from contrast.session import settled
from contrast.sources import formats, tables
from contrast.streaming import histograms


@pytest.fixture(scope="module")
def prep(spark):
    return search.prepare(tables.document_features(spark, "/root/testdata/sf0.01"), tables.DOCUMENTS_SMALL, F.col("cls") == "0")


@pytest.fixture(scope="module")
def answer(prep):
    return search.mine_covering(prep)


def ids(df):
    return sorted((r["pattern_id"], round(r["score"], 9)) for r in df.select("pattern_id", "score").collect())


def test_routes_agree(prep, answer):
    assert ids(answer.patterns) == ids(search.mine_covering(prep, strategy="level").patterns) == ids(search.mine_covering(prep, strategy="depth").patterns)


def test_known_best_scores(prep, answer):
    scores = [s for _, s in ids(answer.patterns)]
    best = constraints.candidate_lists(prep.tx, answer.patterns).groupBy("tx_id").agg(F.max("score").alias("s"))
    assert round(max(scores), 4) == 0.8041
    assert round(best.agg(F.min("s")).first()[0], 4) == 0.2624


def test_rows_sent_or_joined(prep, monkeypatch):
    monkeypatch.setattr(search, "SENT_ROWS", 0)
    monkeypatch.setattr(search, "NODE_ROWS", 150)
    assert ids(search.mine_covering(prep).patterns) == ids(search.mine_covering(prep, strategy="depth").patterns)


def test_answer_holds_its_promises(prep, answer):
    assert search.coverage(prep, answer.patterns).first()["share"] == 1.0
    closed = constraints.closed(prep.tx, answer.patterns, prep.is_symbol(), prep.size_column())
    assert ids(closed) == ids(answer.patterns) == ids(constraints.best_covering(prep.tx, answer.patterns)) == ids(constraints.productive(answer.patterns))


def test_unmerged_cuts_find_the_same(spark, answer):
    plain = search.prepare(tables.document_features(spark, "/root/testdata/sf0.01"), tables.DOCUMENTS_SMALL, F.col("cls") == "0", merge_pos=False, merge_neg=False)
    again = search.mine_covering(plain).patterns
    key = lambda df: sorted((r["n_pos"], r["n_neg"]) for r in df.collect())
    assert key(again) == key(answer.patterns)


def test_merge_of_pure_runs(spark):
    rows = spark.createDataFrame([(float(v), c) for v, cs in zip(range(1, 9), "++--m++-") for c in ("+-" if cs == "m" else cs)], "v double, cls string")
    got = cuts.merged_cuts(cuts.value_histogram(rows, HybridSchema((number("v"),)), F.col("cls") == "+")).orderBy("code").collect()
    assert [(r["lo"], r["hi"], r["purity"]) for r in got] == [(None, 2.5, "pos"), (2.5, 4.5, "neg"), (4.5, 5.5, "mixed"), (5.5, 7.5, "pos"), (7.5, None, "neg")]


def test_encoding_edges(spark):
    rows = spark.createDataFrame([(-3.5, "a", "+"), (float("nan"), "b", "-"), (None, None, "+"), (2.0, "a", "-"), (4.0, "b", "+")], "v double, s string, cls string")
    schema, pos = HybridSchema((number("v"), symbol("s"))), F.col("cls") == "+"
    base = cuts.merged_cuts(cuts.value_histogram(rows, schema, pos))
    book = encode.codebook(rows, schema, pos, base)
    assert book.edges[0] == (-0.75, 3.0)
    assert sorted(r["codes"] for r in encode.encode(rows, book, pos).collect()) == [[-1, -1], [-1, 1], [0, 0], [1, 0], [2, 1]]
    later = spark.createDataFrame([(3.0, "new", "+")], rows.schema)
    assert encode.encode(later, book, pos).first()["codes"] == [2, -1]


@pytest.mark.parametrize("rows", [[], [(1.0, "+")], [(1.0, "+"), (1.0, "-")], [(1.0, "-"), (2.0, "-")]], ids=["empty", "one", "constant", "no positives"])
def test_degenerate_tables(spark, rows):
    df = spark.createDataFrame(rows, "v double, cls string")
    made = search.mine_covering(search.prepare(df, HybridSchema((number("v"),)), F.col("cls") == "+"))
    assert made.patterns.count() == 0
    assert made.stats.count() == 1


def test_prefix_sums_equal_the_recurrence(prep):
    head = lattice.header(prep.tx.select(F.lit("").alias("node"), F.lit(0).alias("first"), "codes", "n_pos", "n_neg", "best")).where("attr = 1")
    row = lambda df: sorted((r["lo"], r["hi"], r["n_pos"], r["n_neg"]) for r in df.collect())
    assert row(lattice.intervals(head.withColumn("last", F.col("code")), closed=False)) == row(lattice.intervals_by_width(head, prep.sizes[1]))


def test_closed_beats_general(spark):
    tx = spark.createDataFrame([("a", [0, 0], 2, 0, 0.0), ("b", [1, 1], 0, 3, 0.0), ("c", [2, 0], 0, 1, 0.0)], "tx_id string, codes array<int>, n_pos long, n_neg long, best double")
    found = spark.createDataFrame([([{"attr": 0, "lo": 0, "hi": 1}],)], f"items {PATTERN}")
    done = constraints.finished(tx, found, FSCORE, 2, 4, F.get(F.array(F.lit(False), F.lit(False)), F.col("attr")), F.array(F.lit(3), F.lit(2)))
    assert [r["pattern_id"] for r in done.collect()] == ["0:0:1;1:0:1"]


def test_sql_surface(spark, tiny):
    register_all(spark)
    assert spark.sql("SELECT contrast_covers(array(named_struct('attr', 0, 'lo', 1, 'hi', 3)), array(2))").first()[0] is True
    assert spark.sql("SELECT round(contrast_floor(contrast_bound(5, 10)) * 10, 6)").first()[0] == 5
    assert spark.sql("SELECT count(*), sum(n_pos) FROM contrast_intervals(array(1L, 2L, 3L), array(0L, 0L, 0L))").first() == (5, 14)
    tables.document_features(spark, tiny).select("uniq_pct", "lang", "cls").createOrReplaceTempView("docs_small")
    mined = contrast_mine(spark, "docs_small", "cls", "0")
    df = spark.table("docs_small")
    book = search.prepare(df, infer_schema(df, ("cls",)), F.col("cls") == "0").book
    for found in mined.collect():
        hit = df.where(as_predicate(found["items"], book))
        assert (hit.where("cls = '0'").count(), hit.where("cls <> '0'").count()) == (found["n_pos"], found["n_neg"])


def test_many_patterns_are_joined(prep, answer, monkeypatch):
    sent = [sorted(map(repr, constraints.candidate_lists(prep.tx, answer.patterns).collect())), sorted(map(repr, constraints.offer(prep.tx, answer.patterns).collect()))]
    for f in (constraints.covered, constraints.offer):
        monkeypatch.setattr(f, "__defaults__", (2,))
    assert sent == [sorted(map(repr, constraints.candidate_lists(prep.tx, answer.patterns).collect())), sorted(map(repr, constraints.offer(prep.tx, answer.patterns).collect()))]


def test_many_symbols_by_a_dictionary(prep, spark, monkeypatch):
    rows = tables.document_features(spark, "/root/testdata/sf0.01")
    key = lambda df: sorted(map(repr, df.collect()))
    mapped = key(encode.encode(rows, prep.book, F.col("cls") == "0", ("doc_id",)))
    monkeypatch.setattr(encode, "MAPPED", 1)
    assert key(encode.encode(rows, prep.book, F.col("cls") == "0", ("doc_id",))) == mapped


def test_floor_before_pairs(prep):
    """The walk from the widest interval down leaves what a filter of all intervals leaves."""
    tx = constraints.offer(prep.tx, workloads._rules(prep))
    head = lattice.header(tx.select(F.lit("").alias("node"), F.lit(0).alias("first"), "codes", "n_pos", "n_neg", "best"))
    admits = lattice.above_floor(FSCORE, prep.p, prep.n)
    for merge, closed in ((True, True), (False, False)):
        walked = lattice.items(head, prep.is_symbol(), prep.size_column(), merge, closed, admits=admits)
        every = lattice.items(head, prep.is_symbol(), prep.size_column(), merge, closed)
        kept = sorted(map(repr, every.where(admits(F.col("n_pos"), F.col("least"))).collect()))
        assert kept == sorted(map(repr, walked.collect())) and 0 < len(kept) < every.count()


def test_formats(spark, tmp_path, answer):
    made = answer.patterns.withColumn("cls", F.lit("0"))
    formats.write_patterns(made, str(tmp_path / "p"))
    assert formats.read(spark, "parquet", str(tmp_path / "p")).count() == made.count()
    formats.write_rules(made, str(tmp_path / "r"))
    assert formats.read(spark, "json", str(tmp_path / "r")).count() == made.count()
    spark.range(3).write.csv(str(tmp_path / "c"), header=True)
    assert formats.read(spark, "csv", str(tmp_path / "c")).schema["id"].dataType.simpleString() == "int"


def test_schema_is_inferred(spark, tiny):
    schema = infer_schema(spark.read.parquet(f"{tiny}/orders.parquet"), ("o_orderkey",), {"o_totalprice": 100.0})
    assert [(a.name, a.kind, a.delta) for a in schema.attributes][1:3] == [("o_orderstatus", "symbol", 1.0), ("o_totalprice", "number", 100.0)]
    assert schema.reordered("symbols_first").attributes[0].kind == "symbol"
    assert len(schema.limited(1).numbers()) == 1


def test_stream_equals_batch(spark, tmp_path, tiny):
    source = spark.read.parquet(f"{tiny}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    source.select("event_id", "ts", "user_id", "event_type", "value", "props").repartition(3).write.parquet(str(tmp_path / "in"))
    schema = HybridSchema((number("value", 10.0), number("k")))
    stream = histograms.event_rows(histograms.distinct_events(histograms.read_events(spark, str(tmp_path / "in")), "3650 days"))
    query = histograms.window_histogram(stream, schema, histograms.tumbling()).writeStream.format("memory").queryName("hist").outputMode("complete").start()
    query.processAllAvailable()
    query.stop()
    batch = histograms.window_histogram(histograms.event_rows(source), schema, histograms.tumbling())
    assert sorted(map(tuple, spark.table("hist").collect())) == sorted(map(tuple, batch.collect()))


def test_sequential_cover_goes_on_to_the_last_positive(spark):
    left = [r["positives_left"] for r in workloads.QUERIES["sequential_cover"](spark, "/root/testdata/sf0.01").orderBy("place").collect()]
    assert len(left) > 6 and left[0] == 58 and left[-1] == 1
    assert all(a > b for a, b in zip(left, left[1:]))


@pytest.mark.parametrize("way", [{}, {"rounds": 3}, {"measure": CHI2}], ids=["to the end", "three rounds", "chi2"])
def test_rounds_in_a_task_are_those_of_single_searches(prep, monkeypatch, way):
    """All rounds in one task, which needs no search, give what a search for each round gives."""
    row = lambda df: [(r["place"], r["pattern_id"], round(r["score"], 9), r["positives_left"]) for r in df.orderBy("place").collect()]
    small = search.Prepared(prep.book, prep.tx.where("n_pos = 0 or codes[0] % 3 = 0"), prep.p, prep.n)
    with monkeypatch.context() as m:
        m.setattr(search, "mine_topk", None)
        at_once = row(rules.sequential_cover(small, strategy="depth", **way))
    monkeypatch.setattr(search, "SENT_ROWS", 0)
    assert at_once and at_once == row(rules.sequential_cover(small, strategy="depth", **way))


def test_contrast_of_ways_needs_no_search_for_each_rule(spark, tiny, monkeypatch):
    monkeypatch.setattr(search, "mine_topk", None)
    got = {r["way"]: r for r in workloads.QUERIES["covering_contrast"](spark, tiny).collect()}
    assert set(got) == {"separate and conquer", "all rows at once"}
    assert got["separate and conquer"]["lowest"] <= got["all rows at once"]["lowest"]
    assert got["separate and conquer"]["best"] == got["all rows at once"]["best"]


def test_contrast_of_ways_over_too_many_patterns_needs_no_search_by_node(spark, tiny, monkeypatch):
    few = sorted(map(tuple, workloads.QUERIES["covering_contrast"](spark, tiny).collect()))
    for module in (workloads, search):
        monkeypatch.setattr(module, "DENSE", 0)
    monkeypatch.setattr(search, "_in_memory", None)
    assert sorted(map(tuple, workloads.QUERIES["covering_contrast"](spark, tiny).collect())) == few


def test_measures_are_judged_by_counts_of_documents(spark, tiny, tmp_path):
    assert {r["measure"]: r["dual_monotone"] for r in workloads.QUERIES["measures_monotone"](spark, tiny).collect()} == dict.fromkeys(MEASURES, True)
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        workloads.QUERIES["measures_monotone"](spark, str(tmp_path))


def test_independent_patterns_are_counted_from_documents(spark, tiny):
    p = workloads._prepared(spark, tiny).p
    rows = workloads.QUERIES["zero_at_independence"](spark, tiny).collect()
    assert {r["n_pos"] for r in rows} == {k * p for k in range(1, 10)}
    assert all(r["score"] == 0 for r in rows if r["measure"] != "fscore") and all(r["score"] > 0 for r in rows if r["measure"] == "fscore")


@pytest.mark.parametrize("measure", [FSCORE, CHI2], ids=lambda m: m.name)
def test_pairs_are_counted_as_searched(spark, tiny, monkeypatch, measure):
    """Counts of two codes give each row the best that a search gives it, of patterns of up to two items; rows without a code too."""
    rows = tables.order_features(spark, tiny).withColumn("month", F.when(F.col("o_orderkey") % 5 > 0, F.col("month")))
    orders = search.prepare(rows, HybridSchema((number("month"), symbol("o_orderpriority"), number("c_acctbal", 2000.0))), F.col("cls") == "F")
    counted, stats = search.search(orders, measure, search.Options(length=2))
    monkeypatch.setattr(search, "PAIRED", 0)
    searched, other = search.search(orders, measure, search.Options(length=2), "depth")
    best = lambda found: sorted((r["tx_id"], round(r["best"], 12)) for r in constraints.offer(orders.tx, found).where("n_pos > 0").collect())
    assert best(counted) == best(searched) and len(best(counted)) > 100
    assert stats.first()["complete"] and stats.first()["pruned_floor"] == 0 < other.first()["pruned_floor"]
    held = {r["tx_id"]: r["best"] for r in constraints.offer(orders.tx, counted).collect()}
    own = counted.select("items", "score").distinct().withColumn("pattern_id", F.monotonically_increasing_id())
    met = constraints.covered(orders.tx.where("n_pos > 0").select("tx_id", "codes"), settled(own, "own"))
    assert all(any(abs(held[t] - r["score"]) < 1e-12 for t in r["rows"]) for r in met.groupBy("pattern_id", "score").agg(F.collect_set("tx_id").alias("rows")).collect())


@pytest.mark.parametrize("measure", [FSCORE, CHI2], ids=lambda m: m.name)
def test_branch_and_bound_finds_what_a_search_finds(prep, monkeypatch, measure):
    searched = ids(search.mine_covering(prep, measure, strategy="depth").patterns)
    monkeypatch.setattr(search, "DENSE", 0)
    monkeypatch.setattr(search, "_in_memory", None)
    assert ids(search.mine_covering(prep, measure).patterns) == searched


def test_covering_over_eight_attributes_needs_no_search_by_node(spark, monkeypatch):
    monkeypatch.setattr(search, "_in_memory", None)
    got = workloads.QUERIES["mine_covering_doc"](spark, "/root/testdata/sf0.01").collect()
    assert got and round(max(r["score"] for r in got), 4) == 0.8163


def test_top_of_all_patterns_by_branch_and_bound(prep, spark, tiny, monkeypatch):
    searched = ids(search.mine_topk(prep, 20, strategy="depth").patterns)
    monkeypatch.setattr(search, "DENSE", 0)
    monkeypatch.setattr(search, "_in_memory", None)
    assert ids(search.mine_topk(prep, 20).patterns) == searched
    assert workloads.QUERIES["mine_topk_doc"](spark, tiny).count() == 20


def test_covering_of_good_documents_needs_no_search_by_node(spark, tiny, monkeypatch):
    monkeypatch.setattr(search, "_in_memory", None)
    got = workloads.QUERIES["mine_covering_good"](spark, tiny).collect()
    assert got and all(0 < r["score"] <= 1 for r in got)


def test_closures_are_found_once_and_by_all_tasks(prep, answer, monkeypatch):
    """An answer is read from closures and scores that are there already; rows meet patterns in all tasks."""
    dealt, covered = [], constraints.covered
    monkeypatch.setattr(constraints, "covered", lambda tx, *more: dealt.append(tx.rdd.getNumPartitions()) or covered(tx, *more))
    again = search.mine_covering(prep).patterns
    assert ids(again) == ids(answer.patterns) and dealt and min(dealt) >= 4
    assert "Generate" not in again._jdf.queryExecution().executedPlan().toString()


def test_texts_of_documents_are_read_once_and_not_moved(spark, tiny):
    """What searches read again and again has shapes of texts, no texts, and meets no labels any more."""
    plan = tables.document_features(spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "text" not in plan and "doc_id" in plan


def test_statistics_of_the_flagship_come_from_few_visits(spark):
    got = workloads.QUERIES["mine_stats_doc"](spark, "/root/testdata/sf0.01").first()
    assert got["complete"] and got["share"] == 1.0 and 0 < got["visited"] < 600
