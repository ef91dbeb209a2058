"""The pipeline's stages, one after the other, against what their operators decide."""

import hashlib
import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from contrast.llm import mixing, quality, simhash
from contrast.llm.common import materialise, table


@pytest.fixture(scope="module")
def steps(spark, tiny):
    out = [table(spark, tiny, "documents")]
    for name, stage in corpus_pipeline.STAGES:
        out.append(materialise(stage(spark, out[-1], tiny), name.replace(" ", "_")))
    return out


def test_stages(spark, tiny, steps):
    docs, good, single, clean, mixed, ids = steps
    for df in steps[1:-1]:
        assert df.columns == corpus_pipeline.COLUMNS
    judged = quality.judged(docs, table(spark, tiny, "labels").where("quality = 1"))
    assert sorted(r[0] for r in good.select("doc_id").collect()) == sorted(r[0] for r in judged.where("kept").select("doc_id").collect())
    classes = {}
    for r in simhash.near_duplicates(good, width=5).collect():
        classes.setdefault(r["component_id"], []).append(r["doc_id"])
    assert sorted(r[0] for r in single.select("doc_id").collect()) == sorted(map(min, classes.values()))
    assert clean.count() == single.count()
    assert clean.where("text rlike '[0-9a-f]{16,}'").count() == 0
    plan = {r["doc_id"]: r["c"] for r in mixing.allot(clean).select("doc_id", mixing.copies(F.col("size"), F.col("taken")).alias("c")).collect()}
    assert {r["doc_id"]: r["count"] for r in mixed.groupBy("doc_id").count().collect()} == {k: c for k, c in plan.items() if c}
    text = {r["doc_id"]: r["text"] for r in mixed.collect()}
    assert all(r["decoded_sha256"] == hashlib.sha256(text[r["doc_id"]].encode()).hexdigest() for r in ids.collect())
    assert ids.count() == mixed.count()


def test_run_is_the_stages(spark, tiny, steps):
    key = lambda df: sorted((r["doc_id"], r["ids_sha256"]) for r in df.collect())
    assert key(corpus_pipeline.run(spark, tiny)) == key(steps[-1])


def test_odd_rows(spark, tmp_path):
    long = " ".join(f"word{i}" for i in range(60))
    rows = [(1, long, "en", None, None), (1, long, "en", None, None), (None, long, None, "a", 3), (2, None, None, None, None), (3, "", "en", "a", 0), (4, long + " more", "en", "a", 9)]
    docs = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, lang string, source string, n_chars long, kept string")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    for df in (docs, docs.limit(0)):
        for _, stage in corpus_pipeline.STAGES:
            df = materialise(stage(spark, df, str(tmp_path)), "odd")
        assert df.count() >= 0
    assert corpus_pipeline.near_dedup(spark, docs.where("doc_id = 1 or doc_id is null"), str(tmp_path)).select("doc_id").collect() == [(1,)]


def test_near_dedup_links_all_similar_pairs(spark, tmp_path):
    """Chains of copies at a similarity of 0.8 and more, at distances far beyond four bits."""
    draw = random.Random(7)
    rows = []
    for k in range(30):
        words = [f"w{draw.randrange(10**6)}" for _ in range(200)]
        for step in range(3):
            rows.append((len(rows), " ".join(words), "en", "a", 0))
            words = words[:]
            for at in (20, 90, 160):
                words[at + step * 6] = f"x{draw.randrange(10**6)}"
    rows += [(1000 + i, " ".join(f"z{draw.randrange(10**6)}" for _ in range(200)), "en", "a", 0) for i in range(20)]
    sets = [set(zip(*(r[1].split()[i:] for i in range(5)))) for r in rows]
    far = 0
    root = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                far += (simhash.fingerprint(rows[i][1], 5) ^ simhash.fingerprint(rows[j][1], 5)).bit_count() > 4
                a, b = root[i], root[j]
                root = [min(a, b) if x in (a, b) else x for x in root]
    assert far > 20
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = corpus_pipeline.near_dedup(spark, docs, str(tmp_path)).select("doc_id").collect()
    assert sorted(r[0] for r in got) == sorted({rows[x][0] for x in root})
