"""The pipeline's stages on planted cases and odd rows, and the operator queries against their SQL."""

import math
import random

import duckdb
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from softdep.llm import queries, sql

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.mark.parametrize("name", sorted(sql.ORACLES))
def test_query_matches_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "labels", "pages", "conversations", "benchmark"):
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = queries.QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    norm = lambda v: (None if math.isnan(v) else round(v, 6) + 0.0) if isinstance(v, float) else v
    rows = lambda names, data: sorted(repr([norm(dict(zip(names, r, strict=True))[c]) for c in columns]) for r in data)
    want = con.sql(sql.ORACLES[name])
    assert sorted(want.columns) == columns
    assert rows(df.columns, df.collect()) == rows(list(want.columns), want.fetchall())


def test_stages_are_the_asked_ones():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "quality_rules", "ngram_jaccard_join", "benchmark_decontamination", "mixing"]


def test_each_stage_on_what_the_one_before_kept(spark, sf, tmp_path):
    """Planted: an exact and a near copy, a leak, a toxic and a junk document, and clean ones that must stay."""
    rng = random.Random(1)
    real = spark.read.parquet(f"{sf}/documents.parquet")
    clean = real.join(spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1 and toxic = 0"), "doc_id", "left_semi").where("n_chars between 1500 and 4000 and lang = 'en'").orderBy("doc_id").limit(3).collect()
    item = spark.read.parquet(f"{sf}/benchmark.parquet").orderBy("item_id").first()["text"]
    junk = " ".join(f"{w}%%% ###" for w in clean[0]["text"].split())
    near = clean[1]["text"].split()
    near[len(near) // 2] = "changed"
    planted = [
        (900001, clean[1]["text"]),
        (900002, " ".join(near)),
        (900003, clean[2]["text"][:900] + " " + item + " " + " ".join(rng.choice(clean[2]["text"].split()) for _ in range(80))),
        (900004, "idiot moron clown " + " ".join(rng.choice(clean[0]["text"].split()) for _ in range(150)) + " worthless scum loser"),
        (900005, junk),
        (900006, None),
        (900007, ""),
    ]
    extra = spark.createDataFrame([(i, t, "en", "src1", len(t or "")) for i, t in planted], real.schema)
    docs = real.unionByName(extra).unionByName(real.where(F.col("doc_id") == clean[0]["doc_id"]))
    seen = [{r["doc_id"] for r in docs.select("doc_id").collect()}]
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf)
        assert out.columns == COLUMNS or k == 4
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        seen.append({r["doc_id"] for r in docs.select("doc_id").collect()})
    tox, qual, near_, leak, mix = (a - b for a, b in zip(seen, seen[1:], strict=False))
    assert 900004 in tox and not tox & {900001, 900002, 900003, 900006}
    assert {900006, 900007} <= qual and not qual & {900001, 900002, 900003}
    assert {900001, 900002} <= near_ and clean[1]["doc_id"] in seen[3] and clean[0]["doc_id"] in seen[3]
    assert 900003 in leak and {c["doc_id"] for c in clean} <= seen[4]
    last = docs.groupBy("doc_id").agg(F.max("copies").alias("k"), F.count("*").alias("n")).where("k != n")
    assert last.isEmpty() and mix <= seen[4]


def test_stages_on_empty_and_odd_tables(spark, sf):
    odd = spark.createDataFrame([(1, None, None, None, None, "x"), (2, "", "en", "a", 0, "y"), (2, "", "en", "a", 0, "y"), (3, "w " * 30_000, "zz9", None, 1, "z"), (4, "a b", "en", "b", 3, None)], "doc_id long, text string, lang string, source string, n_chars long, kept string")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, odd, sf)
        assert set(out.columns) >= set(odd.columns) and out.count() >= 0, name
        assert stage(spark, odd.limit(0), sf).count() == 0, name


def test_rows_without_ids_survive_the_join_stage(spark, sf):
    t = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu"
    rows = [(None, t, "en", "a", 1), (1, t, "en", "a", 1), (2, t, "en", "a", 1), (None, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = corpus_pipeline.jaccard_stage(spark, docs, sf).collect()
    assert sorted(r["doc_id"] or 0 for r in got) == [0, 0, 1]


def test_the_join_stage_keeps_unlike_texts_of_one_id(spark, sf):
    t = " ".join(f"w{k}" for k in range(40))
    rows = [(1, t), (1, "no link with the other text of this id"), (2, t), (1, t), (3, "no link with the other text of this id"), (4, "")]
    docs = spark.createDataFrame([(k, x, "en", "a", 1) for k, x in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = sorted((r["doc_id"], r["text"]) for r in corpus_pipeline.jaccard_stage(spark, docs, sf).collect())
    assert got == sorted([(1, t), (1, "no link with the other text of this id"), (4, "")])


def test_run_gives_whole_copies(spark, sf):
    out = corpus_pipeline.run(spark, sf).select("doc_id", "copies", "copy").collect()
    assert out and all(1 <= r["copy"] <= r["copies"] for r in out)
