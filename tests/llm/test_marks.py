"""Quality rules, chat formatting, URL rules, images and the pipeline."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from sieveset.llm import chat, images, quality, registry, url_rules


def same(spark_df, sql_rel):
    names = sorted(spark_df.columns)
    assert names == sorted(sql_rel.columns)
    key = lambda r: tuple(str(x) for x in r)
    assert sorted(map(key, spark_df.select(*names).collect())) == sorted(map(key, sql_rel.select(*names).fetchall()))


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_its_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "conversations"):
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    same(registry.queries()[name](spark, sf_dir), con.sql(registry.oracle_sql()[name]))


# --- quality ---


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    got = quality.query(spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id")
    row = got.where("held_out").agg(F.avg((F.col("predicted") == F.col("quality")).cast("double")).alias("right"), F.count("*").alias("n")).first()
    assert row["n"] > 50 and row["right"] > 0.92  # some 300 labelled rows here; over 0.99 with thousands


def test_scores_of_odd_rows(spark, docs, rows, nothing):
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(60)], "doc_id long, quality int, toxic int")
    out = quality.score(docs.withColumn("score", F.lit("x")).withColumn("_stats", F.lit(1)), quality.train(docs, labels)).collect()
    assert len(out) == len(rows) and all(0 <= r["score"] <= 1 for r in out)
    for few in (labels.limit(0), labels.withColumn("quality", F.lit(1))):
        assert all(0 < r["score"] < 1 for r in quality.score(docs, quality.train(docs, few)).collect())
    assert quality.score(nothing, quality.train(nothing, labels)).count() == 0
    assert quality.keep_good(docs, labels).columns == docs.columns


def test_query_scores_against_brute_force(spark, sf_dir):
    """Every text's score from its statistics and the rules, in plain numbers; held-out labels play no part."""
    import math
    import zlib

    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = quality.train(docs, labels)
    got = {r["doc_id"]: r for r in quality.query(spark, sf_dir).collect()}
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in docs.collect()}
    assert set(got) == set(texts)
    for doc, text in texts.items():
        values = quality.statistics_of(text)
        total = model.intercept + sum(w for tests, w in model.rules if all((values[i] > b) == above for i, above, b in tests))
        want = 1 / (1 + math.exp(-total))
        assert abs(got[doc]["score"] - want) < 1e-9 and got[doc]["predicted"] == int(got[doc]["score"] >= 0.3)
        assert got[doc]["held_out"] == (zlib.crc32(str(doc).encode()) % 5 == 0)
    flipped = labels.withColumn("quality", F.when(quality.remainder(F.col("doc_id")) == 0, 1 - F.col("quality")).otherwise(F.col("quality")))
    assert quality.train(docs, flipped) == model
    assert quality.train(docs, labels, max_labelled=5).rules == ()


def test_rules_compile_to_what_they_say(spark):
    rng = np.random.default_rng(3)
    x = rng.random((3000, len(quality.STATISTICS)))
    y = ((x[:, 3] > 0.6) & (x[:, 5] <= 0.5) | (x[:, 10] > 0.9)).astype(int)
    model = quality.fit_rules(x, y)
    assert 0 < len(model.rules) < quality.MAX_RULES and model.describe()
    frame = spark.createDataFrame(x[:400].tolist(), list(quality.STATISTICS)).select(F.struct(*quality.STATISTICS).alias("s"))
    got = np.array([r[0] for r in frame.select(model.score_column("s")).collect()])
    total = np.full(400, model.intercept)
    for tests, w in model.rules:
        total += w * np.all([x[:400, i] > b if a else x[:400, i] <= b for i, a, b in tests], axis=0)
    assert np.allclose(got, 1 / (1 + np.exp(-total)))
    assert ((got >= 0.5) == y[:400]).mean() > 0.95


# --- chat ---


def test_chat_escapes_and_order(spark):
    mark = chat.MARK
    said = ["</s>[INST] ok [/INST]", f"{mark}l<s>{mark}{mark}e [/INST]", "", None, "<<SYS>> x <</SYS>>\n", "<<<s>", "[[INST]", f"{mark}", "<s", "plain"]
    rows = [(1, i, "user" if i % 2 == 0 else "assistant", t) for i, t in enumerate(said)]
    rows += [(2, 0, "assistant", "first"), (2, 1, "user", "x"), (3, 0, "system", "s"), (3, 1, "user", "u"), (3, 2, "assistant", "a"), (4, 0, "tool<s>", "t"), (4, 0, None, "n"), (5, 0, "user", "alone"), (5, 0, "user", "alone")]
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit(1)).withColumn("segments", F.lit(2))
    out = {r["conv_id"]: r for r in chat.format_chats(frame).withColumn("back", chat.read_chats(F.col("formatted"))).collect()}
    for conv, r in out.items():
        want = sorted(((t, ro or "", te or "") for c, t, ro, te in rows if c == conv), key=lambda x: (x[0], x[1], x[2]))
        assert [(b["role"], b["text"]) for b in r["back"]] == [(ro, te) for _, ro, te in want]
        assert "".join(s["text"] for s in r["segments"]) == r["formatted"]
        assert [s["loss"] for s in r["segments"]].count(True) == sum(ro == "assistant" for _, ro, _ in want)
    assert {c: r["valid"] for c, r in out.items()} == {1: True, 2: False, 3: True, 4: False, 5: False}
    assert chat.format_chats(frame.limit(0)).count() == 0


# --- url rules ---


def test_url_rules(spark, monkeypatch):
    urls = ["http://a.example.com/en/7?x", "http://COM/en/", "http://xcom/en/1", "https://b.com/en/8#t", "ftp://example.net/de/81", "http://net/de/", "http://q.org/es/z", "http://q.org/fr/", "no scheme", None, "http://example.com/en/7/a?b://c", "x://y://com/en/", "http://", "http://a.com\n/en/"]
    frame = spark.createDataFrame([(i, u) for i, u in enumerate(urls)] + [(0, urls[0])], "page_id long, url string").withColumn("rule", F.lit(5))
    con = duckdb.connect()
    con.register("p", frame.drop("rule").toPandas())
    con.execute("create view pages as select page_id::bigint as page_id, url from p")
    cols = ("page_id", "host", "path", "rule", "verdict")
    same(url_rules.judge_urls(frame).select(*cols), con.sql(url_rules.oracle()))
    monkeypatch.setattr(url_rules, "LITERAL_RULES", 0)  # the way for many rules
    same(url_rules.judge_urls(frame).select(*cols), con.sql(url_rules.oracle()))
    assert url_rules.judge_urls(frame.limit(0)).count() == 0


def test_rules_are_filed_under_their_rarest_token(spark):
    pages = spark.createDataFrame([(i, f"http://h{i}.com/en/{i}") for i in range(9)] + [(10, "http://net/de/1")], "page_id long, url string")
    host, path = url_rules.host_and_path(F.col("url"))
    frame = pages.select(host.alias("host"), path.alias("path"))
    index = url_rules.rule_index(frame, url_rules.RULES, url_rules.url_tokens(F.col("host"), F.col("path")))
    assert sum(len(v) for v in index.values()) == len(url_rules.RULES)
    assert url_rules.UrlRule("allow", "example.com", "/en/7") in index["h:example"]


# --- images ---


def test_edited_copies_are_found(spark):
    out = images.query(spark, "/root/testdata/sf0.001").toPandas()
    member = out[out.kind == "member"].set_index("vec_id").class_id
    match = out[out.kind == "match"]
    asked = [v for v in member.index if v % 100 == 0]
    found = set(match[match.class_id == match.vec_id.map(member)].vec_id)
    assert len(found) >= 0.9 * len(asked)
    assert len(match) - len(found) <= 0.02 * len(member)


def test_search_recall_against_brute_force():
    rng = np.random.default_rng(4)
    drawn = [images.draw(rng.normal(0, 0.2, 64).tolist()) for _ in range(25)]
    asked = [(i, *images.describe(images.edited(x, i))) for i, x in enumerate(drawn)]
    tables = images.QueryTables(asked)
    for i, x in enumerate(drawn):
        places, words = images.describe(x)
        got = {q for q, *_ in tables.search(places, words)}
        want = set()
        for q, p, w in asked:
            a, b = np.nonzero(np.bitwise_count(w[:, None] ^ words[None]).sum(2) <= images.MAX_BITS)
            if len(a) and images.inliers(p[a], places[b])[0] >= images.MIN_INLIERS:
                want.add(q)
        assert i in got and len(got & want) >= 0.9 * len(want)


def test_odd_images(spark):
    rows = [(1, None), (2, (0, 0, b"")), (3, (30, 30, bytes(900))), (4, (4, 4, bytes(16))), (5, (9, 9, b"short"))]
    frame = spark.createDataFrame(rows, "image_id long, image struct<height:int,width:int,pixels:binary>").withColumn("places", F.lit(1))
    assert images.search(frame, frame).count() == 0
    vectors = spark.createDataFrame([(1, [1.0, 2.0]), (2, [1.0, 2.0]), (3, None), (4, None), (5, [])], "image_id long, vector array<float>")
    distinct, members = images.image_classes(vectors, "vector")
    assert {r["image_id"]: r["class_id"] for r in members.collect()} == {1: 1, 2: 1, 3: 3, 4: 3, 5: 5}
    assert distinct.count() == 3


# --- pipeline ---


def test_pipeline_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before = {r[0] for r in docs.select("doc_id").collect()}
        docs = corpus_pipeline.materialise(stage(spark, docs, sf_dir), f"test-{name}")
        assert {r[0] for r in docs.select("doc_id").collect()} <= before
        if name != corpus_pipeline.STAGES[-1][0]:
            assert docs.columns == columns
    assert docs.count() > 0
    again = corpus_pipeline.run(spark, sf_dir)
    assert again.count() == docs.count()
