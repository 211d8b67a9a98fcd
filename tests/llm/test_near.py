"""The pipeline's near-copy stage against a brute-force Jaccard join."""

import random

import corpus_pipeline
import numpy as np
import pytest
from pyspark.sql import functions as F

from sieveset.llm import common, similar, simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def shingles(text, words=5):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[i : i + words]) for i in range(len(w) - words + 1)) if len(w) > words else frozenset([tuple(w)] if w else [])


def leads(rows):
    """Row numbers of the first rows of the components of all pairs of similarity 0.8 or more."""
    sets, root = [shingles(r[1]) for r in rows], list(range(len(rows)))
    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if (a == b or 5 * len(a & b) >= 4 * len(a | b)) and root[i] != root[j]:
                root = [root[j] if x == root[i] else x for x in root]
    return {min((rows[i][0], i) for i in range(len(rows)) if root[i] == r)[1] for r in set(root)}


def near_corpus():
    """Copies with 1 to 6 words changed in 100 to 200, some in chains, and one group of 40."""
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    common, texts = [word() for _ in range(30)], []
    for k in range(50):
        t = [word() for _ in range(rng.randint(100, 200))] + (common if k % 3 == 0 else [])
        texts.append(t)
        for _ in range(40 if k == 7 else 3):
            c = list(rng.choice([t, texts[-1]]))
            for at in rng.sample(range(len(c)), rng.randint(1, 6)):
                c[at] = word()
            texts.append(c)
    rng.shuffle(texts)
    return [(i, " ".join(t), "en", "s", 0) for i, t in enumerate(texts)]


def chains(rows):
    """Numbers of rows left by ``leads`` and the (id, text) of each."""
    return {(rows[i][0], rows[i][1]) for i in leads(rows)}


@pytest.mark.parametrize("codes", [None, ((15, 15), 174)])
def test_near_stage_against_brute_force(spark, rows, monkeypatch, codes):
    """Both sizes of parts. What is linked is right; of links that exist at most 2% may be missed."""
    if codes:
        monkeypatch.setattr(similar, "plan", lambda *_: codes)
    for given in (near_corpus(), sorted({r for r in rows if r[0] not in (901, None)}, key=lambda r: r[0])):
        want = chains(given)
        got = corpus_pipeline.near_stage(spark, spark.createDataFrame(given, SCHEMA).repartition(3), "")
        left = {(r["doc_id"], r["text"]) for r in got.collect()}
        assert want <= left and len(left) - len(want) <= 0.02 * (len(given) - len(want))
        assert got.columns == SCHEMA.replace(" long", "").replace(" string", "").split(", ")


def test_hot_anchors_are_cut_into_cells(spark, monkeypatch):
    """With every key counted as hot the links are the same."""
    given = near_corpus()
    docs = spark.createDataFrame(given, SCHEMA)
    monkeypatch.setattr(common, "CELL_ROWS", 4)
    monkeypatch.setattr(common, "SAMPLED", 1)
    monkeypatch.setattr(similar, "SET_ROWS", 4)
    monkeypatch.setattr(similar, "BROADCAST_ROWS", 0)
    assert {(r["doc_id"], r["text"]) for r in corpus_pipeline.near_stage(spark, docs, "").collect()} >= chains(given)
    cut = {(r["doc_id"], r["component_id"]) for r in simhash.near_copies(docs).collect()}
    monkeypatch.setattr(common, "CELL_ROWS", 1 << 30)
    assert {(r["doc_id"], r["component_id"]) for r in simhash.near_copies(docs).collect()} == cut


def test_recall_of_links_at_the_limit():
    """Pairs of similarity 0.8 to 0.82 share an anchor, and pass the two bit limits, at the planned rate."""
    rng = np.random.default_rng(4)
    codes, parts = similar.plan(10_000)
    made = similar.Anchors(codes, parts)
    found = 0
    for _ in range(300):
        whole = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
        a, b = (similar.wide_print(np.sort(x)) for x in (whole[:360], whole[40:]))  # 320 of 400
        meet = (made.of(a[None]) == made.of(b[None])).any()
        bits = np.bitwise_count(a ^ b).astype(int)
        found += meet and bits[: similar.CARRIED].sum() <= similar.NEAR_BITS and bits.sum() <= similar.wide_limit(np.int64(360))
    assert found >= 0.95 * 300


def test_near_stage_of_null_ids_and_no_rows(spark, nothing):
    text = " ".join(f"w{i}" for i in range(60))
    given = [(None, text, "en", "s", 1), (None, text + " more", "en", "s", 1), (7, text + " and", "en", "s", 1), (None, "another text", None, None, None), (None, None, None, None, None), (8, "", "en", "s", 0)]
    left = corpus_pipeline.near_stage(spark, spark.createDataFrame(given, SCHEMA).withColumn("sid", F.lit("x")), "").collect()
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in left) == [(0, "another text"), (7, text + " and"), (8, "")]
    assert corpus_pipeline.near_stage(spark, nothing, "").count() == 0
