"""Exact copies, near copies and repeated passages against brute force."""

import hashlib
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from sieveset.llm import components, exact_dedup, repeats, simhash
from sieveset.llm.lyndon import suffix_array

# --- exact ---


def test_copies_against_brute_force(docs, rows, nothing):
    norm = lambda t: (t or "").encode().lower()
    groups = defaultdict(list)
    for r in rows:
        groups[norm(r[1])].append(r[0])
    last = lambda ids: max(ids, key=lambda x: (x is not None, x or 0))
    want = Counter((r[0], last(groups[norm(r[1])]), len(groups[norm(r[1])]), hashlib.sha256(norm(r[1])).hexdigest()) for r in rows)
    got = exact_dedup.find_copies(docs.withColumn("keep_id", F.lit("x")).withColumn("uid", F.lit(1))).collect()
    assert Counter((r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in got) == want
    kept = Counter(r["text_sha256"] for r in got if r["kept"])
    assert set(kept.values()) == {1} and len(kept) == len(groups)
    assert all(r["doc_id"] == r["keep_id"] for r in got if r["kept"])
    assert exact_dedup.find_copies(nothing).count() == 0


def test_dropping_copies_keeps_columns(docs, rows, nothing):
    out = exact_dedup.drop_copies(docs)
    assert out.columns == docs.columns
    assert out.count() == len({(r[1] or "").encode().lower() for r in rows})
    assert exact_dedup.drop_copies(nothing).count() == 0


def test_many_ids_go_by_a_shuffle(docs, monkeypatch):
    plain = [sorted(map(str, f(docs).collect())) for f in (exact_dedup.drop_copies, simhash.drop_near_copies)]
    monkeypatch.setattr(exact_dedup, "BROADCAST_IDS", 0)
    monkeypatch.setattr(simhash, "BROADCAST_IDS", 0)
    assert [sorted(map(str, f(docs).collect())) for f in (exact_dedup.drop_copies, simhash.drop_near_copies)] == plain


def test_fingerprints_compose():
    poly, rng = exact_dedup.Polynomial(64), random.Random(1)
    for n in (0, 1, 63, 64, 65, 1000):
        data = bytes(rng.randrange(256) for _ in range(n))
        want = tuple(sum((c + 1) * pow(b, n - 1 - i, p) for i, c in enumerate(data)) % p for p, b in zip(exact_dedup.PRIMES, exact_dedup.BASES, strict=True))
        assert poly.of(data) == want
        for cut in {0, n // 3, n}:
            assert poly.combine(poly.of(data[:cut]), poly.of(data[cut:]), n - cut) == want


def test_texts_that_share_a_fingerprint_are_told_apart(docs, rows, monkeypatch):
    monkeypatch.setattr(exact_dedup, "KEY", ["n_bytes"])  # every two texts of one length collide
    got = exact_dedup.find_copies(docs).collect()
    assert sum(r["kept"] for r in got) == len({(r[1] or "").encode().lower() for r in rows})


# --- near copies ---


def brute_fingerprint(text, words=3):
    w = (text or "").encode().lower().split()
    if not w:
        return 0
    shingles = [b" ".join(w[i : i + words]) for i in range(len(w) - words + 1)] or [b" ".join(w)]
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_near_copies_against_brute_force(docs, rows, nothing):
    fps = [brute_fingerprint(r[1]) for r in rows]
    least = list(range(len(rows)))
    changed = True
    ids = [r[0] for r in rows]
    label = [(x is None, x) for x in ids]  # null ids come last
    while changed:
        changed = False
        for i in least:
            for j in least:
                if (fps[i] ^ fps[j]).bit_count() <= 3 and label[j] != label[i] and (label[i][0] or not label[j][0] and label[j][1] < label[i][1]):
                    label[i] = label[j]
                    changed = True
    label = [x for _, x in label]
    got = simhash.near_copies(docs).collect()
    assert Counter((r["doc_id"], r["fp"] % (1 << 64), r["component_id"]) for r in got) == Counter(zip(ids, fps, label, strict=True))
    assert simhash.near_copies(nothing).count() == 0
    kept = simhash.drop_near_copies(docs, words=3)
    assert kept.columns == docs.columns
    root = list(range(len(rows)))
    for _ in rows:  # components by row, as one id may bear two texts
        root = [min(root[j] for j in least if (fps[i] ^ fps[j]).bit_count() <= 3) for i in least]
    assert kept.count() == len(set(root))


def test_anchors_cover():
    rng = np.random.default_rng(2)
    words = rng.integers(0, 1 << 32, 300, dtype=np.uint64).astype(np.uint32)
    home, row, far = simhash.anchors(words)
    assert (np.bitwise_count(home ^ words) <= 1).all()
    assert (np.bitwise_count(far ^ words[row]) <= 2).all()
    assert not simhash._syndrome(home & np.uint32((1 << 31) - 1)).any()
    for bit in range(32):  # whoever differs in one bit is among the others of this home
        other = words ^ np.uint32(1 << bit)
        h2, r2, f2 = simhash.anchors(other)
        near = {(int(i), int(a)) for i, a in zip(r2, f2, strict=True)} | {(i, int(a)) for i, a in enumerate(h2)}
        assert all((i, int(a)) in near for i, a in enumerate(home))


def test_planted_links_are_found(spark):
    rng = random.Random(3)
    base = [rng.getrandbits(64) for _ in range(300)]
    fps = base + [b ^ sum(1 << x for x in rng.sample(range(64), rng.randint(1, 3))) for b in base]
    sign = lambda x: x - (1 << 64) if x >> 63 else x
    found = simhash.links(spark.createDataFrame([(sign(f),) for f in set(fps)], "fp long"))
    roots = {r["node"]: r["root"] for r in components.components(found).collect()}
    assert all(roots[sign(a)] == roots[sign(b)] for a, b in zip(base, fps[300:], strict=True))


def test_components_of_a_long_chain(spark):
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1001), (1001, 1000), (7, 7)]
    random.Random(1).shuffle(edges)
    got = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {i: 0 for i in range(201)} | {1000: 1000, 1001: 1000}
    assert components.components(spark.createDataFrame([], "u long, v long")).count() == 0


@pytest.mark.parametrize("part_edges", [1 << 19, 100])
def test_links_repeated_over_many_anchors_go_before_the_rounds(spark, monkeypatch, part_edges):
    """A group of 400 with links to eight of its members each, a chain and a pair: one link a node, and a few a part, are left for joins."""
    joined, rounds = [], components.components
    monkeypatch.setattr(components, "components", lambda edges: joined.append(edges.count()) or rounds(edges))
    monkeypatch.setattr(components, "PART_EDGES", part_edges)
    edges = [(u, v) for u in range(8, 400) for v in range(8)] + [(i, i + 1) for i in range(1000, 1030)] + [(-5, 5000), (7, 7)]
    random.Random(1).shuffle(edges)
    got = {r["node"]: r["root"] for r in components.forest_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == dict.fromkeys(range(400), 0) | dict.fromkeys(range(1000, 1031), 1000) | {-5: -5, 5000: -5}
    assert joined == [] if part_edges > len(edges) else 430 <= joined[0] < 600
    assert components.forest_components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_forest_keeps_components():
    rng = np.random.default_rng(1)
    x = rng.integers(0, 1 << 10, 60, dtype=np.uint64)
    x = np.unique(x)
    links = simhash.forest(x, x[:0])
    assert len(links) < len(x) and all((a ^ b).bit_count() <= 3 for a, b in links)


# --- repeated passages ---


def brute_repeats(texts):
    data = [(t or "").encode() for t in texts]
    seen = Counter(d[i : i + 200] for d in data for i in range(len(d) - 199))
    out = []
    for d in data:
        gone = np.zeros(len(d), bool)
        for i in range(len(d) - 199):
            if seen[d[i : i + 200]] > 1:
                gone[i : i + 200] = True
        out.append((len(d), int(gone.sum()), int((np.diff(np.r_[False, gone].astype(int)) == 1).sum()), hashlib.sha256(bytes(np.frombuffer(d, np.uint8)[~gone])).hexdigest()))
    return out


@pytest.mark.parametrize("hot", [None, 1])
def test_repeats_against_brute_force(docs, rows, nothing, monkeypatch, hot):
    if hot:
        monkeypatch.setattr(repeats, "HOT_SPANS", hot)  # the way by window
    texts = [r[1] if r[1] is None or len(r[1]) < 20_000 else r[1][:20_000] for r in rows]
    short = docs.withColumn("text", F.substring("text", 1, 20_000)).withColumn("spans", F.lit(1)).withColumn("tag", F.lit("x"))
    got = Counter(tuple(r) for r in repeats.remove_repeats(short).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect())
    assert got == Counter((r[0], *b) for r, b in zip(rows, brute_repeats(texts), strict=True))
    if not hot:
        assert repeats.remove_repeats(nothing).count() == 0


def test_suffix_array_against_sorting():
    rng = random.Random(6)
    for _ in range(3000):
        x = [rng.randint(1, rng.choice([1, 2, 3, 9])) for _ in range(rng.randint(0, 30))]
        assert suffix_array(x) == sorted(range(len(x)), key=lambda i: x[i:])


def test_windows_of_spans():
    rng = random.Random(8)
    passage = bytes(rng.randrange(97, 123) for _ in range(260))
    spans = [b"left" * 20 + passage, passage[:230] + b"right" * 20, b"a" * 450, bytes(rng.randrange(97, 123) for _ in range(400))]
    flags = repeats.recurring_windows(spans, repeats.Hasher())
    seen = Counter(s[i : i + 200] for s in spans for i in range(len(s) - 199))
    for s, f in zip(spans, flags, strict=True):
        assert f.tolist() == [seen[s[i : i + 200]] > 1 for i in range(len(s) - 199)]
