"""Matches of descriptors up to the limit."""

import numpy as np

from sieveset.llm import images


def flipped(rng, words, bits):
    """Each word with so many of its 256 bits turned."""
    out = np.unpackbits(words.view(np.uint8).reshape(len(words), -1), axis=1)
    for row in out:
        row[rng.choice(256, bits, replace=False)] ^= 1
    return np.packbits(out, axis=1).view(np.uint64)


def picture(rng, n=24):
    places = np.stack([rng.uniform(10, 80, n), rng.uniform(10, 80, n), np.zeros(n), np.ones(n)], 1)
    return places, rng.integers(0, 1 << 64, (n, 4), dtype=np.uint64)


def test_copies_are_found_up_to_the_limit():
    """With so few bits turned that tables find nearly all, and never beyond the limit."""
    rng = np.random.default_rng(7)
    for bits, found in ((0, True), (12, True), (24, True), (45, False)):
        places, words = picture(rng, 80)
        tables = images.QueryTables([(5, places, words), (6, *picture(rng))])
        got = tables.search(places, flipped(rng, words, bits))
        assert [q for q, *_ in got] == ([5] if found else []), bits


def test_matches_are_those_that_share_a_key():
    rng = np.random.default_rng(8)
    words = rng.integers(0, 1 << 64, (300, 4), dtype=np.uint64)
    asked = np.concatenate([flipped(rng, words[:100], 20), flipped(rng, words[:100], 40)])
    mine, theirs = images.QueryTables([(1, np.zeros((300, 4)) + 1, words)]).near(asked)
    share = (images.table_keys(asked)[:, None] == images.table_keys(words)[None]).any(2)
    near = np.bitwise_count(asked[:, None] ^ words[None]).sum(2) <= images.MAX_BITS
    assert {*zip(mine.tolist(), theirs.tolist(), strict=True)} == {*zip(*map(np.ndarray.tolist, np.nonzero(share & near)), strict=True)}


def test_recall_against_all_pairs():
    """Image by image against comparing all descriptors and trying all images: edited, noisy, smaller and cropped copies."""
    rng = np.random.default_rng(4)
    drawn = [images.draw(rng.normal(0, 0.2, 64).tolist()) for _ in range(40)]
    edits = [lambda x: x[14:86, 9:81], lambda x: np.clip(x * 0.7 + 30, 0, 255).astype(np.uint8), lambda x: np.ascontiguousarray(np.rot90(x)), lambda x: np.rint(images._resized(x.astype(float), 0.7)).astype(np.uint8), lambda x: np.clip(x + rng.normal(0, 6, x.shape), 0, 255).astype(np.uint8), lambda x: x[20:80, 22:82]]
    known = [images.describe(x) for x in drawn]
    got, want, own = set(), set(), 0
    for e, edit in enumerate(edits):
        asked = [(i, *images.describe(edit(x))) for i, x in enumerate(drawn)]
        tables = images.QueryTables(asked)
        for i, (places, words) in enumerate(known):
            got |= {(e, i, q) for q, *_ in tables.search(places, words)}
            for q, p, w in asked:
                a, b = np.nonzero(np.bitwise_count(w[:, None] ^ words[None]).sum(2) <= images.MAX_BITS)
                if len(a) >= images.MIN_INLIERS and images.inliers(p[a], places[b], images.MIN_INLIERS)[0] >= images.MIN_INLIERS:
                    want.add((e, i, q))
    own = {(e, i) for e, i, q in got if i == q}
    assert len(got & want) >= 0.95 * len(want) and len(own) >= 0.93 * len(edits) * len(drawn)
    assert len(got) - len(own) <= 0.002 * len(edits) * len(drawn) ** 2


def test_the_rest_of_the_block_does_not_matter():
    """A copy with 20 bits turned, among other queries of random bits or of nearly equal ones."""
    rng = np.random.default_rng(9)
    places, words = picture(rng, 60)
    asked = np.concatenate([flipped(rng, words, 20), np.zeros((8, 4), np.uint64)])
    at = np.concatenate([places, np.zeros((8, 4)) + [0, 0, 0, 1]])
    flat = [(k, picture(rng)[0], np.zeros((24, 4), np.uint64)) for k in range(20, 60)]
    mixed = [(k, *picture(rng)) for k in range(20, 60)]
    for others in ([], flat, mixed):
        got = images.QueryTables([(5, places, words), *others]).search(at, asked)
        assert [x[0] for x in got if x[0] == 5] == [5]
