"""Filters as NumPy arrays: how each kind is built from distinct 64-bit keys and asked.

``build(keys, spec, shard)`` gives a Built; ``contains(built, spec, keys)`` a boolean array. No Spark here.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from itertools import combinations_with_replacement

import numpy as np

from sieveset.functions.hashing import high32, low32, mix64, mix64_np, reduce_range_np
from sieveset.operators.spec import (
    ALTERNATE,
    CELL0,
    CELL1,
    CELL2,
    PLACE,
    PRINT,
    ConstructionFailed,
    FilterSpec,
    LoadExceeded,
    attempt_seed,
    blocked_blocks,
    bloom_bits,
    capacity,
    cuckoo_buckets,
    quotient_bits,
    role_seed,
    segments,
)

from .peel import assign, peel_priority, peel_rounds
from .rank import RANKS, to_words

SLOTS = 4
#: One odd multiplier for each word of a block. Any odd numbers without a pattern would do.
BLOCK_MULTIPLIERS = tuple(mix64(i, 77) >> 32 | 1 for i in range(8))


@dataclass
class Built:
    n_keys: int
    capacity: int
    bits_total: int
    seed: int
    attempts: int = 1
    seg1: int = 0
    seg2: int = 0
    num_hashes: int = 0
    cells: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    aux: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    empty: int = 0
    empty_last: int = 0
    #: What probes derive from the arrays once and keep with them: a worker asks one filter batch after batch.
    ready: dict = field(default_factory=dict, repr=False, compare=False)

    def once(self, name: str, make):
        if name not in self.ready:
            self.ready[name] = make()
        return self.ready[name]

    def __getstate__(self):
        return self.__dict__ | {"ready": {}}


def fingerprints(keys: np.ndarray, seed: int, bits: int) -> np.ndarray:
    return (mix64_np(keys, role_seed(seed, PRINT)) & np.uint64((1 << bits) - 1)).astype(np.int64)


def three_cells(keys: np.ndarray, seed: int | np.ndarray, cells: int) -> np.ndarray:
    """``keys`` may be sets in rows, with a column of seeds."""
    seg1, seg2 = segments(cells)
    bounds = ((CELL0, 0, seg1), (CELL1, seg1, seg2), (CELL2, seg2, cells))
    return np.stack([lo + reduce_range_np(high32(mix64_np(keys, role_seed(seed, r))), hi - lo) for r, lo, hi in bounds])


def _cell_type(bits: int):
    return np.int8 if bits <= 8 else np.int16 if bits <= 16 else np.int32


def narrow(values: np.ndarray, bits: int) -> np.ndarray:
    """The low bits as the narrowest signed type that holds them; probes mask them again."""
    kind = _cell_type(bits)
    return values.astype(np.int64).astype({np.int8: np.uint8, np.int16: np.uint16, np.int32: np.uint32}[kind]).view(kind)


def _peeled(keys: np.ndarray, spec: FilterSpec, shard: int, first_attempt: int = 0):
    cells = capacity(len(keys), spec.slack_hundredths, spec.extra)
    for attempt in range(first_attempt, spec.max_attempts):
        seed = attempt_seed(spec.seed, shard, attempt)
        where = three_cells(keys, seed, cells)
        peeled = peel_priority(where, cells, segments(cells)[1]) if spec.kind == "xor_plus" else peel_rounds(where, cells)
        if peeled is not None:
            return cells, seed, attempt + 1, where, peeled
    raise ConstructionFailed(f"{len(keys)} keys: no seed of {spec.max_attempts} gave an order; are keys distinct?")


def build_xor(keys: np.ndarray, spec: FilterSpec, shard: int = 0, values: np.ndarray | None = None) -> Built:
    """``values`` makes it a static map: a key's cells give its value instead of its fingerprint."""
    cells, seed, attempts, where, peeled = _peeled(keys, spec, shard)
    wanted = fingerprints(keys, seed, spec.fp_bits) if values is None else values.astype(np.int64)
    table = assign(where, wanted, peeled, cells)
    seg1, seg2 = segments(cells)
    if spec.kind == "xor_compact":
        return compacted(build_xor(keys, replace(spec, kind="xor"), shard, values), spec)
    occupied = np.zeros(cells, bool)
    occupied[peeled[1]] = True
    out = Built(len(keys), cells, spec.fp_bits * cells, seed, attempts, seg1, seg2, 3, narrow(table, spec.fp_bits), empty=int((~occupied).sum()), empty_last=int((~occupied[seg2:]).sum()))
    out.aux = to_words(occupied).view(np.int64)
    if spec.kind == "xor_plus":
        rank = RANKS[spec.rank](to_words(occupied[seg2:]))
        out.cells = np.r_[out.cells[:seg2], out.cells[seg2:][occupied[seg2:]]]
        out.aux = np.r_[rank.words.view(np.int64), rank.numbers()]
        out.bits_total = spec.fp_bits * len(out.cells) + (cells - seg2) + rank.bits
    return out


def _xor_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    return xor_values(b, spec, keys) == fingerprints(keys, b.seed, spec.fp_bits)


def compacted(b: Built, spec: FilterSpec) -> Built:
    """Of a plain xor filter: occupied cells only, found by rank over the whole table. ``spec`` is of the kind xor_compact."""
    bits = np.unpackbits(b.aux.view(np.uint8), count=b.capacity, bitorder="little").astype(bool)
    rank = RANKS[spec.rank](to_words(bits))
    total = spec.fp_bits * b.n_keys + b.capacity + rank.bits
    return Built(b.n_keys, b.capacity, total, b.seed, b.attempts, b.seg1, b.seg2, 3, b.cells[bits], np.r_[rank.words.view(np.int64), rank.numbers()], b.empty, b.empty_last)


def _ranked_cells(b: Built, spec: FilterSpec, at: np.ndarray, size: int, first: int) -> np.ndarray:
    """Cells of a part of ``size`` places whose occupied ones lie from ``first`` on; empty ones read as 0."""

    def ready():
        n_words = -(-max(1, size) // 2048) * 32
        return RANKS[spec.rank].of(b.aux[:n_words].view(np.uint64), b.aux[n_words:])

    rank = b.once("rank", ready)
    there = (rank.words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1
    place = np.where(there, first + rank.rank(at), 0)
    return np.where(there, b.cells[np.minimum(place, max(0, len(b.cells) - 1))].astype(np.int64), 0)


def xor_values(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    where = three_cells(keys, b.seed, b.capacity)
    mask = (1 << spec.fp_bits) - 1
    if spec.kind == "xor_compact":
        parts = [_ranked_cells(b, spec, row, b.capacity, 0) for row in where]
        return (parts[0] ^ parts[1] ^ parts[2]) & mask
    out = b.cells[where[0]].astype(np.int64) ^ b.cells[where[1]].astype(np.int64)
    if spec.kind == "xor_plus":
        out = out ^ _ranked_cells(b, spec, where[2] - b.seg2, b.capacity - b.seg2, b.seg2)
    else:
        out = out ^ b.cells[where[2]].astype(np.int64)
    return out & mask


def bloom_positions(keys: np.ndarray, seed: int, bits: int, hashes: int) -> np.ndarray:
    h = mix64_np(keys, role_seed(seed, PLACE))
    first, second = high32(h), low32(h)
    return np.stack([reduce_range_np(low32(first + np.uint64(i) * second), bits) for i in range(hashes)])


def build_bloom(keys: np.ndarray, spec: FilterSpec, shard: int = 0) -> Built:
    seed, m = attempt_seed(spec.seed, shard, 0), bloom_bits(len(keys), spec)
    flags = np.zeros(-(-m // 64) * 64, bool)
    h = mix64_np(keys, role_seed(seed, PLACE))
    first, second = high32(h), low32(h)
    for i in range(spec.hashes):
        flags[reduce_range_np(low32(first + np.uint64(i) * second), m)] = True
    return Built(len(keys), m, m, seed, num_hashes=spec.hashes, aux=np.packbits(flags, bitorder="little").view(np.int64))


def _bloom_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    """Keys that meet an unset bit leave; later hashes run on those that are left."""
    words, alive = b.aux.view(np.uint64), np.arange(len(keys))
    h = mix64_np(keys, role_seed(b.seed, PLACE))
    first, second = high32(h), low32(h)
    for i in range(b.num_hashes):
        at = reduce_range_np(low32(first[alive] + np.uint64(i) * second[alive]), b.capacity)
        alive = alive[(words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1]
    out = np.zeros(len(keys), bool)
    out[alive] = True
    return out


def block_bits(keys: np.ndarray, seed: int, blocks: int) -> tuple[np.ndarray, np.ndarray]:
    """Block of each key and the bit in each of its eight words."""
    h = mix64_np(keys, role_seed(seed, PLACE))
    low = low32(h)
    bits = np.stack([low32(low * np.uint64(m)) >> np.uint64(27) for m in BLOCK_MULTIPLIERS]).astype(np.int64)
    return reduce_range_np(high32(h), blocks), bits


def build_blocked(keys: np.ndarray, spec: FilterSpec, shard: int = 0) -> Built:
    seed, blocks = attempt_seed(spec.seed, shard, 0), blocked_blocks(len(keys), spec)
    flags = np.zeros(256 * blocks, bool)
    block, bits = block_bits(keys, seed, blocks)
    for j in range(8):
        flags[block * 256 + 32 * j + bits[j]] = True
    words = np.packbits(flags, bitorder="little").view(np.uint32)
    return Built(len(keys), blocks, 256 * blocks, seed, num_hashes=8, aux=words.astype(np.int64))


def _blocked_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    block, bits = block_bits(keys, b.seed, b.capacity)
    words = b.once("words", lambda: b.aux.astype(np.uint32))
    out = np.ones(len(keys), np.uint32)
    for j in range(8):
        out &= words[block * 8 + j] >> bits[j].astype(np.uint32)
    return (out & 1).astype(bool)


def cuckoo_places(keys: np.ndarray, seed: int, buckets: int, spec: FilterSpec) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Fingerprint (never 0) and the two buckets of each key."""
    f = np.maximum(fingerprints(keys, seed, spec.fp_bits), 1)
    first = reduce_range_np(high32(mix64_np(keys, role_seed(seed, PLACE))), buckets)
    return f, first, alternate_bucket(first, f, seed, buckets, spec.kind.endswith("pow2"))


def alternate_bucket(bucket: np.ndarray, f: np.ndarray, seed: int, buckets: int, pow2: bool) -> np.ndarray:
    """The other bucket; applied twice it gives the first again. By exclusive-or for powers of two, else by subtraction modulo the count."""
    h = reduce_range_np(high32(mix64_np(np.asarray(f, np.int64), role_seed(seed, ALTERNATE))), buckets)
    return bucket ^ h if pow2 else (buckets - bucket - h) % buckets


def build_cuckoo(keys: np.ndarray, spec: FilterSpec, shard: int = 0) -> Built:
    buckets = cuckoo_buckets(len(keys), spec)
    for attempt in range(spec.max_attempts):
        seed = attempt_seed(spec.seed, shard, attempt)
        slots = _fill_cuckoo(keys, seed, buckets, spec)
        if slots is not None:
            break
    else:
        raise LoadExceeded(f"{len(keys)} keys do not fit {buckets} buckets after {spec.max_attempts} seeds")
    semisorted = "semisort" in spec.kind
    if semisorted:
        slots = np.sort(slots.reshape(-1, SLOTS), axis=1)
    bits = (spec.fp_bits - semisorted) * SLOTS * buckets
    out = Built(len(keys), buckets, bits, seed, attempt + 1, num_hashes=2)
    if semisorted:
        out.aux = semisort_pack(slots, spec.fp_bits)
    else:
        out.cells = narrow(slots.ravel(), max(spec.fp_bits, 9))
    return out


def _fill_cuckoo(keys: np.ndarray, seed: int, buckets: int, spec: FilterSpec) -> np.ndarray | None:
    """Slots by bucket; a key that finds both buckets full turns another out, which goes to its other bucket.

    What ``max_kicks`` rounds leave over, as in large tables near the highest load, is placed by search.
    """
    pow2 = spec.kind.endswith("pow2")
    f, l1, l2 = cuckoo_places(keys, seed, buckets, spec)
    held, fill, left = np.zeros((buckets, SLOTS), np.int64), np.zeros(buckets, np.int64), np.arange(len(keys))
    for choice in (l1, l2):  # keys that find room in their first, then in their second bucket are placed at once
        order = left[np.argsort(choice[left], kind="stable")]
        bucket = choice[order]
        start = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]) if len(order) else np.zeros(0, np.int64)
        nth = np.arange(len(order)) - np.repeat(start, np.diff(np.r_[start, len(order)])) + fill[bucket]
        fits = nth < SLOTS
        held[bucket[fits], nth[fits]] = f[order[fits]]
        fill += np.bincount(bucket[fits], minlength=buckets)
        left = order[~fits]
    other = alternate_bucket(np.zeros(1 << spec.fp_bits, np.int64), np.arange(1 << spec.fp_bits), seed, buckets, pow2) if spec.fp_bits <= 16 else None
    rng = np.random.default_rng(seed & 0xFFFFFFFF)
    x, at = f[left], l2[left]
    for _ in range(spec.max_kicks):  # in each round one key a bucket takes a free slot, or turns another out, which goes to its other bucket
        if not len(x):
            return held
        bucket, own = np.unique(at, return_index=True)
        room = fill[bucket] < SLOTS
        held[bucket[room], fill[bucket[room]]] = x[own[room]]
        fill[bucket[room]] += 1
        full, own_full = bucket[~room], own[~room]
        slot = rng.integers(0, SLOTS, len(full))
        out = held[full, slot]
        held[full, slot] = x[own_full]
        if other is None:
            to = alternate_bucket(full, out, seed, buckets, pow2)
        else:
            to = full ^ other[out] if pow2 else (other[out] - full) % buckets
        rest = np.ones(len(x), bool)
        rest[own] = False
        x, at = np.r_[x[rest], out], np.r_[at[rest], to]
    if len(x) and not (spec.search and _place_by_search(held, fill, x, at, seed, pow2)):
        return None
    return held


def _place_by_search(held: np.ndarray, fill: np.ndarray, x: np.ndarray, at: np.ndarray, seed: int, pow2: bool) -> bool:
    """Places fingerprints ``x``, each by a shortest chain of moves to a free slot. False when one has none: then no placement of all keys exists."""
    buckets, seen = len(held), np.zeros(len(held), bool)
    for f, b in zip(x.tolist(), at.tolist(), strict=True):
        start = np.unique(np.r_[b, alternate_bucket(np.array([b]), np.array([f]), seed, buckets, pow2)])
        levels = [(start, start, start)]  # buckets, where in the level before they were reached from, and from which slot
        seen[start] = True
        while not (free := fill[levels[-1][0]] < SLOTS).any():
            to = alternate_bucket(levels[-1][0][:, None], held[levels[-1][0]], seed, buckets, pow2).ravel()
            new, edge = np.unique(to, return_index=True)
            new, edge = new[~seen[new]], edge[~seen[new]]
            if not len(new):
                return False
            seen[new] = True
            levels.append((new, edge // SLOTS, edge % SLOTS))
        i = int(np.argmax(free))
        to = levels[-1][0][i]
        slot, fill[to] = fill[to], fill[to] + 1
        for (own, parent, turned), (before, _, _) in zip(levels[:0:-1], levels[-2::-1], strict=True):
            j, k = parent[i], turned[i]
            held[own[i], slot] = held[before[j], k]
            i, slot = j, k
        held[levels[0][0][i], slot] = f
        for own, _, _ in levels:
            seen[own] = False
    return True


def insert_cuckoo(b: Built, spec: FilterSpec, key: int) -> tuple[Built, str]:
    """Adds one key where a slot is free: (filter, "added" or "full")."""
    f, l1, l2 = (int(x[0]) for x in cuckoo_places(np.array([key], np.int64), b.seed, b.capacity, spec))
    slots = b.cells.copy().reshape(-1, SLOTS)
    for bucket in (l1, l2):
        free = np.flatnonzero(slots[bucket] == 0)
        if len(free):
            slots[bucket, free[0]] = narrow(np.array([f]), max(spec.fp_bits, 9))[0]
            return Built(b.n_keys + 1, b.capacity, b.bits_total, b.seed, b.attempts, num_hashes=2, cells=slots.ravel()), "added"
    return b, "full"


def semisort_codes() -> dict[tuple[int, ...], int]:
    """Numbers of the rising quadruples of 4-bit values; there are few enough for 12 bits."""
    return {c: i for i, c in enumerate(combinations_with_replacement(range(16), SLOTS))}


def semisort_pack(slots: np.ndarray, fp_bits: int) -> np.ndarray:
    """Per bucket a code for the sorted high 4 bits, then the low bits of each slot; 16 low bits at most fit one number."""
    low_bits = fp_bits - 4
    codes = np.zeros((16,) * SLOTS, np.int64)
    for quadruple, code in semisort_codes().items():
        codes[quadruple] = code
    out = codes[tuple((slots >> low_bits).T)]
    for j in range(SLOTS):
        out |= (slots[:, j] & ((1 << low_bits) - 1)) << (12 + low_bits * j)
    return out


def semisort_unpack(packed: np.ndarray, fp_bits: int) -> np.ndarray:
    low_bits = fp_bits - 4
    table = np.array(list(semisort_codes()), np.int64)
    high = table[packed & 0xFFF]
    low = np.stack([(packed >> (12 + low_bits * j)) & ((1 << low_bits) - 1) for j in range(SLOTS)], -1)
    return (high << low_bits) | low


_LANES, _TOPS = np.uint64(0x0001000100010001), np.uint64(0x8000800080008000)


def _lanes(b: Built, spec: FilterSpec) -> np.ndarray:
    """Each bucket as one number with four 16-bit lanes."""
    slots = semisort_unpack(b.aux, spec.fp_bits) if "semisort" in spec.kind else b.cells.astype(np.int64) & ((1 << spec.fp_bits) - 1)
    return np.ascontiguousarray(slots.reshape(-1, SLOTS).astype("<u2")).view("<u8").ravel()


def _cuckoo_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    f, l1, l2 = cuckoo_places(keys, b.seed, b.capacity, spec)
    if spec.fp_bits <= 16:
        lanes, wanted = b.once("lanes", lambda: _lanes(b, spec)), f.astype(np.uint64) * _LANES
        out = np.zeros(len(keys), bool)
        for at in (l1, l2):  # a lane that is zero after the exclusive-or holds the fingerprint
            x = lanes[at] ^ wanted
            out |= ((x - _LANES) & ~x & _TOPS) != 0
        return out
    slots = b.cells.reshape(-1, SLOTS)
    read = lambda at: slots[at].astype(np.int64) & ((1 << spec.fp_bits) - 1)
    return (read(l1) == f[:, None]).any(1) | (read(l2) == f[:, None]).any(1)


def gcs_values(keys: np.ndarray, seed: int, n: int, bits: int) -> np.ndarray:
    """Hashes below n times 2**bits, which must fit 32 bits."""
    return reduce_range_np(high32(mix64_np(keys, role_seed(seed, PLACE))), n << bits)


def build_gcs(keys: np.ndarray, spec: FilterSpec, shard: int = 0) -> Built:
    """Sorted hashes as differences: a unary quotient and ``fp_bits`` low bits, with an index entry for each stretch that holds ``bucket`` keys on average."""
    n, k = len(keys), spec.fp_bits
    if n << k >= 1 << 32:
        raise ValueError("a shard's hashes must fit 32 bits; use more shards")
    seed = attempt_seed(spec.seed, shard, 0)
    values = np.sort(gcs_values(keys, seed, n, k))
    span = spec.bucket << k
    stretch = values // span
    base = np.r_[True, stretch[1:] != stretch[:-1]] if n else np.zeros(0, bool)
    delta = np.where(base, values - stretch * span, np.diff(values, prepend=0))
    quotient = delta >> k
    # quotient ones, a zero, then the low bits
    length = quotient + 1 + k
    start = np.cumsum(length) - length
    total = int(length.sum())
    bits = np.zeros(total + 64, np.uint8)
    ones = np.repeat(start, quotient) + (np.arange(int(quotient.sum())) - np.repeat(np.cumsum(quotient) - quotient, quotient))
    bits[ones] = 1
    for j in range(k):
        bits[start + quotient + 1 + j] = (delta >> (k - 1 - j)) & 1
    n_stretch = -(-n // spec.bucket) if n else 0
    index = np.r_[np.searchsorted(stretch, np.arange(n_stretch)), n].astype(np.int64)
    entry = np.r_[start, total][index] if n else np.zeros(1, np.int64)
    words = to_words(bits)
    return Built(n, n << k, total + n_stretch * spec.bucket // 2, seed, num_hashes=1, aux=np.r_[len(words), words.view(np.int64), index, entry])


def gcs_decode(b: Built, spec: FilterSpec) -> np.ndarray:
    """The sorted hashes again."""
    n_words = int(b.aux[0]) if len(b.aux) else 0
    if not b.n_keys:
        return np.zeros(0, np.int64)
    bits = np.unpackbits(b.aux[1 : 1 + n_words].view(np.uint8), bitorder="little")
    n_stretch = -(-b.n_keys // spec.bucket)
    index = b.aux[1 + n_words : 2 + n_words + n_stretch]
    entry = b.aux[2 + n_words + n_stretch :]
    out = np.zeros(b.n_keys, np.int64)
    zeros = np.flatnonzero(bits == 0)
    starts, at = entry[:-1].copy(), index[:-1].copy()
    value = np.arange(n_stretch) * (spec.bucket << spec.fp_bits)
    powers = 1 << np.arange(spec.fp_bits - 1, -1, -1)
    live = np.flatnonzero(at < index[1:])
    while len(live):  # all stretches step together
        s = starts[live]
        stop = zeros[np.searchsorted(zeros, s)]
        low = (bits[stop[:, None] + 1 + np.arange(spec.fp_bits)] * powers).sum(1)
        value[live] += ((stop - s) << spec.fp_bits) + low
        out[at[live]] = value[live]
        starts[live] = stop + 1 + spec.fp_bits
        at[live] += 1
        live = live[at[live] < index[1:][live]]
    return out


def _gcs_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    """The stretch of a key is walked in the decoded sequence, about one value long; decoding is done once for a filter."""

    def ready():
        values = gcs_decode(b, spec)
        return values.astype(np.uint32), np.searchsorted(values, np.arange(b.n_keys + 1) << spec.fp_bits).astype(np.int32)

    values, first = b.once("decoded", ready)
    asked = gcs_values(keys, b.seed, b.n_keys, spec.fp_bits)
    slot = asked >> spec.fp_bits
    at, end = first[slot], first[slot + 1]
    out, live = np.zeros(len(keys), bool), np.flatnonzero(at < end)
    asked, at, end = asked[live].astype(np.uint32), at[live], end[live]
    while len(live):
        hit = values[at] == asked
        out[live[hit]] = True
        on = ~hit & (at + 1 < end)
        live, asked, at, end = live[on], asked[on], at[on] + 1, end[on]
    return out


def quotient_remainder(keys: np.ndarray, seed: int, q: int, r: int) -> np.ndarray:
    """The leading q + r bits of the hash."""
    return (mix64_np(keys, role_seed(seed, PLACE)) >> np.uint64(64 - q - r)).astype(np.int64)


def build_cqf(keys: np.ndarray, spec: FilterSpec, shard: int = 0, counts: np.ndarray | None = None) -> Built:
    """Remainders in rising order, each as near to its quotient's slot as those before it let it; two bits a slot mark quotients in use and ends of runs."""
    n, r = len(keys), spec.fp_bits
    q = quotient_bits(n)
    seed = attempt_seed(spec.seed, shard, 0)
    values, back = np.unique(quotient_remainder(keys, seed, q, r), return_inverse=True)
    times = np.bincount(back, weights=np.ones(n) if counts is None else counts).astype(np.int64)
    quotient = values >> r
    slot = np.maximum.accumulate(quotient - np.arange(len(values))) + np.arange(len(values)) if len(values) else values
    slots = (1 << q) + (int(slot[-1]) + 1 - (1 << q) if len(slot) and slot[-1] >= 1 << q else 0)
    remainder, occupied, ends = np.zeros(slots, np.int64), np.zeros(slots, bool), np.zeros(slots, bool)
    count = np.zeros(slots, np.int64)
    remainder[slot], count[slot] = values & ((1 << r) - 1), times
    occupied[quotient] = True
    ends[slot[np.r_[quotient[1:] != quotient[:-1], True]] if len(values) else slot] = True
    words = to_words(occupied), to_words(ends)
    bits = (1 << q) * (r * 1000 + 2125) // 1000
    return Built(n, 1 << q, bits, seed, seg1=slots, num_hashes=1, cells=narrow(remainder, max(r, 9)), aux=np.r_[len(words[0]), words[0].view(np.int64), words[1].view(np.int64), count])


def _cqf_find(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    """Slot of each key's remainder in its quotient's run, or -1."""
    r, n_words = spec.fp_bits, int(b.aux[0])

    def ready():
        unpack = lambda w: np.unpackbits(w.view(np.uint8), bitorder="little").astype(bool)
        occupied, ends = unpack(b.aux[1 : 1 + n_words]), unpack(b.aux[1 + n_words : 1 + 2 * n_words])
        used, end = np.flatnonzero(occupied), np.flatnonzero(ends)
        begin_of, end_of = np.zeros(max(b.capacity, len(occupied)), np.int32), np.full(max(b.capacity, len(occupied)), -1, np.int32)
        # a run begins after the run before it, and not before its quotient
        begin_of[used], end_of[used] = np.maximum(np.r_[0, end[:-1] + 1][: len(used)], used), end[: len(used)]
        return begin_of, end_of

    begin_of, end_of = b.once("runs", ready)
    value = quotient_remainder(keys, b.seed, b.capacity.bit_length() - 1, r)
    quotient, wanted = value >> r, value & ((1 << r) - 1)
    out = np.full(len(keys), -1, np.int64)
    live = np.flatnonzero(end_of[quotient] >= 0)
    at, begin = end_of[quotient[live]], begin_of[quotient[live]]
    while len(live):
        hit = (b.cells[at].astype(np.int64) & ((1 << r) - 1)) == wanted[live]
        out[live[hit]] = at[hit]
        on = ~hit & (at > begin)
        live, at, begin = live[on], at[on] - 1, begin[on]
    return out


def _cqf_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    return _cqf_find(b, spec, keys) >= 0


def cqf_counts(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    """How often each key was added, at least."""
    at = _cqf_find(b, spec, keys)
    counts = b.aux[1 + 2 * int(b.aux[0]) :]
    return np.where(at >= 0, counts[np.maximum(at, 0)], 0)


#: A block of 512 bits: 64 buckets with 2-bit counts, 46 slots of 8 bits, 16 overflow bits. Fixed values.
MORTON = {"buckets": 64, "slots": 46, "overflow": 16, "most": 3}


def _morton_places(keys: np.ndarray, seed: int, blocks: int, fp_bits: int):
    n = blocks * MORTON["buckets"]
    f = fingerprints(keys, seed, fp_bits)
    first = reduce_range_np(high32(mix64_np(keys, role_seed(seed, PLACE))), n)
    return f, first, alternate_bucket(first, f, seed, n, False)


def build_morton(keys: np.ndarray, spec: FilterSpec, shard: int = 0) -> Built:
    """Buckets share the slots of their block. A key that its first bucket refuses sets an overflow bit there and goes to its second."""
    blocks = max(1, -(-len(keys) * 100 // (95 * MORTON["slots"])))
    for attempt in range(spec.max_attempts):
        seed = attempt_seed(spec.seed, shard, attempt)
        built = _fill_morton(keys, seed, blocks, spec)
        if built is not None:
            break
        blocks += max(1, blocks // 100)
    else:
        raise LoadExceeded(f"{len(keys)} keys do not fit {blocks} blocks")
    stored, overflow = built
    counts = np.array([len(b) for b in stored], np.int64)
    start = np.cumsum(counts.reshape(blocks, -1), 1) - counts.reshape(blocks, -1)
    slots = np.zeros((blocks, MORTON["slots"]), np.int64)
    for i, bucket in enumerate(stored):
        for j, x in enumerate(bucket):
            slots[i // MORTON["buckets"], start[i // MORTON["buckets"], i % MORTON["buckets"]] + j] = x
    return Built(len(keys), blocks, 512 * blocks, seed, attempt + 1, num_hashes=2, cells=narrow(slots.ravel(), spec.fp_bits), aux=np.r_[counts, overflow.ravel().astype(np.int64)])


def _fill_morton(keys: np.ndarray, seed: int, blocks: int, spec: FilterSpec):
    per, most, room, marks = MORTON["buckets"], MORTON["most"], MORTON["slots"], MORTON["overflow"]
    n = blocks * per
    f, l1, l2 = (x.tolist() for x in _morton_places(keys, seed, blocks, spec.fp_bits))
    other = alternate_bucket(np.zeros(1 << spec.fp_bits, np.int64), np.arange(1 << spec.fp_bits), seed, n, False).tolist()
    stored: list[list[int]] = [[] for _ in range(n)]
    used = [0] * blocks
    overflow = np.zeros((blocks, marks), bool)
    fits = lambda b: len(stored[b]) < most and used[b // per] < room
    state = seed & 0xFFFFFFFF | 1
    for x, a, b in zip(f, l1, l2, strict=True):
        at = a
        if not fits(a):
            overflow[a // per, a % marks] = True
            at = b
        for _ in range(spec.max_kicks):
            if fits(at):
                stored[at].append(x)
                used[at // per] += 1
                break
            # turn one out: of this bucket, or of any bucket of a full block; it goes to its other place
            state = (state * 1664525 + 1013904223) & 0xFFFFFFFF
            full = at
            if len(stored[at]) < most:
                base = at // per * per
                full = base + (state >> 8) % per
                while not stored[full]:
                    full = base + (full + 1 - base) % per
            slot = (state >> 24) % len(stored[full])
            y = stored[full].pop(slot)
            used[full // per] -= 1
            stored[at].append(x)
            used[at // per] += 1
            overflow[full // per, full % marks] = True
            x, at = y, (other[y] - full) % n
        else:
            return None
    return stored, overflow


def _morton_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    per, marks = MORTON["buckets"], MORTON["overflow"]
    f, l1, l2 = _morton_places(keys, b.seed, b.capacity, spec.fp_bits)

    def ready():
        counts = b.aux[: b.capacity * per].reshape(-1, per)
        return counts, b.aux[b.capacity * per :].reshape(-1, marks), b.cells.reshape(b.capacity, -1).astype(np.int64) & ((1 << spec.fp_bits) - 1), np.cumsum(counts, 1) - counts

    counts, overflow, slots, start = b.once("blocks", ready)

    def held(bucket: np.ndarray) -> np.ndarray:
        block, own = bucket // per, bucket % per
        out = np.zeros(len(bucket), bool)
        for j in range(MORTON["most"]):
            at = np.minimum(start[block, own] + j, MORTON["slots"] - 1)
            out |= (j < counts[block, own]) & (slots[block, at] == f)
        return out

    return held(l1) | (overflow[l1 // per, l1 % marks] == 1) & held(l2) | (overflow[l2 // per, l2 % marks] == 1) & held(l2)


def build_exact(keys: np.ndarray, spec: FilterSpec, shard: int = 0) -> Built:
    return Built(len(keys), len(keys), 64 * len(keys), attempt_seed(spec.seed, shard, 0), aux=np.sort(keys.view(np.int64)))


def _exact_contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    at = np.searchsorted(b.aux, keys)
    return (at < len(b.aux)) & (b.aux[np.minimum(at, len(b.aux) - 1)] == keys)


_KINDS = {
    "xor": (build_xor, _xor_contains),
    "xor_plus": (build_xor, _xor_contains),
    "xor_compact": (build_xor, _xor_contains),
    "bloom": (build_bloom, _bloom_contains),
    "blocked_bloom": (build_blocked, _blocked_contains),
    "cuckoo": (build_cuckoo, _cuckoo_contains),
    "cuckoo_pow2": (build_cuckoo, _cuckoo_contains),
    "cuckoo_semisort": (build_cuckoo, _cuckoo_contains),
    "cuckoo_semisort_pow2": (build_cuckoo, _cuckoo_contains),
    "gcs": (build_gcs, _gcs_contains),
    "cqf": (build_cqf, _cqf_contains),
    "morton": (build_morton, _morton_contains),
    "exact": (build_exact, _exact_contains),
}


def build(keys: np.ndarray, spec: FilterSpec, shard: int = 0) -> Built:
    """``keys``: distinct int64."""
    return _KINDS[spec.kind][0](np.ascontiguousarray(keys, np.int64), spec, shard)


def contains(b: Built, spec: FilterSpec, keys: np.ndarray) -> np.ndarray:
    if not b.n_keys:
        return np.zeros(len(keys), bool)
    return _KINDS[spec.kind][1](b, spec, np.ascontiguousarray(keys, np.int64)).astype(bool)
