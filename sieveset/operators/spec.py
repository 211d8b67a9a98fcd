"""What a filter is to be: its kind, widths, sizes and seeds."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, replace

from sieveset.functions.hashing import derived_seed

KINDS = ("xor", "xor_plus", "xor_compact", "bloom", "blocked_bloom", "cuckoo", "cuckoo_pow2", "cuckoo_semisort", "cuckoo_semisort_pow2", "gcs", "cqf", "morton", "exact")
#: Roles of derived seeds.
SHARD, CELL0, CELL1, CELL2, PRINT, PLACE, ALTERNATE = range(7)


class ConstructionFailed(Exception):
    """No seed worked within the allowed attempts."""


class LoadExceeded(ConstructionFailed):
    """A cuckoo-like table had no room for a key."""


class SchemaMismatch(Exception):
    """A frame is not a filter set."""


@dataclass(frozen=True)
class FilterSpec:
    kind: str = "xor"
    fp_bits: int = 8
    bits_per_key: float | None = None
    num_hashes: int | None = None
    slack_hundredths: int = 123
    extra: int = 32
    load: float = 0.94
    seed: int = 42
    shard_keys: int = 1_000_000
    max_attempts: int = 64
    hash_mode: str = "identity"
    rank: str = "two_level"
    bucket: int = 16
    max_kicks: int = 500
    #: Keys of a cuckoo table that random evictions leave over are placed by search, which fails only when nothing fits.
    search: bool = True
    sized_for: int | None = None

    def __post_init__(self):
        if self.kind not in KINDS:
            raise ValueError(f"unknown kind {self.kind!r}; one of {', '.join(KINDS)}")
        if not 1 <= self.fp_bits <= 32:
            raise ValueError("fp_bits must lie in 1..32")

    @property
    def hashes(self) -> int:
        """Of a Bloom filter: as many as give the fewest false positives for its size."""
        return self.num_hashes or max(1, round((self.bits_per_key or 8) * math.log(2)))

    @classmethod
    def from_fpp(cls, fpp: float, kind: str = "bloom", **more) -> FilterSpec:
        """The smallest filter of a kind whose false-positive probability is at most ``fpp``."""
        bits = -math.log2(fpp)
        if kind == "bloom":
            return cls(kind, bits_per_key=bits / math.log(2), num_hashes=max(1, math.ceil(bits)), **more)
        return cls(kind, fp_bits=math.ceil(bits + (3 if kind.startswith("cuckoo") else 0)), **more)

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @classmethod
    def from_json(cls, text: str) -> FilterSpec:
        return cls(**json.loads(text))

    def with_seed(self, seed: int) -> FilterSpec:
        return replace(self, seed=seed)


def capacity(n: int, slack_hundredths: int = 123, extra: int = 32) -> int:
    """Cells for n keys; whole numbers only, as floats would err for some n."""
    return slack_hundredths * n // 100 + extra


def segments(cells: int) -> tuple[int, int]:
    """First cells of the second and the third part; parts differ by one cell at most."""
    return cells // 3, 2 * cells // 3


def attempt_seed(seed: int, shard: int, attempt: int) -> int:
    """A function of shard and attempt alone, so a task that runs again builds the same filter."""
    return derived_seed(derived_seed(seed, 1000 + attempt), 2000 + shard)


def role_seed(seed: int, role: int) -> int:
    return derived_seed(seed, role)


def bloom_bits(n: int, spec: FilterSpec) -> int:
    """With ``sized_for`` the room is that of so many keys, so filters of different sets have one shape and can merge."""
    n = n if spec.sized_for is None else spec.sized_for
    return max(1, int((spec.bits_per_key or 8) * n))


def blocked_blocks(n: int, spec: FilterSpec) -> int:
    """Blocks of 256 bits; tenths of bits keep the arithmetic whole."""
    tenths = round(10 * (spec.bits_per_key or 10.7))
    return max(1, -(-tenths * n // 2560))


def cuckoo_buckets(n: int, spec: FilterSpec) -> int:
    """Buckets of four slots."""
    hundredths = round(100 * spec.load)
    buckets = max(1, -(-100 * n // (4 * hundredths)))
    return 1 << (buckets - 1).bit_length() if spec.kind.endswith("pow2") else buckets


def quotient_bits(n: int) -> int:
    return max(1, math.ceil(math.log2(max(2, n / 0.95))))
