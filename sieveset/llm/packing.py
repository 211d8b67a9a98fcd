"""Packing by cutting-stock column generation.

Token counts are cut at the sequence length first; what remains of each document falls into classes of equal length. A linear program
over the histogram of classes finds patterns (how many pieces of each class share a sequence); new patterns are priced by
an unbounded knapsack. Rounded patterns are laid out one after another, and the documents of each class, ranked, take its
places. Sequences of the worst patterns are then taken apart again: their documents are cut to fill what the others have
left, so that all sequences are full but for the last tokens, which go to sequences whose lengths are powers of two.

Only the histogram reaches the driver, with one entry per class. Ranks, sequence numbers and the lines along which documents are
cut come from running sums over slices.

Defined cases: a null text is empty and has the closing token alone; a null doc_id is kept as null; a very long text is cut into
full sequences and one remainder; of repeated rows each is packed; an empty table gives an empty result; further columns are
ignored; a vocabulary with ids over 65,535 is refused.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import BINARY, LONG, fields, materialise, release_memory, table, to_python

LENGTH = 4096
END_ID = 2
#: Tokens of a class: remainders of 1 to 16 tokens are class 1, and so on.
STEP = 16
TOKENIZER = "word_bpe_49k.json"
#: Rows that are ranked together and slices of running sums, on average at most.
SLICE_ROWS = 32_768
#: Documents whose words are looked up together.
SLICE_DOCS = 800
#: Slices after which a worker gives freed memory back.
TRIM_EVERY = 4
#: Words whose ids a worker remembers: the first it meets, among which are the frequent ones.
CACHE_WORDS = 600_000


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordTokenizer:
    """Ids of whole texts, word by word.

    The vocabulary's rules never join characters across white space, nor letters with what follows them, and drop white
    space. So a text's ids are those of its words, one after another, and each distinct word is encoded once. A-Z are
    lower-cased first, as the rules do. Texts that hold the opening of a special token are encoded whole.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.inner = Tokenizer.from_file(path)
        self.words = pa.array([], pa.string())
        self.flat, self.start, self.size = np.zeros(1 << 16, np.uint32), np.zeros(1 << 14, np.int64), np.zeros(1 << 14, np.int32)
        self.used, self.limit = 0, CACHE_WORDS

    def _learn(self, words: list[str], first: int) -> None:
        """Files the ids of words as entries ``first`` and on. Plain words go to the model itself; all else passes the vocabulary's other rules first."""
        model = self.inner.model
        ids: list = [[t.id for t in model.tokenize(w)] if w.isascii() and w.isalpha() else None for w in words]
        rest = [i for i, x in enumerate(ids) if x is None]
        for at in range(0, len(rest), 10_000):
            some = rest[at : at + 10_000]
            for i, e in zip(some, self.inner.encode_batch_fast([words[i] for i in some], add_special_tokens=False), strict=True):
                ids[i] = e.ids
        sizes = np.fromiter(map(len, ids), np.int64, len(ids))
        total = int(sizes.sum())
        while self.used + total > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        while first + len(ids) > len(self.start):
            self.start, self.size = (np.concatenate([x, np.zeros_like(x)]) for x in (self.start, self.size))
        self.flat[self.used : self.used + total] = np.fromiter((i for x in ids for i in x), np.uint32, total)
        self.start[first : first + len(ids)] = self.used + np.cumsum(sizes) - sizes
        self.size[first : first + len(ids)] = sizes
        self.used += total

    def ids_of(self, texts: pa.Array) -> list[np.ndarray]:
        """Each text's ids; null is an empty text."""
        texts = pc.fill_null(texts, "")
        special = np.flatnonzero(pc.match_substring(texts, "<|").to_numpy(zero_copy_only=False))
        whole = {int(i): np.array(self.inner.encode(texts[int(i)].as_py(), add_special_tokens=False).ids, np.uint32) for i in special}
        if whole:
            texts = pc.if_else(pc.match_substring(texts, "<|"), "", texts)
        texts = pc.ascii_lower(pc.replace_substring(texts, "\n", " "))
        texts = pc.replace_substring_regex(texts, r"([a-z])([,.]+) ", r"\1 \2 ")
        words = pc.split_pattern(texts, " ")
        coded = words.flatten().dictionary_encode()
        entry = pc.fill_null(pc.index_in(coded.dictionary, value_set=self.words), -1).to_numpy().astype(np.int64)
        missing = np.flatnonzero(entry < 0)
        before, known = self.used, len(self.words)
        if len(missing):
            new = coded.dictionary.take(pa.array(missing))
            entry[missing] = known + np.arange(len(missing))
            self._learn(new.to_pylist(), known)
        code = entry[coded.indices.to_numpy()]
        sizes = self.size[code].astype(np.int64)
        ends = np.cumsum(sizes)
        out = self.flat[np.repeat(self.start[code] - (ends - sizes), sizes) + np.arange(int(sizes.sum()))]
        if len(missing) and known < self.limit:
            self.words = pa.concat_arrays([self.words, new])
        else:  # words that come late are rare: they aren't kept
            self.used = before
        cuts = np.r_[0, ends][np.cumsum(pc.list_value_length(words).to_numpy())]
        found = np.split(out, cuts[:-1])
        for i, ids in whole.items():
            found[i] = ids
        return found


_TOKENIZERS: dict[str, WordTokenizer] = {}


def _tokenizer(path: str) -> WordTokenizer:
    """One for each Python worker, so words that earlier tasks met need no encoding."""
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = WordTokenizer(path)
    return _TOKENIZERS[path]


def _tokenize(path: str, length: int, end_id: int, slice_docs: int = SLICE_DOCS, cache_words: int = CACHE_WORDS):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = _tokenizer(path)
        words.limit = cache_words
        end = np.array([end_id], np.uint32)
        slices = (b.slice(at, slice_docs) for b in batches for at in range(0, max(1, b.num_rows), slice_docs))
        for number, batch in enumerate(slices):
            if number % TRIM_EVERY == 0:
                release_memory()
            out: list[tuple] = []
            for doc, ids in zip(batch.column("doc_id").to_pylist(), words.ids_of(batch.column("text")), strict=True):
                ids = np.concatenate([ids, end]).astype("<u4", copy=False)
                n = len(ids)
                if ids.max() > 0xFFFF:
                    raise ValueError(f"id {ids.max()} does not fit the two bytes in which ids of cut pieces are kept")
                for start in range(0, n, length):
                    piece = ids[start : start + length]
                    kept = None if len(piece) == length else piece.astype("<u2").tobytes()
                    out.append((doc, n, start, len(piece), zlib.crc32(piece), kept))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], ["doc_id", "doc_tokens", "start", "length", "ids_crc32", "ids"])

    return run


def tokenized(docs: DataFrame, path: str, length: int = LENGTH, end_id: int = END_ID, slice_docs: int = SLICE_DOCS, cache_words: int = CACHE_WORDS) -> DataFrame:
    """Pieces of at most ``length`` ids. Ids of shorter ones are kept, two bytes each, as they may be cut further."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    kinds = fields(doc_id=LONG, doc_tokens=LONG, start=LONG, length=LONG, ids_crc32=LONG, ids=BINARY)
    return to_python(rows, _tokenize(path, length, end_id, slice_docs, cache_words), kinds)


# --- patterns ------------------------------------------------------------------------------------------------------


def _best_pattern(prices: np.ndarray, room: int) -> tuple[float, np.ndarray]:
    """Unbounded knapsack: class w (1-based) takes w units of ``room`` and is worth prices[w - 1]."""
    worth, took = np.zeros(room + 1), np.zeros(room + 1, np.int64)
    n = len(prices)
    for w in range(1, room + 1):
        m = min(w, n)
        options = worth[w - m : w][::-1] + prices[:m]
        k = int(np.argmax(options))
        if options[k] > worth[w - 1] + 1e-15:
            worth[w], took[w] = options[k], k + 1
        else:
            worth[w] = worth[w - 1]
    pattern, w = np.zeros(n, np.int64), room
    while w > 0:
        if took[w]:
            pattern[took[w] - 1] += 1
            w -= took[w]
        else:
            w -= 1
    return float(worth[room]), pattern


def _times(matrix: np.ndarray, vector: np.ndarray) -> np.ndarray:
    """Matrix by vector without the linear algebra library: its threads can hang in a process that has forked, as a driver has."""
    return np.einsum("ij,j->i", matrix, vector)


def _inverse(matrix: np.ndarray) -> np.ndarray:
    """Gauss-Jordan elimination with row exchanges, in plain vector operations for the same reason."""
    n = len(matrix)
    work = np.concatenate([matrix, np.eye(n)], axis=1)
    for i in range(n):
        at = i + int(np.argmax(np.abs(work[i:, i])))
        if at != i:
            work[[i, at]] = work[[at, i]]
        work[i] /= work[i, i]
        factor = work[:, i].copy()
        factor[i] = 0
        work -= factor[:, None] * work[i]
    return work[:, n:]


def solve_patterns(demand: np.ndarray, room: int, max_columns: int = 1500, gap: float = 1e-4) -> list[tuple[np.ndarray, float]]:
    """Patterns and how often the linear program uses each, by revised simplex with generated columns.

    It starts from one pattern per class that repeats it, and stops when no pattern gains, or when the bound that the best
    reduced cost gives is within ``gap``.
    """
    used = np.flatnonzero(demand)
    if not len(used):
        return []
    widths = used + 1
    d = demand[used].astype(float)
    m = len(used)
    columns = np.diag(room // widths).astype(float)
    inverse = np.diag(1.0 / (room // widths))
    x = _times(inverse, d)
    for step in range(max_columns):
        prices = inverse.sum(0)
        full = np.full(room, -1.0)
        full[used] = prices
        value, pattern = _best_pattern(np.maximum(full, 0), room)
        total = x.sum()
        if value <= 1 + 1e-9 or total - total / value <= max(0.5, gap * total):  # half a sequence is less than rounding costs
            break
        column = pattern[used].astype(float)
        direction = _times(inverse, column)
        ok = direction > 1e-9
        if not ok.any():
            break
        ratios = np.where(ok, x / np.where(ok, direction, 1), np.inf)
        leave = int(np.argmin(ratios))
        t = ratios[leave]
        x = x - t * direction
        x[leave] = t
        pivot = inverse[leave] / direction[leave]
        inverse -= np.outer(direction, pivot)
        inverse[leave] = pivot
        columns[:, leave] = column
        if step % 200 == 199:
            inverse = _inverse(columns)
            x = np.maximum(_times(inverse, d), 0)
    out = []
    for j in range(m):
        if x[j] > 1e-9:
            whole = np.zeros(room, np.int64)
            whole[used] = columns[:, j].astype(np.int64)
            out.append((whole, float(x[j])))
    return out


def rounded_patterns(demand: np.ndarray, room: int) -> list[tuple[dict[int, int], int]]:
    """(pieces by class, number of sequences); together they hold exactly ``demand``.

    Shares are rounded down; what is left over, less than a sequence for each pattern, is packed first-fit by falling length.
    """
    left = demand.astype(np.int64).copy()
    out: list[tuple[dict[int, int], int]] = []
    for pattern, share in sorted(solve_patterns(demand, room), key=lambda p: -p[1]):
        used = np.flatnonzero(pattern)
        times = int(min(int(share + 1e-6), *(left[used] // pattern[used])))
        if times > 0:
            left[used] -= times * pattern[used]
            out.append(({int(c) + 1: int(pattern[c]) for c in used}, times))
    while left.any():
        space, one = room, {}
        for c in np.flatnonzero(left)[::-1]:
            n = int(min(left[c], space // (c + 1)))
            if n:
                one[int(c) + 1] = n
                space -= n * (int(c) + 1)
        times = int(min(left[c - 1] // n for c, n in one.items()))
        for c, n in one.items():
            left[c - 1] -= times * n
        out.append((one, times))
    return out


def layout(patterns: list[tuple[dict[int, int], int]]) -> list[tuple[int, int, int, int, int]]:
    """(class, first rank, last rank + 1, first sequence, pieces a sequence), fullest patterns first."""
    ordered = sorted(patterns, key=lambda p: -sum(c * n for c, n in p[0].items()))
    at: dict[int, int] = {}
    out, sequence = [], 0
    for pattern, times in ordered:
        for c, n in pattern.items():
            first = at.get(c, 0)
            out.append((c, first, first + n * times, sequence, n))
            at[c] = first + n * times
        sequence += times
    return out


# --- assignment -----------------------------------------------------------------------------------------------------


def _running(rows: DataFrame, order: str, amount: str, name: str) -> DataFrame:
    """Adds ``name``, the sum of ``amount`` over all rows of smaller ``order``, a dense number; taken in slices."""
    cut = rows.withColumn("_slice", F.expr(f"{order} div {SLICE_ROWS // 8}"))
    sums = cut.groupBy("_slice").agg(F.sum(amount).alias("_sum"))
    # one row for 4096 sequences: the only window without a key, and it stays small
    before = Window.orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("_slice", F.coalesce(F.sum("_sum").over(before), F.lit(0)).alias("_start"))
    within = Window.partitionBy("_slice").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    return cut.withColumn("_in", F.coalesce(F.sum(amount).over(within), F.lit(0))).join(starts, "_slice").withColumn(name, F.col("_start") + F.col("_in")).drop("_slice", "_start", "_in")


def _ranked(pieces: DataFrame, n: int) -> DataFrame:
    """Adds ``rank``, a dense number from 0 within each class; a class may hold any share of the rows."""
    slices = max(64, n // SLICE_ROWS)
    cut = pieces.withColumn("_slice", F.pmod(F.xxhash64("uid"), F.lit(slices)))
    sums = cut.groupBy("class", "_slice").agg(F.count("*").alias("_sum"))
    before = Window.partitionBy("class").orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("class", "_slice", F.coalesce(F.sum("_sum").over(before), F.lit(0)).alias("_start"))
    within = Window.partitionBy("class", "_slice").orderBy("uid")
    return cut.withColumn("_in", F.row_number().over(within)).join(starts, ["class", "_slice"]).withColumn("rank", F.col("_start") + F.col("_in") - 1).drop("_slice", "_start", "_in")


def _cut_ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Checksums of the parts that a piece is cut into; ``parts`` has (from, to, sequence, offset)."""
    for batch in batches:
        out = []
        for doc, n, start, ids, parts in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "doc_tokens", "start", "ids", "parts")), strict=True):
            wide = np.frombuffer(ids, "<u2").astype("<u4")
            for p in parts:
                out.append((doc, start + p["lo"], p["hi"] - p["lo"], zlib.crc32(wide[p["lo"] : p["hi"]].tobytes()), n, p["sequence"], p["offset"]))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], pa.int64()) for i in range(7)], COLUMNS)


COLUMNS = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


def powers(rest: int) -> list[int]:
    """Powers of two that sum to ``rest``, falling."""
    return [1 << b for b in range(rest.bit_length() - 1, -1, -1) if rest >> b & 1]


def pack(docs: DataFrame, path: str | None = None, length: int = LENGTH, end_id: int = END_ID, step: int = STEP, slice_docs: int = SLICE_DOCS, cache_words: int = CACHE_WORDS) -> DataFrame:
    """Per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    ``slice_docs`` and ``cache_words`` trade a worker's memory for time: 800 and 600,000 take 380 MB, 200 and 50,000 take 270 MB and 1.6 times as long.
    """
    spark = docs.sparkSession
    made = materialise(tokenized(docs, path or tokenizer_path(), length, end_id, slice_docs, cache_words).withColumn("uid", F.monotonically_increasing_id()), "pack-pieces")
    light = made.drop("ids")
    whole, rests = light.where(f"length = {length}"), light.where(f"length < {length}").withColumn("class", F.ceil(F.col("length") / step).cast("int"))
    counts = rests.groupBy("class").agg(F.count("*").alias("n"), F.sum("length").alias("tokens")).collect()
    demand = np.zeros(length // step, np.int64)
    for r in counts:
        demand[r["class"] - 1] = r["n"]
    tokens = sum(r["tokens"] for r in counts)
    plan = layout(rounded_patterns(demand, length // step))
    n_full = tokens // length

    # at most a few entries per class, so the table of places is broadcast
    places = F.broadcast(spark.createDataFrame(plan, "class int, lo long, hi long, first long, each long"))
    ranked = _ranked(rests, int(demand.sum()))
    seated = ranked.join(places, (ranked["class"] == places["class"]) & (ranked["rank"] >= places["lo"]) & (ranked["rank"] < places["hi"]))
    seated = materialise(seated.select("uid", "doc_id", "doc_tokens", "start", "length", "ids_crc32", (F.col("first") + F.expr("(rank - lo) div each")).alias("seq")), "pack-seated")

    order = Window.partitionBy("seq").orderBy(F.col("length").desc(), "uid").rowsBetween(Window.unboundedPreceding, -1)
    kept = seated.where(F.col("seq") < n_full).withColumn("offset", F.coalesce(F.sum("length").over(order), F.lit(0)))
    fills = seated.where(F.col("seq") < n_full).groupBy("seq").agg(F.sum("length").alias("fill"))
    slack = _running(fills.withColumn("room", F.lit(length) - F.col("fill")), "seq", "room", "at").where("room > 0")

    # what the sequences beyond n_full hold is laid along a line and cut where room on it ends
    taken = seated.where(F.col("seq") >= n_full)
    heads = taken.groupBy("seq").agg(F.sum("length").alias("fill")).withColumn("seq0", F.col("seq") - n_full)
    along = _running(heads, "seq0", "fill", "line").select("seq", "line")
    taken = taken.withColumn("in_seq", F.coalesce(F.sum("length").over(order), F.lit(0))).join(along, "seq")
    taken = taken.select("uid", (F.col("line") + F.col("in_seq")).alias("f0"), (F.col("line") + F.col("in_seq") + F.col("length")).alias("f1"))

    rest = tokens - n_full * length
    total_room = slack.agg(F.coalesce(F.sum("room"), F.lit(0)).alias("s"))
    base = total_room.first()["s"]
    tails, at = [], base
    for i, size in enumerate(powers(rest)):
        tails.append((n_full + i, at, size))
        at += size
    rooms = slack.select("seq", F.col("at").alias("s0"), (F.col("at") + F.col("room")).alias("s1"), F.col("fill").alias("base"))
    if tails:
        ends = spark.createDataFrame(tails, "seq long, s0 long, size long")
        rooms = rooms.unionByName(ends.select("seq", "s0", (F.col("s0") + F.col("size")).alias("s1"), F.lit(0).cast("long").alias("base")))

    def bucketed(df: DataFrame, lo: str, hi: str) -> DataFrame:
        return df.withColumn("bucket", F.explode(F.sequence(F.expr(f"{lo} div {length}"), F.expr(f"({hi} - 1) div {length}"))))

    a, b = bucketed(taken, "f0", "f1"), bucketed(rooms, "s0", "s1")
    lo, hi = F.greatest("f0", "s0"), F.least("f1", "s1")
    met = a.join(b, "bucket").where(lo < hi).where(F.expr(f"greatest(f0, s0) div {length}") == F.col("bucket"))
    cuts = met.select("uid", F.struct((lo - F.col("f0")).alias("lo"), (hi - F.col("f0")).alias("hi"), F.col("seq").alias("sequence"), (F.col("base") + lo - F.col("s0")).alias("offset")).alias("part"))
    parts = cuts.groupBy("uid").agg(F.array_sort(F.collect_list("part")).alias("parts"))
    filled = made.where(f"length < {length}").select("uid", "doc_id", "doc_tokens", "start", "ids").join(parts, "uid")
    filled = to_python(filled.drop("uid"), _cut_ids, fields(**{c: LONG for c in COLUMNS}))

    n_seq = n_full + len(tails)
    numbered = _numbered(whole, n_seq, whole.count())
    cols = lambda df, seq: df.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", seq.cast("long").alias("sequence_id"), F.col("offset").cast("long").alias("offset"))
    return cols(kept, F.col("seq")).unionByName(cols(numbered.withColumn("offset", F.lit(0)), F.col("seq"))).unionByName(filled.select(*COLUMNS))


def _numbered(whole: DataFrame, first: int, n: int) -> DataFrame:
    """Sequences of one full piece: any distinct numbers from ``first`` on would do, and these are dense."""
    slices = max(64, n // SLICE_ROWS)
    cut = whole.withColumn("_slice", F.pmod(F.xxhash64("uid"), F.lit(slices)))
    sums = cut.groupBy("_slice").agg(F.count("*").alias("_sum"))
    before = Window.orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("_slice", F.coalesce(F.sum("_sum").over(before), F.lit(0)).alias("_start"))  # one row for SLICE_ROWS pieces
    return cut.withColumn("_in", F.row_number().over(Window.partitionBy("_slice").orderBy("uid"))).join(starts, "_slice").withColumn("seq", F.lit(first) + F.col("_start") + F.col("_in") - 1).drop("_slice", "_start", "_in")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
