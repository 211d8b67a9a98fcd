"""Quality classifier: a sparse ensemble of rules.

Small trees are grown on statistics of labelled documents; every path from a root is a rule, a conjunction of comparisons.
A logistic model with an L1 penalty weighs the rules and drops most. The rules that remain are compiled into one Spark column
expression over the statistics.

The model is fitted on at most MAX_LABELLED labelled rows, taken by the hash of their id; statistics read whole texts.

Defined cases: a null text is empty, its statistics are zero and it gets a score like any other; without labels, or with labels of
one kind only, the score is the share of good labels (one half without any); repeated rows are scored each; an empty table
gives an empty result; further columns pass through.
"""

from __future__ import annotations

from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import small_batches, table

#: Labelled rows that a model is fitted on, at most.
MAX_LABELLED = 20_000
THRESHOLD = 0.3
HOLD_OUT = 5
TREES, DEPTH, BINS, LEAF_ROWS = 60, 3, 48, 20
MAX_RULES = 300
PENALTY = 2e-4
ROUNDS = 400
SEED = 7

_UPPER = bytes(range(65, 91))
_DIGITS = bytes(range(48, 58))
_SYMBOLS = b"#$%&*+<=>@[]^_`{}~\\/"
STATISTICS = ("words", "chars_per_word", "longest_word", "upper", "digits", "symbols", "bars", "bangs", "periods", "commas", "repeated_next", "distinct", "lines_per_word", "repeated_lines", "high_bytes", "capital_words", "single_byte_words")


def statistics_of(data: bytes) -> tuple[float, ...]:
    """Numbers about a whole text; all zero for an empty one."""
    n = len(data)
    words = data.split()
    w = len(words)
    if not w:
        return (0.0,) * len(STATISTICS)
    share = lambda drop: (n - len(data.translate(None, drop))) / n
    lines = data.split(b"\n")
    sizes = list(map(len, words))
    return (
        float(w),
        sum(sizes) / w,
        float(max(sizes)),
        share(_UPPER),
        share(_DIGITS),
        share(_SYMBOLS),
        data.count(b"|") / w,
        data.count(b"!") / w,
        data.count(b".") / w,
        data.count(b",") / w,
        sum(map(eq, words[1:], words)) / w,
        len(set(words)) / w,
        len(lines) / w,
        1 - len(set(lines)) / len(lines),
        1 - len(data.decode("utf-8", "replace")) / n,
        sum(map(bytes.isupper, words)) / w,
        sizes.count(1) / w,
    )


_KIND = T.StructType([T.StructField(s, T.DoubleType()) for s in STATISTICS])


def with_statistics(docs: DataFrame, name: str, text: str = "text") -> DataFrame:
    """Adds a struct of statistics. Only the text goes to Python; all other columns stay in the JVM."""

    @F.arrow_udf(_KIND)
    def stats(texts: pa.Array) -> pa.Array:
        rows = [statistics_of(t.as_py() or b"") for t in texts]
        return pa.StructArray.from_arrays([pa.array([r[i] for r in rows], pa.float64()) for i in range(len(STATISTICS))], list(STATISTICS))

    small_batches(docs.sparkSession)
    return docs.withColumn(name, stats(F.coalesce(F.col(text), F.lit("")).cast("binary")))


#: A comparison: statistic, whether it must exceed, bound.
Test = tuple[int, bool, float]


@dataclass(frozen=True)
class RuleModel:
    intercept: float
    rules: tuple[tuple[tuple[Test, ...], float], ...]

    def score_column(self, stats: str) -> Column:
        """The model as one expression; conditions are shared by Catalyst where they recur."""
        total = F.lit(self.intercept)
        for tests, weight in self.rules:
            fits = None
            for i, above, bound in tests:
                value = F.col(f"{stats}.{STATISTICS[i]}")
                one = value > bound if above else value <= bound
                fits = one if fits is None else fits & one
            total = total + F.when(fits, F.lit(weight)).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))

    def describe(self) -> list[str]:
        return [f"{w:+.3f} if " + " and ".join(f"{STATISTICS[i]} {'>' if a else '<='} {b:.4g}" for i, a, b in tests) for tests, w in self.rules]


def _paths(x: np.ndarray, y: np.ndarray, bounds: list[np.ndarray], rng: np.random.Generator) -> set[tuple[Test, ...]]:
    """Paths of one tree on a bootstrap of binned rows; each node looks at half of the statistics."""
    n, k = x.shape
    found: set[tuple[Test, ...]] = set()

    def grow(rows: np.ndarray, tests: tuple[Test, ...]) -> None:
        if tests:
            found.add(tuple(sorted(tests)))
        if len(tests) >= DEPTH or len(rows) < 2 * LEAF_ROWS or y[rows].min() == y[rows].max():
            return
        best = (1e-9, -1, -1)
        base = y[rows].mean()
        for i in rng.choice(k, max(2, k // 2), replace=False):
            if not len(bounds[i]):
                continue
            count = np.bincount(x[rows, i], minlength=len(bounds[i]) + 1).cumsum()[:-1]
            good = np.bincount(x[rows, i], weights=y[rows], minlength=len(bounds[i]) + 1).cumsum()[:-1]
            ok = (count >= LEAF_ROWS) & (len(rows) - count >= LEAF_ROWS)
            if ok.any():
                c = np.where(ok, count, 1)
                gain = np.where(ok, (good - c * base) ** 2 / c + (good - c * base) ** 2 / np.maximum(len(rows) - c, 1), 0)
                j = int(np.argmax(gain))
                if gain[j] > best[0]:
                    best = (float(gain[j]), int(i), j)
        if best[1] < 0:
            return
        _, i, j = best
        side = x[rows, i] <= j
        grow(rows[side], (*tests, (i, False, float(bounds[i][j]))))
        grow(rows[~side], (*tests, (i, True, float(bounds[i][j]))))

    grow(rng.choice(n, n), ())
    return found


def fit_rules(values: np.ndarray, labels: np.ndarray) -> RuleModel:
    """``values``: rows by statistics; ``labels``: 0 or 1."""
    share = float(labels.mean()) if len(labels) else 0.5
    if len(labels) < 2 * LEAF_ROWS or labels.min() == labels.max():
        share = min(max(share, 1e-3), 1 - 1e-3)
        return RuleModel(float(np.log(share / (1 - share))), ())
    y = labels.astype(float)
    bounds = [np.unique(np.quantile(values[:, i], np.linspace(0, 1, BINS + 1)[1:-1])) for i in range(values.shape[1])]
    bounds = [b[b < values[:, i].max()] for i, b in enumerate(bounds)]
    binned = np.stack([np.searchsorted(b, values[:, i], side="left") for i, b in enumerate(bounds)], 1)
    rng = np.random.default_rng(SEED)
    rules: dict[bytes, tuple[Test, ...]] = {}
    for _ in range(TREES):
        for tests in sorted(_paths(binned, y, bounds, rng), key=lambda t: (len(t), t)):
            fits = np.ones(len(y), bool)
            for i, above, bound in tests:
                fits &= values[:, i] > bound if above else values[:, i] <= bound
            if LEAF_ROWS <= fits.sum() < len(y):
                rules.setdefault(np.packbits(fits).tobytes(), tests)  # of rules that fit the same rows the first and shortest stays
    unpack = lambda b: np.unpackbits(np.frombuffer(b, np.uint8), count=len(y)).astype(float)
    strength = lambda b: abs(float((unpack(b) * (y - share)).sum()))
    chosen = sorted(rules, key=lambda b: (-strength(b), rules[b]))[:MAX_RULES]
    weights, intercept = _lasso(np.stack([unpack(b) for b in chosen], 1), y) if chosen else (np.zeros(0), float(np.log(share / (1 - share))))
    return RuleModel(intercept, tuple((rules[b], float(w)) for b, w in zip(chosen, weights, strict=True) if abs(w) > 1e-6))


def _lasso(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
    """Logistic weights under an L1 penalty, by accelerated proximal steps; columns are centred, the intercept is free."""
    mean = x.mean(0)
    z = x - mean
    # not the linear algebra library: its threads can hang in a process that has forked, as a driver has
    times, back = lambda w: np.einsum("ij,j->i", z, w), lambda g: np.einsum("ij,i->j", z, g)
    v = np.ones(z.shape[1])
    for _ in range(20):  # largest eigenvalue, for the step
        v = back(times(v))
        v /= float((v * v).sum()) ** 0.5 or 1.0
    step = 4 * len(y) / max(1e-9, float((v * back(times(v))).sum()) + len(y))
    w, b = np.zeros(z.shape[1]), float(np.log(y.mean() / (1 - y.mean())))
    w_, b_, t = w, b, 1.0
    for _ in range(ROUNDS):
        p = 1 / (1 + np.exp(-np.clip(times(w_) + b_, -30, 30)))
        g = (p - y) / len(y)
        nw, nb = w_ - step * back(g), b_ - step * g.sum()
        nw = np.sign(nw) * np.maximum(np.abs(nw) - step * PENALTY, 0)
        nt = (1 + (1 + 4 * t * t) ** 0.5) / 2
        w_, b_ = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = nw, nb, nt
    return w, b - float((mean * w).sum())


def remainder(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % HOLD_OUT


def train(docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED) -> RuleModel:
    """Fitted on labelled documents whose crc32(doc_id) is not divisible by HOLD_OUT; of more than ``max_labelled`` those of least hash."""
    known = labels.where(F.col("quality").isNotNull() & (remainder(F.col("doc_id")) != 0)).groupBy(F.col("doc_id").alias("_id")).agg((F.avg("quality") >= 0.5).cast("int").alias("_label"))
    chosen = known.orderBy(F.xxhash64("_id"), "_id").limit(max_labelled)  # the documented bound
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_id"))
    measured = with_statistics(sample.select("_id", "text", "_label"), "s").groupBy("_id").agg(F.min("s").alias("s"), F.max("_label").alias("_label"))
    rows = measured.select("s.*", "_label").toPandas()  # one row for each chosen label at most
    rows = rows.sort_values([*STATISTICS, "_label"])  # the same model whatever order rows came in
    return fit_rules(rows[list(STATISTICS)].to_numpy(float), rows["_label"].to_numpy(int))


def score(docs: DataFrame, model: RuleModel) -> DataFrame:
    """``docs`` with score and predicted."""
    base = docs.drop("score", "predicted", "_stats")
    out = with_statistics(base, "_stats").withColumn("score", model.score_column("_stats")).drop("_stats")
    return out.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` without those predicted bad, all columns as they were."""
    columns = docs.columns
    scored = with_statistics(docs, "_stats")
    return scored.where(train(docs, labels).score_column("_stats") >= THRESHOLD).select(*columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", (remainder(F.col("doc_id")) == 0).alias("held_out"), "score", "predicted")
