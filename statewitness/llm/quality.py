"""Quality classifier: a sparse ensemble of conjunctive rules, compiled to column expressions.

1. Statistics of a whole text (lengths, shares of kinds of characters and words, repetition, line shapes) come
   from one scan of Arrow batches, all vectorised. No language, source, id or label is among them.
2. A bounded sample of labelled rows (``MAX_ROWS``, smallest hashes of the id first) is gathered at the
   driver with its statistics; gradient boosting grows small trees on it.
3. Every path from a root to a node below it is a rule: a conjunction of comparisons. Logistic
   regression with an absolute-value penalty (proximal gradient steps with momentum) gives most rules the
   weight zero; the penalty is chosen on a fifth of the sample.
4. The rules left are compiled to one sum of CASE expressions over the statistics, so scoring is a scan and a
   projection: no shuffle, any number of rows.

Defined results: null text counts as empty and is scored; a null id is scored and is in no fold (``held_out`` is
false), nor is it trained on; labels that are null are ignored, and a
document with contradicting labels counts as label 0; with no labels, or labels of one kind, the score
is the share of label 1 (0.5 without any); a repeated row is scored each time; an empty table gives
no rows; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from statewitness.llm.arrow_text import column, text_buffers, text_slices, tidied
from statewitness.llm.wordhash import SPACE, family, find_words

QUALITY_SEED = 101
MAX_ROWS = 6_000
TREES, DEPTH, RATE, BINS = 24, 3, 0.3, 32
PENALTIES = (0.01, 0.004, 0.0015, 0.0006)
KEEP_AT = 0.7
HELD_OUT = 2

# --- statistics -------------------------------------------------------------------------------------

#: Symbols that prose hardly has.
SYMBOLS = b"#$%&*|@^~<>=_+\\/{}[]"
FEATURES = ("chars", "words", "upper_share", "letter_share", "symbol_share", "bang_share", "digit_share", "word_length", "line_words", "sentence_words", "short_share", "distinct_share", "distinct_scaled")
LETTER, UPPER = 1, 2


@lru_cache(1)
def kinds() -> np.ndarray:
    """LETTER and UPPER bits of every code point."""
    out = np.zeros(0x200000, np.uint8)
    for k in range(0x110000):
        kind = unicodedata.category(chr(k))
        if kind[0] == "L":
            out[k] = LETTER | (UPPER if kind == "Lu" else 0)
    return out


def letter_bits(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Kind bits at the first byte of every character, and the LETTER bit at its last byte."""
    table = kinds()
    first = table[:128][np.minimum(raw, 127)] * (raw < 128)
    last = first & LETTER
    at = np.flatnonzero(raw >= 0xC0)
    if len(at):
        padded = np.r_[raw, np.zeros(3, np.uint8)].astype(np.uint32)
        lead = padded[at]
        tail = [padded[at + k] & 0x3F for k in (1, 2, 3)]
        size = 2 + (lead >= 0xE0) + (lead >= 0xF0)
        two, three = (lead & 0x1F) << 6 | tail[0], (lead & 0x0F) << 12 | tail[0] << 6 | tail[1]
        four = (lead & 0x07) << 18 | tail[0] << 12 | tail[1] << 6 | tail[2]
        first[at] = table[np.where(size == 2, two, np.where(size == 3, three, four))]
        last[np.minimum(at + size - 1, len(raw) - 1)] = first[at] & LETTER
    return first, last


def statistics(texts: pa.Array) -> np.ndarray:
    """One row of FEATURES for each text; null counts as empty."""
    raw, offsets = text_buffers(texts)
    w = find_words(raw, offsets)
    per = lambda mask: np.diff(np.r_[0, np.cumsum(mask)][offsets])
    first, last = letter_bits(raw)
    starts_char = (raw & 0xC0) != 0x80
    before = np.r_[0, np.cumsum(starts_char)]
    n = np.diff(before[offsets])
    space = SPACE[raw]
    ends_text = np.zeros(len(raw), bool)
    ends_text[offsets[1:][np.diff(offsets) > 0] - 1] = True
    stop = (raw == 0x2E) | (raw == 0x3F)
    if len(raw):
        stop[1:] &= last[:-1] > 0
        stop[offsets[:-1][np.diff(offsets) > 0]] = False
        stop &= ends_text | np.r_[space[1:], False]
    count = np.diff(w.docs)
    brief = np.r_[0, np.cumsum(before[w.ends] - before[w.starts] <= 3)][w.docs]
    h = family(QUALITY_SEED).word_hashes(raw, w.starts, w.ends)
    distinct = np.ones(len(count), np.int64)
    for i in np.flatnonzero(count > 1).tolist():
        x = np.sort(h[w.docs[i] : w.docs[i + 1]])
        distinct[i] = 1 + np.count_nonzero(x[1:] != x[:-1])
    words, letters = np.maximum(count, 1), per(first & LETTER)
    share = lambda part, whole: part / np.maximum(whole, 1)
    return np.stack(
        [
            n,
            words,
            share(per(first & UPPER) // UPPER, letters),
            share(letters, n),
            share(per(np.isin(raw, np.frombuffer(SYMBOLS, np.uint8))), n),
            per(raw == 0x21) / words,
            share(per((raw >= 0x30) & (raw <= 0x39)), n),
            n / words,
            words / (per(raw == 0x0A) + 1),
            words / (per(stop) + 1),
            np.diff(brief) / words,
            distinct / words,
            distinct / np.sqrt(words),
        ],
        1,
    ).astype(np.float64)


def with_statistics(docs: DataFrame, text_col: str, carry: list[Column]) -> DataFrame:
    """``carry`` and one column ``f_<name>`` for each statistic, from one narrow scan in Arrow batches."""
    rows = docs.select(F.struct(*carry).alias("carried"), F.col(text_col).cast("string").alias("text"))
    return _scanned(rows, lambda batch: column(batch, "text")).select("carried.*", *[f"f_{k}" for k in FEATURES])


def _scanned(rows: DataFrame, text_of: Callable[[pa.RecordBatch], pa.Array]) -> DataFrame:
    """``carried`` of ``rows`` with the statistics of each row's text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo, hi in text_slices(text_of(whole)):
                batch = whole.slice(lo, hi - lo)
                x = statistics(text_of(batch))
                yield pa.RecordBatch.from_arrays([column(batch, "carried"), *[pa.array(x[:, k]) for k in range(len(FEATURES))]], names=["carried", *[f"f_{k}" for k in FEATURES]])

    schema = T.StructType([rows.schema["carried"], *[T.StructField(f"f_{k}", T.DoubleType()) for k in FEATURES]])
    return rows.mapInArrow(tidied(run), schema)


# --- trees and rules --------------------------------------------------------------------------------


@dataclass(frozen=True)
class Rule:
    """A conjunction of bounds: (feature position, is an upper bound, threshold)."""

    bounds: tuple[tuple[int, bool, float], ...]

    def holds(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for k, upper, t in self.bounds:
            out &= (x[:, k] <= t) if upper else (x[:, k] > t)
        return out

    def column(self, names: tuple[str, ...]) -> Column:
        out = F.lit(True)
        for k, upper, t in self.bounds:
            c = F.col(f"f_{names[k]}")
            out = out & ((c <= F.lit(t)) if upper else (c > F.lit(t)))
        return out


def narrowed(bounds: list[tuple[int, bool, float]]) -> tuple[tuple[int, bool, float], ...]:
    """One bound for each side of each feature: the tightest."""
    best: dict[tuple[int, bool], float] = {}
    for k, upper, t in bounds:
        have = best.get((k, upper))
        best[(k, upper)] = t if have is None else (min(have, t) if upper else max(have, t))
    return tuple(sorted((k, upper, t) for (k, upper), t in best.items()))


def grow(codes: np.ndarray, edges: list[np.ndarray], g: np.ndarray, h: np.ndarray, depth: int) -> tuple[np.ndarray, list[Rule]]:
    """One boosted tree on binned features: its step for every row, and the rules on its paths."""
    step, rules = np.zeros(len(g)), []

    def split(rows: np.ndarray, bounds: list, left: int) -> None:
        total_g, total_h = g[rows].sum(), h[rows].sum()
        if bounds:
            rules.append(Rule(narrowed(bounds)))
        best = (1e-3, -1, 0)
        if left and len(rows) >= 20:
            for k in range(codes.shape[1]):
                hist_g = np.bincount(codes[rows, k], g[rows], BINS).cumsum()[:-1]
                hist_h = np.bincount(codes[rows, k], h[rows], BINS).cumsum()[:-1]
                gain = hist_g**2 / (hist_h + 1) + (total_g - hist_g) ** 2 / (total_h - hist_h + 1) - total_g**2 / (total_h + 1)
                b = int(gain.argmax())
                if gain[b] > best[0] and b < len(edges[k]):
                    best = (gain[b], k, b)
        _, k, b = best
        if k < 0:
            step[rows] = -total_g / (total_h + 1)
            return
        under = codes[rows, k] <= b
        split(rows[under], [*bounds, (k, True, float(edges[k][b]))], left - 1)
        split(rows[~under], [*bounds, (k, False, float(edges[k][b]))], left - 1)

    split(np.arange(len(g)), [], depth)
    return step, rules


def boosted_rules(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH) -> list[Rule]:
    edges = [np.unique(np.quantile(x[:, k], np.linspace(0, 1, BINS + 1)[1:-1])) for k in range(x.shape[1])]
    codes = np.stack([np.searchsorted(e, x[:, k], side="left") for k, e in enumerate(edges)], 1)
    margin, rules = np.zeros(len(y)), {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        step, found = grow(codes, edges, p - y, p * (1 - p), depth)
        margin += RATE * step
        rules |= dict.fromkeys(found)
    return list(rules)


def lasso(r: np.ndarray, y: np.ndarray, penalty: float, start: tuple[np.ndarray, float], rounds: int = 250) -> tuple[np.ndarray, float]:
    """Logistic weights under an absolute-value penalty (the intercept is free)."""
    w, b = start[0].copy(), start[1]
    z, c, t = w.copy(), b, 1.0
    v = np.full(r.shape[1], 1.0)
    for _ in range(12):
        v = r.T @ (r @ v)
        v /= np.linalg.norm(v) + 1e-12
    step = 1 / (0.25 * (np.linalg.norm(r @ v) ** 2 / len(y) + 1) + 1e-9)
    for _ in range(rounds):
        e = 1 / (1 + np.exp(-(r @ z + c))) - y
        new = z - step * (r.T @ e) / len(y)
        new = np.sign(new) * np.maximum(np.abs(new) - step * penalty, 0)
        free = c - step * e.mean()
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        z, c = new + (t - 1) / t2 * (new - w), free + (t - 1) / t2 * (free - b)
        w, b, t = new, free, t2
    return w, b


def log_loss(r: np.ndarray, y: np.ndarray, w: np.ndarray, b: float) -> float:
    m = r @ w + b
    return float(np.mean(np.logaddexp(0, m) - y * m))


@dataclass
class RuleModel:
    """A weight for each rule, and an intercept."""

    rules: list[Rule] = field(default_factory=list)
    weights: list[float] = field(default_factory=list)
    intercept: float = 0.0
    names: tuple[str, ...] = FEATURES

    def scores(self, x: np.ndarray) -> np.ndarray:
        m = np.full(len(x), self.intercept)
        for rule, w in zip(self.rules, self.weights):
            m += w * rule.holds(x)
        return 1 / (1 + np.exp(-m))

    def column(self) -> Column:
        """The score over columns ``f_<name>``."""
        m = F.lit(self.intercept)
        for rule, w in zip(self.rules, self.weights):
            m = m + F.when(rule.column(self.names), F.lit(w)).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-m))


def fit(x: np.ndarray, y: np.ndarray) -> RuleModel:
    """Rules and weights from statistics and labels 0/1."""
    if not len(y) or y.min() == y.max():
        share = (float(y.mean()) if len(y) else 0.5) * 0.998 + 0.001
        return RuleModel(intercept=float(np.log(share / (1 - share))))
    rules = boosted_rules(x, y)
    r = np.stack([rule.holds(x) for rule in rules], 1).astype(np.float32) if rules else np.zeros((len(y), 0), np.float32)
    check = np.arange(len(y)) % 5 == 0
    share = y.mean()
    start = (np.zeros(r.shape[1]), float(np.log(share / (1 - share))))
    best, chosen, at = np.inf, PENALTIES[0], start
    part, rest = r[~check], r[check]
    for penalty in PENALTIES:
        at = lasso(part, y[~check], penalty, at)
        loss = log_loss(rest, y[check], *at)
        if loss < best * 0.98:  # a smaller penalty has to earn its rules
            best, chosen = loss, penalty
    w, b = lasso(r, y, chosen, start)
    kept = np.flatnonzero(np.abs(w) > 1e-6)
    return RuleModel([rules[k] for k in kept], [float(w[k]) for k in kept], float(b))


# --- on tables --------------------------------------------------------------------------------------


def fold(doc_id: Column) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string")), F.lit(4))


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS) -> RuleModel:
    """Fit on at most ``max_rows`` labelled documents outside the held-out fold."""
    rows = labels.filter((fold(F.col("doc_id")) != HELD_OUT) & F.col("quality").isin(0, 1)).groupBy("doc_id").agg(F.min("quality").alias("label"))
    sample = rows.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    some = docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id")  # at most max_rows ids
    got = with_statistics(some, "text", [F.col("doc_id"), F.col("label")]).collect()
    got.sort(key=lambda row: row["doc_id"])
    order = np.random.Generator(np.random.PCG64(77)).permutation(len(got))
    x = np.array([[row[f"f_{k}"] for k in FEATURES] for row in got], np.float64).reshape(len(got), len(FEATURES))[order]
    return fit(x, np.array([row["label"] for row in got], np.float64)[order])


def score(docs: DataFrame, model: RuleModel) -> DataFrame:
    """doc_id, held_out, score and predicted for every row."""
    rows = with_statistics(docs, "text", [F.col("doc_id")])
    value = model.column()
    return rows.select("doc_id", F.coalesce(fold(F.col("doc_id")) == HELD_OUT, F.lit(False)).alias("held_out"), value.alias("score")).withColumn("predicted", (F.col("score") >= KEEP_AT).cast("int"))


def keep_good(docs: DataFrame, model: RuleModel, keep_at: float = KEEP_AT) -> DataFrame:
    """The rows scored ``keep_at`` or more, with their own columns only.

    The score is a column over statistics that come out of the scan, so the filter can't be moved before them.
    """
    names = docs.columns
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("carried"))
    place = names.index("text")
    return _scanned(rows, lambda batch: pc.struct_field(column(batch, "carried"), [place])).filter(model.column() >= keep_at).select("carried.*")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return score(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
