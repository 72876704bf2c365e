"""Benchmark decontamination: word n-gram seeds, plain and gapped, then Smith-Waterman alignment of words.

1. Every run of ``SEED_WORDS`` words of an item is a seed, however often documents have it, and so are two
   words, any one word and two words again. So an edited copy is found by any three words in a row, or by
   two pairs around one changed word.
2. One scan joins seeds to passages inside each text and aligns the words around them with the
   item (local alignment, linear gaps). The score is the share of the item's own score; edited copies
   keep most of it. The scan is narrow: no text is shuffled.

The test items travel to the workers, so their size is checked; a larger benchmark is taken in blocks
below the bound, each with its own scan.

Defined results: null or empty texts and items match nothing; an item of three words up to ``MIN_WORDS`` - 1
matches only where all its words stand in a row, an item of one or two words only a text that has no other words
(both with score 1); case is ignored; a repeated row is reported each time;
a repeated item id is reported for each of its texts; empty tables give no rows;
extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from statewitness.llm.arrow_text import chunks, column, text_buffers, tidied
from statewitness.llm.wordhash import Family, Words, family, find_words, inside, mix

SEED_WORDS = 3
#: Words from the start of a gapped seed to its end.
GAPPED_WORDS = 5
MIN_WORDS = 5
THRESHOLD = 0.5
MATCH, MISMATCH, GAP = 2, -1, -1
#: Most bytes of test items in one block.
BLOCK_BYTES = 16_000_000
FAMILY_SEED = 901
FILTER_BITS = 20


class Lookup:
    """Positions in a sorted list of 64-bit keys, behind a bit filter on their leading bits."""

    def __init__(self, keys: np.ndarray):
        self.keys = np.unique(keys)
        self.filter = np.zeros(1 << FILTER_BITS, bool)
        self.filter[self.keys >> np.uint64(64 - FILTER_BITS)] = True

    def find(self, values: np.ndarray, valid: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(positions in ``values``, positions in the keys) of the values that are keys."""
        at = np.flatnonzero(self.filter[values >> np.uint64(64 - FILTER_BITS)] & valid)
        if not len(at) or not len(self.keys):
            return at[:0], at[:0]
        k = np.minimum(np.searchsorted(self.keys, values[at]), len(self.keys) - 1)
        hit = self.keys[k] == values[at]
        return at[hit], k[hit]


def gapped(hashes: Family, h: np.ndarray) -> np.ndarray:
    """Hashes of the words at 0, 1, 3 and 4 from every position on (the caller masks those across texts)."""
    pairs = hashes.grams(h, 2)
    return mix(pairs[:-3] * np.uint64(3) + mix(pairs[3:])) if len(pairs) > 3 else np.zeros(0, np.uint64)


def seed_hits(lookup: Lookup, hashes: Family, h: np.ndarray, w: Words, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions in the words, positions in the keys) of plain and gapped seeds."""
    plain, spaced = lookup.find(hashes.grams(h, n), inside(w, n)), lookup.find(gapped(hashes, h), inside(w, GAPPED_WORDS))
    return np.concatenate([plain[0], spaced[0]]), np.concatenate([plain[1], spaced[1]])


@dataclass
class Items:
    """Test items as word hashes, and their seeds: hash, item, position."""

    ids: list
    words: list[np.ndarray]
    gram: np.ndarray
    item: np.ndarray
    pos: np.ndarray
    whole: dict[int, list[int]]


def read_items(rows: list[tuple], n: int) -> Items:
    hashes = family(FAMILY_SEED)
    out = Items([], [], np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), {})
    grams, items, places = [], [], []
    for item_id, text in rows:
        w = find_words(*text_buffers(pc.utf8_lower(pa.array([text], pa.string()))))
        if not len(w.starts):
            continue
        h = hashes.word_hashes(w.raw, w.starts, w.ends)
        if len(h) < n:
            out.whole.setdefault(int(hashes.grams(h, len(h))[0]), []).append(len(out.ids))
        for g in (hashes.grams(h, n), gapped(hashes, h)):
            grams.append(g)
            items.append(np.full(len(g), len(out.ids)))
            places.append(np.arange(len(g)))
        out.ids.append(item_id)
        out.words.append(h)
    if grams:
        out.gram, out.item, out.pos = np.concatenate(grams), np.concatenate(items), np.concatenate(places)
    return out


def local_alignment(item: np.ndarray, passage: np.ndarray) -> tuple[int, int]:
    """Best local score of two word sequences and the end (exclusive) of the alignment in the passage."""
    steps = np.arange(len(passage)) * -GAP
    row = np.zeros(len(passage) + 1, np.int64)
    best, end = 0, 0
    for word in item:
        new = np.maximum(row[:-1] + np.where(passage == word, MATCH, MISMATCH), np.maximum(row[1:] + GAP, 0))
        new = np.maximum.accumulate(new + steps) - steps  # gaps along the passage
        row[1:] = new
        k = int(new.argmax())
        if new[k] > best:
            best, end = int(new[k]), k + 1
    return best, end


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def needed(n_words: int, threshold: float) -> float:
    """The score from which an item of that many words is found."""
    return threshold if n_words >= MIN_WORDS else 1.0


MATCHES = "doc_id long, item int, score double, start_word long, end_word long"


def align(shared, n: int, threshold: float):
    """Seeds and items in ``shared``; gives the best alignment of each (document, item) at the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lookup, first, item_of, pos_of, items, whole_texts = shared.value
        hashes = family(FAMILY_SEED)
        memory: dict[tuple[int, bytes], tuple[int, int, int]] = {}

        def best(item: int, passage: np.ndarray) -> tuple[int, int, int]:
            key = (item, passage.tobytes())
            if key not in memory:
                if len(memory) > 2000:
                    memory.clear()
                words = items[item]
                need = needed(len(words), threshold) * MATCH * len(words)
                score = start = end = 0
                if MATCH * int(np.isin(words, passage).sum()) >= need:
                    score, end = local_alignment(words, passage)
                    if score >= need:
                        start = end - local_alignment(words[::-1], passage[:end][::-1])[1]
                memory[key] = score, start, end
            return memory[key]

        for whole in batches:
            out: list[tuple] = []
            for batch in chunks(whole):
                w = find_words(*text_buffers(pc.utf8_lower(column(batch, "text"))))
                h = hashes.word_hashes(w.raw, w.starts, w.ends)
                ids = column(batch, "doc_id").to_pylist()
                for d in np.flatnonzero((np.diff(w.docs) > 0) & (np.diff(w.docs) < n)).tolist() if whole_texts else ():
                    words = h[w.docs[d] : w.docs[d + 1]]
                    out += [(ids[d], item, 1.0, 0, len(words)) for item in whole_texts.get(int(hashes.grams(words, len(words))[0]), ())]
                at, key = seed_hits(lookup, hashes, h, w, n)
                if not len(at):
                    continue
                many = first[key + 1] - first[key]
                e = np.repeat(first[key + 1] - np.cumsum(many), many) + np.arange(many.sum())
                hits = np.unique(np.stack([w.doc_of[np.repeat(at, many)], item_of[e], np.repeat(at, many) - pos_of[e]], 1), axis=0)
                spans: dict[tuple[int, int], list[tuple[int, int]]] = {}
                for d, item, a in hits.tolist():
                    size = len(items[item])
                    spans.setdefault((d, item), []).append((max(int(w.docs[d]), a - size // 2), min(int(w.docs[d + 1]), a + size + size // 2)))
                for (d, item), found in spans.items():
                    top = max(((*best(item, h[a:b]), a) for a, b in merged(found)), key=lambda x: (x[0], -x[3]))
                    score = top[0] / (MATCH * len(items[item]))
                    if score >= needed(len(items[item]), threshold):
                        base = top[3] - int(w.docs[d])
                        out.append((ids[d], item, score, base + top[1], base + top[2]))
            cols = list(zip(*out)) or [()] * 5
            kinds = (pa.int64(), pa.int32(), pa.float64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=[x.split()[0] for x in MATCHES.split(", ")])

    return run


def item_blocks(benchmark: DataFrame, limit: int) -> list[DataFrame]:
    """The items that have text, as blocks of about ``limit`` bytes each (one where they all fit)."""
    items = benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).filter("text IS NOT NULL AND text <> ''")
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = -(-total * 2 // limit) if total > limit else 1
    return [items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k) if n > 1 else items for k in range(n)]


def lookups(spark: SparkSession, benchmark: DataFrame, n: int, block_bytes: int) -> Iterator[tuple]:
    """For each block of items: their ids, and a broadcast of what a scan needs to find them."""
    for block in item_blocks(benchmark, block_bytes):
        items = read_items([tuple(r) for r in block.collect()], n)  # at most block_bytes, as counted
        if not items.ids:
            continue
        order = np.lexsort((items.pos, items.item, items.gram))
        gram, item_of, pos_of = (x[order] for x in (items.gram, items.item, items.pos))
        seeds = Lookup(gram)
        first = np.r_[np.searchsorted(gram, seeds.keys), len(gram)]
        yield items.ids, spark.sparkContext.broadcast((seeds, first, item_of, pos_of, items.words, items.whole))


def find_leaks(
    docs: DataFrame,
    benchmark: DataFrame,
    n: int = SEED_WORDS,
    threshold: float = THRESHOLD,
    block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """One row per (document, item) whose alignment reaches the threshold: score and word span in the text."""
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    found = None
    for ids, shared in lookups(spark, benchmark, n, block_bytes):
        rows = texts.mapInArrow(tidied(align(shared, n, threshold)), MATCHES)
        names = spark.createDataFrame([(k, i) for k, i in enumerate(ids)], "item int, item_id long")
        part = rows.join(F.broadcast(names), "item").select("doc_id", "item_id", "score", "start_word", "end_word")
        found = part if found is None else found.unionByName(part)
    if found is None:
        return spark.createDataFrame([], "doc_id long, item_id long, score double, start_word long, end_word long")
    return found


def without_leaks(docs: DataFrame, benchmark: DataFrame, n: int = SEED_WORDS, threshold: float = THRESHOLD, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of ``docs`` in whose text no item is found, whatever their ids: one narrow scan for each block of items."""
    names = docs.columns
    place = names.index("text")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"))
    for _, shared in lookups(docs.sparkSession, benchmark, n, block_bytes):
        find = align(shared, n, threshold)

        def run(batches: Iterator[pa.RecordBatch], find=find) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                texts = pc.struct_field(column(batch, "row"), [place]).cast(pa.string())
                numbered = pa.RecordBatch.from_arrays([pa.array(np.arange(batch.num_rows)), texts], names=["doc_id", "text"])
                clean = np.ones(batch.num_rows, bool)
                for found in find(iter([numbered])):
                    clean[found.column(0).to_numpy(zero_copy_only=False)] = False
                yield batch.filter(pa.array(clean))

        rows = rows.mapInArrow(tidied(run), rows.schema)
    return rows.select("row.*")


def query(spark, sf_dir: str) -> DataFrame:
    return find_leaks(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
