"""Removal of word windows that occur more than once, over a log-structured fingerprint index.

A window is ``window`` consecutive words. Its fingerprint is the smallest hash of the ``gram``-word
sequences in it: equal windows have equal fingerprints, and neighbours mostly share theirs, so a
document of n words has some 2n / (window - gram + 2) fingerprints instead of n.

1. One scan gives each document's fingerprints with their counts, and its result if nothing is removed.
2. Batches enter the index as sorted runs, are merge-joined and compacted; a fingerprint that occurs
   once in all runs can't belong to a repeated window.
3. For documents with other fingerprints the text is read again. Consecutive windows with one
   fingerprint form a stretch; stretches are verified on a hash of all their words by a second,
   independent family. A stretch that occurs twice is repeated as a whole; the stretches that do not
   (at the edges of repeated passages) are verified window by window against all windows with the same
   fingerprint, each distinct stretch being listed once however many copies it has.
4. Texts with repeated windows are read once more and the covered words are dropped.

Judgements refer to the input, never to what is left. Defined results: null counts as empty (no words,
SHA-256 of nothing); texts shorter than a window keep all words; a repeated row counts as another
occurrence and is returned again; a row whose id is null is treated like any other; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from statewitness.llm.arrow_text import chunks, column, text_buffers
from statewitness.llm.bounded import BROADCAST_KEYS, keep_keys
from statewitness.llm.fingerprint_index import FingerprintIndex
from statewitness.llm.scratch import Scratch
from statewitness.llm.wordhash import family, find_words

WINDOW, GRAM, BATCHES = 35, 8, 2
GRAM_SEED, WINDOW_SEED = 201, 202


def sliding(x: np.ndarray, width: int, op) -> np.ndarray:
    """Minimum or maximum of every ``width`` consecutive values."""
    have, out = 1, x
    while have < width:
        step = min(have, width - have)
        out = op(out[:-step], out[step:])
        have += step
    return out


def fingerprints(grams: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(fingerprint of every window, positions of the grams that are one) for one text's gram hashes."""
    least = sliding(grams, width, np.minimum)
    pad = np.zeros(width - 1, np.uint64)
    return least, np.flatnonzero(sliding(np.r_[pad, least, pad], width, np.maximum) == grams)


def scan_grams(batch: pa.RecordBatch, window: int, gram: int):
    """(row, its words' range, its gram hashes) for each text with a window; the words of the batch first."""
    hashes = family(GRAM_SEED)
    w = find_words(*text_buffers(column(batch, "text")))
    g = hashes.grams(hashes.word_hashes(w.raw, w.starts, w.ends), gram)
    rows = np.flatnonzero(np.diff(w.docs) >= window)
    return w, [(int(i), int(w.docs[i]), int(w.docs[i + 1]), g[w.docs[i] : w.docs[i + 1] - gram + 1]) for i in rows]


def read_fingerprints(window: int, gram: int):
    """One row for each text: its result if nothing is removed, and its distinct fingerprints with counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in chunks(whole):
                w, texts = scan_grams(batch, window, gram)
                g: list = [[]] * batch.num_rows
                n: list = [[]] * batch.num_rows
                for i, _, _, grams in texts:
                    _, at = fingerprints(grams, window - gram + 1)
                    values, counts = np.unique(grams[at], return_counts=True)
                    g[i], n[i] = values.view(np.int64), counts
                sha = [hashlib.sha256(b" ".join((t or "").encode().split())).digest() for t in column(batch, "text").to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [column(batch, "uid"), column(batch, "doc_id"), pa.array(np.diff(w.docs).astype(np.int64)), pa.array(sha, pa.binary()), pa.array(g, pa.list_(pa.int64())), pa.array(n, pa.list_(pa.int64()))],
                    names=["uid", "doc_id", "n_words", "sha", "gs", "ns"],
                )

    return run


READ = "uid binary, doc_id long, n_words long, sha binary, gs array<long>, ns array<long>"


def read_stretches(window: int, gram: int):
    """Stretches of windows whose fingerprint is among the text's ``gs``: place, hash, and each window's hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = family(WINDOW_SEED)
        for whole in batches:
            for batch in chunks(whole):
                w, texts = scan_grams(batch, window, gram)
                h = hashes.word_hashes(w.raw, w.starts, w.ends)
                uids, wanted = column(batch, "uid"), column(batch, "gs")
                parts: list[tuple] = []
                for i, lo, hi, grams in texts:
                    least = sliding(grams, window - gram + 1, np.minimum)
                    first = np.flatnonzero(np.r_[True, least[1:] != least[:-1]])
                    length = np.diff(np.r_[first, len(least)])
                    hit = np.isin(least[first].view(np.int64), wanted[i].values.to_numpy())
                    if hit.any():
                        parts.append((np.full(int(hit.sum()), i), first[hit] + lo, length[hit], least[first[hit]], np.full(int(hit.sum()), lo)))
                if not parts:
                    continue
                row, at, length, g, lo = (np.concatenate(x) for x in zip(*parts))
                span = hashes.spans(h, at, at + length + window - 1)
                inner = np.repeat(at, length) + (np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length))
                each = hashes.spans(h, inner, inner + window).view(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(length)].astype(np.int32)), pa.array(each))
                yield pa.RecordBatch.from_arrays(
                    [uids.take(pa.array(row)), pa.array((at - lo).astype(np.int64)), pa.array(length.astype(np.int32)), pa.array(g.view(np.int64)), pa.array(span.view(np.int64)), lists],
                    names=["uid", "at", "len", "g", "span", "ws"],
                )

    return run


STRETCHES = "uid binary, at long, len int, g long, span long, ws array<long>"


def drop_covered(window: int):
    """Texts without the words that the stretches (at, len) of repeated windows cover."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            removed, sha = [], []
            texts, ats, lens = (column(batch, k) for k in ("text", "ats", "lens"))
            for i, text in enumerate(texts.to_pylist()):
                words = (text or "").encode().split()
                edge = np.zeros(len(words) + 1, np.int64)
                a, n = ats[i].values.to_numpy(), lens[i].values.to_numpy()
                np.add.at(edge, a, 1)
                np.add.at(edge, a + n + window - 1, -1)
                gone = edge.cumsum()[:-1] > 0
                removed.append(int(gone.sum()))
                sha.append(hashlib.sha256(b" ".join([x for x, out in zip(words, gone.tolist()) if not out])).digest())
            yield pa.RecordBatch.from_arrays([column(batch, "uid"), pa.array(removed, pa.int64()), pa.array(sha, pa.binary())], names=["uid", "n_removed", "kept"])

    return run


def repeated_windows(s: Scratch, stretches: DataFrame) -> DataFrame:
    """(uid, at, len) of stretches of windows that occur elsewhere too."""
    groups = s.save(stretches.groupBy("g", "span", "len").agg(F.count("*").alias("n"), F.first("ws").alias("ws")), "groups")
    sure = stretches.select("uid", "at", "len", "g", "span").join(groups.filter("n > 1").select("g", "span", "len"), ["g", "span", "len"], "left_semi")
    alone = groups.filter("n = 1").select("g").distinct()
    listed = groups.join(alone, "g", "left_semi").select("g", "n", F.explode("ws").alias("w"))
    again = s.save(listed.groupBy("g", "w").agg(F.sum("n").alias("n")).filter("n > 1").select("g", "w"), "again")
    lone = stretches.join(groups.filter("n = 1").select("g", "span", "len"), ["g", "span", "len"], "left_semi")
    windows = lone.select("uid", "at", "g", F.posexplode("ws").alias("k", "w")).join(again, ["g", "w"], "left_semi")
    return sure.select("uid", "at", "len").unionByName(windows.select("uid", (F.col("at") + F.col("k")).alias("at"), F.lit(1).alias("len")))


def row_name() -> Column:
    """128 bits that name a row by its id and text; repeated rows share it."""
    return F.unhex(F.md5(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.lit(" "), F.coalesce("text", F.lit("")))))


def remove_repeats(
    docs: DataFrame,
    window: int = WINDOW,
    gram: int = GRAM,
    batches: int = BATCHES,
    broadcast_keys: int = BROADCAST_KEYS,
) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, kept_sha256."""
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("uid", row_name())
    s = Scratch(spark)
    read = s.save(texts.mapInArrow(read_fingerprints(window, gram), READ), "read")
    pairs = read.select("uid", F.explode(F.arrays_zip("gs", "ns")).alias("p")).select("uid", F.col("p.gs").alias("g"), F.col("p.ns").alias("n"))
    index = FingerprintIndex(spark, s.path("index"))
    for b in range(batches):
        part = pairs.filter(F.pmod(F.xxhash64("uid"), F.lit(batches)) == b)
        index.ingest(part.groupBy("g").agg(F.sum("n").alias("n")))
        index.compact()
    hot = index.known(pairs.select("uid", "g")).filter("n > 1").select("uid", "g").distinct()
    wanted = s.save(hot.groupBy("uid").agg(F.collect_list("g").alias("gs")), "wanted")
    index.close()
    base = s.save(read.select("uid", "doc_id", "n_words", "sha"), "base", keep=True)
    s.drop("read")
    again = keep_keys(texts, wanted, "uid", wanted.count(), broadcast_keys).select("uid", "text").join(wanted, "uid")
    stretches = s.save(again.mapInArrow(read_stretches(window, gram), STRETCHES), "stretches")
    found = s.save(repeated_windows(s, stretches).groupBy("uid").agg(F.collect_list("at").alias("ats"), F.collect_list("len").alias("lens")), "found")
    for name in ("wanted", "groups", "again", "stretches"):
        s.drop(name)
    cut = keep_keys(texts, found, "uid", found.count(), broadcast_keys).select("uid", "text").join(found, "uid")
    changed = s.save(cut.mapInArrow(drop_covered(window), "uid binary, n_removed long, kept binary").dropDuplicates(["uid"]), "changed", keep=True)
    s.drop("found")
    return base.join(changed, "uid", "left").select(
        "doc_id", "n_words", F.coalesce("n_removed", F.lit(0)).cast("long").alias("n_removed"), F.lower(F.hex(F.coalesce("kept", "sha"))).alias("kept_sha256")
    )


def read_windows(window: int):
    """(uid, doc_id, n_words, sha, ws): the hash of every window of a text in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = family(WINDOW_SEED)
        for whole in batches:
            for batch in chunks(whole):
                w = find_words(*text_buffers(column(batch, "text")))
                grams = hashes.grams(hashes.word_hashes(w.raw, w.starts, w.ends), window).view(np.int64)
                ws = [grams[lo : max(lo, hi - window + 1)] for lo, hi in zip(w.docs[:-1].tolist(), w.docs[1:].tolist())]
                sha = [hashlib.sha256(b" ".join((t or "").encode().split())).digest() for t in column(batch, "text").to_pylist()]
                columns = [column(batch, "uid"), column(batch, "doc_id"), pa.array(np.diff(w.docs).astype(np.int64)), pa.array(sha, pa.binary()), pa.array(ws, pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(columns, names=["uid", "doc_id", "n_words", "sha", "ws"])

    return run


def ingest(docs: DataFrame, index: FingerprintIndex, window: int = WINDOW) -> DataFrame:
    """A batch against all that ``index`` holds: one row per document, as ``remove_repeats`` gives; the batch enters the index.

    ``index`` is kept by the caller from batch to batch. Its runs hold the hash of every window of the batches
    before, with its number; the new batch is one more sorted run, met with them in merge joins, and runs are
    compacted then. A window goes if it starts elsewhere in this batch or in any batch before; texts of
    earlier batches are not changed any more, so the rows of the last batch equal those of one run over all batches.
    """
    s = Scratch(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("uid", row_name())
    read = s.save(texts.mapInArrow(read_windows(window), "uid binary, doc_id long, n_words long, sha binary, ws array<long>"), "windows", keep=True)
    places = read.select("uid", F.posexplode("ws").alias("at", "g"))
    counts = s.save(places.groupBy("g").agg(F.count("*").alias("n")), "batch")
    before = index.known(counts.select("g")).select("g", F.lit(True).alias("seen"))
    again = counts.join(before, "g", "left").filter(F.coalesce("seen", F.lit(False)) | (F.col("n") > 1)).select("g")
    found = places.distinct().join(again, "g", "left_semi").groupBy("uid").agg(F.collect_list(F.col("at").cast("long")).alias("ats"), F.collect_list(F.lit(1)).alias("lens"))
    cut = texts.dropDuplicates(["uid"]).select("uid", "text").join(found, "uid")
    changed = s.save(cut.mapInArrow(drop_covered(window), "uid binary, n_removed long, kept binary"), "changed", keep=True)
    index.ingest(counts)
    index.compact()
    s.drop("batch")
    return read.select("uid", "doc_id", "n_words", "sha").join(changed, "uid", "left").select(
        "doc_id", "n_words", F.coalesce("n_removed", F.lit(0)).cast("long").alias("n_removed"), F.lower(F.hex(F.coalesce("kept", "sha"))).alias("kept_sha256")
    )


def query(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"))


ORACLE = r"""
WITH w AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
g AS (SELECT doc_id, s, md5(array_to_string(ws[s:s + 34], ' ')) AS h FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) AS s FROM w WHERE len(ws) >= 35)),
again AS (SELECT h FROM g GROUP BY h HAVING count(*) > 1),
gone AS (SELECT DISTINCT doc_id, s + k AS i FROM g JOIN again USING (h), range(35) r(k)),
words AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS i FROM w),
kept AS (SELECT doc_id, string_agg(word, ' ' ORDER BY i) AS t FROM words ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id),
n AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n, 0)::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id) LEFT JOIN n USING (doc_id)
"""
