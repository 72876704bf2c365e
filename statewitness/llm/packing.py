"""Packing of documents into fixed-length sequences by bin completion.

Piece lengths are integers up to the capacity, so a corpus of any size is described by one count for
each length. The solver works on those counts alone (a bounded table), with patterns that repeat:

* a best-fit decreasing packing of the counts is the first incumbent;
* bin completion takes the largest length left, enumerates undominated fillings of the room beside
  it, applies a filling as often as the counts allow, and searches depth first; a branch ends when
  bins so far plus the bins that the rest needs at least can't beat the incumbent (the waste bound);
* the search stops when the incumbent meets the lower bound, or after ``node_limit`` nodes.

What a node enumerates is bounded: at most four undominated fillings, each a greedy head and up to three lengths
from the 16 fullest pairs and the 64 largest first lengths; dominance is tested length by length. So a search
that ends without meeting the bound does not prove its packing best; ``Plan.lower_bound`` tells the gap.

The plan is then dealt to pieces by their rank within their length: ranks are local running numbers
plus prefix sums over input partitions, so no task holds a whole length class.

Defined results: null text counts as empty (one piece holding only the end id); a repeated row is
packed once for each time it occurs; an empty table gives no sequence; extra columns are ignored.
"""

from __future__ import annotations

import os
import re
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from statewitness.llm.arrow_text import column, tidied
from statewitness.llm.scratch import Scratch

CAPACITY = 2048
END_ID = 0
NODE_LIMIT = 20_000
#: Words whose ids a worker remembers; the half that was not asked for lately goes first.
WORD_MEMORY = 1_000_000


# --- token ids -------------------------------------------------------------------------------------


#: A full stop or comma that ends a word and follows one letter stands alone for the tokenizer too.
LOOSE = re.compile(rb"[.,](?=[\x20\x09-\x0D]|\Z)(?:(?<=[a-z].)|(?<=\xc3[\x80-\x96\x98-\xb6\xb8-\xbf].))")


#: Words of visible ASCII and Latin-1 letters: composed already, so they can be cut without the tokenizer's normaliser.
PLAIN = re.compile(rb"(?:[!-~]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+")
#: How the tokenizer cuts such a lower-case word.
CUTS = re.compile(rb"'(?:s|t|re|ve|m|ll|d)|(?:[a-z]|\xc3[\x9f-\xb6\xb8-\xbf])+|[0-9]|[^a-z0-9\xc3]+")
#: Bytes that its byte alphabet renames, in order, to the characters from 256 on (the others stand for themselves).
RENAMED = {b: 256 + k for k, b in enumerate([*range(0x21), *range(0x7F, 0xA1), 0xAD])}


class WordIds(dict):
    """Ids (little-endian uint32 bytes) of white-space separated words, as the tokenizer gives them.

    The tokenizer drops white space, never joins across it and ignores case, so a text's ids are its
    words' ids in order and one memory of words serves all texts. A new plain word is cut here and its
    parts go straight to the tokenizer's merges; any other new word goes through the whole tokenizer. The
    short way is taken only if the tokenizer gives the same ids on ``PROBES``.
    """

    PROBES = ("it's", "we'll''s", "d'été", "straße99,5%", "ÀÿÞß(x)_y", "'re-'ve'm't", "a---b\"!?", "être***", "''d'st")

    def __init__(self, path: str, memory: int = WORD_MEMORY):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.merges = self.tokenizer.model
        self.older: dict[bytes, bytes] = {}
        self.memory = memory
        probes = [p.encode() for p in self.PROBES]
        self.short = all(self.by_merges(p) == self.by_tokenizer(p) for p in probes if PLAIN.fullmatch(p))

    def by_tokenizer(self, word: bytes) -> list[int]:
        return self.tokenizer.encode(word.decode(), add_special_tokens=False).ids

    def by_merges(self, word: bytes) -> list[int]:
        if not word.isascii():
            return [t.id for p in CUTS.findall(word.decode().lower().encode()) for t in self.merges.tokenize(p.decode("latin-1").translate(RENAMED))]
        return [t.id for p in CUTS.findall(word.lower()) for t in self.merges.tokenize(p.decode())]

    def __missing__(self, word: bytes) -> bytes:
        if len(self) >= self.memory // 2:
            self.older = dict(self)
            self.clear()
        ids = self.older.get(word)
        if ids is None:
            plain = self.short and PLAIN.fullmatch(word) and b"<|" not in word
            found = self.by_merges(word) if plain else self.by_tokenizer(word)
            ids = struct.pack(f"<{len(found)}I", *found)
        self[word] = ids
        return ids

    def encode(self, text: str | None) -> bytes:
        raw = (text or "").encode()
        words = raw.split() if b"<|" in raw else LOOSE.sub(rb" \g<0>", raw.lower()).split()
        return b"".join(map(self.__getitem__, words))


_ENCODERS: dict[str, WordIds] = {}


def encoder(path: str, memory: int) -> WordIds:
    if path not in _ENCODERS:
        _ENCODERS[path] = WordIds(path, memory)
    _ENCODERS[path].memory = memory
    return _ENCODERS[path]


PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, rank long"


def cut_pieces(path: str, capacity: int, end_id: int, memory: int):
    """Batches of (doc_id, text) to pieces, with the partition and the running number within a length."""
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, part, seen = encoder(path, memory), TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)
        for whole in batches:
            for lo in range(0, whole.num_rows, 500):
                batch = whole.slice(lo, 500)
                out: list[tuple] = []
                for doc, text in zip(column(batch, "doc_id").to_pylist(), column(batch, "text").to_pylist()):
                    ids = words.encode(text) + end
                    for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                        cut = ids[at : at + 4 * capacity]
                        n = len(cut) // 4
                        out.append((doc, k, at // 4, n, zlib.crc32(cut), part, int(seen[n])))
                        seen[n] += 1
                cols = list(zip(*out)) or [()] * 7
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64())
                names = [x.split()[0] for x in PIECES.split(", ")]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    return run


# --- the plan on length counts ----------------------------------------------------------------------


@dataclass
class Plan:
    """Patterns (lengths in one sequence) and how often each is used."""

    capacity: int
    patterns: list[tuple[tuple[int, ...], int]] = field(default_factory=list)
    lower_bound: int = 0
    nodes: int = 0

    @property
    def bins(self) -> int:
        return sum(m for _, m in self.patterns)


def lower_bound(counts: np.ndarray, capacity: int) -> int:
    """Largest of the sum bound and the bounds that set lengths over a threshold's complement apart."""
    sizes = np.arange(capacity + 1, dtype=object)
    total = int(np.dot(counts.astype(object), sizes)) if counts.any() else 0
    best = -(-total // capacity)
    num, vol = np.cumsum(counts.astype(np.int64)), np.cumsum(counts.astype(np.int64) * np.arange(capacity + 1))
    for k in range(0, capacity // 2 + 1):
        big = int(num[capacity] - num[capacity - k])  # no other item of at least k fits beside these
        half = int(num[capacity - k] - num[capacity // 2])
        room = half * capacity - int(vol[capacity - k] - vol[capacity // 2])
        small = int(vol[capacity // 2] - (vol[k - 1] if k else 0))
        best = max(best, big + half + max(0, -(-(small - room) // capacity)))
    return best


def best_fit_decreasing(counts: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit decreasing on counts: bins with the same contents are one group."""
    groups: dict[int, list[list]] = {}
    for size in range(capacity, 0, -1):
        left = int(counts[size])
        room = size
        while left and room <= capacity:
            while left and groups.get(room):
                items, n = groups[room].pop()
                fit = room // size
                whole = min(n, left // fit)
                if whole:
                    groups.setdefault(room - fit * size, []).append([items + (size,) * fit, whole])
                    left -= whole * fit
                    n -= whole
                if n and left:
                    groups.setdefault(room - left * size, []).append([items + (size,) * left, 1])
                    n, left = n - 1, 0
                if n:
                    groups.setdefault(room, []).append([items, n])
            room += 1
            while room <= capacity and not groups.get(room):
                room += 1
        if left:
            fit = capacity // size
            if left // fit:
                groups.setdefault(capacity - fit * size, []).append([(size,) * fit, left // fit])
            if left % fit:
                groups.setdefault(capacity - left % fit * size, []).append([(size,) * (left % fit), 1])
    return [(items, n) for same in groups.values() for items, n in same]


def fillings(room: int, counts: np.ndarray, most: int = 4) -> list[tuple[int, ...]]:
    """Undominated fillings of ``room`` (each of up to three lengths after a greedy start), fullest first."""
    head: list[int] = []
    counts = counts[: room + 1]
    biggest = int(np.flatnonzero(counts)[-1]) if counts.any() else 0
    if not biggest:
        return [()]
    if room > 3 * biggest:
        counts = counts.copy()
        while room > 3 * biggest and biggest:
            take = min(int(counts[biggest]), (room - 3 * biggest) // biggest + 1)
            head += [biggest] * take
            room -= take * biggest
            counts[biggest] -= take
            at = np.flatnonzero(counts[: room + 1])
            biggest = int(at[-1]) if len(at) else 0
        counts = counts[: room + 1]
        if not biggest:
            return [tuple(head)]
    have = counts > 0
    largest = np.maximum.accumulate(np.where(have, np.arange(len(counts)), 0))  # largest length there of at most x
    found: dict[tuple[int, ...], int] = {(int(largest[room]),): int(largest[room])}
    first = np.flatnonzero(have)

    def pair(space: int, under: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each length the largest second one that fits beside it, no longer than itself."""
        other = largest[np.minimum(under, space - under)]
        same = (other == under) & (counts[under] < 2)
        other = np.where(same, largest[np.maximum(np.minimum(under - 1, space - under), 0)], other)
        return under, other

    a, b = pair(room, first[first < room])
    order = np.argsort(-(a + b), kind="stable")[: 4 * most]
    for i in sorted(order.tolist(), key=lambda i: (-(a[i] + b[i]), -a[i])):
        if b[i]:
            found[(int(a[i]), int(b[i]))] = int(a[i] + b[i])
    if max(found.values()) < room:
        for x in first[first < room][::-1][:64].tolist():
            rest = room - x
            under = first[first <= min(x, rest - 1)]
            if len(under):
                counts[x] -= 1
                a, b = pair(rest, under)
                ok = (counts[a] > 0) & ((b == 0) | (counts[b] > 0))
                s = np.where(ok & (b > 0), a + b, 0)
                i = int(np.argmax(s))
                counts[x] += 1
                if s[i]:
                    found[(x, int(a[i]), int(b[i]))] = x + int(s[i])
                    if x + s[i] == room:
                        break
    ranked = sorted(found, key=lambda f: (-found[f], [-x for x in f]))
    kept: list[tuple[int, ...]] = []
    for f in ranked:
        if not any(len(g) == len(f) and all(y >= x for x, y in zip(f, g)) for g in kept):  # dominated: item by item no longer
            kept.append(f)
        if len(kept) == most:
            break
    return [tuple(head) + f for f in kept]


def bin_completion(counts: np.ndarray, capacity: int = CAPACITY, node_limit: int = NODE_LIMIT) -> Plan:
    """Pack counts of lengths 0..capacity (0 unused) into as few sequences as the search finds."""
    counts = counts.astype(np.int64).copy()
    plan = Plan(capacity, best_fit_decreasing(counts, capacity), lower_bound(counts, capacity))
    best = plan.bins
    if best == plan.lower_bound:
        return plan
    sizes = np.arange(capacity + 1)
    used: list[tuple[tuple[int, ...], int]] = []
    volume, bins, nodes = int((counts * sizes).sum()), 0, 0
    stack: list[tuple] = []

    def options() -> tuple[int, Iterator[tuple[int, ...]]]:
        top = int(np.flatnonzero(counts)[-1])
        counts[top] -= 1
        found = fillings(capacity - top, counts)
        counts[top] += 1
        return top, iter(found)

    stack.append(options() + (None,))
    while stack and nodes < node_limit:
        top, left, undo = stack.pop()
        if undo is not None:
            pattern, m = undo
            for x in pattern:
                counts[x] += m
            volume += m * sum(pattern)
            bins -= m
            used.pop()
        filling = next(left, None)
        if filling is None:
            continue
        nodes += 1
        pattern = (top, *filling)
        values, each = np.unique(pattern, return_counts=True)
        m = int((counts[values] // each).min())
        for x in pattern:
            counts[x] -= m
        volume -= m * sum(pattern)
        bins += m
        used.append((pattern, m))
        stack.append((top, left, (pattern, m)))
        if not volume:
            if bins < best:
                best, plan.patterns = bins, list(used)
                if best == plan.lower_bound:
                    break
        elif bins + -(-volume // capacity) < best:  # the waste bound
            stack.append(options() + (None,))
    plan.nodes = nodes
    return plan


def runs(plan: Plan) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each length: first rank, first sequence and offset of each run of ranks that a slot takes."""
    at = np.zeros(plan.capacity + 1, np.int64)
    out: dict[int, list[tuple[int, int, int]]] = {}
    base = 0
    for pattern, m in plan.patterns:
        offset = 0
        for size in pattern:
            out.setdefault(size, []).append((int(at[size]), base, offset))
            at[size] += m
            offset += size
        base += m
    return {k: tuple(np.array(x, np.int64) for x in zip(*v)) for k, v in out.items()}


PACKED = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"


def place(table):
    """Pieces with their rank within a length to their sequence and offset; ``table`` is a broadcast of runs()."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length = column(batch, "length").to_numpy(zero_copy_only=False)
            rank = column(batch, "rank").to_numpy(zero_copy_only=False)
            seq, off = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for n in np.unique(length).tolist():
                rows = np.flatnonzero(length == n)
                first, base, offset = table.value[n]
                k = np.searchsorted(first, rank[rows], side="right") - 1
                seq[rows], off[rows] = base[k] + rank[rows] - first[k], offset[k]
            keep = [column(batch, c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*keep, pa.array(seq), pa.array(off)], names=[x.split()[0] for x in PACKED.split(", ")])

    return run


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID, node_limit: int = NODE_LIMIT, word_memory: int = WORD_MEMORY) -> DataFrame:
    """One row per piece of every document: where it starts, how long it is, and where it was packed."""
    spark = docs.sparkSession
    s = Scratch(spark)
    pieces = s.save(docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(tidied(cut_pieces(tokenizer_path, capacity, end_id, word_memory)), PIECES), "pieces", keep=True)
    per_part = s.save(pieces.groupBy("length", "part").agg(F.count("*").alias("n")), "per_part", keep=True)
    counts = np.zeros(capacity + 1, np.int64)
    for row in per_part.groupBy("length").agg(F.sum("n").alias("n")).collect():  # one row for each length, at most ``capacity``
        counts[row["length"]] = row["n"]
    table = spark.sparkContext.broadcast(runs(bin_completion(counts, capacity, node_limit)))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = per_part.select("length", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    ranked = pieces.join(base, ["length", "part"]).withColumn("rank", F.col("rank") + F.col("base"))
    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank").mapInArrow(tidied(place(table)), PACKED)


def word_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def query(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), word_tokenizer())
