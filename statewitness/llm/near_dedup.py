"""Near-duplicate classes by a chosen-path set similarity join.

Documents with equal shingle sets are one class from the start; a class has a running number of its own, so
neither shared ids nor missing ones mix up texts. Each class has ``POSITIONS`` minwise values. A tree starts
with all classes in its root; a node picks one position (sometimes two, so that a pair at the threshold keeps one
common path on average), and classes go to the child named by their minwise value there. Nodes of one class
end; nodes of up to ``LEAF`` classes are compared exhaustively; larger ones branch again. Independent trees repeat
this until the chance to miss a pair at the threshold is below ``1 - target recall``.

Large groups of copies are contracted before the trees grow: in the large nodes of the first few roots, members
meet a few pivots, and then those outside a node's largest component meet members of it, so a group is linked with
comparisons in proportion to its size. A node all of whose classes are already linked ends at once, and only
pairs between components are listed. What is still in several components in a node after the last
level is compared in full: by an exact bound on shared rare shingles, the members outside the node's largest
component against all of the node.

Candidates pass a filter on 64 short minwise values (a true pair fails it with a chance below 1e-8) and
a size filter (exact), and are then confirmed on their full sets: first the most alike partner of each
class, then every candidate pair that is not connected yet. Components come from star contractions.

Defined results: null or empty texts and texts of white space have no shingle, are their own component
and are kept; fewer words than a shingle give one shingle; repeated rows share a class (each row is
returned); rows whose id is null are linked like others, but can't name a component: they are kept
only where their component has no id at all (``component_id`` is null then); rows that share an id but not a text
are judged by their texts; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from statewitness.llm.arrow_text import chunks, column, text_buffers, tidied
from statewitness.llm.bounded import BROADCAST_KEYS, keep_keys
from statewitness.llm.components import grown
from statewitness.llm.scratch import Scratch
from statewitness.llm.wordhash import family, find_words, mix

POSITIONS = 64
LEAF = 24
LEVELS = 4
PIVOTS = 3
#: Roots whose large nodes are contracted first.
HEADS = 3
REST_PIVOTS = 6
RARE = 16
#: Sketch of the shingles that are not rare: buckets, and bits for each.
BUCKETS, UNARY = 128, 4
TARGET_RECALL = 0.9999999
FAMILY_SEED = 502


# --- shingle sets -----------------------------------------------------------------------------------


def sets_of(batch: pa.RecordBatch, words_each: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, bounds): the sorted distinct shingle hashes of every text of a batch, end to end."""
    hashes = family(FAMILY_SEED, fold_case=True)
    w = find_words(*text_buffers(column(batch, "text")))
    h = hashes.word_hashes(w.raw, w.starts, w.ends)
    n = np.diff(w.docs)
    take = np.where(n >= words_each, n - words_each + 1, np.minimum(n, 1))
    at = np.repeat(w.docs[:-1], take) + (np.arange(take.sum()) - np.repeat(np.cumsum(take) - take, take))
    end = np.minimum(at + words_each, np.repeat(w.docs[1:], take))
    grams = hashes.spans(h, at, end)
    parts, size, lo = [], np.zeros(len(n), np.int64), 0
    for i, k in enumerate(take.tolist()):
        x = np.sort(grams[lo : lo + k])
        lo += k
        if k > 1:
            x = x[np.r_[True, x[1:] != x[:-1]]]
        parts.append(x)
        size[i] = len(x)
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint64)), np.r_[0, np.cumsum(size)]


def digests(x: np.ndarray, starts: np.ndarray) -> list[bytes]:
    """128-bit names of the sets that begin at ``starts``."""
    one, two = np.add.reduceat(mix(x), starts), np.add.reduceat(mix(x ^ np.uint64(0x5851F42D4C957F2D)), starts)
    return [a.tobytes() + b.tobytes() for a, b in zip(one, two)]


SIGNED = "doc_id long, key long, mark binary, n int, digest binary, sig array<int>"


def sign(words_each: int):
    rng = np.random.Generator(np.random.PCG64(FAMILY_SEED + 1))
    mults, adds = rng.integers(0, 1 << 64, POSITIONS, np.uint64) | np.uint64(1), rng.integers(0, 1 << 64, POSITIONS, np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in chunks(whole):
                x, bounds = sets_of(batch, words_each)
                n = np.diff(bounds)
                some = np.flatnonzero(n)
                sig = np.zeros((len(n), POSITIONS), np.int32)
                digest: list[bytes | None] = [None] * len(n)
                if len(some):
                    starts = bounds[some]
                    for k in range(POSITIONS):
                        sig[some, k] = (np.minimum.reduceat(x * mults[k] + adds[k], starts) >> np.uint64(32)).astype(np.uint32).view(np.int32)
                    for row, name in zip(some.tolist(), digests(x, starts)):
                        digest[row] = name
                flat = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1, dtype=np.int32) * POSITIONS), pa.array(sig.ravel()))
                carried = ["doc_id", "key", "mark"]
                yield pa.RecordBatch.from_arrays([*(column(batch, c) for c in carried), pa.array(n.astype(np.int32)), pa.array(digest, pa.binary()), flat], names=[*carried, "n", "digest", "sig"])

    return run


def shingle_sets(words_each: int):
    """(digest, n, items) of every text that has a shingle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in chunks(whole):
                x, bounds = sets_of(batch, words_each)
                bounds = bounds[np.r_[True, np.diff(bounds) > 0]]
                names = digests(x, bounds[:-1]) if len(x) else []
                flat = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(x.view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(np.diff(bounds).astype(np.int32)), flat], names=["digest", "n", "items"])

    return run


# --- the trees --------------------------------------------------------------------------------------


def trees_needed(similarity: float, target: float, depth: int = 3) -> int:
    """Trees until a pair at the threshold is missed with a chance of at most 1 - target (leaves by ``depth``)."""
    return math.ceil(math.log(1 - target) / math.log(1 - similarity**depth))


def short_agreement(similarity: float, of: int = POSITIONS) -> int:
    """How many of ``of`` short values a pair at the threshold shares at least: six deviations below the mean."""
    return int(of * (similarity + (1 - similarity) / 16) - 6 * math.sqrt(of * similarity * (1 - similarity)))


def value_at(position: Column) -> Column:
    return F.element_at("sig", position + 1)


#: What a class carries through the trees: number, set size, component so far, and a first part of its short values.
CARRIED = ("rep", "n", "c", "s0")


def roots(n_trees: int, similarity: float) -> list[tuple[int, int]]:
    """(tree, position) of the choices of every tree's root."""
    rng = np.random.Generator(np.random.PCG64(FAMILY_SEED + 2))
    order, chosen = rng.permutation(POSITIONS), []
    for tree in range(n_trees):
        chosen.append((tree, int(order[tree % POSITIONS])))
        if rng.random() < 1 / similarity - 1:
            chosen.append((tree, int(order[(tree + POSITIONS // 2) % POSITIONS])))
    return chosen


def root_nodes(classes: DataFrame, chosen: list[tuple[int, int]]) -> DataFrame:
    """Every class in the children that the roots choose."""
    pairs = F.array(*[F.struct(F.lit(t).alias("t"), F.lit(p).alias("p")) for t, p in chosen])
    return classes.withColumn("k", F.explode(pairs)).select(*CARRIED, F.xxhash64("k.t", "k.p", value_at(F.col("k.p"))).alias("node"))


def one_row_each(members: DataFrame, *of_node: str) -> DataFrame:
    """Members of nodes as one row for each class, with its nodes as a list: what a class is joined with comes once."""
    rest = [c for c in members.columns if c not in (*of_node, "rep")]
    node = F.col(of_node[0]) if len(of_node) == 1 else F.struct(*of_node)
    return members.groupBy("rep").agg(*[F.first(c).alias(c) for c in rest], F.collect_list(node).alias("nodes"))


def child_nodes(members: DataFrame, classes: DataFrame, level: int, similarity: float) -> DataFrame:
    """Members of large nodes in the children that each node chooses."""
    first = F.pmod(F.xxhash64("node", F.lit(level)), F.lit(POSITIONS)).cast("int")
    second = F.pmod(first + 1 + F.pmod(F.xxhash64("node", F.lit(-level)), F.lit(POSITIONS - 1)).cast("int"), F.lit(POSITIONS)).cast("int")
    both = F.pmod(F.xxhash64("node", F.lit(level), F.lit(2)), F.lit(1000)) < int(1000 * (1 / similarity - 1))
    rows = one_row_each(members.select(*CARRIED, "node"), "node").join(classes.select("rep", "sig"), "rep").withColumn("node", F.explode("nodes"))
    rows = rows.withColumn("p", F.explode(F.when(both, F.array(first, second)).otherwise(F.array(first))))
    return rows.select(*CARRIED, F.xxhash64("node", "p", value_at(F.col("p"))).alias("node"))


def live_members(rows: DataFrame) -> DataFrame:
    """Members of the nodes that hold several components, with their node's size."""
    per = rows.groupBy("node").agg(F.count("*").alias("size"), F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo < hi")
    return rows.join(per.select("node", "size"), "node")


def like_sizes(a: str, b: str, percent: int) -> Column:
    """No pair outside this range of sizes reaches the similarity."""
    return F.least(a, b).cast("long") * 100 >= F.greatest(a, b).cast("long") * percent


def ordered(a: str, b: str) -> list[Column]:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def leaf_pairs(members: DataFrame, percent: int, agree: int) -> DataFrame:
    """Pairs between components in nodes with at most LEAF classes, if the first of their short values allow."""
    leaf = members.filter(F.col("size") <= LEAF)
    x, y = (leaf.select("node", *[F.col(c).alias(f"{c}{side}") for c in CARRIED]) for side in ("x", "y"))
    could = (F.col("repx") < F.col("repy")) & (F.col("cx") != F.col("cy")) & like_sizes("nx", "ny", percent) & (same_values("s0x", "s0y") >= agree)
    return x.join(y, "node").filter(could).select(*ordered("repx", "repy"))


def pivot_pairs(big: DataFrame, percent: int) -> DataFrame:
    """Every member of a large node with the node's pivots."""
    draw = F.xxhash64("rep")  # the same in every node, so nodes that hold one group mostly share their pivots
    pivots = big.groupBy("node", F.pmod(draw, F.lit(PIVOTS)).alias("k")).agg(F.min(F.struct(draw.alias("d"), "rep", "n")).alias("v"))
    pivots = pivots.select("node", F.col("v.rep").alias("y"), F.col("v.n").alias("ny"))
    x = big.select("node", F.col("rep").alias("x"), F.col("n").alias("nx"))
    return x.join(pivots, "node").filter((F.col("x") != F.col("y")) & like_sizes("nx", "ny", percent)).select(*ordered("x", "y")).distinct()


def short_codes() -> list[Column]:
    """Four longs of sixteen 4-bit values each, taken from the minwise values."""
    words = []
    for w in range(4):
        terms = [F.shiftleft((F.element_at("sig", 16 * w + k + 1).bitwiseAND(F.lit(15))).cast("long"), 4 * k) for k in range(16)]
        total = terms[0]
        for t in terms[1:]:
            total = total.bitwiseOR(t)
        words.append(total.alias(f"s{w}"))
    return words


def same_values(left: str, right: str) -> Column:
    """How many of 16 short values two longs share."""
    x = F.col(left).bitwiseXOR(F.col(right))
    any_bit = x.bitwiseOR(F.shiftrightunsigned(x, 1)).bitwiseOR(F.shiftrightunsigned(x, 2)).bitwiseOR(F.shiftrightunsigned(x, 3))
    return 16 - F.bit_count(any_bit.bitwiseAND(F.lit(0x1111111111111111)))


def agreement(left: str, right: str) -> Column:
    """How many of the 64 short values two codes share."""
    total = same_values(f"{left}0", f"{right}0")
    for w in range(1, 4):
        total = total + same_values(f"{left}{w}", f"{right}{w}")
    return total


def likely(pairs: DataFrame, codes: DataFrame, agree: int) -> DataFrame:
    """Pairs (a, b) that share enough short values, with their number."""
    side = lambda k, p: codes.select(F.col("rep").alias(k), *[F.col(f"s{w}").alias(f"{p}{w}") for w in range(4)])
    both = pairs.join(side("a", "u"), "a").join(side("b", "v"), "b")
    return both.select("a", "b", agreement("u", "v").alias("agree")).filter(F.col("agree") >= agree)


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs whose full shingle sets reach the similarity."""
    left = pairs.select("a", "b").join(sets.select(F.col("rep").alias("b"), F.col("items").alias("ib")), "b")
    both = left.join(sets.select(F.col("rep").alias("a"), F.col("items").alias("ia")), "a")
    common = F.size(F.array_intersect("ia", "ib"))
    union = F.size("ia") + F.size("ib") - common
    return both.filter(common.cast("long") * 100 >= union.cast("long") * percent).select("a", "b")


def with_component(rows: DataFrame, comp: DataFrame | None) -> DataFrame:
    """``rows`` (rep, ...) with the component ``c`` that ``comp`` (id, component) names, else the number itself."""
    if comp is None:
        return rows.withColumn("c", F.col("rep"))
    return rows.join(comp.select(F.col("id").alias("rep"), "component"), "rep", "left").withColumn("c", F.coalesce("component", "rep")).drop("component")


@dataclass
class Search:
    """Texts, their classes, and what has been found out about them so far."""

    texts: DataFrame
    classes: DataFrame
    s: Scratch
    words_each: int
    percent: int
    broadcast_keys: int
    sets: DataFrame | None = None
    comp: DataFrame | None = None
    step: int = 0
    n_edges: int = 0

    @property
    def similarity(self) -> float:
        return self.percent / 100

    def close(self, pairs: DataFrame) -> DataFrame:
        """Pairs that may reach the similarity by their short values, written."""
        self.step += 1
        codes = self.classes.select("rep", *[f"s{w}" for w in range(4)])
        return self.s.save(likely(pairs, codes, short_agreement(self.similarity)), f"close-{self.step}")

    def need_sets(self, reps: DataFrame) -> None:
        """Read the texts again that the full sets of ``reps`` come from, but for sets that are there."""
        if self.sets is not None:
            reps = reps.join(self.sets.select("rep"), "rep", "left_anti")
        named = self.classes.select("rep", "key", "digest", "n").join(reps, "rep")
        wanted, seen = self.s.save_seen(named, f"wanted-{self.step}")
        if seen["n"]:
            chosen = keep_keys(self.texts, wanted, "key", seen["n"], self.broadcast_keys)
            sets = chosen.mapInArrow(tidied(shingle_sets(self.words_each)), "digest binary, n int, items array<long>").dropDuplicates(["digest", "n"])
            more = self.s.save(sets.join(wanted.select("rep", "digest", "n"), ["digest", "n"]).select("rep", "items"), f"sets-{self.step}")
            self.sets = more if self.sets is None else self.sets.union(more)

    def link(self, pairs: DataFrame) -> None:
        """Confirm pairs and let the components grow by them."""
        self.step += 1
        if self.sets is not None:
            edges, seen = self.s.save_seen(confirmed(pairs, self.sets, self.percent), f"edges-{self.step}")
            if seen["n"]:
                self.n_edges += seen["n"]
                self.comp = grown(self.comp, edges, self.n_edges, self.s, f"known-{self.step}")

    def with_component(self, rows: DataFrame) -> DataFrame:
        """``rows`` (rep, ...) with the component so far as ``c``."""
        return with_component(rows, self.comp)


def ends_of(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("a").alias("rep")).union(pairs.select("b")).distinct()


def contract_groups(q: Search, chosen: list[tuple[int, int]]) -> None:
    """Link the large nodes of a few roots through pivots, in two turns."""
    rows = root_nodes(q.classes.withColumn("c", F.col("rep")), chosen)
    large = rows.groupBy("node").agg(F.count("*").alias("size")).filter(F.col("size") > LEAF).select("node")
    hot, seen = q.s.save_seen(rows.join(large, "node").select("node", "rep", "n"), "hot")
    if not seen["n"]:
        return
    first = q.close(pivot_pairs(hot, q.percent))
    q.need_sets(ends_of(first))
    q.link(first)
    again = q.close(outsiders_with_pivots(named_members(q.s, q.with_component(hot), "named-0"), q.percent, 0))
    q.need_sets(ends_of(again))
    q.link(again)


def search_trees(q: Search, chosen: list[tuple[int, int]]) -> DataFrame | None:
    """Grow all trees and link what their leaves hold; gives the members of nodes that stayed large."""
    agree = short_agreement(q.similarity, 16)
    rows = root_nodes(q.with_component(q.classes), chosen)
    pairs, last = None, None
    for level in range(1, LEVELS + 1):
        members, seen = q.s.save_seen(live_members(rows), f"members-{level}", F.count_if(F.col("size") > LEAF).alias("big"))
        found = leaf_pairs(members, q.percent, agree)
        pairs = found if pairs is None else pairs.union(found)
        last = members.filter(F.col("size") > LEAF) if seen["big"] else None
        if last is None:
            break
        rows = child_nodes(last, q.classes, level, q.similarity)
    close = q.close(pairs.distinct())
    ids = ends_of(close)
    if last is not None:
        last = last.select("node", "rep", "n")
        ids = ids.union(last.select("rep")).distinct()
    q.need_sets(ids)
    best = close.groupBy("b").agg(F.max(F.struct("agree", (-F.col("a")).alias("m"))).alias("v")).select((-F.col("v.m")).alias("a"), "b")
    q.link(best)
    q.link(not_connected(close, q.comp))
    return last


def classify(docs: DataFrame, s: Scratch, words_each: int, percent: int, target_recall: float, broadcast_keys: int) -> DataFrame:
    """Every row with its set size ``n``, its component's number ``root`` and smallest id ``component_id``.

    ``mark`` is the MD5 of the text. Texts without a shingle have no root.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    texts = rows.select("doc_id", "text", F.xxhash64("doc_id", "text").alias("key"), F.unhex(F.md5(F.coalesce("text", F.lit("")))).alias("mark"))
    signed = s.save(texts.mapInArrow(tidied(sign(words_each)), SIGNED), "signed")
    merged = signed.filter("n > 0").groupBy("digest", "n").agg(F.min("doc_id").alias("least"), F.min("key").alias("key"), F.first("sig").alias("sig"))
    classes = s.save(merged.select(F.monotonically_increasing_id().alias("rep"), "n", "digest", "least", "key", "sig", *short_codes()), "classes")
    q = Search(rows.select("text", F.xxhash64("doc_id", "text").alias("key")), classes, s, words_each, percent, broadcast_keys)
    chosen = roots(trees_needed(q.similarity, target_recall), q.similarity)
    contract_groups(q, chosen[:HEADS])
    s.release()
    last = search_trees(q, chosen)
    if last is not None:
        s.release()
        join_the_rest(q, last)
    named = q.with_component(classes.select("digest", "n", "rep", "least"))
    if q.comp is not None:
        ends = q.comp.union(q.comp.select("component", "component").distinct())
        linked = classes.select(F.col("rep").alias("id"), "least").join(ends, "id").groupBy(F.col("component").alias("c")).agg(F.min("least").alias("smallest"))
        named = named.join(linked, "c", "left").withColumn("least", F.coalesce("smallest", "least"))
    out = signed.select("doc_id", "mark", "n", "digest").join(named.select("digest", "n", F.col("c").alias("root"), "least"), ["digest", "n"], "left")
    out = s.save(out.select("doc_id", "mark", "n", "root", F.when(F.col("root").isNull(), F.col("doc_id")).otherwise(F.col("least")).alias("component_id")), "classified", keep=True)
    s.drop_all()
    return out


def near_classes(
    docs: DataFrame,
    words_each: int = 5,
    percent: int = 80,
    target_recall: float = TARGET_RECALL,
    broadcast_keys: int = BROADCAST_KEYS,
) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (smallest id reachable), kept."""
    rows = classify(docs, Scratch(docs.sparkSession), words_each, percent, target_recall, broadcast_keys)
    return rows.select("doc_id", F.col("n").cast("long").alias("n_shingles"), "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def keep_one(docs: DataFrame, words_each: int = 5, percent: int = 80, target_recall: float = TARGET_RECALL, broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """The rows of ``docs`` without all but one of each component: the smallest id (then the smallest MD5) stays.

    Rows are told apart by id and text, so a shared or missing id costs no other text; rows that repeat
    the one that stays, id and text alike, stay with it.
    """
    s = Scratch(docs.sparkSession)
    rows = classify(docs, s, words_each, percent, target_recall, broadcast_keys).filter("root IS NOT NULL")
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "mark")
    stays = rows.groupBy("root").agg(F.min(place).alias("stays"), F.max(place).alias("other")).filter("stays <> other").select("root", "stays")
    lost = rows.join(stays, "root").filter(place != F.col("stays")).select(F.col("doc_id").alias("_id"), F.col("mark").alias("_mark")).distinct()
    lost, seen = s.save_seen(lost, "lost", keep=True)
    side = F.broadcast(lost) if seen["n"] <= broadcast_keys else lost.hint("merge")
    mark = F.unhex(F.md5(F.coalesce(F.col("text").cast("string"), F.lit(""))))
    return docs.join(side, F.col("doc_id").cast("long").eqNullSafe(F.col("_id")) & (mark == F.col("_mark")), "left_anti")


def not_connected(pairs: DataFrame, comp: DataFrame | None) -> DataFrame:
    """Pairs whose ends are in different components so far."""
    if comp is None:
        return pairs.select("a", "b")
    side = lambda k, out: comp.select(F.col("id").alias(k), F.col("component").alias(out))
    both = pairs.join(side("a", "ca"), "a", "left").join(side("b", "cb"), "b", "left")
    return both.filter(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b")


def join_the_rest(q: Search, last: DataFrame) -> None:
    """Links in nodes that stayed large: first to members of the node's largest component, then in full."""
    q.link(q.close(outsiders_with_pivots(named_members(q.s, q.with_component(last), "named-1"), q.percent, 1)))
    rare, common = item_kinds(q, last)
    named = named_members(q.s, q.with_component(last), "named-2")
    q.link(q.close(left_apart(named, common, q.percent).union(sharing_rare(rare, q.percent)).distinct()))


def named_members(s: Scratch, members: DataFrame, name: str) -> DataFrame:
    """(node, rep, n, c, top) in nodes of several components: ``members`` with the node's largest component."""
    named = s.save(members, name)
    per = named.groupBy("node", "c").agg(F.count("*").alias("m"))
    top = per.groupBy("node").agg(F.max(F.struct("m", "c")).alias("v"), F.count("*").alias("k")).filter("k > 1").select("node", F.col("v.c").alias("top"))
    return named.join(top, "node")


def outsiders_with_pivots(named: DataFrame, percent: int, turn: int) -> DataFrame:
    """Members outside their node's largest component, each once with a few members of every such component."""
    draw = F.xxhash64("rep", F.lit(turn))
    pivots = named.filter("c = top").groupBy("top", F.pmod(draw, F.lit(REST_PIVOTS)).alias("k")).agg(F.min(F.struct(draw.alias("d"), "rep", "n")).alias("v"))
    pivots = pivots.select("top", F.col("v.rep").alias("y"), F.col("v.n").alias("ny"))
    outside = named.filter("c <> top").select("top", F.col("rep").alias("x"), F.col("n").alias("nx")).distinct()
    return outside.join(pivots, "top").filter(like_sizes("nx", "ny", percent)).select(*ordered("x", "y")).distinct()


def item_kinds(q: Search, last: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rep, n, c, item) of the shingles that at most RARE members have, in several components, and a sketch of
    each member's shingles that more have.

    The sketch deals the other shingles out to BUCKETS buckets and writes each bucket's number in unary, up to
    UNARY bits; what goes beyond is summed up in ``over``.
    """
    members = q.with_component(last.select("rep", "n").distinct())
    items = q.s.save(members.join(q.sets, "rep").select("rep", "n", "c", F.explode("items").alias("item")), "items")
    few = items.groupBy("item").agg(F.count("*").alias("k"), F.min("c").alias("lo"), F.max("c").alias("hi")).filter(F.col("k") <= RARE)
    rare = q.s.save(items.join(few.filter("lo < hi").select("item"), "item").select("rep", "n", "c", "item"), "rare")
    per = items.join(few.select("item"), "item", "left_anti").groupBy("rep", F.pmod("item", F.lit(BUCKETS)).cast("int").alias("b")).agg(F.count("*").cast("int").alias("m"))
    each = 64 // UNARY
    ones = F.expr(f"shiftleft(shiftleft(1L, least(m, {UNARY})) - 1L, b % {each} * {UNARY})")
    words = [F.bit_or(F.when(F.floor(F.col("b") / each) == w, ones).otherwise(F.lit(0).cast("long"))).alias(f"u{w}") for w in range(BUCKETS // each)]
    return rare, q.s.save(per.groupBy("rep").agg(F.sum("m").alias("s"), F.sum(F.greatest(F.col("m") - UNARY, F.lit(0))).alias("over"), *words), "common")


def sharing_rare(rare: DataFrame, percent: int) -> DataFrame:
    """Pairs of members in different components that share a rare shingle (RARE members each at most)."""
    x = rare.select("item", F.col("rep").alias("x"), F.col("n").alias("nx"), F.col("c").alias("cx"))
    y = rare.select("item", F.col("rep").alias("y"), F.col("n").alias("ny"), F.col("c").alias("cy"))
    apart = (F.col("x") < F.col("y")) & (F.col("cx") != F.col("cy"))
    return x.join(y, "item").filter(apart & like_sizes("nx", "ny", percent)).select(*ordered("x", "y")).distinct()


def left_apart(named: DataFrame, common: DataFrame, percent: int) -> DataFrame:
    """Members outside the node's largest component with all others that they could be linked with.

    Two sets without a common rare shingle share, bucket by bucket, at most the smaller number of their others,
    which bounds their similarity exactly, and closely where copies were edited in different places; pairs
    with a common rare shingle are listed by it (``sharing_rare``).
    """
    rows = one_row_each(named, "node", "top").join(common, "rep").filter(F.col("s") * 100 >= F.col("n") * percent)
    named = rows.withColumn("v", F.explode("nodes")).select("*", "v.node", "v.top")
    words = [c for c in common.columns if c[0] == "u"]
    side = lambda k: named.select("node", *[F.col(c).alias(f"{c}{k}") for c in ("rep", "n", "c", "top", "over", *words)])
    shared = F.least("overx", "overy")
    for w in words:
        shared = shared + F.bit_count(F.col(f"{w}x").bitwiseAND(F.col(f"{w}y")))
    could = shared * 100 >= (F.col("nx") + F.col("ny") - shared) * percent
    outside = side("x").filter("cx <> topx")
    return outside.join(side("y"), "node").filter((F.col("cx") != F.col("cy")) & could).select(*ordered("repx", "repy")).distinct()


def query(spark, sf_dir: str) -> DataFrame:
    return near_classes(spark.read.parquet(f"{sf_dir}/documents.parquet"), words_each=3, percent=85)
