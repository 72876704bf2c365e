"""Exact copies, near copies, lines and windows against brute force, with nulls, empties, ties and clashing columns."""

import hashlib
import random

import pytest
from pyspark.sql import functions as F

from statewitness.llm import exact_dedup, line_dedup, near_dedup, substring_dedup
from statewitness.llm.components import components
from statewitness.llm.fingerprint_index import FingerprintIndex
from statewitness.llm.scratch import Scratch

EMPTY = "doc_id long, text string"


def frame(spark, texts, parts=3):
    """Texts by position, with columns whose names clash with those that operators use inside."""
    rows = [(k, t, "x", 1, "y") for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, keep_id string, n int, _t string").repartition(parts)


def vocabulary(seed, n=400):
    r = random.Random(seed)
    return ["".join(r.choice("abcdefghij") for _ in range(r.randint(2, 8))) for _ in range(n)]


def corpus(seed=3):
    r, words = random.Random(seed), vocabulary(seed)
    text = lambda n: " ".join(r.choice(words) for _ in range(n))
    base = [text(r.randint(40, 120)) for _ in range(25)]
    out = list(base) + [None, "", "   \n\t", "one", "one two", "One  TWO", "a b c", "a b c"]
    big = text(100)
    for k in range(60):  # a group of near copies that are partly linked
        ws = big.split()
        for _ in range(r.randint(0, 5)):
            ws[r.randrange(len(ws))] = r.choice(words)
        out.append(" ".join(ws))
    for b in base[:10]:
        ws = b.split()
        ws[5] = "changed"
        out += [b, b.replace(" ", "\n", 1), " ".join(ws)]
    out.append(" ".join([text(30), big[:300], text(30)]))
    out.append("w " * 3000)
    return out


# --- exact ------------------------------------------------------------------------------------------


def exact_brute(texts):
    import re

    norm = [re.sub(r"[ \t-\r]+", " ", t or "") for t in texts]
    groups = {}
    for k, t in enumerate(norm):
        groups.setdefault(t, []).append(k)
    return {k: (min(groups[t]), len(groups[t]), k == min(groups[t]), hashlib.sha256(t.encode()).hexdigest()) for k, t in enumerate(norm)}


@pytest.mark.parametrize("weak", [False, True])
@pytest.mark.parametrize("limit", [0, 1000])
def test_exact_groups(spark, weak, limit):
    texts = corpus()
    key = (lambda t: F.unhex(F.lpad(F.hex(F.length(t) % 2), 2, "0"))) if weak else exact_dedup.md5_key
    got = exact_dedup.exact_groups(frame(spark, texts), content_key=key, broadcast_keys=limit).collect()
    assert {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for r in got} == exact_brute(texts)


def test_exact_repeated_rows_and_empty_table(spark):
    got = exact_dedup.exact_groups(spark.createDataFrame([(1, "a"), (1, "a"), (None, "a"), (None, "z")], EMPTY)).collect()
    assert sorted((r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in got if r["doc_id"]) == [(1, 1, 3, True)] * 2
    assert exact_dedup.exact_groups(spark.createDataFrame([], EMPTY)).count() == 0


# --- near -------------------------------------------------------------------------------------------


def components_of(n, links):
    parent = list(range(n))

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return [find(k) for k in range(n)]


def near_brute(texts, words_each, percent):
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[k : k + words_each]) for k in range(len(w) - words_each + 1)} if len(w) >= words_each else ({tuple(w)} if w else set()))
    links = [(a, b) for a in range(len(sets)) for b in range(a) if sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    return sets, components_of(len(texts), links)


@pytest.mark.parametrize(("words_each", "percent"), [(3, 85), (5, 80)])
def test_near_classes(spark, words_each, percent, monkeypatch):
    monkeypatch.setattr(near_dedup, "LEAF", 6)  # so that large nodes, pivots and the rest are met
    texts = corpus()
    got = near_dedup.near_classes(frame(spark, texts), words_each, percent, broadcast_keys=0 if percent == 80 else 10**6).collect()
    sets, comp = near_brute(texts, words_each, percent)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in got} == {k: (len(sets[k]), comp[k], comp[k] == k) for k in range(len(texts))}


def test_near_edge_cases(spark):
    assert near_dedup.near_classes(spark.createDataFrame([], EMPTY)).count() == 0
    got = near_dedup.near_classes(spark.createDataFrame([(4, "a b"), (4, "a b"), (9, "A B"), (None, "a b"), (2, None)], EMPTY)).collect()
    assert sorted(((r["doc_id"], r["component_id"], r["kept"]) for r in got), key=str) == [(2, 2, True), (4, 4, True), (4, 4, True), (9, 4, False), (None, 4, False)]
    got = near_dedup.near_classes(spark.createDataFrame([(5, "a b"), (5, "c d"), (None, "c d"), (None, "e"), (None, None)], EMPTY)).collect()  # one id, two texts
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in got), key=str) == [(5, 1, 5, True), (5, 1, 5, True), (None, 0, None, True), (None, 1, 5, False), (None, 1, None, True)]


def test_components_of_chains_and_hubs(spark):
    r = random.Random(5)
    edges = [(k, k + 1) for k in range(40)] + [(100, k) for k in range(101, 160)] + [(r.randrange(200, 260), r.randrange(200, 260)) for _ in range(50)] + [(300, 300)]
    want = components_of(400, edges)
    with Scratch(spark) as s:
        got = {x["id"]: x["component"] for x in components(spark.createDataFrame(edges, "a long, b long"), s, "t").collect()}
        assert components(spark.createDataFrame([], "a long, b long"), s, "none").count() == 0
    assert got == {k: want[k] for e in edges for k in e if want[k] != k}


# --- windows ----------------------------------------------------------------------------------------


def windows_brute(texts, window):
    words = [(t or "").encode().split() for t in texts]
    seen = {}
    for w in words:
        for k in range(len(w) - window + 1):
            seen[tuple(w[k : k + window])] = seen.get(tuple(w[k : k + window]), 0) + 1
    out = []
    for w in words:
        gone = set()
        for k in range(len(w) - window + 1):
            if seen[tuple(w[k : k + window])] > 1:
                gone.update(range(k, k + window))
        out.append((len(w), len(gone), hashlib.sha256(b" ".join(x for k, x in enumerate(w) if k not in gone)).hexdigest()))
    return out


@pytest.mark.parametrize(("window", "gram", "batches", "limit"), [(35, 8, 2, 10**6), (10, 4, 3, 0)])
def test_repeated_windows(spark, window, gram, batches, limit):
    texts = corpus(7)
    got = substring_dedup.remove_repeats(frame(spark, texts), window, gram, batches, limit).collect()
    want = windows_brute(texts, window)
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got} == dict(enumerate(want))


def test_windows_edge_cases(spark):
    assert substring_dedup.remove_repeats(spark.createDataFrame([], EMPTY)).count() == 0
    long = " ".join(f"w{k}" for k in range(50))
    got = substring_dedup.remove_repeats(spark.createDataFrame([(1, long), (1, long), (2, "x")], EMPTY)).collect()
    assert sorted((r["doc_id"], r["n_words"], r["n_removed"]) for r in got) == [(1, 50, 50), (1, 50, 50), (2, 1, 0)]


def test_batches_meet_the_index(spark):
    """The last of three batches is cleaned as in one run over all of them; ids may be shared or missing."""
    texts = corpus(9)
    rows = [(None if k % 17 == 0 else k % 40, t, k % 3) for k, t in enumerate(texts)]
    want = [(d, *w) for (d, _, b), w in zip(rows, windows_brute(texts, 12)) if b == 2]
    with Scratch(spark) as s:
        index = FingerprintIndex(spark, s.path("kept"), buckets=4)
        for b in range(3):
            got = substring_dedup.ingest(spark.createDataFrame([r[:2] for r in rows if r[2] == b], EMPTY), index, 12).collect()
        assert sorted(map(str, map(tuple, got))) == sorted(map(str, want)) and len(index.runs) == 1
        index.close()


def test_index_runs_merge_and_compact(spark):
    with Scratch(spark) as s:
        index = FingerprintIndex(spark, s.path("index"), buckets=4)
        for batch in ([(1, 1), (2, 5)], [(2, 1), (3, 1)], [(1, 2)]):
            index.ingest(spark.createDataFrame(batch, "g long, n long"))
        want = [(1, 3), (2, 6), (3, 1)]
        assert sorted(map(tuple, index.counts().collect())) == want
        index.compact()
        assert len(index.runs) == 1 and sorted(map(tuple, index.counts().collect())) == want
        assert [tuple(r) for r in index.known(spark.createDataFrame([(2,), (9,)], "g long")).collect()] == [(2, 6)]
        index.close()


# --- lines ------------------------------------------------------------------------------------------


def lines_brute(texts, percent=80):
    lines = [(d, k, x, x.strip(" \t\r\x0b\x0c").lower()) for d, t in enumerate(texts) for k, x in enumerate((t or "").split("\n") if t else [])]
    kinds = list(dict.fromkeys(n for *_, n in lines if n))
    sets = [{n[j : j + 5] for j in range(len(n) - 4)} if len(n) >= 5 else {n} for n in kinds]
    links = [(a, b) for a in range(len(sets)) for b in range(a) if 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    comp = dict(zip(kinds, components_of(len(kinds), links)))
    seen, out = set(), [[0, []] for _ in texts]
    for d, _, raw, n in lines:
        if n and comp[n] in seen:
            out[d][0] += 1
        else:
            seen.add(comp.get(n))
            out[d][1].append(raw)
    return [(len((t or "").split("\n")) if t else 0, gone, hashlib.sha256("\n".join(kept).encode()).hexdigest()) for t, (gone, kept) in zip(texts, out)]


def test_fuzzy_lines(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "LEAF", 5)
    r, words = random.Random(11), vocabulary(11)
    line = lambda n: " ".join(r.choice(words) for _ in range(n))
    pool = [line(r.randint(1, 40)) for _ in range(30)]
    texts: list = []
    for _ in range(40):
        rows = [line(20)]
        for _ in range(4):
            p = r.choice(pool)
            rows.append(p if r.random() < 0.5 else p + " " + r.choice(["x", "yz", words[0]]) if r.random() < 0.5 else p.upper())
        texts.append("\n".join(rows) + ("\n\n" if r.random() < 0.3 else ""))
    texts += [None, "", "\n", "  ", "same\nsame"]
    got = line_dedup.dedup_lines(frame(spark, texts)).collect()
    assert {x["doc_id"]: (x["n_lines"], x["n_removed"], x["kept_sha256"]) for x in got} == dict(enumerate(lines_brute(texts)))
    assert line_dedup.dedup_lines(spark.createDataFrame([], EMPTY)).count() == 0


def test_lines_without_blanks(spark):
    """Solid, Chinese and tab-separated lines that differ in one character, and documents told apart by id and text."""
    r, han = random.Random(5), [chr(0x4E00 + k) for k in range(2000)]
    solid = lambda n, of="abcdefghijklmnopqrstuvwxyz0123456789": "".join(r.choice(of) for _ in range(n))
    texts = []
    for _ in range(20):
        for line in (solid(120), solid(120, han), "\t".join(solid(20) for _ in range(6)), " ".join(solid(14) for _ in range(9))):
            k = r.randrange(8, 100)
            texts += [line, line[:k] + "-" + line[k + 1 :]]
    r.shuffle(texts)
    got = line_dedup.dedup_lines(frame(spark, texts)).collect()
    want = lines_brute(texts)
    assert {x["doc_id"]: (x["n_lines"], x["n_removed"], x["kept_sha256"]) for x in got} == dict(enumerate(want)) and sum(w[1] for w in want) > 60
    same = "some line that repeats itself here"
    rows = [(2**45 + 7, same + "\nother"), (7, same), (1, "a first text"), (1, "a first text"), (1, "yet another line"), (None, same + "\nits own"), (None, None)]
    got = sorted(((x["doc_id"], x["n_lines"], x["n_removed"]) for x in line_dedup.dedup_lines(spark.createDataFrame(rows, EMPTY)).collect()), key=str)
    assert got == sorted([(2**45 + 7, 2, 1), (7, 1, 0), (1, 1, 0), (1, 1, 0), (1, 1, 0), (None, 2, 1), (None, 0, 0)], key=str)


def test_edited_copies_of_one_line(spark):
    """A hot group at the default leaf size: pairs that are not alike to a pivot, also outside the largest component."""
    r, words = random.Random(17), vocabulary(17)
    line = lambda n: " ".join(r.choice(words) for _ in range(n))
    base, head = line(24), line(14)

    def edited(text, n):
        out = list(text)
        for _ in range(n):
            out[r.randrange(len(out))] = r.choice("klmnopqrstuvwxyz")
        return "".join(out)

    lines = [edited(base, r.randint(2, 4)) for _ in range(500)]
    for _ in range(40):  # one hot head, and tails of which two each are alike
        tail = line(12)
        lines += [f"{head} {tail}", f"{head} {edited(tail, 3)}"]
    r.shuffle(lines)
    texts = ["\n".join(lines[k : k + 10]) for k in range(0, len(lines), 10)]
    got = line_dedup.dedup_lines(frame(spark, texts)).collect()
    assert {x["doc_id"]: (x["n_lines"], x["n_removed"], x["kept_sha256"]) for x in got} == dict(enumerate(lines_brute(texts)))


@pytest.mark.parametrize("length", [100, 160, 320, 700])
def test_bands_of_pairs_at_the_threshold(spark, length):
    r, words = random.Random(length), vocabulary(5)
    grams = lambda x: {x[k : k + 5] for k in range(len(x) - 4)}
    pairs = []
    while len(pairs) < 1000:
        old = " ".join(r.choice(words) for _ in range(length))[:length].strip()
        new = list(old)
        for _ in range(length):
            new[r.randrange(len(new))] = r.choice("klmnopqrst")
            x, y = grams(old), grams("".join(new))
            if len(x & y) <= 0.85 * len(x | y):
                break
        if len(x & y) >= 0.8 * len(x | y):
            pairs.append((old, "".join(new)))
    rows = spark.createDataFrame(pairs, "a string, b string")
    shared = F.arrays_overlap(line_dedup.bottom_keys(F.col("a")), line_dedup.bottom_keys(F.col("b")))
    assert rows.filter(~shared).count() <= 2


def test_rest_of_large_bands_carries_few_values_a_line(spark):
    """The rest of a large band holds at most SKETCH values of a line, whatever its length, and loses no pair of a node."""
    r, words = random.Random(23), vocabulary(23)
    line = lambda n: " ".join(r.choice(words) for _ in range(n))
    rows = ["abc", "abcdefghij \U0001f600\U0001f601\U0001f600", "ab" * 40]
    for n in (3, 5, 9, 90, 120):
        for _ in range(6):
            old = line(n)
            rows += [old, old[: len(old) // 2] + "#" + old[len(old) // 2 + 1 :]]
    rows = list(dict.fromkeys(rows))
    sets = [{x[k : k + 5] for k in range(len(x) - 4)} if len(x) >= 5 else {x} for x in rows]
    lines = spark.createDataFrame(list(enumerate(rows)), "rep long, line string").withColumn("g", line_dedup.grams(F.col("line")))
    texts = lines.select("rep", "line", F.size("g").alias("size"), F.slice(F.sort_array("g"), 1, line_dedup.SKETCH).alias("low"))
    assert {x["rep"]: x["size"] for x in texts.collect()} == dict(enumerate(map(len, sets)))
    named = texts.select(F.lit(7).cast("long").alias("node"), "rep", F.col("size").alias("n"), F.col("rep").alias("c"))
    near = {(a, b) for b in range(len(sets)) for a in range(b) if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])}
    with Scratch(spark) as s:
        items = s.save(line_dedup.ranked_grams(named, texts), "items")
        assert max(len(x["items"]) for x in items.collect()) == line_dedup.SKETCH < max(map(len, sets))
        pairs = line_dedup.sharing_prefix(s, named, items, 80)
        listed = {(x["a"], x["b"]) for x in pairs.collect()}
        assert len(near) >= 12 and near <= listed
        some = line_dedup.like_sized(pairs.withColumn("hits", F.lit(1)), texts, 80)
        assert {(x["a"], x["b"]) for x in line_dedup.confirmed(some, texts, 80).collect()} == near
        apart = named.withColumn("node", F.col("rep"))
        assert line_dedup.sharing_prefix(s, apart, items, 80).count() == 0


def test_rest_of_large_bands_lists_few_unlike_pairs(spark):
    """Lines of one language that share a band, but are not alike, are hardly listed; alike ones of other lengths are."""
    r = random.Random(31)
    parts = r.sample([a + b + c for a in "bdfghklmnprst" for b in "aeiou" for c in ("", "n")], 60)
    words = [r.choice(parts) + r.choice(parts) for _ in range(150)]
    line = lambda n: " ".join(r.choice(words) for _ in range(n))
    rows = [line(30) for _ in range(120)]
    for _ in range(20):
        old = line(r.randint(30, 40))
        rows += [old, old + " " + line(r.randint(1, 4))]
    sets = [{x[k : k + 5] for k in range(len(x) - 4)} for x in rows]
    lines = spark.createDataFrame(list(enumerate(rows)), "rep long, line string").withColumn("g", line_dedup.grams(F.col("line")))
    texts = lines.select("rep", "line", F.size("g").alias("size"), F.slice(F.sort_array("g"), 1, line_dedup.SKETCH).alias("low"))
    named = texts.select(F.lit(7).cast("long").alias("node"), "rep", F.col("size").alias("n"), F.col("rep").alias("c"))
    with Scratch(spark) as s:
        listed = {(x["a"], x["b"]) for x in line_dedup.sharing_prefix(s, named, line_dedup.ranked_grams(named, texts), 80).collect()}
    alike = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for b in range(len(sets)) for a in range(b)}
    assert {k for k, v in alike.items() if v >= 0.8} <= listed and sum(v >= 0.8 for v in alike.values()) >= 15
    assert len(listed) < 0.03 * len(alike)


def test_rest_of_a_large_group_lists_only_what_is_apart(spark):
    """Shingles that one component has, or one text, list no pair; a class meets its sketch once, whatever its nodes."""
    items = lambda rep: {1: [1, 2, 9], 2: [1, 2, 9], 3: [1, 5, 7], 4: [5, 8, 9]}[rep]
    with Scratch(spark) as s:
        q = near_dedup.Search(None, None, s, 3, 10, 0)
        q.sets = spark.createDataFrame([(k, items(k)) for k in (1, 2, 3, 4)], "rep long, items array<long>")
        q.comp = spark.createDataFrame([(2, 1)], "id long, component long")
        last = spark.createDataFrame([(n, k, 3) for n in (10, 11, 12) for k in (1, 2, 3, 4)], "node long, rep long, n int")
        rare, _ = near_dedup.item_kinds(q, last)
        assert sorted((r["rep"], r["item"]) for r in rare.collect()) == [(1, 1), (1, 9), (2, 1), (2, 9), (3, 1), (3, 5), (4, 5), (4, 9)]
        assert sorted(map(tuple, near_dedup.sharing_rare(rare, 10).collect())) == [(1, 3), (1, 4), (2, 3), (2, 4), (3, 4)]
        each = near_dedup.one_row_each(last, "node").collect()
    assert sorted((r["rep"], sorted(r["nodes"])) for r in each) == [(k, [10, 11, 12]) for k in (1, 2, 3, 4)]
