"""Quality rules, packing, decontamination, URL trust, sharding, archives and the pipeline."""

import random
import zlib

import numpy as np
import pytest

from statewitness.llm import decontaminate, entries, packing, quality, sharding, url_trust, web_archive
from statewitness.llm.scratch import Scratch

SF = "/root/testdata/sf0.001"
EMPTY = "doc_id long, text string"


# --- quality ----------------------------------------------------------------------------------------


def test_quality_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.01"
    rows = quality.query(spark, sf).toPandas()
    labels = spark.read.parquet(f"{sf}/labels.parquet").toPandas()
    both = rows.merge(labels, on="doc_id")
    held = both[both["held_out"]]
    assert all((zlib.crc32(str(d).encode()) % 4 == 2) == h for d, h in zip(rows["doc_id"], rows["held_out"]))
    assert (held["predicted"] == held["quality"]).mean() > 0.95
    assert rows["score"].between(0, 1).all()


def test_quality_columns_equal_the_model(spark):
    r = np.random.default_rng(1)
    x = r.random((600, len(quality.FEATURES)))
    y = ((x[:, 2] > 0.6) & (x[:, 4] < 0.5)).astype(float)
    model = quality.fit(x, y)
    assert (np.abs((model.scores(x) > 0.5) - y)).mean() < 0.05 and len(model.rules) < 120
    rows = spark.createDataFrame(x[:50].tolist(), ", ".join(f"f_{k} double" for k in quality.FEATURES))
    assert np.allclose([v[0] for v in rows.select(model.column()).collect()], model.scores(x[:50]))


def test_quality_without_labels_or_text(spark):
    docs = spark.createDataFrame([(1, None, 5), (2, "", 6), (2, "", 6)], "doc_id long, text string, n int")
    none = quality.train(docs, spark.createDataFrame([], "doc_id long, quality int"))
    assert [r["score"] for r in quality.score(docs, none).collect()] == pytest.approx([0.5] * 3)
    one = quality.train(docs, spark.createDataFrame([(1, 1), (2, None)], "doc_id long, quality int"))
    assert quality.keep_good(docs, one).columns == docs.columns
    assert quality.score(spark.createDataFrame([], EMPTY), one).count() == 0
    lost = spark.createDataFrame([(None, "x", 1.0)], "doc_id long, text string, f_chars double")
    assert [(r["doc_id"], r["held_out"], r["predicted"] in (0, 1)) for r in quality.score(lost, one).collect()] == [(None, False, True)]


def test_quality_statistics_against_patterns():
    import pyarrow as pa
    import regex

    def slow(t):
        ws = regex.split(r"[\x20\x09-\x0D]+", regex.sub(r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "", t or ""))
        t, w, n = t or "", len(ws), len(t or "")
        count = lambda p: len(regex.findall(p, t))
        letters, distinct = count(r"\p{L}"), len(set(ws))
        short = count(r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D]{1,3}(?![^\x20\x09-\x0D])")
        stops = count(r"\p{L}[.?](?=[\x20\x09-\x0D]|\Z)")
        return [n, w, count(r"\p{Lu}") / max(letters, 1), letters / max(n, 1), count(r"[#$%&*|@^~<>=_+\\/{}\[\]]") / max(n, 1), t.count("!") / w, count("[0-9]") / max(n, 1), n / w, w / (t.count("\n") + 1), w / (stops + 1), short / w, distinct / w, distinct / w**0.5]

    texts = ["", None, "Hello World! a.b? Ça É. ß Ω x?\nyes. No", "   ", "a", "日本語 テスト. 12# é.", "\U0001F600 𝐀b. z?", "x.\n\nY! " * 9]
    assert np.allclose(quality.statistics(pa.array(texts)), [slow(t) for t in texts])


# --- packing ----------------------------------------------------------------------------------------


@pytest.mark.parametrize("letters", ["".join(map(chr, range(33, 127))), "'stdmlrve.,-0É<|>", "".join(map(chr, range(0xA1, 0x100))) + "ab'", "Àþÿß×÷s9a\u0301\u0130\u03a3\u03c2中 .,\u00a0"])
def test_words_are_cut_as_the_tokenizer_cuts(letters):
    words, r = packing.WordIds(packing.word_tokenizer(), 1000), random.Random(5)
    assert words.short
    for _ in range(4000):
        text = "".join(r.choices(letters, k=r.randint(1, 14)))
        ids = words.tokenizer.encode(text, add_special_tokens=False).ids
        assert words.encode(text) == np.array(ids, "<u4").tobytes(), text


def test_packing_round_trip(spark):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.word_tokenizer())
    texts = ["a b, c.", None, "", "Hello, it's <|endoftext|> me. É", "word " * 700, "x\x1cy z", "tail. " * 333]
    docs = spark.createDataFrame([(k, t, "e") for k, t in enumerate(texts)], "doc_id long, text string, length string").repartition(3)
    got = packing.pack(docs, packing.word_tokenizer(), capacity=256).toPandas()
    for k, t in enumerate(texts):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        mine = got[got["doc_id"] == k].sort_values("piece")
        assert mine["length"].sum() == len(ids) and (mine["length"].iloc[:-1] == 256).all()
        for r in mine.itertuples():
            assert zlib.crc32(ids[r.start : r.start + r.length].tobytes()) == r.ids_crc32
    for _, seq in got.groupby("sequence_id"):
        seq = seq.sort_values("offset")
        assert seq["length"].sum() <= 256 and (seq["offset"].to_numpy() == np.r_[0, seq["length"].cumsum().to_numpy()[:-1]]).all()
    assert packing.pack(spark.createDataFrame([], EMPTY), packing.word_tokenizer()).count() == 0


def best_bins(items, capacity):
    best = [len(items)]

    def go(k, bins):
        if len(bins) >= best[0]:
            return
        if k == len(items):
            best[0] = len(bins)
            return
        for i in range(len(bins)):
            if bins[i] + items[k] <= capacity:
                bins[i] += items[k]
                go(k + 1, bins)
                bins[i] -= items[k]
        bins.append(items[k])
        go(k + 1, bins)
        bins.pop()

    go(0, [])
    return best[0]


@pytest.mark.parametrize("seed", range(12))
def test_bin_completion_is_optimal_on_small_cases(seed):
    r = random.Random(seed)
    items = sorted((r.randint(1, 30) for _ in range(11)), reverse=True)
    counts = np.bincount(items, minlength=41)
    plan = packing.bin_completion(counts, 40)
    used = np.zeros(41, int)
    for pattern, m in plan.patterns:
        assert sum(pattern) <= 40
        for x in pattern:
            used[x] += m
    assert (used == counts).all() and plan.lower_bound <= plan.bins == best_bins(items, 40)


# --- decontamination --------------------------------------------------------------------------------


def test_leaks_planted_and_edited(spark):
    r = random.Random(2)
    words = ["".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7))) for _ in range(500)]
    text = lambda n: " ".join(r.choice(words) for _ in range(n))
    items = [text(30) for _ in range(6)] + [None, "", "too short"]
    edited = items[1].split()
    for k in (6, 13, 20):
        edited[k] = "changed"
    edited.insert(25, "more")
    docs = [text(80) + " " + items[0] + " " + text(50), text(40) + " " + " ".join(edited), text(200), None, "", items[2].upper(), " ".join(items[3].split()[:8]) + " " + text(50)]
    frame = spark.createDataFrame([(k, t, 1) for k, t in enumerate(docs)], "doc_id long, text string, score int")
    bench = spark.createDataFrame([(k, t) for k, t in enumerate(items)], "item_id long, text string")
    for block in (decontaminate.BLOCK_BYTES, 300):
        got = decontaminate.find_leaks(frame, bench, block_bytes=block).collect()
        assert sorted((x["doc_id"], x["item_id"]) for x in got) == [(0, 0), (1, 1), (5, 2)]
    whole = next(x for x in got if x["doc_id"] == 0)
    assert (whole["score"], whole["start_word"], whole["end_word"]) == (1.0, 80, 110)
    assert decontaminate.find_leaks(frame, spark.createDataFrame([], "item_id long, text string")).count() == 0
    assert decontaminate.find_leaks(spark.createDataFrame([], EMPTY), bench).count() == 0


def test_edited_copies_of_a_common_item(spark):
    """Every edited copy that scores at the threshold is found, also of an item that a third of documents carry."""
    r = random.Random(8)
    words = [f"w{k}" for k in range(900)]
    item = [r.choice(words) for _ in range(36)]
    docs = [" ".join(item)] * 300
    docs += [" ".join("x" if k % 4 == shift else x for k, x in enumerate(item)) for shift in range(4)]
    docs += [" ".join("x" if k % 3 == shift else x for k, x in enumerate(item)) for shift in range(3)]
    docs += [" ".join(f"e{r.random()}" if r.random() < share else x for x in item) for share in (0.2, 0.3) for _ in range(150)]
    frame = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    bench = spark.createDataFrame([(1, " ".join(item))], "item_id long, text string")
    code = {x: k for k, x in enumerate(dict.fromkeys(" ".join(docs).split()))}
    numbers = lambda t: np.array([code[x] for x in t])
    want = [k for k, t in enumerate(docs) if decontaminate.local_alignment(numbers(item), numbers(t.split()))[0] >= 36]
    assert sorted(x["doc_id"] for x in decontaminate.find_leaks(frame, bench).collect()) == want


def test_local_alignment_against_plain_recursion():
    r = random.Random(4)
    for _ in range(30):
        a, b = ([r.randint(0, 5) for _ in range(r.randint(1, 9))] for _ in range(2))
        h = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a)):
            for j in range(len(b)):
                h[i + 1][j + 1] = max(0, h[i][j] + (2 if a[i] == b[j] else -1), h[i][j + 1] - 1, h[i + 1][j] - 1)
        assert decontaminate.local_alignment(np.array(a), np.array(b))[0] == max(map(max, h))


# --- urls -------------------------------------------------------------------------------------------


def page(spark, rows):
    return spark.createDataFrame([(k, u, h, "z") for k, (u, h) in enumerate(rows)], "page_id long, url string, html string, host string")


def link(*hosts):
    return " ".join(f'<a href="https://{h}/x">t</a>' for h in hosts)


def test_rules_and_hosts(spark):
    rows = [("http://Example.ORG/es/a", None), ("http://a.example.org/en/12", ""), ("http://example.org?x", None), ("x://badexample.org/es/", None), (None, None), ("no scheme", None), ("http://b.com/de/q#f", None), ("http://b.com/fr", None), ("http://b.com/fr/", None)]
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_trust.filter_urls(page(spark, rows)).collect()}
    assert got[0] == ("example.org", "/es/a", "example.org/es/", "block") and got[1] == ("a.example.org", "/en/12", "example.org/en/1", "block")
    assert got[2] == ("example.org", "", None, "block") and got[3] == ("badexample.org", "/es/", "org/", "allow")
    assert got[4] == got[5] == ("", "", None, "allow")
    # no rule fits pages 2 and 7: half of the first's host is blocked, the second's host is as much allowed as blocked
    assert got[6][2:] == ("com/de/", "block") and got[7][2:] == (None, "allow") and got[8][2:] == ("com/fr/", "allow")
    assert url_trust.filter_urls(page(spark, rows).limit(0)).count() == 0


def test_trust_and_distrust_against_power_iteration(spark):
    rules = (url_trust.Rule("good.example", "/", "allow"), url_trust.Rule("bad.example", "/", "block"))
    graph = {"good.example": ["a.example", "b.example"], "a.example": ["b.example"], "farm.example": ["bad.example", "bad.example", "a.example"], "b.example": ["good.example"], "bad.example": ["farm.example"], "lone.example": []}
    pages = page(spark, [(f"http://{h}/", link(*out)) for h, out in graph.items()])
    hosts = sorted(set(graph) | {x for o in graph.values() for x in o})

    def rank(edges, seed):
        w = {h: {} for h in hosts}
        for a, b in edges:
            w[a][b] = w[a].get(b, 0) + 1
        now = {h: float(h == seed) for h in hosts}
        for _ in range(200):
            got = dict.fromkeys(hosts, 0.0)
            for a in hosts:
                for b, n in w[a].items():
                    got[b] += now[a] * n / sum(w[a].values())
            back = 1 - 0.85 * sum(got.values())
            now = {h: 0.85 * got[h] + (back if h == seed else 0) for h in hosts}
        return now

    links = [(a, b) for a, o in graph.items() for b in o]
    want = {"trust": rank(links, "good.example"), "distrust": rank([(b, a) for a, b in links], "bad.example")}
    with Scratch(spark) as s:
        edges = s.save(url_trust.host_edges(pages), "e")
        seed = url_trust.seeds(pages, edges, rules)
        got = {(r["kind"], r["host"]): r["rank"] for r in url_trust.spread(s, edges, seed, 0.85, 200, 1e-9).collect()}
    for (kind, host), value in got.items():
        assert value == pytest.approx(want[kind][host], abs=1e-5)
    verdicts = {r["host"]: r["verdict"] for r in url_trust.filter_urls(pages, rules).collect()}
    assert verdicts["farm.example"] == "block" and verdicts["a.example"] == "allow" and verdicts["lone.example"] == "allow"


def test_unruled_pages_follow_their_hosts(spark):
    """Hosts are seeds by the share of their pages; who links to a blocked host shares in its distrust."""
    rules = (url_trust.Rule("example", "/no/", "block"), url_trust.Rule("example", "/yes/", "allow"))
    rows = [("http://a.example/no/1", None), ("http://a.example/no/2", None), ("http://a.example/yes/1", None), ("http://a.example/x", None)]
    rows += [("http://b.example/no/1", None), ("http://b.example/yes/1", None), ("http://b.example/yes/2", None), ("http://b.example/x", None)]
    rows += [("http://far.net/x", link("a.example")), ("http://near.net/x", link("b.example")), ("http://lone.net/x", None)]
    got = {r["page_id"]: r["verdict"] for r in url_trust.filter_urls(page(spark, rows), rules).collect()}
    assert [got[k] for k in (3, 7, 10)] == ["block", "allow", "allow"] and got[8] == "block"
    assert [got[k] for k in (0, 2, 4, 5)] == ["block", "allow", "block", "allow"]


# --- sharding ---------------------------------------------------------------------------------------


def test_table_is_even_and_stable():
    names = tuple(f"s{k}" for k in range(10))
    full, less = sharding.lookup_table(names, 1009), sharding.lookup_table(names[:-1], 1009)
    sizes = np.bincount(full)
    assert sizes.max() - sizes.min() <= 1
    stayed = full != 9
    assert (full[stayed] == less[stayed]).mean() > 0.75
    for bad in ((), ("a", "a")):
        with pytest.raises(ValueError):
            sharding.lookup_table(bad, 1009)
    with pytest.raises(ValueError):
        sharding.lookup_table(("a",), 10)


def test_placement(spark, tmp_path):
    docs = spark.createDataFrame([(1, "x"), (1, "y"), (None, "z"), (77, "w")], "doc_id long, text string")
    rows = sharding.place(docs, shards=("a", "b", "c"), slots=101).collect()
    table = sharding.lookup_table(("a", "b", "c"), 101)
    assert len(rows) == 4 and all(table[r["slot"]] == r["shard"] for r in rows)
    assert len({r["shard"] for r in rows if r["doc_id"] == 1}) == 1
    assert sharding.place(docs.limit(0)).count() == 0
    clash = sharding.place(docs.selectExpr("doc_id", "text AS shard", "'q' AS slot"), shards=("a", "b", "c"), slots=101)
    assert clash.columns.count("shard") == clash.columns.count("slot") == 1 and all(table[r["slot"]] == r["shard"] for r in clash.collect())
    sharding.write_shards(docs, str(tmp_path / "out"), shards=("a", "b", "c"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 4


# --- archives ---------------------------------------------------------------------------------------


@pytest.mark.parametrize("version", [1, 2])
def test_archives(spark, version):
    rows = [(1, "http://a/", "same é\r\n\r\nWARC/1.1"), (2, "http://b c/", "same é\r\n\r\nWARC/1.1"), (5, None, None), (7, "u", ""), (3, "http://d/", "other\n"), (9, "http://a/", "same é\r\n\r\nWARC/1.1")]
    pages = spark.createDataFrame([(*r, "q") for r in rows], "page_id long, url string, html string, value string").repartition(2)
    got = {r["page_id"]: r for r in web_archive.archive_report(pages, version=version, per_file=2).collect()}
    for k, _, html in rows:
        raw = (html or "").encode()
        assert (got[k]["payload_bytes"], got[k]["payload_digest"]) == (len(raw), web_archive.sha1_32(raw))
    assert {k: r["refers_to"] for k, r in got.items()} == {1: 9, 2: 9, 9: None, 5: 7, 7: None, 3: None}
    assert {k for k, r in got.items() if r["record_type"] == "revisit"} == {1, 2, 5}
    large = {r["page_id"]: r["record_type"] for r in web_archive.archive_report(pages, min_bytes=1).collect()}
    assert large[5] == large[7] == "response" and large[1] == "revisit"
    assert web_archive.archive_report(pages.limit(0)).count() == 0


def test_archives_without_ids_and_with_long_pages(spark):
    rows = [(None, "u", "same"), (4, "u", "same"), (None, "v" * 5000, "alone"), (None, "v", "alone"), (8, "w", "x" * 3_000_000), (8, "w", "x" * 3_000_000)]
    got = sorted(((r["page_id"], r["payload_bytes"], r["record_type"], r["refers_to"]) for r in web_archive.archive_report(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()), key=str)
    assert got == sorted([(None, 4, "revisit", 4), (4, 4, "response", None), *[(None, 5, "response", None)] * 2, *[(8, 3_000_000, "response", None)] * 2], key=str)
    assert web_archive.records_per_file(40_000_000) == 1 and web_archive.records_per_file(None) == 2000


def test_converter_on_bytes():
    raw = (web_archive.arc_version_block(1, "f.arc", "20240101000000") + web_archive.arc_record(1, "f.arc", "http://a/", "20240203040506", 4, "<p>é</p>") + "\n").encode()
    (record,) = web_archive.parse_arc(raw)
    out = web_archive.convert(record, None)
    assert b"WARC-Date: 2024-02-03T04:05:06Z" in out and web_archive.convert(record, None) == out
    (headers, block), = web_archive.parse_warc(out + b"\r\n\r\n")
    assert headers["warc-type"] == "response" and block == record.content
    revisit = web_archive.convert(record, 9)
    (headers, block), = web_archive.parse_warc(revisit + b"\r\n\r\n")
    assert headers["warc-refers-to"] == web_archive.record_id(9, web_archive.sha1_32("<p>é</p>".encode())) and block.endswith(b"\r\n\r\n")
    for broken in (raw[:-8], b"http://a/ 1 2 3 4\nabcd\n", raw.replace(b"1 0 statewitness", b"3 0 statewitness")):
        with pytest.raises(ValueError):
            list(web_archive.parse_arc(broken))


# --- pipeline and oracles ---------------------------------------------------------------------------


def test_pipeline_stages_against_brute_force(spark):
    """Each stage on what the one before kept: the rows that stay are those that brute force keeps."""
    import corpus_pipeline
    from test_copies import exact_brute, near_brute

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    items = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    stages = dict(corpus_pipeline.STAGES)
    with Scratch(spark) as s:
        for name, stage in corpus_pipeline.STAGES[:-1]:
            before = {r["doc_id"]: r["text"] for r in docs.collect()}
            docs = s.save(stage(spark, docs, SF), name)
            after = {r["doc_id"]: r["text"] for r in docs.collect()}
            assert docs.columns == spark.read.parquet(f"{SF}/documents.parquet").columns and all(before[k] == t for k, t in after.items())
            ids = sorted(before)
            if name == "quality_rules":
                assert 100 < len(after) < len(before)
            elif name == "exact_copies":
                want = exact_brute([before[k] for k in ids])
                assert set(after) == {k for i, k in enumerate(ids) if want[i][2]}
            elif name == "near_copies":
                _, comp = near_brute([before[k] for k in ids], 5, 80)
                assert set(after) == {k for i, k in enumerate(ids) if comp[i] == i}
            else:
                words = [(t or "").lower().split() for t in items]
                assert set(after) == {k for k in ids if not any(holds((before[k] or "").lower().split(), w) for w in words)}
        packed = stages["best_fit_packing"](spark, docs, SF).toPandas()
    assert set(packed["doc_id"]) == set(after) and packed.groupby("sequence_id")["length"].sum().max() <= packing.CAPACITY
    counts = np.bincount(packed["length"], minlength=packing.CAPACITY + 1)
    assert packed["sequence_id"].nunique() <= packing.lower_bound(counts, packing.CAPACITY) * 1.01 + 1


def holds(text, item):
    """Whether the whole text has a local alignment with the item at the threshold (no seeds)."""
    if not item or 2 * len(set(item) & set(text)) < len(set(item)) * 0.5:
        return False
    code = {w: k for k, w in enumerate(dict.fromkeys(text + item))}
    score, _ = decontaminate.local_alignment(np.array([code[w] for w in item]), np.array([code[w] for w in text], int))
    return score >= decontaminate.needed(len(item), decontaminate.THRESHOLD) * decontaminate.MATCH * len(item)


def test_pipeline_tells_rows_apart(spark):
    """Repeated rows, shared ids and missing ids: one row of each text stays, and no other text goes."""
    from statewitness.llm import exact_dedup, near_dedup

    other = "wholly other text here that stands alone and is long enough"
    rows = [(1, "a b c", 7), (1, "a b c", 7), (2, "a  b c", 1), (2, other, 1), (None, other + " x", 5), (None, None, None), (3, "", 2), (None, "solo words", 1), (None, "Solo words", 1)]
    exact = exact_dedup.keep_first(spark.createDataFrame(rows, "doc_id long, text string, _k int"))
    assert exact.columns == ["doc_id", "text", "_k"]
    assert sorted(map(tuple, exact.collect()), key=str) == sorted([rows[0], *rows[3:5], *rows[6:]], key=str)
    near = sorted(map(tuple, near_dedup.keep_one(exact).collect()), key=str)
    assert [r for r in near if r[1] not in ("solo words", "Solo words")] == sorted([rows[0], rows[3], rows[6]], key=str) and len(near) == 4
    items = spark.createDataFrame([(1, "solo words"), (2, "other text here"), (3, "other here")], "item_id long, text string")
    left = decontaminate.without_leaks(exact, items)
    assert sorted(map(tuple, left.collect()), key=str) == sorted([rows[0], rows[6]], key=str)
    empty = exact.limit(0)
    assert all(f(empty).count() == 0 for f in (exact_dedup.keep_first, near_dedup.keep_one, lambda d: decontaminate.without_leaks(d, items)))


@pytest.mark.parametrize("name", sorted(entries.oracle_sql()))
def test_queries_against_sql(spark, duck, name):
    from conftest import canonical

    assert canonical(entries.queries()[name](spark, SF).toPandas()) == canonical(duck.execute(entries.oracle_sql()[name]).df())
