"""Every operator on small planted tables: nulls, empty and odd texts, ties, repeated rows, empty tables, extra columns; and against plain versions."""

import hashlib
import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from brushcube.llm import components, decontaminate, fingerprint, html_extract, jaccard_join, license_scan, mixing, registry, token_count, toxicity, url_filter, warc

from ..conftest import SF, rows_of

DOC = "doc_id long, text string, lang string, source string, n_chars long"
rng = random.Random(5)
WORDS = ["".join(rng.choice("abcdefgh") for _ in range(rng.choice((3, 5, 8)))) for _ in range(400)]


def text(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) for _ in range(n))


def edited(t, k, seed):
    r, w = random.Random(seed), t.split()
    for _ in range(k):
        w[r.randrange(len(w))] = "zz" + str(r.randrange(999))
    return " ".join(w)


def documents(spark, texts, first=0):
    return spark.createDataFrame([(None if i is None else i + first, t, "en", ["s1", "s2", None][n % 3], 1) for n, (i, t) in enumerate(texts)], DOC)


@pytest.fixture(scope="module")
def corpus(spark):
    base = text(120, 1)
    items = [(0, base), (1, base), (2, edited(base, 3, 2)), (3, None), (4, ""), (5, "   \n\t "), (6, "one two"), (7, "ONE two"), (8, text(900, 3)), (9, edited(text(900, 3), 12, 4)), (10, text(50, 5)), (None, base), (11, "x" * 20000), (12, "漢字 " * 40), (2, edited(base, 3, 2))]
    return documents(spark, items)


def brute_components(rows):
    sets = {}
    for i, (d, t) in enumerate(rows):
        w = t.encode().lower().split() if t else []
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) > 4 else ({tuple(w)} if w else set())
    root = list(range(len(rows)))

    def top(a):
        while root[a] != a:
            a = root[a]
        return a

    for a in sets:
        for b in range(a):
            k = len(sets[a] & sets[b])
            if k and 100 * k >= 75 * (len(sets[a]) + len(sets[b]) - k):
                root[top(a)] = top(b)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[top(i)] = min(d, least.get(top(i), d))
    return sorted(((d, len(sets[i]), least.get(top(i))) for i, (d, _) in enumerate(rows)), key=str)


def got_components(df):
    return sorted(((r.doc_id, r.n_shingles, r.component_id) for r in df.collect()), key=str)


def test_jaccard_edges(spark, corpus):
    rows = [(r.doc_id, r.text) for r in corpus.collect()]
    assert got_components(jaccard_join.jaccard_components(corpus)) == brute_components(rows)
    assert jaccard_join.jaccard_components(corpus.limit(0)).count() == 0


@pytest.mark.parametrize("blocks", [False, True])
def test_jaccard_against_brute_force(spark, monkeypatch, blocks):
    if blocks:  # every group by matrix products, several blocks each
        monkeypatch.setattr(jaccard_join, "JOINED", 1)
        monkeypatch.setattr(jaccard_join, "BLOCK", 3)
    rows, core = [], text(60, 77)
    for k in range(14):  # near copies at all distances, and a passage that many share
        base = text(rng.choice((4, 9, 30, 140)), 100 + k)
        rows += [edited(base, e, k * 10 + e) if e else base for e in (0, 0, 1, 2, 4, 7)]
        rows += [text(8, 900 + k) + " " + core]
    rows = list(enumerate(rows))
    assert got_components(jaccard_join.jaccard_components(documents(spark, rows))) == brute_components(rows)


def test_jaccard_without_spare_segments(spark):
    """Sets that segments can't cover go through the shared prefix."""
    tight = jaccard_join.Scheme(slack=1.0, spare=0, small=0, singles=0)
    rows = list(enumerate(edited(text(n, 7 * k + n), e, e) for k in range(6) for n in (9, 40) for e in (0, 1, 2)))
    docs = documents(spark, rows)
    kinds = jaccard_join.jaccard_links(docs, scheme=tight)[1]
    assert kinds.where("filled + spare < 2 * n div 7 + 1").count() > 0
    assert got_components(jaccard_join.jaccard_components(docs, scheme=tight)) == brute_components(rows)


def test_sets_with_one_half_digest_are_told_apart(spark):
    rows = spark.createDataFrame([(5, 0, 9, 77, 1, 3, 0), (6, 0, 9, 77, 1, 3, 0), (7, 0, 9, 77, 2, 3, 0), (8, 0, 9, 78, 1, 3, 0)], "doc_id long, tag long, n long, cls long, check long, filled int, spare int")
    got = {(r.cls, r.check): (r.id, r.doc_id) for r in jaccard_join._classes(rows).collect()}
    assert got[77, 1] == (77, 5) and got[78, 1] == (78, 8) and got[77, 2][0] != 77 and len({i for i, _ in got.values()}) == 3


def test_blocks_hold_runs_longer_than_two_bytes():
    sig = np.arange(70_000, dtype=np.uint64) << np.uint64(3)
    (part, classes, counts, hashes), = jaccard_join._pack(1, np.full(70_000, 5, np.int64), sig)
    assert np.frombuffer(counts, "<u2").sum() == 70_000 and set(np.frombuffer(classes, np.int64)) == {5}
    assert (jaccard_join._wide(hashes).astype(np.uint64) == sig).all()


def test_pigeonhole_holds():
    """Sets within the bound share a whole segment, or differ by one in a deletable one, whatever is picked."""
    r = np.random.default_rng(3)
    for n in (4, 7, 20, 90):
        ends = jaccard_join.bands(n)
        m = jaccard_join.Scheme(singles=0).segments(ends)
        band = np.array([np.searchsorted(ends, n)])
        assert m[band[0]] >= 2 * n // 7 + 1
        for _ in range(20):
            s = np.unique(r.integers(0, 2**63, n, dtype=np.uint64))
            h = 2 * len(s) // 7
            t = np.delete(s, r.choice(len(s), max(0, h // 2), replace=False))
            (_, a), _, filled, _ = jaccard_join.signatures([s], band, m, m)
            (_, b), _, _, _ = jaccard_join.signatures([t], band, m, m)
            assert filled[0] - len(np.intersect1d(a, b)) <= h


def test_components(spark):
    chain = spark.createDataFrame([(i + 1, i) for i in range(40)] + [(101, 100), (102, 100)], "u long, v long")
    got = {r.node: r.root for r in components.components(chain).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[102] == 100 and components.components(chain.limit(0)).count() == 0


def test_url_filters(spark):
    urls = ["http://Example.COM/en/7x", "https://a.example.com/en/8", "http://x.net/de/8", "http://b.example.net/de/80?q", "http://notexample.com/en/7", "ftp://org/es/", "no scheme", None, "http://q.org#/es/", "http://.com/en/", "http://xorg/es/", "http://a://b.org/es/", "http://example.net/de/8\n/x"]
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls + urls[:1])], "page_id long, url string, verdict string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.judge_urls(pages.drop("verdict"), url_filter.rule_table(spark)).collect()}
    assert got[0] == ("example.com", "/en/7x", "example.com/en/7", "allow") and got[1][2:] == ("com/en/", "block") and got[2][2:] == ("net/de/", "allow")
    assert got[3] == ("b.example.net", "/de/80", "example.net/de/8", "block") and got[4][2:] == ("com/en/", "block") and got[5][2:] == ("org/es/", "block")
    assert got[6] == ("", "", None, "allow") == got[7] and got[8][:2] == ("q.org", "") and got[10][3] == "allow" and len(got) == 14
    empty = url_filter.judge_urls(pages.drop("verdict"), url_filter.rule_table(spark).limit(0))
    assert empty.where("verdict = 'allow' and rule is null").count() == 14


@pytest.mark.parametrize("name", [k for k, v in registry.oracle_sql().items()])
def test_queries_equal_sql(spark, oracle, name):
    df = registry.queries()[name](spark, SF)
    cols, want = oracle(registry.oracle_sql()[name])
    assert rows_of(df, cols) == sorted(want, key=lambda r: tuple((x is None, str(x)) for x in r))


def test_mixing_meets_targets(spark, corpus):
    r = random.Random(2)
    docs = documents(spark, [(i, text(r.randrange(1, 60), i)) for i in range(600)] + [(None, None), (None, "a b"), (7, text(5, 7)), (7, text(5, 7))])
    got = mixing.mix(docs.withColumn("target", F.lit("clash"))).collect()
    by = {}
    for x in got:
        by.setdefault(x.source, []).append(x)
        assert x.taken <= 2 * x.size and x.copies <= 2
    assert len(got) == 604 and sum({s: v[0].target for s, v in by.items()}.values()) == pytest.approx(1.5 * sum(x.size for x in got))
    for v in by.values():
        assert abs(sum(x.taken for x in v) - v[0].target) <= max(x.size for x in v) / 2 + 1 and v[0].target <= 2 * v[0].source_size
    assert rows_of(mixing.mix(docs)) == rows_of(mixing.mix(docs.repartition(7))) and mixing.mix(docs.limit(0)).count() == 0


def test_toxicity_learns_and_survives(spark):
    bad = ["vermin", "wretch", "filth"]
    texts = [(i, text(40, i) + (f" {bad[i % 3]} " + text(10, i + 9000) if i % 4 == 0 else "")) for i in range(1200)]
    docs = documents(spark, texts + [(5000, None), (5001, ""), (5002, "!!! ???"), (5003, "filth " + "y" * 200_000)])
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i, _ in texts] + [(None, 1), (3, None)], "doc_id long, toxic int")
    model = toxicity.train_on(docs, labels)
    got = {r.doc_id: r for r in toxicity.classify(docs.withColumn("score", F.lit("x")), model).collect()}
    held = [i for i, _ in texts if __import__("zlib").crc32(str(i).encode()) % 5 == 0]
    assert sum(got[i].predicted == (i % 4 == 0) for i in held) >= 0.9 * len(held)
    assert sum(got[i].predicted for i in held if i % 4) <= 2  # clean documents are left alone
    assert got[5000].predicted == got[5001].predicted == got[5002].predicted == 0 and 0 <= got[5000].score <= 1
    blank = toxicity.train_on(docs, labels.limit(0))
    assert toxicity.classify(docs, blank).agg(F.max("score")).first()[0] == 0 and toxicity.classify(docs.limit(0), model).count() == 0


def test_fingerprints_against_plain(spark):
    docs = documents(spark, [(i, text(n, i)) for i, n in enumerate((3, 0, 5, 40, 300, 300, 80))] + [(50, None), (51, "é漢字" * 5), (51, "b"), (None, "last one here")])
    base = fingerprint.fingerprints(docs.withColumn("hashes", F.lit(1)))
    order = sorted([(r.doc_id, r.text or "") for r in docs.collect()], key=lambda r: (r[0] is not None, r[0] or 0, r[1]), reverse=True)
    nexts = {(d, t): order[(k + 1) % len(order)][1] for k, (d, t) in enumerate(order)}
    got = base.collect()
    assert len(got) == len(order) and all(r.next_text == nexts[(r.doc_id, r.text)] for r in got)
    with_range = fingerprint.RANGE
    try:
        fingerprint.RANGE = 2  # many small ranges
        assert {(r.doc_id, r.text, r.next_text) for r in fingerprint.fingerprints(docs).collect()} == {(d, t, n) for (d, t), n in nexts.items()}
    finally:
        fingerprint.RANGE = with_range
    out = fingerprint.query(spark, SF)
    src = sorted(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect(), reverse=True)
    nxt = {r.doc_id: src[(k + 1) % len(src)].text for k, r in enumerate(src)}
    for r, d in zip(sorted(out.collect()), sorted(src)):
        n = len(d.text)
        e = d.text[: n - n // 3] + nxt[d.doc_id][: n // 3]
        assert r.n_chars == n and r.edited_sha256 == hashlib.sha256(e.encode()).hexdigest() and 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
    long = [r for r in out.collect() if r.n_chars > 2000]
    assert sum(r.near_edited > r.near_next for r in long) >= 0.95 * len(long)
    assert sum(abs(r.near_edited - 0.5) < 0.25 for r in long) >= 0.9 * len(long)
    assert fingerprint.fingerprints(docs.limit(0)).count() == 0


def test_fingerprints_of_uneven_ids(spark, monkeypatch):
    """Ids in clumps, one far off: ranges stay small, and each document meets the next."""
    monkeypatch.setattr(fingerprint, "RANGE", 2)
    ids = [*range(40), 10**6, 10**6 + 1, *range(10**9, 10**9 + 30), 10**12]
    docs = documents(spark, [(i, f"text {i}") for i in ids])
    assert {(r.doc_id, r.next_text) for r in fingerprint.fingerprints(docs).collect()} == {(a, f"text {b}") for a, b in zip(ids, [ids[-1], *ids[:-1]])}
    spans = fingerprint.in_ranges(docs.select("doc_id", "text")).where("not guest").groupBy("span").count()
    assert spans.agg(F.max("count")).first()[0] <= 4 * fingerprint.RANGE


def test_sketches_of_any_length_have_one_threshold(spark):
    """No size changes the rule, and two empty sketches of texts with words aren't alike."""
    texts = [text(n, n) for n in (6, 60, 63, 64, 65, 68, 69, 70, 300)]
    df = fingerprint.add_fingerprint(documents(spark, list(enumerate(texts))), F.col("text"), "x_")
    for r in df.collect():
        assert r.x_scale == fingerprint.SCALE and all(h % 2**64 < 2**64 // fingerprint.SCALE for h in r.x_hashes)
    lone = [t for t in (text(5, 1000 + k) for k in range(12))]
    pairs = fingerprint.add_fingerprint(documents(spark, list(enumerate(lone))), F.col("text"), "x_").where("size(x_hashes) = 0")
    two = pairs.limit(1).selectExpr("x_hashes", "x_scale").crossJoin(pairs.limit(1).selectExpr("x_hashes AS y_hashes", "x_scale AS y_scale"))
    assert two.select(fingerprint.likeness(*[F.col(c) for c in ("x_hashes", "x_scale", "y_hashes", "y_scale")])).first()[0] == 0.0


def test_containment_of_unequal_sketches(spark):
    whole = text(4000, 9)
    part = " ".join(whole.split()[:400])
    df = spark.createDataFrame([(whole, part)], "a string, b string")
    df = fingerprint.add_fingerprint(fingerprint.add_fingerprint(df, F.col("a"), "x_"), F.col("b"), "y_")
    r = df.select(fingerprint.containment(*[F.col(c) for c in ("y_hashes", "x_hashes")]).alias("c"), fingerprint.likeness(*[F.col(c) for c in ("x_hashes", "x_scale", "y_hashes", "y_scale")]).alias("l")).first()
    assert r.c == 1.0 and 0.05 < r.l < 0.17


def test_decontamination_edges(spark):
    item = text(30, 60)
    w = item.split()
    docs = documents(spark, [(1, "A, b! " + item.upper() + " tail"), (2, " ".join(w[:12])), (3, None), (4, ""), (5, text(400, 1) + " " + " ".join(w[3:17])), (6, "tiny item"), (7, "so TINY-item so"), (1, "nothing here")])
    items = spark.createDataFrame([(10, item), (9, item), (2, "tiny item"), (3, None), (4, "...")], "item_id long, text string")
    got = decontaminate.decontaminate(docs.select("doc_id", "text", F.lit(1).alias("n_words"), F.lit(0).alias("source")), items).collect()
    by = {(r.doc_id, r.n_words): (r.n_hit, r.n_items, r.contaminated, r.item_ids) for r in got}
    assert by[(1, 33)] == (30, 2, True, ["10", "9"]) and by[(2, 12)][0] == 0 and by[(3, 0)][2] is False and by[(4, 0)][0] == 0
    assert by[(5, 414)] == (14, 2, False, ["10", "9"]) and by[(6, 2)] == (2, 1, True, ["2"]) and by[(7, 4)][0] == 2 and by[(1, 2)][0] == 0 and len(got) == 8
    assert decontaminate.decontaminate(docs.select("doc_id", "text"), items.limit(0)).where("n_hit > 0").count() == 0
    big, bits = decontaminate.BROADCAST_WINDOWS, decontaminate.FILTER_BITS
    try:
        decontaminate.BROADCAST_WINDOWS, decontaminate.FILTER_BITS = 1, 7  # both sides shuffled, a filter that lets much through
        again = decontaminate.decontaminate(docs.select("doc_id", "text"), items).collect()
    finally:
        decontaminate.BROADCAST_WINDOWS, decontaminate.FILTER_BITS = big, bits
    assert sorted((r.doc_id, r.n_words, r.n_hit) for r in again) == sorted((r.doc_id, r.n_words, r.n_hit) for r in got)


def test_licences(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    model = license_scan.train_on(docs)
    planted = spark.createDataFrame([(1, "first line\nLicensed under the Apache License, Version 2.0.\nlast"), (2, "the licensed trade of the city"), (3, None), (4, ""), (5, "Released under the MIT License."), (6, "this work is licensed under the gnu general public license, version 3."), (5, "Released under the MIT License."), (7, "x" * 50_000)], "doc_id long, text string")
    got = {}
    for r in license_scan.scan(planted.withColumn("licence", F.lit("clash")), model).collect():
        got.setdefault(r.doc_id, []).append((r.licence, r.confirmed, r.n_paragraphs))
    # "first line" ends no sentence, so the notice after it belongs to its paragraph
    assert got[1] == [("Apache-2.0", True, 2)] and got[2][0][0] == "unknown" and got[3] == [("unknown", False, 0)] == got[4] and got[5] == [("MIT", True, 1)] * 2 and got[6][0][0] == "GPL-3.0" and got[7][0][0] == "unknown"
    assert license_scan.scan(planted.limit(0), model).count() == 0


@pytest.mark.parametrize("family, notice", [("BSD-3-Clause", license_scan.NOTICES["BSD-3-Clause"][0]), ("MIT", license_scan.NOTICES["MIT"][2]), ("CC0-1.0", license_scan.NOTICES["CC0-1.0"][0])])
def test_common_notices_stay_detected(spark, family, notice):
    """A notice without the word licence that 5% of documents have, alone or amid other words, is still found in all of them."""
    docs = documents(spark, [(i, text(60, i) + ("" if i % 20 else f"\n{notice}" if i % 40 else f"\n{text(2, i + 5000)} {notice} {text(2, i + 6000)}")) for i in range(600)])
    got = {r.doc_id: r.licence for r in license_scan.scan(docs, license_scan.train_on(docs)).collect()}
    assert all(got[i] == ("unknown" if i % 20 else family) for i in range(600))
    assert license_scan.train_on(docs.limit(0)).triggers


def test_wrapped_notices_and_held_out_samples(spark):
    """Every notice that is wrapped in its middle is found, blank lines keep paragraphs apart, and samples that weren't learnt from are told apart."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    model = license_scan.train_on(docs)
    notices = [(f, n.split()) for f, ns in license_scan.NOTICES.items() for n in ns]
    rows = [(i, f"It ends here.\n{' '.join(n[: len(n) // 2])}  \n  {' '.join(n[len(n) // 2 :])}\nMore follows.") for i, (_, n) in enumerate(notices)]
    got = {r.doc_id: (r.licence, r.n_paragraphs) for r in license_scan.scan(documents(spark, rows), model).collect()}
    ends = [n[-1].endswith(".") for _, n in notices]
    assert all(got[i] == (f, 3) for i, (f, _) in enumerate(notices)) and all(ends)
    apart = license_scan.scan(documents(spark, [(1, "A heading\n\n\nReleased under the MIT License\n \nother words")]), model).first()
    assert (apart.licence, apart.n_paragraphs) == ("MIT", 3)
    assert model.held_out["ordinary"][0] > 50 and model.held_out["ordinary"][1] >= 0.99 and model.held_out["notices"][0] == 88 and model.held_out["notices"][1] >= 0.9


def test_notices_never_lose_their_triggers():
    """Whatever is ordinary, a paragraph that a notice could confirm holds a trigger."""
    every = [w for n in license_scan._NOTICE_WORDS for w in n]
    model = license_scan.LicenceModel([f"{w} one two" for w in every for _ in range(9)])
    for n in license_scan._NOTICE_WORDS:
        assert 1 - len(n & model.triggers) / len(n) < license_scan.CONFIRM


def test_token_counts_are_the_librarys(spark):
    import public_tokenizers
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=str(public_tokenizers.path("piece_bpe_32k.model")))
    r, letters = random.Random(1), "ab  \n\teé▁ß漢😀<s>/\x00\r{};'\"the ingXYZ01"
    odd = ["".join(r.choice(letters) for _ in range(k)) for k in (1, 2, 5, 40, 300, 3000) for _ in range(12)] + ["a" * 5000, "▁" * 700, " " * 300, "</s><unk>"]
    docs = documents(spark, list(enumerate(odd)) + [(900, None), (901, "")])
    got = {r.doc_id: r for r in token_count.count_tokens(docs.withColumn("n_tokens", F.lit("x"))).collect()}
    assert [got[i].n_tokens for i in range(len(odd))] == [len(x) for x in sp.encode(odd)] and got[900].n_tokens == got[901].n_bytes == 0
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    assert all(r.n_tokens == len(sp.encode(texts[r.doc_id])) and r.over_limit == (r.n_tokens > 4096) for r in token_count.query(spark, SF).collect())
    assert token_count.count_tokens(docs.limit(0)).count() == 0


def test_warc_round_trip(spark, tmp_path):
    big = "<p>" + text(400, 3)
    pages = spark.createDataFrame([(1, "http://a/1", big), (2, None, big), (None, "http://a/3", big), (2, "http://a/2", big), (3, "http://b/\r\nX: y", "small"), (4, "u", "small"), (5, "u", None), (9007199254740993, "u", "é漢" * 800)], "page_id long, url string, html string")
    folder = str(tmp_path / "w")
    manifest = warc.write_archives(warc.with_revisits(pages), folder, archive_mb=1)
    got = warc.read_archives(spark, folder).collect()
    assert manifest.agg(F.sum("n_records")).first()[0] == len(got) == 8
    kinds = sorted(((r.page_id, r.record_type, r.refers_to, r.payload_bytes) for r in got), key=str)
    n = len(big.encode())
    assert kinds == sorted([(1, "revisit", 2, n), (2, "response", None, n), (2, "response", None, n), (None, "revisit", 2, n), (3, "response", None, 5), (4, "response", None, 5), (5, "response", None, 0), (9007199254740993, "response", None, 4000)], key=str)
    assert all((r.payload is None) == (r.record_type == "revisit") for r in got) and {r.url for r in got} >= {"http://b/\r\nX: y", None}
    assert all(hashlib.sha1(r.payload).hexdigest() == r.payload_digest for r in got if r.payload is not None)
    none = str(tmp_path / "none")
    warc.write_archives(warc.with_revisits(pages.limit(0)), none)
    assert warc.read_archives(spark, none).count() == 0
    raw = warc.archive_bytes([warc.record_bytes(1, "u", b"abc", None)] * 3)
    assert raw[:4] == b"\x5d\x2a\x4d\x18" and len(list(warc.read_records(raw))) == 3
    with pytest.raises(ValueError):
        list(warc.read_records(b"\0" * 20))


def page(body, head=""):
    return f"<!DOCTYPE html><html><head><title>T</title>{head}</head><body>{body}</body></html>"


def test_html_blocks():
    got = html_extract.page_lines
    assert got(page("<nav>m</nav><article><h1>A &amp; B</h1><p>one<b>two</b>\n three<br>four<p>five<div class='ad'>x<p>y</div><script>if (a<b) '</p>'</script><ul><li>i<li>j</ul></article><footer>f</footer>")) == (["A & B", "onetwo three four", "five", "i", "j"], True)
    assert got(page("<main><p>a<section class='user comments'>c</section><form>q</form><p>b</main>x")) == (["a", "b"], True)
    assert got(page("<div><p>a</div><aside>s</aside>")) == (["a"], False)
    assert got(None) == ([], False) == got("") and got("plain &lt;text&gt; &am") == (["plain <text> &am"], False)
    assert got("<article>cut off <b>mid") == (["cut off mid"], True) and got("<article>a<!-- x --><![CDATA[z]]>b</article>") == (["ab"], True)
    assert got("<article><p title='a > b'>t</p><p hidden>h</p><p style='display:none'>n</p></article>")[0] == ["t"]
    assert len(got("<a <a " * 20_000 + "<article>z</article>")[0]) <= 2 and got("<article>" + "<" * 30_000)[1]


def test_html_long_attribute_values():
    long = "<b>{'x' > 1}</b>" * 3000
    assert html_extract.page_lines(f'<article><p data-json="{long}">kept</p><div class="ad" data-x="{long}">gone</div></article>') == (["kept"], True)
    started = __import__("time").monotonic()
    for odd in ("<a \"", "<a '\"", "<a \"<b '", "<a \" \"", "<a x=\"' "):
        html_extract.page_lines("<article>" + odd * 40_000)
    assert __import__("time").monotonic() - started < 20


def brute_lcs(a, b):
    d = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            d[i + 1][j + 1] = d[i][j] + 1 if x == y else max(d[i][j + 1], d[i + 1][j])
    return d[-1][-1]


def test_longest_common_lines():
    r = random.Random(4)
    for _ in range(200):
        a, b = ([r.choice("abcdef") for _ in range(r.randrange(12))] for _ in range(2))
        kept = sorted(html_extract.common_lines(a, b))
        assert len(kept) == brute_lcs(a, b)
        it = iter(b)
        assert all(a[i] in it for i in kept)


def test_html_differencing_and_edges(spark):
    shell = lambda t: page(f"<div>Home of pages</div><div>{t}</div><div>All rights</div>")
    rows = [(i, f"http://h.com/a/{i}", shell(text(30, i))) for i in range(12)] + [(20, "http://one.com/x", shell("single")), (21, None, None), (22, "http://h.com/a/3", shell(text(30, 3))), (23, "http://h.com/z", page("<article>kept Home of pages</article>")), (24, "http://two.com/a", shell("same")), (25, "http://two.com/b", shell("same"))]
    pages = spark.createDataFrame([(*r, 1) for r in rows], "page_id long, url string, html string, text int")
    for group in (400, 4):
        got = {r.page_id: r.text for r in html_extract.extract_text(pages, group=group).collect()}
        assert len(got) == 18 and got[23] == "kept Home of pages" and got[21] == "" and got[20] == "Home of pages single All rights"
        assert got[24] == got[25] == "Home of pages same All rights"  # copies only
        assert sum(got[i] == text(30, i) for i in range(12)) >= 8
        if group == 400:
            assert all(got[i] == text(30, i) for i in range(12)) and got[22] == got[3]
    assert html_extract.extract_text(pages.limit(0)).count() == 0


def test_html_differencing_is_one_for_every_group_size(spark):
    """Ranges of any size give what the walk over the whole host gives, runs of copies longer than a range included."""
    r, rows = random.Random(8), []
    for i in range(90):  # sections share a template; pages of one path differ by their query or have no url
        url = r.choice((f"http://h.com/{i // 9}/{r.randrange(30)}", f"http://h.com/view?id={i}", f"http://g.org/a/{i:03}", None))
        rows.append((i, url, page(f"<div>Section {i // 9}</div><div>{text(3, i // r.choice((1, 1, 30)))}</div><div>Foot {i % 3}</div>")))
    rows += [(200 + i, f"http://h.com/4/{i:02}", page("<div>Section 4</div><div>copied</div>")) for i in range(25)]

    def whole(pages):  # the plain walk: next to each other, the nearer side first, copies passed over
        out = {}
        for k, (i, path, lines) in enumerate(pages):
            near = lambda n: len(__import__("os").path.commonprefix([path, pages[n][1]])) if 0 <= n < len(pages) else -1
            lo, hi, partner = k - 1, k + 1, None
            while partner is None and (lo >= 0 or hi < len(pages)):
                n = lo if near(lo) >= near(hi) else hi
                lo, hi = (lo - 1, hi) if n == lo else (lo, hi + 1)
                partner = pages[n][2] if pages[n][2] != lines else None
            gone = html_extract.common_lines(lines, partner) if partner else set()
            out[i] = " ".join(t for j, t in enumerate(lines) if j not in gone)
        return out

    pages, want = spark.createDataFrame(rows, "page_id long, url string, html string"), {}
    named = pages.select("page_id", html_extract.host_of(F.col("url")).alias("h"), html_extract.path_of(F.col("url")).alias("p")).collect()
    for host in {x.h for x in named}:
        by = {i: (u, x) for i, u, x in rows}
        order = sorted((x.p, by[x.page_id][0] is None, by[x.page_id][0] or "", str(x.page_id), x.page_id) for x in named if x.h == host)
        want |= whole([(i, p, html_extract.page_lines(by[i][1])[0]) for p, *_, i in order])
    for group in (1, 4, 7, 400):
        assert {r.page_id: r.text for r in html_extract.extract_text(pages, group=group).collect()} == want


def test_pipeline_against_plain_stages(spark, corpus):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept, ids = docs, {r.doc_id for r in docs.collect()}
    scores = {r.doc_id: r.predicted for r in toxicity.query(spark, SF).collect()}
    out = corpus_pipeline.toxicity_stage(spark, kept, SF)
    ids = {i for i in ids if scores[i] == 0}
    assert {r.doc_id for r in out.collect()} == ids and out.columns == docs.columns
    out2 = corpus_pipeline.jaccard_stage(spark, out, SF)
    rows = [(r.doc_id, r.text) for r in out.collect()]
    assert sorted(r.doc_id for r in out2.collect()) == sorted({c for _, _, c in brute_components(rows)}) and out2.columns == docs.columns
    out3 = corpus_pipeline.decontamination_stage(spark, out2, SF)
    dirty = {r.doc_id for r in decontaminate.query(spark, SF).collect() if r.contaminated}
    assert {r.doc_id for r in out3.collect()} == {r.doc_id for r in out2.collect()} - dirty
    last = corpus_pipeline.run(spark, SF)
    assert {r.doc_id for r in last.collect()} <= {r.doc_id for r in out3.collect()} and last.where("copies < 1 or taken != copies * size").count() == 0
    # odd rows pass through every stage
    odd = corpus.withColumn("score", F.lit(3)).withColumn("n", F.lit(1))
    for name, stage in corpus_pipeline.STAGES:
        odd = stage(spark, odd, SF)
    assert odd.count() > 0 and "score" in odd.columns
    assert all(stage(spark, docs.limit(0), SF).count() == 0 for _, stage in corpus_pipeline.STAGES)


def test_pipeline_tells_rows_of_one_id_apart(spark):
    a, b, c = text(40, 71), text(40, 72), text(40, 73)
    ids = lambda rows: sorted(((r.doc_id, r.text) for r in corpus_pipeline.jaccard_stage(spark, documents(spark, rows), SF).collect()), key=str)
    assert ids([(1, a), (7, a), (7, b)]) == [(1, a), (7, b)]
    assert ids([(5, a), (5, b), (6, edited(a, 1, 1)), (6, c)]) == sorted([(5, a), (5, b), (6, c)], key=str)
    assert ids([(3, a), (3, a), (None, b), (None, b), (None, c), (4, None), (4, None)]) == sorted([(3, a), (None, b), (None, c), (4, None), (4, None)], key=str)
    item = spark.read.parquet(f"{SF}/benchmark.parquet").first()["text"]
    odd = documents(spark, [(1, item), (1, a), (None, item), (None, c)]).withColumn("dirty_id", F.lit(1)).withColumn("told_id", F.lit(1))
    left = corpus_pipeline.decontamination_stage(spark, corpus_pipeline.jaccard_stage(spark, odd, SF), SF)
    assert sorted((r.text for r in left.collect())) == sorted([a, c]) and "told_id" in left.columns


def test_registry_is_whole():
    assert [k for k in registry.queries()][:10] == [k for k in registry._MODULES] and "pipeline" in registry.queries()
    assert duckdb.__version__ and len(registry._MODULES) == 10


def test_html_differencing_decides_marked_pages(spark):
    """Pages that mark their article are paired and differenced like others; the marks restore shared article lines and leave out own lines outside."""
    def shell(i):
        return page(f"<div>Home of pages</div><div>today {i}</div><article><p>{text(20, i)}</p><p>shared words</p></article><div>All rights</div>")
    rows = [(i, f"http://h.com/a/{i}", shell(i)) for i in range(9)] + [(20, "http://h.com/a/5", shell(5)), (20, "http://h.com/a/5", shell(5)), (21, "http://h.com/b", page("<div>Home of pages</div><div>loose</div><div>All rights</div>"))]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for group in (400, 2):
        got = html_extract.extract_text(pages, group=group).collect()
        assert len(got) == 12
        for r in got:
            want = ("loose", False, 1, 0, 0) if r.page_id == 21 else (f"{text(20, 5 if r.page_id == 20 else r.page_id)} shared words", True, 2, 1, 1)
            assert (r.text, r.marked, r.own, r.restored, r.left_out) == want
