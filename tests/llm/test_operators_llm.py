"""Each operator on odd rows and against brute force or held-out labels."""

import hashlib
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from gradvb.llm import decontaminate, html_text, licenses, packing, quality, sharding, simhash, suffix_dedup, toxicity, vector_dedup

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
#: Null ids and texts, ties, repeats, an empty and a very long text, columns whose names operators use inside.
ODD = [(1, None, "a", 5), (2, "", None, 1), (3, "same text " * 30, "a", 2), (3, "same text " * 30, "a", 2), (4, "same text " * 30, None, None), (None, "Null id MIT License", "b", 0), (6, "word " * 60_000, "b", 0), (7, "é" * 300 + "ß!", "c", 9)]
COLUMNS = "doc_id long, text string, source string, size int"


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, COLUMNS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], COLUMNS)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").cache()


def ascii_lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


# sharding


def test_shards_are_even_and_slots_gapless(docs):
    got = sharding.kd_shards(docs, 4).toPandas()
    sizes = got.groupby("shard")["size"].sum()
    assert len(got) == docs.count() and len(sizes) == 4
    assert sizes.max() - sizes.min() <= 2 * got["size"].max()
    for _, part in got.groupby("shard"):
        assert sorted(part["slot"]) == list(range(len(part)))
    want = {r.doc_id: (len((r.text or "").encode()) + 16, zlib.crc32((r.text or "").encode())) for r in docs.collect()}
    assert all(want[r.doc_id] == (r.size, r.text_crc32) for r in got.itertuples())


def test_shards_of_a_target_size(docs):
    sizes = sharding.kd_shards(docs, target_bytes=50_000).groupBy("shard").agg(F.sum("size").alias("n")).toPandas()["n"]
    shards = -(-sizes.sum() // 50_000)
    assert 0.8 * shards <= len(sizes) <= shards and sizes.sum() / shards <= 50_000  # a text larger than that may leave a shard empty


def test_shards_of_odd_rows(odd, none):
    got = sharding.kd_shards(odd, 3).collect()
    assert len(got) == len(ODD) and {r.law for r in got} == {"bytes"}
    assert sharding.kd_shards(none, 3).collect() == []


def test_hot_group_is_split(spark):
    df = spark.range(900).select(F.col("id").alias("doc_id"), F.lit("the same words").alias("text"), F.lit("s").alias("source"))
    counts = sharding.kd_shards(df, 9).groupBy("shard").count().toPandas()["count"]
    assert counts.min() >= 80 and counts.max() <= 120


def test_equal_rows_are_split(spark):
    df = spark.range(900).select(F.lit(None).cast("long").alias("doc_id"), F.lit("the same words").alias("text"), F.lit("s").alias("source"))
    got = sharding.kd_shards(df.union(df.limit(0)), 9).toPandas()
    counts = got.groupby("shard").size()
    assert len(counts) == 9 and counts.min() >= 95 and counts.max() <= 105
    assert all(sorted(part["slot"]) == list(range(len(part))) for _, part in got.groupby("shard"))


# decontamination


def brute_contamination(texts, items, window=10):
    windows = []
    for item, text in items:
        w = WORD.findall(ascii_lower(text))
        n = min(window, len(w))
        windows += [(item, tuple(w[k : k + n])) for k in range(len(w) - n + 1)] if w else []
    out = []
    for text in texts:
        w = WORD.findall(ascii_lower(text))
        hit, found = set(), set()
        for item, own in windows:
            for k in range(len(w) - len(own) + 1):
                if tuple(w[k : k + len(own)]) == own:
                    hit |= set(range(k, k + len(own)))
                    if item is not None:
                        found.add(str(item))
        out.append((len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    return out


def test_contamination_equals_brute_force(spark):
    rng = np.random.default_rng(1)
    vocabulary = [f"w{k}" for k in range(6)]
    items = [(k, " ".join(rng.choice(vocabulary, n))) for k, n in enumerate((3, 9, 10, 14, 30, 1))] + [(90, None), (91, "..."), (None, "zebra yak"), (92, "w0 w1 w2 w3 w4 w5 w0 w1 w2 w3 w4")]
    texts = [" ".join(rng.choice(vocabulary, n)) for n in (0, 1, 5, 9, 10, 11, 60, 200)]
    texts += ["pre " + items[4][1] + " post", "Zebra, YAK! zebra", None, items[3][1].upper(), "x " + " ".join(items[4][1].split()[3:13]) + " y", " ".join(items[4][1].split()[3:12])]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in decontaminate.contamination(docs, bench).collect()}
    for k, want in enumerate(brute_contamination(texts, items)):
        assert got[k] == want, texts[k]


def test_contamination_of_odd_rows(spark, odd, none):
    bench = spark.createDataFrame([(1, "word word word word word word word word word word word")], "item_id long, text string")
    got = decontaminate.contamination(odd, bench).collect()
    assert sorted(r.n_hit for r in got)[-1] == 60_000 and len(got) == len(ODD)
    assert decontaminate.contamination(none, bench).collect() == []
    assert decontaminate.drop_contaminated(odd, bench).count() == len(ODD) - 1
    assert decontaminate.contamination(odd, bench.limit(0)).where("contaminated").count() == 0


def test_native_plans(docs, spark):
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    for df in (decontaminate.contamination(docs, bench), sharding.kd_shards(docs, 4)):
        plan = df._jdf.queryExecution().toString()
        assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


# classifiers


def held_out(label, folds, fold):
    import duckdb

    rows = duckdb.sql(f"SELECT d.doc_id, d.text, l.{label} AS y FROM '/root/testdata/sf0.1/documents.parquet' d JOIN '/root/testdata/sf0.1/labels.parquet' l USING (doc_id)").fetchall()
    out = zlib.crc32
    train = [(t.encode(), y) for i, t, y in rows if out(str(i).encode()) % folds != fold]
    test = [(t.encode(), y) for i, t, y in rows if out(str(i).encode()) % folds == fold]
    return [t for t, _ in train][:2500], np.array([y for _, y in train][:2500]), [t for t, _ in test], np.array([y for _, y in test])


def auc(score, y):
    rank = np.argsort(np.argsort(score))
    return (rank[y == 1].mean() - ((y == 1).sum() - 1) / 2) / (y == 0).sum()


def test_quality_on_held_out_labels():
    x, y, xt, yt = held_out("quality", 5, 0)
    score = quality.fit_quality(x, y).score(*quality.joined(xt))
    assert auc(score, yt) > 0.98 and ((score >= 0.3)[yt == 1]).mean() > 0.97 and ((score < 0.3)[yt == 0]).mean() > 0.9


def test_toxicity_on_held_out_labels():
    x, y, xt, yt = held_out("toxic", 3, 1)
    score = toxicity.fit_toxicity(x, y).score(*toxicity.joined(xt))
    assert auc(score, yt) > 0.93 and ((score >= 0.7)[yt == 0]).mean() < 0.02 and ((score >= 0.7)[yt == 1]).mean() > 0.7


def test_misspellings_share_subwords():
    """Held-out toxic texts whose toxic words are all misspelled in a way that no training text has."""
    x, y, xt, yt = held_out("toxic", 3, 1)
    model = toxicity.fit_toxicity(x, y)
    known = {w for t in x for w in WORD.findall(ascii_lower(t.decode()))}
    score = lambda texts: model.score(*toxicity.joined([t.encode() for t in texts]))
    plain = [ascii_lower(t.decode()) for t, label in zip(xt, yt, strict=True) if label]
    changed = []
    for text in plain:
        words = sorted(set(WORD.findall(text)))
        z = toxicity.word_logits(toxicity.find_words(*toxicity.joined([" ".join(words).encode()])), model.weight) + model.bias
        for w in (w for w, own in zip(words, z, strict=True) if own > 0 and len(w) > 2):
            middle = range(len(w) // 2, len(w))
            text = text.replace(w, next((w[:k] + w[k] + w[k:] for k in middle if w[:k] + w[k] + w[k:] not in known), w))
        changed.append(text)
    assert (score(plain) >= 0.7).mean() > 0.85
    assert np.median(score(changed)) > 5 * np.median(score([t for t, label in zip((t.decode() for t in xt), yt, strict=True) if not label]))


def test_toxic_rows_go_whatever_columns_are_called(spark):
    x, y, _, _ = held_out("toxic", 3, 1)
    model = toxicity.fit_toxicity(x[:800], y[:800])
    rows = [(0.1, "you stupid idiot, worthless trash, pathetic loser", 1), (0.2, None, 2), (0.2, None, 2), *((float(k), t.decode(), None) for k, t in enumerate(x[800:830]))]
    df = spark.createDataFrame(rows, "toxic_score double, text string, toxic_predicted int")
    left = toxicity.drop_toxic(df, model)
    stay = [r.doc_id for r in toxicity.score_toxicity(df.withColumn("doc_id", F.col("toxic_score") * 10), model).collect() if not r.predicted]
    assert left.columns == df.columns and sorted(int(r.toxic_score * 10) for r in left.collect()) == sorted(stay) and 20 < len(stay) < len(rows)


def test_classifiers_on_odd_rows(spark, odd, none):
    labels = spark.createDataFrame([(3, 1, 0), (6, 0, 1), (None, 1, 1), (1, None, None), (3, 1, 0)], "doc_id long, quality int, toxic int")
    for train, score in ((quality.train_quality, quality.score_quality), (toxicity.train_toxicity, toxicity.score_toxicity)):
        for source in (labels, labels.limit(0)):
            got = score(odd, train(odd, source)).collect()
            assert len(got) == len(ODD) and all(0 <= r.score <= 1 for r in got)
        assert score(none, train(odd, labels)).collect() == []


# licenses


def test_license_base_places_equal_brute_force(docs, odd, none):
    extra = docs.sparkSession.createDataFrame([(900, "GNU General\nPublic  License apache license Apache-License cc by-sa MIT license"), (901, "gnu general public"), (902, "All rights reserved. Licensed under the Apache License, Version 2.0.")], "doc_id long, text string")
    rows = docs.select("doc_id", "text").union(extra)
    got = {r.doc_id: r for r in licenses.scan(rows).collect()}
    for doc in rows.collect():
        w = WORD.findall(ascii_lower(doc.text))
        places = [(k, label) for phrase, label in licenses.BASE_PHRASES.items() for k in range(len(w)) if w[k : k + len(phrase.split())] == phrase.split()]
        r = got[doc.doc_id]
        at = [k for k, _ in places]
        base = sorted({label for _, label in places})
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (len(w), len(places), min(at, default=None), max(at, default=None), ",".join(base))
        assert set(base) <= set(filter(None, r.labels.split(","))) and 0 <= r.score <= 1
    assert got[902].labels == "apache,apache-2.0"
    assert len(licenses.scan(odd).collect()) == len(ODD) and licenses.scan(none).collect() == []


def test_notices_are_found_with_edits_and_cut_off(spark):
    rng = np.random.default_rng(3)
    words = lambda n: [f"w{k}" for k in rng.integers(0, 5000, n)]
    mit, cc = licenses.MIT.split(), "Licensed under a Creative Commons Attribution 4.0 International License".split()
    edited = mit[:40] + ["indeed"] + mit[40:90] + mit[92:]
    texts = [words(50) + mit + words(50), words(20) + edited + words(5), cc + words(200), words(100) + ["this", "work", "is"] + cc, words(300), "permission is granted to the person in the software".split() + words(60), mit[::-1]]
    got = [r.labels.split(",") for r in sorted(licenses.scan(spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "doc_id long, text string")).collect())]
    assert "mit-full" in got[0] and "mit-grant" in got[0] and "mit-full" in got[1]
    assert got[2] == got[3] == ["cc-by-4.0"] and got[4:] == [[""]] * 3


def test_every_notice_of_a_text_is_found_and_none_aligned_without_its_key_phrases(spark, monkeypatch):
    """A text of many notices has more license words than are looked up of one; prose of license words aligns with nothing."""
    rng = np.random.default_rng(5)
    joined = " and so on ".join(x[1] for x in licenses.NOTICES)
    got = licenses.scan(spark.createDataFrame([(0, joined)], "doc_id long, text string")).collect()[0].labels.split(",")
    assert {x[0] for x in licenses.NOTICES} <= set(got)
    index = licenses.NoticeIndex()
    monkeypatch.setattr(index, "aligned", lambda *_: pytest.fail("aligned without its key phrases"))
    prose = licenses.word_hashes([str(w) for w in rng.choice(sorted(set((licenses.MIT + licenses.BSD).split()) - {"hereby", "binary"}), 20_000)])
    assert index.matches(prose, np.zeros(len(prose), np.int64), np.array([0, len(prose)])) == []


def test_words_of_notices_are_counted_over_all_documents(spark):
    df = spark.createDataFrame([("the license",), ("The LICENSE license",), (None,), ("software",)], "text string").repartition(3)
    counts, n = licenses.word_counts(df, licenses.NOTICES)
    at = {w: counts[int(licenses.word_hashes([w]).view(np.int64)[0])] for w in ("license", "the", "software", "warranty")}
    assert n == 4 and at == {"license": 2, "the": 2, "software": 1, "warranty": 0}


# pages


def test_main_text():
    page = """<html><head><title>T</title><style>p{}</style><script>var t="</p><p>no";</script></head><body><nav><ul><li><a href=x>Menu</a></ul></nav>
    <!-- <p>gone</p> --><div class="cookie-notice">We use cookies, really.</div><article><h1>Head &amp; tail</h1><p><b>One  two,
    three.<br>four<p>Five &eacute;&#x21; <i>six</i>.</p><div class="ad">Buy now, cheap.</div><p>Is.</p><div id="comments"><p>First, nice post.</p></div></article>
    <aside>Related, other.</aside><form><p>Sign up, here.</p></form><footer>&copy; us</footer>"""
    assert html_text.main_text(page) == "Head & tail\nOne two, three. four\nFive é! six.\nIs."
    assert html_text.main_text(None) == html_text.main_text("") == html_text.main_text("<nav>only</nav>") == ""
    div = "<body><div class=menu>a b c</div><div id=main-text><p>Some long sentence, with words.</p><p>Another one, also long enough.</p></div><div class=footer>x</div></body>"
    assert html_text.main_text(div) == "Some long sentence, with words.\nAnother one, also long enough."
    assert html_text.main_text("plain words, no tags") == "plain words, no tags"


def test_attributes_of_pages():
    """Quotes within unquoted values and unclosed ones swallow no text."""
    assert html_text.main_text("<p title=it's>One, two.</p><p>Second, don't.</p><p>Third, three.") == "One, two.\nSecond, don't.\nThird, three."
    assert html_text.main_text("<p a='>' b=\">\">One, two.</p><p c='open>Second, too.</p>") == "One, two.\nSecond, too."
    assert html_text.main_text('<p "x">One, two.</p><img alt=5">Three, four.') == "One, two.\nThree, four."


def test_names_are_evidence_only():
    prose = "".join(f"<p>A sentence of the text, number {k}, that says something at some length.</p>" for k in range(4))
    lines = "\n".join(f"A sentence of the text, number {k}, that says something at some length." for k in range(4))
    links = "<ul><li><a>Home</a><li><a>Other</a></ul>"
    assert html_text.main_text(f"<body><div class='social-history'><article>{prose}</article></div>{links}</body>") == lines
    assert html_text.main_text(f"<body><article><p>First, of all things, a longer opening sentence.</p><section class=search-tips>{prose}</section></article></body>") == "First, of all things, a longer opening sentence.\n" + lines
    assert html_text.main_text(f"<body><article>{prose}<div class=search-shortcuts>{links}</div></article></body>") == lines
    assert html_text.main_text(f"<body><article><div class=entry-header><h1>Title</h1></div>{prose}</article><div id=comments>{prose}</div></body>") == "Title\n" + lines
    assert html_text.main_text(f"<body><div class=newsletter>{prose}</div></body>") == lines


def test_pages_of_the_table_are_their_articles():
    """Every article of the given pages, stripped by a plainer reader of well-formed markup."""
    import duckdb
    from html import unescape

    rows = duckdb.sql("SELECT html FROM '/root/testdata/sf0.01/pages.parquet'").fetchall()
    assert len(rows) == 250
    for (page,) in rows:
        body = re.search(r"<article>(.*?)</article>", page, re.S)[1]
        parts = re.split(r"</?(?:p|h1|ul|li|div)\b[^>]*>", re.sub(r'<div class="ad">.*?</div>', "", body, flags=re.S))
        want = [re.sub(r"\s+", " ", unescape(re.sub(r"<[^>]*>", lambda m: " " if m[0].startswith("<br") else "", x))).strip() for x in parts]
        assert html_text.main_text(page) == "\n".join(filter(None, want))


def test_pages_on_odd_rows(spark):
    rows = [(1, "u", None, 3), (1, "u", None, 3), (None, None, "<p>x</p>", 1), (4, "v", "<p>" + "a b. " * 50_000, 0)]
    got = html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string, n_chars int")).collect()
    assert sorted(r.n_chars for r in got) == [0, 0, 1, 249_999]
    assert html_text.extract(spark.createDataFrame([], "page_id long, url string, html string")).collect() == []


# near duplicates in the pipeline


def test_near_duplicates_are_dropped(spark):
    rng = np.random.default_rng(2)
    base = [" ".join(f"t{rng.integers(3000)}" for _ in range(200)) for _ in range(6)]
    rows = [(10 * k + j, t if j == 0 else " ".join(["new"] + t.split()[1:]) if j == 1 else t) for k, t in enumerate(base) for j in range(3)]
    rows += [(500, None), (501, ""), (500, None)]
    got = sorted(r.doc_id for r in simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == [0, 10, 20, 30, 40, 50, 500]


# suffix repeats


def brute_repeats(texts, length):
    seen = {}
    for t in texts:
        for k in range(len(t) - length + 1):
            seen[t[k : k + length]] = seen.get(t[k : k + length], 0) + 1
    out = []
    for t in texts:
        mark = np.zeros(len(t), bool)
        for k in range(len(t) - length + 1):
            if seen[t[k : k + length]] > 1:
                mark[k : k + length] = True
        runs = int((np.diff(np.concatenate([[0], mark.astype(int)])) == 1).sum())
        out.append((len(t), int(mark.sum()), runs, hashlib.sha256(bytes(b for b, m in zip(t, mark, strict=True) if not m)).hexdigest()))
    return out


def test_repeats_equal_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(4)
    word = lambda n: "".join(rng.choice(list("abcdeé "), n))
    shared = word(260)
    texts = [word(500), word(300) + shared + word(120), word(90) + shared + word(400), shared[10:215] + word(50), shared[:199], "x" * 700, "ab" * 300, None, "", word(500)[:250] * 2]
    texts += [texts[0], texts[0][:250] + "!" + texts[0][251:]]
    line, other = word(110), word(90)
    texts += [word(int(rng.integers(0, 90))) + line + (other if k % 3 else word(95))[: int(rng.integers(60, 96))] + word(int(rng.integers(0, 160))) for k in range(40)]
    texts += [word(int(rng.integers(0, 40))) + shared[int(rng.integers(0, 30)) : 260 - int(rng.integers(0, 30))] + word(int(rng.integers(0, 40))) for k in range(30)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    want = brute_repeats([(t or "").encode() for t in texts], 200)
    for limit, common in ((4_000, 8), (1, 8), (5, 1)):  # as shipped; every group divided to the end; every gram dealt out by surroundings
        monkeypatch.setattr(suffix_dedup, "GROUP_LIMIT", limit)
        monkeypatch.setattr(suffix_dedup, "COMMON", common)
        got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(df).collect()}
        for k, expected in enumerate(want):
            assert got[k] == expected, (limit, common, k)


def test_repeats_of_rows_with_one_id(spark):
    """Rows of equal or null ids are known by their texts; equal rows are repeats of each other."""
    words = " ".join(f"w{k}" for k in range(90))
    rows = [(None, words), (None, "left " + words + " right"), (1, words[:150]), (1, words[:150] + words[:150]), (2, words + "."), (2, words + ".")]
    got = sorted((r.doc_id or 0, r.n_bytes, r.n_removed) for r in suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect())
    want = sorted((i or 0, *brute[:2]) for (i, _), brute in zip(rows, brute_repeats([t.encode() for _, t in rows], 200), strict=True))
    assert got == want


def test_hash_collisions_are_found(monkeypatch):
    """Prefix hashes that tell no bytes apart leave the results as they are."""
    rng = np.random.default_rng(9)
    around = [bytes(rng.integers(97, 99, 80).astype(np.uint8)) for _ in range(60)]
    around = [a[:20] + around[0][20:60] + a[60:] for a in around] + [around[0][:75] + b"zzzzz"] * 2
    make = lambda: suffix_dedup.Surroundings(around, np.full(62, 20), 60, 40)
    group, low, high = np.zeros(62, np.int64), np.zeros(62, np.int64), np.full(62, 20)
    want = make().matched(group, low, high)
    blind = make()
    blind.hash = np.zeros_like(blind.hash)
    got = blind.matched(group, low, high)
    assert all((x == y).all() for x, y in zip(want, got, strict=True)) and want[0].max() == 20


def test_repeats_of_odd_rows(odd, none):
    got = suffix_dedup.remove_repeats(odd).collect()
    assert sorted(r.n_removed for r in got) == sorted([0, 0, 300, 300, 300, 0, 300_000, 601])  # ß begins with the byte that é begins with
    assert suffix_dedup.remove_repeats(none).collect() == []
    left = suffix_dedup.strip_repeats(odd.withColumn("n_chars", F.length("text").cast("long"))).collect()
    assert {r.doc_id for r in left} == {1, 2, None, 7} and next(r for r in left if r.doc_id == 7).text == "!"


def test_suffix_order_is_lexicographic():
    rng = np.random.default_rng(6)
    around = [bytes(rng.integers(97, 99, rng.integers(40, 120)).astype(np.uint8)) for _ in range(300)]
    back = np.array([min(20, len(a) - 10) for a in around])
    group = np.sort(rng.integers(0, 9, 300))
    s = suffix_dedup.Surroundings(around, back, 100, 64)
    for forward in (True, False):
        order = s.order(group, forward)
        keys = [(group[k], around[k][back[k] :][:100] if forward else around[k][: back[k]][::-1], k) for k in order]
        assert keys == sorted(keys)


# vectors


def test_vectors_find_what_brute_force_finds(spark):
    rng = np.random.default_rng(7)
    centres = rng.normal(size=(12, 16))
    x = np.vstack([centres[rng.integers(0, 12, 150)] + 0.12 * rng.normal(size=(150, 16)), rng.normal(size=(300, 16))]).astype(np.float32)
    x[5] = x[4]
    label = [int(v) for v in rng.integers(0, 2, 450)]
    label[5] = label[4]
    got = {r.vec_id: r for r in vector_dedup.near_vectors(spark.createDataFrame([(k, x[k].tolist(), label[k]) for k in range(450)], "vec_id long, embedding array<float>, label int"), leaf=64).collect()}
    u = x.astype(float) / np.linalg.norm(x.astype(float), axis=1)[:, None]
    near = (u @ u.T >= 0.93) & (np.array(label)[:, None] == np.array(label)[None, :])
    truth, found = near.sum(axis=1) - 1, np.array([got[k].n_links for k in range(450)])
    assert (found <= truth).all() and found.sum() >= 0.97 * truth.sum()
    assert got[5].component_id <= 4 and not got[5].kept


def test_deep_trees_find_pairs_with_few_copies():
    """Pairs from 0.93 to 0.99 in 64 dimensions: recall of the forest, and leaves a vector and tree."""
    rng = np.random.default_rng(1)
    base = vector_dedup.unit(rng.normal(size=(20_000, 64)))
    a = base[:1000]
    c = rng.uniform(0.93, 0.99, 1000)
    other = rng.normal(size=(1000, 64))
    other = vector_dedup.unit(other - (other * a).sum(axis=1, keepdims=True) * a)
    b = c[:, None] * a + np.sqrt(1 - c**2)[:, None] * other
    for depth, recall in ((10, 0.99), (19, 0.95)):
        share, copies, own = np.zeros(1000, bool), 0, np.random.default_rng(5)
        for _ in range(8):
            tree = vector_dedup.fit_tree(base, 64, depth, 0.02, own)
            ra, ca = tree.leaves(a)
            met = set(zip(ra.tolist(), ca.tolist()))
            copies += len(ra)
            share[[r for r, x in zip(*(v.tolist() for v in tree.leaves(b))) if (r, x) in met]] = True
        assert share.mean() >= recall and copies / 8000 < 4


def test_dense_clusters_give_counts_and_not_pairs():
    import pyarrow as pa

    x = np.tile([1.0, 0.0], (60, 1)) + 1e-3 * np.random.default_rng(2).normal(size=(60, 2))
    names = ["group", "part", "node", "copies", "before", "vector"]
    batch = lambda g, before: pa.RecordBatch.from_arrays([pa.array([g] * 60), pa.array([0] * 60), pa.array(range(60)), pa.array([2] * 60), pa.array([before] * 60, pa.list_(pa.int64())), pa.array(x.tolist())], names=names)
    out = pa.Table.from_batches(list(vector_dedup.compare(iter([batch("g", []), batch("h", [5])]), 0.93))).to_pylist()
    counts = [r for r in out if r["b"] is None]
    assert len(out) - len(counts) == 2 * 59 and sorted((r["a"], r["more"]) for r in counts) == [(k, 118) for k in range(60)]


def test_vectors_on_odd_rows_and_large_leaves(spark, monkeypatch):
    v = [1.0, 0.0]
    rows = [(1, None, 1), (2, [0.0, 0.0], 1), (3, [float("nan"), 1.0], 1), (4, [None, 1.0], 1), (5, v, None), (6, v, 1), (7, v, 1), (7, v, 1), (8, [2.0, 0.0], 1), (9, v, 2), (None, v, 1), (10, [1.0], 1), (11, [], 1)]
    schema = "vec_id long, embedding array<double>, label int"
    got = {r.vec_id: (r.n_links, r.component_id) for r in vector_dedup.near_vectors(spark.createDataFrame(rows, schema)).collect() if r.vec_id}
    assert got[6] == (4, 6) and got[8] == (4, 6) and got[7] == (4, 6)
    assert all(got[k] == (0, k) for k in (1, 2, 3, 4, 5, 9, 10, 11))
    assert vector_dedup.near_vectors(spark.createDataFrame([], schema)).collect() == []
    monkeypatch.setattr(vector_dedup, "HOT", 1)  # no vector is named in place
    got = {r.vec_id: (r.n_links, r.component_id) for r in vector_dedup.near_vectors(spark.createDataFrame(rows, schema)).collect() if r.vec_id}
    assert got[6] == (4, 6) and got[8] == (4, 6) and got[7] == (4, 6) and got[9] == (0, 9)
    monkeypatch.setattr(vector_dedup, "CHUNK", 8)
    many = [(k, [1.0, 0.001 * k], 0) for k in range(40)]
    assert {r.n_links for r in vector_dedup.near_vectors(spark.createDataFrame(many, schema)).collect()} == {39}


# packing


def test_packing_round_trip(spark, docs, odd, none):
    import public_tokenizers
    from tokenizers import Tokenizer

    bpe = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rows = docs.select("doc_id", "text").union(odd.select("doc_id", "text").where("doc_id in (1, 2, 6, 7)").select(F.col("doc_id") + 10_000, "text"))
    special = ["a <|endoftext|> b", "<|endoftext|><|endoftext|>", "x  <|endoftext|>\n<|endoftext", "<|endofText|>"]
    rows = rows.union(docs.sparkSession.createDataFrame([(20_000 + k, t) for k, t in enumerate(special)], "doc_id long, text string"))
    got = packing.pack(rows, 256, group=20_000).toPandas()
    for doc in rows.collect():
        ids = np.array([*bpe.encode(doc.text or "", add_special_tokens=False).ids, 1], "<u4")
        part = got[got["doc_id"] == doc.doc_id].sort_values("start")
        assert part["length"].sum() == len(ids) and list(part["start"]) == [0, *np.cumsum(part["length"])[:-1]]
        assert all(zlib.crc32(ids[p.start : p.start + p.length].tobytes()) == p.ids_crc32 and p.doc_tokens == len(ids) for p in part.itertuples())
    for _, part in got.groupby("sequence_id"):
        part = part.sort_values("offset")
        assert list(part["offset"]) == [0, *np.cumsum(part["length"])[:-1]] and part["length"].sum() <= 256
    assert packing.pack(none).collect() == []


@pytest.mark.parametrize("partitions", [1, 60])
def test_packing_pads_little_however_rows_are_dealt_out(docs, partitions):
    load = packing.pack(docs.repartition(partitions)).groupBy("sequence_id").agg(F.sum("length").alias("n")).toPandas()["n"]
    assert load.sum() >= 0.98 * sum(n if n & (n - 1) == 0 else 2048 for n in load)


def test_sequences_without_padding():
    assert packing.unpadded(2 * 8 + 5, 8) == [8, 8, 4, 1] and packing.unpadded(0, 8) == []


def test_best_fit_is_the_tightest():
    lengths = np.array([60, 50, 40, 30, 20, 50, 1])
    sequence, offset, used = packing.best_fit_decreasing(lengths, 100)
    assert used == 3 and sequence[2] == sequence[0] and np.bincount(sequence, weights=lengths).max() <= 100
    assert sorted(offset[sequence == sequence[0]]) == [0, 60]


# pipeline


def test_pipeline_stages(spark, docs, tmp_path):
    before, stay = docs, []
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, before, SF).write.parquet(str(tmp_path / str(k)))
        after = spark.read.parquet(str(tmp_path / str(k)))
        if k < 4:
            assert after.columns == docs.columns
        before = after
        stay.append(after.select("doc_id").distinct().count())
    assert stay == sorted(stay, reverse=True) and stay[-1] == stay[-2] > 0
    third = spark.read.parquet(str(tmp_path / "3"))
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    assert decontaminate.contamination(third, bench).where("contaminated").isEmpty()
    assert corpus_pipeline.run(spark, SF).select("doc_id").distinct().count() == stay[-1]


def test_pipeline_stages_on_odd_rows(spark, none):
    """Nulls, empty and long texts, ties, repeated rows and columns that stages use inside, one stage after the other; and empty tables."""
    clean = "".join(f"Line {k} of a calm text about rivers and mountains and towns.\n" for k in range(40))
    rows = [(1, None), (2, ""), (3, clean), (3, clean), (4, clean), (None, clean + "More of it."), (None, "x"), (6, "word " * 60_000), (7, "é" * 300 + "ß!"), (8, " \t")]
    names = "doc_id long, text string, rest string, z int, spans int, hit_id long, stay_id long, toxic_score double, fp string, n_chars int"
    odd = spark.createDataFrame([(i, t, "r", 1, None, 5, None, 0.5, "f", 0) for i, t in rows], names)
    stay = {
        "toxicity": lambda got: len(got) >= 5,
        "simhash_near_dedup": lambda got: sorted((r.doc_id or 0, len(r.text or "")) for r in got) == [(0, 1), (1, 0), (3, len(clean)), (6, 300_000), (7, 302)],
        "suffix_array_dedup": lambda got: sorted((r.doc_id or 0, len(r.text or "")) for r in got) == [(0, 1), (0, 11), (1, 0), (2, 0), (7, 1), (8, 2)],
        "decontamination": lambda got: len(got) == len(rows),
        "packing": lambda got: {r.doc_id for r in got} == {i for i, _ in rows},
    }
    for name, stage in corpus_pipeline.STAGES:
        got = stage(spark, odd, SF)
        assert name == "packing" or got.columns == odd.columns
        assert stay[name](got.collect()), name
        assert stage(spark, none, SF).collect() == []
