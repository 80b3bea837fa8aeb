"""The pipeline's near-duplicate stage against all pairs of texts."""

import numpy as np
import pytest

from gradvb.llm import simhash
from test_components_simhash import plain_components


def brute_stay(texts, least=0.8):
    sets = [simhash.shingle_set(t.encode(), 5) for t in texts]
    links = [(i, j) for i in range(len(texts)) for j in range(i + 1, len(texts)) if simhash.similarity(sets[i], sets[j]) >= least]
    label = plain_components(links)
    return sorted(k for k in range(len(texts)) if label.get(k, k) == k), links, sets


def stay(spark, texts):
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return sorted(r.doc_id for r in simhash.drop_near_duplicates(rows).collect())


def changed(rng, words, changes):
    words = list(words)
    for k in rng.choice(len(words), changes, replace=False):
        words[k] = f"z{rng.integers(10**9)}"
    return " ".join(words)


@pytest.mark.parametrize("small", [24, 3])
def test_pairs_behind_a_failed_leader_are_looked_at(spark, monkeypatch, small):
    """Equal fingerprints of repeated shingles, other sets of shingles: each pair of copies hangs on no leader."""
    monkeypatch.setattr(simhash, "SMALL", small)
    rng = np.random.default_rng(4)
    line = "the same line of words stands here again and once more"
    texts = []
    for _ in range(30):
        own = [f"w{rng.integers(10**9)}" for _ in range(60)]
        for text in (" ".join(own), changed(rng, own, 1)):
            texts.append(" ".join([line] * 400) + " " + text)
    want, links, _ = brute_stay(texts)
    assert len(links) == 30 and stay(spark, texts) == want


@pytest.mark.parametrize("run", [500_000, 4])
def test_common_lines_and_blocks(spark, monkeypatch, run):
    """Texts of one common passage and little else, in buckets of several blocks, held whole or in pieces."""
    monkeypatch.setattr(simhash, "RUN", run)
    monkeypatch.setattr(simhash, "SMALL", 3)
    monkeypatch.setattr(simhash, "BLOCK", 7)
    rng = np.random.default_rng(6)
    line = [f"c{k}" for k in range(40)]
    texts = [" ".join(line[: rng.integers(3, 40)] + [f"w{rng.integers(10**9)}" for _ in range(rng.integers(0, 8))]) for _ in range(120)]
    want, links, _ = brute_stay(texts)
    assert links and stay(spark, texts) == want


def test_all_pairs_from_eight_to_nine_tenths_are_found(spark):
    rng = np.random.default_rng(8)
    texts = []
    for _ in range(60):
        own = [f"w{rng.integers(10**9)}" for _ in range(rng.integers(60, 400))]
        texts += [" ".join(own), changed(rng, own, max(1, len(own) // 60))]
    want, links, sets = brute_stay(texts)
    assert sum(simhash.similarity(sets[i], sets[j]) < 0.9 for i, j in links) >= 40
    assert stay(spark, texts) == want


def test_large_buckets_give_each_pair_once_and_rule_none_out_that_is_near():
    """Two large buckets with the same texts: pairs come out of the first alone, all near ones among them and few others."""
    import pyarrow as pa

    rng = np.random.default_rng(3)
    base = [f"b{k}" for k in range(245)]
    texts = [changed(rng, base + [f"c{k}" for k in range(rng.integers(0, 30))], int(rng.integers(0, 7))) for _ in range(60)]
    sets = [simhash.shingle_set(t.encode(), 5) for t in texts]
    bits = simhash.bitmaps(pa.array(texts), 5).to_pylist()
    order = sorted(range(60), key=lambda k: len(sets[k]))
    rows = [(g, key, len(sets[key]), pos, key, 0, 1, before, bits[key]) for g, pos, before in ((1, 0, []), (2, 1, [77])) for key in order]
    names = ["g", "key", "n", "pos", "label", "block", "same", "before", "bits"]
    batch = pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.int64()) for k in range(7)] + [pa.array([r[7] for r in rows], pa.list_(pa.int64())), pa.array([r[8] for r in rows])], names=names)
    got = [(x, y) for b in simhash.open_pairs(0.8)(iter([batch.slice(0, 13), batch.slice(13)])) for x, y in zip(b["x"].to_pylist(), b["y"].to_pylist(), strict=True)]
    like = {(i, j): simhash.similarity(sets[i], sets[j]) for i in range(60) for j in range(i + 1, 60)}
    assert len(set(got)) == len(got) and {p for p, v in like.items() if v >= 0.8} <= set(got) < set(like)
    assert min(like[p] for p in got) > 0.7 and len({len(b) for b in bits}) > 1


def test_fingerprints_pair_near_texts_and_the_stage_uses_them(spark, monkeypatch):
    """SimHash joins the keys of each group of close fingerprints; the stage keeps what brute force keeps, with its pairs among the candidates."""
    rng = np.random.default_rng(12)
    texts = []
    for _ in range(20):
        own = [f"w{rng.integers(10**9)}" for _ in range(400)]
        texts += [" ".join(own), changed(rng, own, 1), changed(rng, own, 2)]
    texts += ["", " ", "\t"]
    prints = [simhash.fingerprint(t.encode(), 3, 42) & (1 << 64) - 1 for t in texts]
    want = plain_components([(i, j) for i in range(len(texts)) for j in range(i + 1, len(texts)) if (prints[i] ^ prints[j]).bit_count() <= 3])
    got = plain_components([tuple(r) for r in simhash.fingerprint_pairs(spark.createDataFrame(list(enumerate(texts)), "key long, text string")).collect()])
    assert got == want and len(want) > 20
    seen, search = [], simhash.fingerprint_pairs
    monkeypatch.setattr(simhash, "fingerprint_pairs", lambda *a: seen.append(search(*a)) or seen[-1])
    assert stay(spark, texts) == brute_stay(texts)[0] and len(seen) == 1
