"""Components against a plain search, SimHash links against all pairs."""

import numpy as np
import pytest
import xxhash

from gradvb.llm.components import components
from gradvb.llm.simhash import fingerprint, near_links, simhash_groups


def plain_components(links):
    near = {}
    for a, b in links:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    label = {}
    for start in sorted(near):
        todo = [start] if start not in label else []
        while todo:
            node = todo.pop()
            if node not in label:
                label[node] = start
                todo.extend(near[node])
    return label


@pytest.mark.parametrize("kind", ["path", "star", "random", "rings"])
def test_components(spark, kind):
    rng = np.random.default_rng(3)
    links = {
        "path": [(k, k + 1) for k in rng.permutation(60).tolist()],
        "star": [(500, k) for k in range(40)] + [(500, 900)],
        "random": [(int(a), int(b)) for a, b in rng.integers(-200, 200, (260, 2)) if a != b],
        "rings": [(10 * r + k, 10 * r + (k + 1) % 10) for r in range(8) for k in range(10)],
    }[kind]
    found = components(spark.createDataFrame(links, "a long, b long").repartition(7)).collect()
    assert {r.node: r.component for r in found} == plain_components(links)
    assert len(found) == len({r.node for r in found})


def test_components_of_nothing(spark):
    assert components(spark.createDataFrame([], "a long, b long")).collect() == []
    assert components(spark.createDataFrame([(1, 1), (None, 2)], "a long, b long")).collect() == []


def near_prints(rng, centres, each):
    out = set()
    for c in rng.integers(0, 2**63, centres, dtype=np.uint64):
        out.add(int(c))
        for _ in range(each):
            flips = rng.choice(64, rng.integers(1, 5), replace=False)
            out.add(int(c) ^ sum(1 << int(f) for f in flips))
    return np.array(sorted(out), np.uint64)


@pytest.mark.parametrize(("centres", "each"), [(30, 6), (2, 250)])
def test_near_links_connect_what_all_pairs_connect(spark, centres, each):
    x = near_prints(np.random.default_rng(5), centres, each)
    a, b = np.nonzero(np.triu(np.bitwise_count(x[:, None] ^ x[None, :]) <= 3, 1))
    want = plain_components(list(zip(x[a].view(np.int64).tolist(), x[b].view(np.int64).tolist())))
    frame = spark.createDataFrame([(int(v),) for v in x.view(np.int64)], "fp long")
    links = near_links(frame)
    got = {r.node: r.component for r in components(links).collect()}
    assert got == want
    for r in links.collect():
        assert (r.a ^ r.b).__and__((1 << 64) - 1).bit_count() <= 3


def test_fingerprint_is_the_majority_of_shingle_hashes():
    text = "One two  THREE\tfour Éa é five six".encode()
    found = [w for w in text.lower().split()]
    hashes = [xxhash.xxh64_intdigest(b" ".join(found[k : k + 3]), 42) for k in range(len(found) - 2)]
    want = sum(1 << bit for bit in range(64) if 2 * sum(h >> bit & 1 for h in hashes) > len(hashes))
    assert fingerprint(text, 3, 42) & (2**64 - 1) == want
    assert fingerprint(b" \t", 3, 42) == 0
    assert fingerprint(b"a b", 3, 42) & (2**64 - 1) == xxhash.xxh64_intdigest(b"a b", 42)


@pytest.mark.parametrize("hot", [10_000, 1])
def test_groups_on_odd_rows(spark, monkeypatch, hot):
    """All texts named in place, and none of them."""
    monkeypatch.setattr("gradvb.llm.simhash.HOT", hot)
    rows = [(5, "a b c d e", "x"), (3, "A b c d e", None), (3, "A b c d e", None), (9, None, "y"), (8, "", "y"), (None, "z", None), (7, "q " * 30000, None)]
    got = sorted((r.doc_id if r.doc_id is not None else -1, r.component_id) for r in simhash_groups(spark.createDataFrame(rows, "doc_id long, text string, fp string")).collect())
    assert got == [(-1, None), (3, 3), (3, 3), (5, 3), (7, 7), (8, 8), (9, 8)]
    assert simhash_groups(spark.createDataFrame([], "doc_id long, text string")).collect() == []
