import random

import numpy as np
import pytest
import xxhash

from vertexlog.llm import links, simhash


def plain_fingerprint(text):
    words = text.encode().lower().split() if text else []
    if not words:
        return 0
    parts = [b" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hashes = [xxhash.xxh64_intdigest(p, 42) for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_fingerprint_bit_by_bit():
    for text in ("", "one", "one two three four", "a b c d e f g h a b c d", "É x\ty\nz É x y z q"):
        assert simhash.fingerprint(text.encode()) % 2**64 == plain_fingerprint(text)


def test_every_pattern_of_four_bits_meets_at_a_home_anchor():
    r = np.random.default_rng(5)
    base = r.integers(-(2**63), 2**63 - 1, 300, dtype=np.int64)
    masks = [sum(1 << int(b) for b in r.choice(64, k, replace=False)) for k in (0, 1, 2, 3, 4) for _ in range(60)]
    other = base ^ np.array(masks, np.uint64).view(np.int64)
    key_a, own_a, home_a = simhash.anchors(base)
    key_b, own_b, _ = simhash.anchors(other)
    homes = [set() for _ in base]
    for k, o in zip(key_a[home_a].tolist(), own_a[home_a].tolist(), strict=True):
        homes[o].add(k)
    met = np.zeros(len(base), bool)
    for k, o in zip(key_b.tolist(), own_b.tolist(), strict=True):
        met[o] |= k in homes[o]
    assert met.all()


def test_anchors_are_codewords_within_their_radius():
    fps = np.random.default_rng(1).integers(-(2**63), 2**63 - 1, 50, dtype=np.int64)
    keys, _, home = simhash.anchors(fps)
    core = keys & 0x7FFFFFFF
    assert (simhash._LOW[core & 0xFFFF] ^ simhash._HIGH[core >> 16] == 0).all()
    assert home.sum() == 50 * len(simhash.triples())


@pytest.mark.parametrize("n", [1, 7, 60])
def test_groups_keep_their_components(n):
    r = np.random.default_rng(n)
    fps = (r.integers(0, 2**63 - 1, 3, dtype=np.int64)[r.integers(0, 3, n)]) ^ (1 << r.integers(0, 6, n)).astype(np.int64)
    a, b = simhash.link_group(np.unique(fps), np.ones(len(np.unique(fps)), bool))
    u, roots = links.forest(a, b)
    label = dict(zip(u.tolist(), roots.tolist(), strict=True))
    values = np.unique(fps)
    for x in values:
        for y in values:
            if bin(int(x ^ y) % 2**64).count("1") <= 4:
                assert label.get(int(x), int(x)) == label.get(int(y), int(y))


def test_components_of_chains_and_stars(spark):
    rows = [(i, i + 1) for i in range(30)] + [(100, i) for i in range(101, 150)] + [(7, 7), (200, 201), (201, 200)]
    got = dict(map(tuple, links.components(spark.createDataFrame(rows, "u bigint, v bigint").repartition(3)).collect()))
    assert got == {**{i: 0 for i in range(1, 31)}, **{i: 100 for i in range(101, 150)}, 201: 200}
    assert links.components(spark.createDataFrame([], "u bigint, v bigint")).count() == 0


def test_report_equals_brute_force(make, awkward):
    r = random.Random(2)
    vocabulary = [f"w{i}" for i in range(300)]
    texts = [" ".join(r.choices(vocabulary, k=200)) for _ in range(30)]
    for t in list(texts[:10]):
        for _ in range(6):
            words = t.split()
            words[r.randrange(200)] = "changed"
            texts.append(" ".join(words))
    docs = list(enumerate(texts)) + [(500, None), (501, "  "), (502, texts[3]), (502, texts[3])]
    got = simhash.near_duplicate_report(make(docs)).collect()
    fp = {i: plain_fingerprint(t) for i, t in docs}
    parent = {i: i for i in fp}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a in fp:
        for b in fp:
            if bin(fp[a] ^ fp[b]).count("1") <= 4:
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    assert len(got) == len(docs)
    for row in got:
        assert row["fingerprint"] == f"{fp[row['doc_id']]:016x}" and row["component_id"] == find(row["doc_id"])
    kept = simhash.keep_one_of_each(awkward)
    assert kept.columns == awkward.columns and sorted(str(x["doc_id"]) for x in kept.collect()) == ["1", "4", "4", "6", "7", "None"]
    assert simhash.near_duplicate_report(awkward.limit(0)).count() == 0 and simhash.near_duplicate_report(awkward).count() == 9
