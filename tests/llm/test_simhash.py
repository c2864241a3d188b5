import numpy as np
import pytest

from lattice_pages.llm import simhash


def brute(fps):
    """Component name of every fingerprint: the least row number reachable."""
    label = list(range(len(fps)))
    changed = True
    a = np.array(fps, np.uint64)
    near = np.bitwise_count(a[:, None] ^ a[None, :]) <= simhash.THRESHOLD
    while changed:
        new = [min(label[j] for j in np.flatnonzero(near[i])) for i in range(len(fps))]
        changed, label = new != label, new
    return label


def plain_fingerprint(text):
    import re

    import xxhash

    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not words:
        return 0
    grams = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_views_cover_every_spread():
    assert simhash.views_cover(simhash.VIEWS)
    assert not simhash.views_cover(simhash.VIEWS[:5])


@pytest.mark.parametrize("text", [None, "", "one", "A b C", "a b c d", "É A b\x0bc\td e f", "w " * 700, " ".join(f"x{i}" for i in range(900))])
def test_fingerprint(text):
    assert simhash.fingerprint(text) == plain_fingerprint(text)


def test_components_equal_brute_force(spark):
    r = np.random.default_rng(3)
    fps = [int(x) for x in r.integers(0, 2**63, 60, dtype=np.uint64)]
    for base in list(fps[:30]):
        for _ in range(4):  # chains of near fingerprints, some just beyond the threshold
            for b in r.choice(64, int(r.integers(1, 7)), replace=False):
                base ^= 1 << int(b)
            fps.append(base)
    hub = 0x0123456789ABCDEF
    fps += [hub ^ (1 << i) ^ (1 << j) for i in range(20) for j in range(i)] + [0, 0]
    nodes = spark.createDataFrame([(int(np.uint64(f).astype(np.int64)),) for f in set(fps)], "fp long")
    want = brute(fps)
    for block in (simhash.HOME_BLOCK, 8):  # the second splits anchors into blocks
        found = {(x.a, x.b) for x in simhash.links(nodes, home_block=block).collect()}
        parent = {f: f for f in fps}

        def root(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for a, b in found:
            a, b = (int(np.int64(x).astype(np.uint64)) for x in (a, b))
            assert bin(a ^ b).count("1") <= simhash.THRESHOLD
            parent[root(a)] = root(b)
        groups = {}
        for i, f in enumerate(fps):
            groups.setdefault(root(f), []).append(i)
        assert sorted(map(tuple, groups.values())) == sorted(tuple(i for i, w in enumerate(want) if w == k) for k in set(want))


def test_odd_rows(spark):
    rows = [(1, None, "x"), (2, "", "y"), (3, "a b c d e f", None), (3, "a b c d e f", None), (None, "A B c d e f", "z"), (9, "q " * 50000, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string, component_id string")
    got = {(r.doc_id, r.component_id) for r in simhash.near_components(df).collect()}
    assert {(1, 1), (2, 1), (3, 3), (None, 3)} <= got
    assert simhash.near_components(df.limit(0)).count() == 0
    kept = simhash.keep_one(df).select("doc_id").collect()
    assert sorted((r[0] is None, r[0]) for r in kept) == [(False, 1), (False, 3), (False, 9), (True, None)]
