"""Near duplicates against all pairs on sets of word tuples."""

import random

import numpy as np

from temporal_rules.llm import minhash_dedup, shingles
from temporal_rules.llm.components import components


def plain_set(text, width=5):
    words = (text or "").encode().lower().split()
    if not words:
        return set()
    k = min(width, len(words))
    return {tuple(words[i : i + k]) for i in range(len(words) - k + 1)}


def brute(rows, percent=75):
    """rows: (doc_id, text) -> {doc_id: (n, component)} by comparing every pair that shares a shingle."""
    sets = {i: plain_set(t) for i, t in rows}
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    by = {}
    for i in sorted(sets):
        for s in sets[i]:
            by.setdefault(s, []).append(i)
    done = set()
    for ids in by.values():
        for a in range(len(ids)):
            for b in range(a):
                p = (ids[b], ids[a])
                if p in done:
                    continue
                done.add(p)
                x, y = sets[p[0]], sets[p[1]]
                if 100 * len(x & y) >= percent * len(x | y):
                    ra, rb = root(p[0]), root(p[1])
                    up[max(ra, rb)] = min(ra, rb)
    return {i: (len(sets[i]), root(i)) for i in sets}


def check(df):
    rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash_dedup.near_duplicates(df).collect()}
    want = brute([r for r in rows if r[0] is not None])
    assert {i: v[:2] for i, v in got.items() if i is not None} == want
    assert all(v[2] == (i == v[1]) for i, v in got.items() if i is not None)


def test_tables(spark):
    for d in ("sf0.001", "sf0.01"):
        check(spark.read.parquet(f"/root/testdata/{d}/documents.parquet"))


def test_groups_around_the_threshold(spark):
    rng = random.Random(4)
    rows = []
    for base in range(12):
        words = [f"w{rng.randrange(10**6)}" for _ in range(rng.choice([3, 5, 60, 200]))]
        for _ in range(25):
            w = list(words)
            for _ in range(rng.randrange(8)):
                w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
            rows.append((len(rows) * 7 % 1000, rng.choice([" ", "\n", "  "]).join(w), 0, "k"))
    rows += [(1001, None, 1, "k"), (1002, "", 1, "k"), (1003, " \t", 1, "k"), (1004, "One\x0bTWO", 1, "k"), (1005, "one two", 1, "k"), (1006, "long " * 50_000, 1, "k"), (None, "one two", 1, "k")]
    check(spark.createDataFrame(rows, "doc_id long, text string, n long, key string"))


def test_empty_and_repeated(spark):
    df = spark.createDataFrame([(1, "a b c"), (1, "a b c"), (2, "a b c")], "doc_id long, text string")
    got = sorted(map(tuple, minhash_dedup.near_duplicates(df).collect()))
    assert got == [(1, 1, 1, True), (1, 1, 1, True), (2, 1, 1, False)]
    assert minhash_dedup.near_duplicates(df.limit(0)).collect() == []


def test_sketch_estimates_jaccard():
    rng = np.random.default_rng(1)
    pool = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
    for n in (1, 3, 40, 1000):
        for j in (0.5, 0.75, 1.0):
            both = max(1, int(n * j))
            gap = (n - both) // 2
            a, b = np.unique(pool[: both + gap]), np.unique(np.concatenate([pool[:both], pool[both + gap : both + 2 * gap]]))
            sk = shingles.sketch([a, b, np.zeros(0, np.uint64)], 1024)
            want = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
            assert abs((sk[0] == sk[1]).mean() - want) < 0.08
            assert not sk[2].any() and sk[0].all()


def test_blocks_equal_whole(spark):
    """A bucket cut in blocks gives the same components as one block."""
    rng = random.Random(7)
    words = [f"w{i}" for i in range(40)]
    sets, ids = [], []
    for i in range(60):
        w = list(words)
        w[rng.randrange(40)] = f"y{i}"
        sets.append(shingles.shingle_hashes(" ".join(w)))
        ids.append(i)
    keys = shingles.bands(shingles.sketch(sets, 128), 4)
    part, found, cut = np.arange(60), set(), set()
    for key in np.unique(keys):
        inside = np.flatnonzero((keys == key).any(axis=1))
        if len(inside) < 2:
            continue
        args = (128, 4, 0.0, 75)
        found |= set(minhash_dedup.block_links(int(key), [ids[i] for i in inside], part[inside], np.full(len(inside), 2), [sets[i] for i in inside], *args))
        for a in range(3):
            for b in range(a, 3):
                rows = [i for i in inside if i % 3 in (a, b)]
                side = np.array([2 if a == b else int(i % 3 == b) for i in rows])
                if len(rows) > 1:
                    cut |= set(minhash_dedup.block_links(int(key), rows, part[rows], side, [sets[i] for i in rows], *args))
    get = lambda e: sorted(map(tuple, components(spark.createDataFrame([(int(a), int(b)) for a, b in e], "a long, b long")).collect()))
    assert get(found) == get(cut)


def test_components_of_paths_and_stars(spark):
    rng = random.Random(3)
    edges = [(i, i + 1) for i in range(100, 160)] + [(500, i) for i in range(501, 560)] + [(7, 7), (None, 3)]
    rng.shuffle(edges)
    got = dict(map(tuple, components(spark.createDataFrame(edges, "a long, b long")).collect()))
    assert got == {**{i: 100 for i in range(100, 161)}, **{i: 500 for i in range(500, 560)}}
