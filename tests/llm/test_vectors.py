"""Nearest neighbours and the vector join against brute force."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from temporal_rules.llm import ego_join, stable_ann
from temporal_rules.llm.queries import op1_stable_projection_ann, op9_vector_near_duplicates

ROWS = "vec_id long, embedding array<double>, label int, cell long, v string"
NAN, INF = float("nan"), float("inf")


@pytest.fixture(scope="module")
def odd(spark):
    rng = np.random.default_rng(3)
    rows = [(i, rng.standard_normal(6).tolist(), 1, 2, "x") for i in range(0, 300, 10)]
    rows += [(i + 1, (np.array(v) * 3 if i % 20 else np.array(v)).tolist(), None, None, None) for i, v, *_ in rows]
    rows += [(900, None, 0, 0, ""), (1000, [0.0] * 6, 0, 0, ""), (1100, [NAN] * 6, 0, 0, ""), (1200, [INF] + [1.0] * 5, 0, 0, ""), (1300, [None] + [1.0] * 5, 0, 0, ""), (1400, [1.0, 2.0], 0, 0, ""), (None, [1.0] * 6, 0, 0, ""), (1500, [], 0, 0, "")]
    return spark.createDataFrame(rows, ROWS)


def valid(df):
    rows = [(r.vec_id, r.embedding) for r in df.select("vec_id", "embedding").collect()]
    width = max({len(v) for _, v in rows if v}, key=[len(v) for _, v in rows if v].count)
    ok = [(i, np.array(v, float)) for i, v in rows if i is not None and v and len(v) == width and None not in v and np.isfinite(v).all() and np.any(v)]
    return rows, ok


def recall(got, ok, k=10):
    by = {}
    for r in got:
        by.setdefault(r.query_id, []).append(r)
    ids, x = np.array([i for i, _ in ok]), np.array([v for _, v in ok])
    at = {i: n for n, i in enumerate(ids.tolist())}
    queries = [i for i in ids.tolist() if i % 100 == 0]
    assert set(by) == set(queries)
    hit = total = 0
    for q in queries:
        d = np.sqrt(((x - x[at[q]]) ** 2).sum(1))
        other = np.flatnonzero(ids != q)
        want = other[np.lexsort((ids[other], d[other]))][:k]
        mine = sorted(by[q], key=lambda r: r.rank)
        assert [r.rank for r in mine] == list(range(1, len(mine) + 1))
        assert [(r.score, r.vec_id) for r in mine] == sorted((r.score, r.vec_id) for r in mine)
        for r in mine:
            assert r.vec_id != q and r.score == pytest.approx(d[at[r.vec_id]], abs=1e-12)
        hit += len({r.vec_id for r in mine} & set(ids[want].tolist()))
        total += len(want)
        assert len(mine) == len(want)
    return hit / total


def test_recall_of_table(spark):
    d = "/root/testdata/sf0.1"
    got = op1_stable_projection_ann(spark, d).collect()
    assert recall(got, valid(spark.read.parquet(f"{d}/embeddings.parquet"))[1]) >= 0.95


def test_cells_and_odd_rows(spark, odd):
    from pyspark.sql import functions as F

    got = stable_ann.nearest_neighbours(odd, F.col("vec_id") % 100 == 0, cell_rows=8, query_rows=2).collect()
    assert recall(got, valid(odd)[1]) >= 0.9
    few = odd.where("vec_id in (100, 110, 120, 900)")
    assert len(stable_ann.nearest_neighbours(few, F.col("vec_id") % 100 == 0).collect()) == 2
    assert stable_ann.nearest_neighbours(odd.limit(0), F.col("vec_id") % 100 == 0).collect() == []


def test_quantile():
    assert stable_ann.chi_square_quantile(0.95, 2) == pytest.approx(5.991, abs=1e-3)
    assert stable_ann.chi_square_quantile(0.95, 8) == pytest.approx(15.507, abs=1e-3)


def brute_links(rows, ok, t=0.95):
    ids, x = np.array([i for i, _ in ok]), np.array([v for _, v in ok])
    u = x / np.sqrt((x * x).sum(1))[:, None]
    link = u @ u.T >= t
    np.fill_diagonal(link, False)
    label = ids.copy()
    while True:
        new = np.minimum(label, np.where(link, label[None, :], np.iinfo(np.int64).max).min(1))
        if (new == label).all():
            break
        label = new
    want = {int(i): (int(n), int(c)) for i, n, c in zip(ids, link.sum(1), label)}
    return {i: want.get(i, (0, i)) for i, _ in rows}


def test_links_of_table_and_odd_rows(spark, odd):
    for df, got in ((spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet"), op9_vector_near_duplicates(spark, "/root/testdata/sf0.1")), (odd, ego_join.similar_vectors(odd, interval=7))):
        got = got.collect()
        assert {r.vec_id: (r.n_links, r.component_id) for r in got} == brute_links(*valid(df))
        assert all(r.kept == (r.vec_id is None or r.vec_id == r.component_id) for r in got)
        assert len(got) == df.count()
    assert ego_join.similar_vectors(odd.limit(0)).collect() == []


def test_copies_count_each_other(spark):
    df = spark.createDataFrame([(5, [1.0, 0.0]), (3, [1.0, 0.0]), (9, [0.0, 1.0]), (7, [1.0, 0.0]), (8, [0.999, 0.01])], "vec_id long, embedding array<float>")
    got = sorted(map(tuple, ego_join.similar_vectors(df).collect()))
    assert got == [(3, 3, 3, True), (5, 3, 3, False), (7, 3, 3, False), (8, 3, 3, False), (9, 0, 9, True)]


def test_repeated_keys_and_widths(spark):
    import numpy as np

    rng = np.random.default_rng(2)
    rows = [(i, rng.standard_normal(6).tolist()) for i in range(60)] + [(100, rng.standard_normal(6).tolist()), (100, rng.standard_normal(6).tolist())]
    rows += [(1000 + i, rng.standard_normal(3).tolist()) for i in range(12)] + [(200, [1.0, 2.0, 3.0]), (2000, [1.0, 2.0, 3.01])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = stable_ann.nearest_neighbours(df, F.col("vec_id") % 100 == 0, k=4, confidence=0.999999).collect()
    want = []
    for i, (key, v) in enumerate(rows):
        if key % 100 == 0:
            near = sorted((float(np.linalg.norm(np.array(v) - np.array(w))), k) for j, (k, w) in enumerate(rows) if j != i and len(w) == len(v))[:4]
            want += [(key, r + 1, k, round(d, 9)) for r, (d, k) in enumerate(near)]
    assert sorted((r.query_id, r["rank"], r.vec_id, round(r.score, 9)) for r in got) == sorted(want)
    linked = {r.vec_id: r.n_links for r in ego_join.similar_vectors(df, 0.95).collect()}
    assert linked[200] >= 1 and linked[2000] >= 1 and len(linked) == len({k for k, _ in rows})
