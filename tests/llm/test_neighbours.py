import numpy as np
from pyspark.sql import functions as F

from predtopics.llm import neighbours as nb


def brute(ids, x, queries, k=5):
    out = {}
    for i in queries:
        s = nb.cosines(x[i], x)
        order = [j for j in np.lexsort((ids, -s)) if ids[j] != ids[i]][:k]
        out[int(ids[i])] = [(int(ids[j]), float(s[j])) for j in order]
    return out


def recall(got, want):
    hit = sum(len({v for v, _ in got.get(q, [])} & {v for v, _ in w}) for q, w in want.items())
    return hit / sum(map(len, want.values()))


def collected(frame):
    out = {}
    for r in frame.orderBy("query_id", "rank").collect():
        out.setdefault(r.query_id, []).append((r.vec_id, r.score))
        assert len(out[r.query_id]) == r["rank"]
    return out


def test_recall_against_brute_force(spark, monkeypatch):
    rows = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").select("vec_id", "embedding").orderBy("vec_id").collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], np.float64)
    want = brute(ids, x, np.flatnonzero(ids % 50 == 0))
    for block in (32_768, 300):  # the smaller one splits shards
        monkeypatch.setattr(nb, "BLOCK", block)
        got = collected(nb.op7_neighbours(spark, "/root/testdata/sf0.1"))
        assert set(got) == set(want) and all(len(v) == 5 for v in got.values())
        assert recall(got, want) >= 0.9
        for q, found in got.items():
            exact = dict(zip(ids.tolist(), nb.cosines(x[np.flatnonzero(ids == q)[0]], x).tolist()))
            assert all(exact[v] == s for v, s in found) and found == sorted(found, key=lambda r: (-r[1], r[0]))


def test_probes_come_in_order_of_success():
    h = nb.Hashing(8, hashes=3, probes=27)
    u = nb.unit(np.random.default_rng(1).normal(size=(5, 8)))
    cells, place = h.cells(u, 0)
    probed = h.probe(u, 0)
    assert (probed[:, 0] == h.code(cells)).all() and all(len(set(p)) == 27 for p in probed.tolist())
    nearest_wall = np.minimum(place, 1 - place).argmin(axis=1)
    for i in range(5):
        j, moved = nearest_wall[i], cells[i].copy()
        moved[j] += 1 if place[i, j] > 0.5 else -1
        assert probed[i, 1] == h.code(moved[None])[0]


def test_edges(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (1, [2.0, 0.0]), (2, [1.0, 0.0]), (3, [0.0, 1.0]), (4, None), (5, [0.0, 0.0]), (6, [nan, 1.0]), (7, [inf, 0.0]), (8, [None, 1.0]), (9, [1.0]), (None, [1.0, 0.0]), (2, [1.0, 0.0]), (50, [0.0, 0.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit("clash")).withColumn("shard", F.lit(1))
    assert collected(nb.nearest(frame, F.col("vec_id") % 50 == 0)) == {0: [(1, 1.0), (2, 1.0), (3, 0.0)]}
    assert nb.nearest(frame.limit(0), F.col("vec_id") % 50 == 0).count() == 0


def test_many_copies_of_one_vector(spark, monkeypatch):
    monkeypatch.setattr(nb, "BLOCK", 100)
    rng = np.random.default_rng(3)
    x = rng.normal(size=(900, 16)).astype(np.float32)
    x[::3] = x[0]
    frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = collected(nb.nearest(frame, F.col("vec_id") % 50 == 0))
    assert [v for v, _ in got[0]] == [3, 6, 9, 12, 15] and [v for v, _ in got[150]] == [0, 3, 6, 9, 12]


def test_isolated_queries_find_k_rows(spark, monkeypatch):
    rng = np.random.default_rng(5)
    centres = rng.normal(size=(40, 64))
    x = centres[rng.integers(0, 40, 4000)] + 0.02 * rng.normal(size=(4000, 64))
    lone = rng.choice(4000, 60, replace=False)
    x[lone] = rng.normal(size=(60, 64))
    x = x.astype(np.float32)
    monkeypatch.setattr(nb, "BLOCK", 1500)
    frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    asked = [int(i) for i in [*lone, *range(0, 4000, 100)]]
    got = collected(nb.nearest(frame, F.col("vec_id").isin(asked)))
    assert set(got) == set(asked) and all(len(v) == 5 for v in got.values())
    double = x.astype(np.float64)
    monkeypatch.setattr(nb, "fitted", lambda sample, dim, k: nb.Hashing(dim, cell=1e-3, probes=1))  # buckets of one row: all are compared with all
    got = collected(nb.nearest(frame, F.col("vec_id").isin(asked[:20])))
    assert got == brute(np.arange(4000), double, asked[:20])


def test_repeated_ids_do_not_push_out_others(spark):
    rows = [(0, [1.0, 0.0])] + [(1, [1.0, 0.01])] * 20 + [(i, [1.0, 0.1 * i]) for i in range(2, 9)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    assert [v for v, _ in collected(nb.nearest(frame, F.col("vec_id") == 0))[0]] == [1, 2, 3, 4, 5]
