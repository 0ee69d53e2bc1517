"""The vector operators against brute force."""

from __future__ import annotations

import math

import numpy as np
import pytest

from pointloom.llm import egojoin, topk
from pointloom.llm.components import unite

NAN, INF = float("nan"), float("inf")


def frame(spark, rows):
    return spark.createDataFrame([(i, v, 0, "own") for i, v in rows], "vec_id long, embedding array<float>, label int, n_links string")


def clustered(n, dim=16, seed=0):
    rng = np.random.default_rng(seed)
    c = rng.normal(size=(n // 10, dim))
    x = c[rng.integers(0, len(c), n)] + rng.normal(size=(n, dim)) * 0.22
    x[:: 7] *= 3.0
    x[5] = x[4]
    x[6] = x[4]
    return [(k, v.tolist()) for k, v in enumerate(x.astype(np.float32))]


ODD = [(900, None), (901, [0.0] * 16), (902, [NAN] + [1.0] * 15), (903, [INF] + [1.0] * 15), (904, [None] + [1.0] * 15), (905, []), (906, [1.0, 0.0]), (907, [2.0, 0.0]), (908, [1e-30] * 16), (909, [1e30] * 16)]


def brute(rows, cosine=0.95):
    good = [(i, np.array(v, np.float32).astype(float)) for i, v in rows if v and all(x is not None and math.isfinite(x) for x in v) and any(v)]
    links, root = {i: 0 for i, _ in rows}, {i: i for i, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in range(len(good)):
        for b in range(a + 1, len(good)):
            (i, x), (j, y) = good[a], good[b]
            if len(x) == len(y) and (x / np.abs(x).max()) @ (y / np.abs(y).max()) >= cosine * np.linalg.norm(x / np.abs(x).max()) * np.linalg.norm(y / np.abs(y).max()):
                links[i] += 1
                links[j] += 1
                p, q = sorted((find(i), find(j)))
                root[q] = p
    return sorted((i, links[i], find(i), find(i) == i) for i, _ in rows)


@pytest.mark.parametrize("interval,tile,leaf", [(4 << 20, 32 << 20, 1024), (32 * 128, 64 * 128, 16)])
def test_ego_join_matches_brute_force(spark, monkeypatch, interval, tile, leaf):
    monkeypatch.setattr(egojoin, "INTERVAL_BYTES", interval)
    monkeypatch.setattr(egojoin, "TILE_BYTES", tile)
    monkeypatch.setattr(egojoin, "LEAF", leaf)
    rows = clustered(400) + ODD
    got = sorted((r.vec_id, r.n_links, r.component_id, r.kept) for r in egojoin.near_duplicates(frame(spark, rows)).collect())
    assert got == brute(rows)
    assert sum(r[1] for r in got) > 200


def by_blocks(x, cosine=0.95):
    """Links and components of unit vectors by plain products."""
    n, label = np.zeros(len(x), np.int64), np.arange(len(x))
    for lo in range(0, len(x), 1000):
        i, j = np.nonzero(x[lo : lo + 1000] @ x.T >= cosine)
        n += np.bincount(j, minlength=len(x))
        label = unite(label, i + lo, j)
    return n - 1, label


@pytest.mark.parametrize("kind", ["clustered", "isotropic"])
def test_ego_join_of_ten_thousand(spark, monkeypatch, kind):
    monkeypatch.setattr(egojoin, "INTERVAL_BYTES", 500 * 8 * 24)
    monkeypatch.setattr(egojoin, "TILE_BYTES", 2000 * 8 * 24)
    rng = np.random.default_rng(1)
    x = rng.normal(size=(10_000, 24))
    if kind == "clustered":
        x = rng.normal(size=(300, 24))[rng.integers(0, 300, len(x))] + 0.15 * x
    else:
        x[5000:5200] = x[:200] + 0.01
    df = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = sorted(tuple(r) for r in egojoin.near_duplicates(df).select("vec_id", "n_links", "component_id").collect())
    n, root = by_blocks(x / np.linalg.norm(x, axis=1, keepdims=True))
    assert got == list(zip(range(len(x)), n.tolist(), root.tolist(), strict=True))


def test_ego_join_ids_that_repeat(spark):
    rows = [(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 0.01]), (3, [0.01, 1.0]), (3, [0.01, 1.0])]
    got = sorted(tuple(r) for r in egojoin.near_duplicates(frame(spark, rows)).collect())
    assert got == [(1, 1, 1, True), (1, 2, 1, True), (2, 1, 1, False), (3, 2, 1, False), (3, 2, 1, False)]


def test_boxes_with_the_rest_are_no_farther_than_vectors():
    rng = np.random.default_rng(0)
    u = egojoin._unit(rng.normal(size=(300, 20)))
    p = egojoin._leading(u, egojoin._axes(u, 4))
    far = ((u[:, None] - u[None]) ** 2).sum(axis=2)
    assert (((p[:, None] - p[None]) ** 2).sum(axis=2) <= far + egojoin.SLACK).all()


def test_ego_join_empty(spark):
    assert egojoin.near_duplicates(frame(spark, [])).collect() == []
    assert len(egojoin.near_duplicates(frame(spark, [(1, None)])).collect()) == 1


def brute_top(rows, every=100, k=10):
    good = [(i, [math.floor(1024 * float(np.float32(x))) for x in v]) for i, v in rows if v and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for i, q in good:
        if i % every == 0:
            s = sorted((-sum(a * b for a, b in zip(q, p)), j) for j, p in good if j != i and len(p) == len(q))
            out += [(i, n + 1, j, -v) for n, (v, j) in enumerate(s[:k])]
    return sorted(out)


@pytest.mark.parametrize("bucket", [2048, 32])
def test_top_k_matches_brute_force(spark, monkeypatch, bucket):
    monkeypatch.setattr(topk, "BUCKET_ROWS", bucket)
    rows = clustered(500) + [r for r in ODD if r[0] not in (909,)] + [(1000 + k, [0.5] * 16) for k in range(30)] + [(1100, [-0.5] * 16)]
    got = sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in topk.top_k(frame(spark, rows)).collect())
    assert got == brute_top(rows)


def test_top_k_large_components_stay_exact(spark):
    rows = [(0, [1e5, 3.0]), (1, [12345.678, 2.0]), (2, [99999.9, -7.0]), (3, [-1e5, 0.0]), (100, [1e5, 3.0])]
    got = sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in topk.top_k(frame(spark, rows)).collect())
    assert got == brute_top(rows)


def test_top_k_query_blocks(spark):
    rows = clustered(300) + [(40, [0.25] * 16)] * 9
    got = sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in topk.top_k(frame(spark, clustered(300)), every=20, query_bytes=300).collect())
    assert got == brute_top(clustered(300), 20)
    # an id that repeats is dealt over the blocks and is no candidate for itself
    got = topk.top_k(frame(spark, rows), every=20, query_bytes=300).where("query_id = 40").collect()
    assert len(got) == 10 and all(r.vec_id != 40 for r in got)


def plain_retrieve(qid, q, pid, p, k):
    score = np.where(qid[:, None] == pid[None, :], np.iinfo(np.int64).min + 1, (q @ p.T).astype(np.int64))
    order = np.lexsort((np.broadcast_to(pid, score.shape), -score), axis=1)[:, :k]
    return np.take_along_axis(score, order, axis=1), pid[order]


@pytest.mark.parametrize("spread,tile", [(0.05, 1 << 12), (0.05, 8 << 20), (1.0, 1 << 14)])
def test_retrieve_prunes_without_loss(monkeypatch, spread, tile):
    monkeypatch.setattr(topk, "TILE_BYTES", tile)
    monkeypatch.setattr(topk, "BUCKET_ROWS", 128)
    rng = np.random.default_rng(3)
    c = rng.normal(size=(12, 32))
    p = topk.integers((c[rng.integers(0, 12, 1500)] + spread * rng.normal(size=(1500, 32))) * rng.lognormal(0, 0.5, (1500, 1)))
    p[7:40] = p[7]
    p[50] = 0
    pid = rng.permutation(1500)
    q, qid = p[:300], pid[:300]
    best = topk.retrieve(qid, q, pid, p, np.full(300, topk.NONE))
    score, vec = plain_retrieve(qid, q, pid, p, 10)
    assert np.array_equal(best.score, score) and np.array_equal(best.vec, vec)


def test_retrieve_memory_does_not_grow_with_queries_times_bucket():
    import tracemalloc

    rng = np.random.default_rng(0)
    x = topk.integers(rng.normal(size=(65_536, 64)))
    floor = np.full(len(x), 100 * 1024 * 1024, np.int64)
    tracemalloc.start()
    topk.retrieve(np.arange(len(x)), x, np.arange(4096) + len(x), x[:4096] + 1, floor)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 300 << 20


def test_top_k_empty(spark):
    assert topk.top_k(frame(spark, [])).collect() == []
