"""Neighbour searches, measures and byte codecs against brute force and hand-made examples."""

import numpy as np
import pytest

from shotgrid.operators import bytecodecs, coders, geometry, masks, measures

POINT = "frame_id long, id long, x double, y double, z double"


def test_local_tree_equals_brute_force():
    rng = np.random.default_rng(0)
    p, q = np.round(rng.random((700, 3)) * 20, 1), rng.random((90, 3)) * 24 - 2
    at, d = geometry.LocalTree(p).query(q, 5)
    full = ((q[:, None] - p[None]) ** 2).sum(2)
    order = np.lexsort((np.broadcast_to(np.arange(700), full.shape), full))[:, :5]
    assert np.allclose(d, np.take_along_axis(full, order, 1)) and (at == order).mean() > 0.999
    at, d = geometry.LocalTree(p[:3]).query(q[:2], 5)
    assert (at[:, 3:] == -1).all() and np.isinf(d[:, 3:]).all()


def test_nearest_with_far_points_and_frames_without_partners(spark):
    rng = np.random.default_rng(1)
    p = [(0, i, *map(float, rng.random(3) * 10)) for i in range(60)] + [(0, 100, 9e5, 0.0, 0.0), (1, 101, 0.0, 0.0, 0.0)]
    q = [(0, i, *map(float, rng.random(3) * 10)) for i in range(50)]
    a, b = spark.createDataFrame(p, POINT), spark.createDataFrame(q, POINT)
    want = {r[1]: min(np.sqrt(sum((u - v) ** 2 for u, v in zip(r[2:], s[2:]))) for s in q) for r in p if not r[0]}
    got = {r.id: r.dist for r in geometry.nearest(a, b, 1.0, rounds=3).collect()}
    assert got.pop(101) is None and got == pytest.approx(want)


def test_psnr_and_resolution_by_hand(spark):
    p = spark.createDataFrame([(0, i, x, 0.0, 0.0, 1.0, 0.0, 0.0) for i, x in enumerate((0.0, 1.0, 3.0))], POINT + ", nx double, ny double, nz double")
    q = spark.createDataFrame([(0, i, x, 0.0, 0.0) for i, x in enumerate((0.0, 1.2))], POINT)
    r = measures.psnr(p, q, 1.0).first()
    assert (r.r, r.mse, r.back, r.psnr) == pytest.approx((2, 3.28 / 3, 0.02, 5.63307), abs=1e-5)


def test_asof_carries_poses_over_buckets(spark):
    shots = spark.createDataFrame([("a", f"2024-01-0{d} 12:00:00") for d in (1, 2, 4)] + [("b", "2024-01-04 00:00:00")], "s string, t string").selectExpr("s", "cast(t as timestamp) as ts")
    poses = spark.createDataFrame([("a", "2024-01-01 13:00:00", 1), ("a", "2024-01-02 12:00:00", 2)], "s string, t string, v int").selectExpr("s", "cast(t as timestamp) as ts", "v")
    assert sorted((r.s, r.ts.day, r.v) for r in geometry.asof(shots, poses, ["s"], "ts", ["v"]).collect()) == [("a", 1, None), ("a", 2, 2), ("a", 4, 2), ("b", 4, None)]


def test_point_and_image_codecs_invert():
    rng = np.random.default_rng(2)
    for n in (0, 1, 2, 300):
        p = rng.integers(0, 64, (n, 3))
        for context in ("none", "parent", "level"):
            got = bytecodecs.octree_unpack(bytecodecs.octree_pack(p, 6, context), 6, context)
            assert sorted(map(tuple, got)) == sorted(set(map(tuple, p)))
        assert sorted(map(tuple, bytecodecs.kdtree_unpack(bytecodecs.kdtree_pack(p, 6), 6))) == sorted(map(tuple, p))
        assert bytecodecs.fieldwise_unpack(bytecodecs.fieldwise_pack(p)).tolist() == p.tolist()
    for h, w in ((1, 1), (9, 17), (16, 24)):
        v = np.where(rng.random((h, w)) < 0.8, rng.integers(1, 65536, (h, w)), 0)
        assert (bytecodecs.png16_unpack(bytecodecs.png16_pack(v), h, w) == v).all()
        smooth = np.cumsum(rng.integers(0, 9, (h, w)), 1) + 1
        later = np.roll(smooth, 1, 1)
        assert (bytecodecs.video_unpack(bytecodecs.video_pack(later, smooth), smooth, h, w) == later).all()
        assert (bytecodecs.video_unpack(bytecodecs.video_pack(v, None), None, h, w) == v).all()
        ground = np.full((h, w), 20)
        assert (bytecodecs.cluster_unpack(bytecodecs.cluster_pack(smooth, ground, 5), ground) == smooth).all()
    v = rng.integers(1, 1000, (20, 30))
    assert np.abs(bytecodecs.dct8(v, 1e-3)[0] - v).max() < 0.01


def test_sizes_follow_entropy():
    rng = np.random.default_rng(3)
    x = np.round(rng.laplace(0, 2, 4000)).astype(int)
    n = np.unique(x, return_counts=True)[1]
    bits = -(n * np.log2(n / len(x))).sum()
    table = 8 * 200
    assert bits <= 8 * len(coders.huffman(x)) < bits + len(x) + table and 8 * len(coders.arith(x)) < bits + table
    assert abs(coders.estimate(x) - len(coders.arith(x))) < 24
    assert coders.smallest(x)[0] in coders.CODERS and len(coders.smallest(x)[1]) <= len(coders.choose(x, ("deflate", "varint_lzma", "arith"))[1])


def test_masks_invert():
    rng = np.random.default_rng(4)
    for h, w, p in ((1, 1, 0), (1, 1, 1), (5, 7, 0.5), (16, 50, 0.95), (3, 4, 0)):
        v = rng.random((h, w)) < p
        for m in (*masks.METHODS, "auto"):
            assert (masks.decode(masks.encode(v, m), h, w) == v).all()


def test_precision_curve_equals_average_precision(spark):
    rng = np.random.default_rng(5)
    rows = spark.createDataFrame([("ab"[i % 2], i, float(rng.integers(0, 20)), bool(rng.random() < 0.3)) for i in range(400)], "class string, id long, score double, positive boolean")
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(measures.precision_curve(rows, 7)) == key(measures.average_precision(rows))
